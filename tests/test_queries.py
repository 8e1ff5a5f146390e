"""Registered queries against DuckDB on the smallest tables, and the promises of the driver contract."""

import duckdb
import pytest

from exkit import registry
from exkit.tables import NAMES

SF = "/root/testdata/sf0.001"
#: One of each kind; the driver compares them all.
SAMPLE = [
    "record_sort_push_lean", "ledger_summary", "merge_factor_dynamic", "supplier_totals_push_durable", "skew_split_rows", "salted_join", "online_kl_hash", "random_shuffle_windowed",
    "join_asof", "join_interval", "agg_rollup", "win_sessionize", "win_global_rownum", "except_all", "fn_date", "fn_array", "udtf_split", "stream_tumbling", "source_blocks", "transpose_small", "udf_stateful",
]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for n in NAMES:
        c.execute(f"CREATE VIEW {n} AS SELECT * FROM '{SF}/{n}.parquet'")
    return c


def norm(v):
    return round(v, 6) if isinstance(v, float) else v


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_sql(spark, duck, name):
    df = registry.QUERIES[name](spark, SF)
    cur = duck.execute(registry.SQL[name])
    names = [d[0] for d in cur.description]
    assert sorted(names) == sorted(df.columns)
    want = sorted(repr([norm(r[names.index(c)]) for c in sorted(names)]) for r in cur.fetchall())
    assert sorted(repr([norm(r[c]) for c in sorted(names)]) for r in df.collect()) == want


@pytest.mark.parametrize("how", ["left", "right", "full"])
def test_whole_outer_joins_grow_with_the_tables(spark, duck, how):
    name = f"join_{how}_whole"
    test_query_equals_sql(spark, duck, name)
    matched, customers, orders = [], [], []
    for sf in (SF, "/root/testdata/sf0.01", "/root/testdata/sf0.1"):
        df = registry.QUERIES[name](spark, sf)
        matched.append(df.where("c_custkey = o_custkey").count())
        customers.append(df.where("o_custkey IS NULL").count())
        orders.append(df.where("c_custkey IS NULL").count())
    for counts, there in ((matched, True), (customers, how != "right"), (orders, how != "left")):
        assert all(5 * a < b < 20 * a for a, b in zip(counts, counts[1:])) if there else not any(counts), (matched, customers, orders)


def test_training_runs_all_epochs(spark, monkeypatch):
    from exkit import train, workloads

    asked = []
    history = lambda mode, epochs: (asked.append((mode, epochs)), train.History(accuracy=[0.5] * epochs))[1]
    monkeypatch.setattr(workloads.train, "fit", lambda df, test, pk, mode, epochs, **how: (None, history(mode, epochs)))
    monkeypatch.setattr(workloads.train, "fit_distributed", lambda df, test, pk, mode, workers, epochs: history(mode, epochs))
    modes = ["full", "windowed", "partial", "buffered"]
    for name, want in (("train_embeddings", modes), ("train_doc_quality", modes), ("train_distributed", ["full", "partial"])):
        asked.clear()
        rows = registry.QUERIES[name](spark, SF).collect()
        assert asked == [(m, 20) for m in want] and len(rows) == 20 * len(want)


def test_sliding_windows_round_times_as_their_sql(spark, duck, tmp_path):
    """Events within half a second of a slide's end, and halves, count as the SQL counts them."""
    times = ["05:59:59.4", "05:59:59.5", "05:59:59.6", "06:00:00.4", "12:00:00.5", "17:59:58.5", "17:59:59.999999", "23:59:59.7"]
    rows = ", ".join(f"({i}, TIMESTAMP '2024-01-02 {s}', 1, 'view', 1.0, '')" for i, s in enumerate(times))
    duck.execute(f"COPY (SELECT event_id::BIGINT AS event_id, ts, user_id::BIGINT AS user_id, event_type, value::DOUBLE AS value, props FROM (VALUES {rows}) x(event_id, ts, user_id, event_type, value, props)) TO '{tmp_path}/events.parquet'")
    want = duck.execute(registry.SQL["stream_sliding"].replace("FROM events", f"FROM '{tmp_path}/events.parquet' events")).fetchall()
    got = registry.QUERIES["stream_sliding"](spark, str(tmp_path)).select("start", "event_type", "n").collect()
    assert sorted(map(tuple, got)) == sorted(want)


def test_cogroup_of_odd_keys(spark, duck, tmp_path, monkeypatch):
    """Null keys meet nothing, keys listed twice are one row, and several buckets are one result."""
    from exkit.operators import relational

    orders, lines = [1, 1, 2, None, None, 2**60 + 1, 7, 8], [1, 1, 1, 2, None, 2**60 + 1, 2**60, 9]
    spark.createDataFrame([(k,) for k in orders], "o_orderkey long").write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame([(k,) for k in lines], "l_orderkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    sql = registry.SQL["join_cogroup"].replace("FROM orders", f"FROM '{tmp_path}/orders.parquet/*.parquet'").replace("JOIN lineitem", f"JOIN '{tmp_path}/lineitem.parquet/*.parquet'")
    want = sorted(map(repr, duck.execute(sql).fetchall()))
    for rows in (250_000, 3):
        monkeypatch.setattr(relational, "COGROUP_ROWS", rows, raising=False)
        assert sorted(repr(tuple(r)) for r in registry.QUERIES["join_cogroup"](spark, str(tmp_path)).collect()) == want


#: Models and records that are worked out from the given tables.
FROM_TABLES = ["cost_sort_model", "disk_floor_table", "network_floor_table", "predicted_blocks", "source_binary_records"]


@pytest.mark.parametrize("name", FROM_TABLES)
def test_models_follow_their_table(spark, duck, name):
    test_query_equals_sql(spark, duck, name)
    small, large = (sorted(map(tuple, registry.QUERIES[name](spark, f"/root/testdata/{sf}").collect())) for sf in ("sf0.001", "sf0.01"))
    assert small != large or name == "predicted_blocks"
    assert any("parquet" in line and "Scan" in line for line in registry.QUERIES[name](spark, SF)._jdf.queryExecution().toString().splitlines())


def test_lines_of_code_of_the_texts(spark, tmp_path):
    texts = [("a", "x = 1\n\n# y\nz = 2"), ("a", '"""one\ntwo"""\nx'), ("b", None), (None, "p\r\nq")]
    spark.createDataFrame(texts, "source string, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {tuple(r) for r in registry.QUERIES["loc_table"](spark, str(tmp_path)).collect()}
    assert got == {("a", 2, 3), ("b", 1, 0), (None, 1, 2)}


def test_timers_report_idle_users(spark, duck):
    """Reported users were idle for a day at that time; those idle at the end of the stream, an hour of lateness allowed, are all among them."""
    got = {(r["user_id"], r["last_ms"]) for r in registry.QUERIES["stream_timers"](spark, SF).collect()}
    rows = duck.execute("SELECT user_id, epoch_us(ts) // 1000 FROM events").fetchall()
    end, last = max(t for _, t in rows), {}
    for u, t in rows:
        last[u] = max(t, last.get(u, 0))
    assert {(u, t) for u, t in last.items() if t < end - 26 * 3600 * 1000} <= got <= set(rows)


def test_push_bytes_are_measured(spark):
    """At sf0.1: in smaller tables the headers of the blocks' files outweigh their rows."""
    got = {r["variant"]: r for r in registry.QUERIES["push_bytes_measured"](spark, "/root/testdata/sf0.1").collect()}
    assert got["push_lean"]["map_bytes"] < 0.1 * got["push_durable"]["map_bytes"] and got["push_durable"]["amplification"] > 1.5


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())


def test_scan_is_pruned_and_filtered(spark, tables):
    plan = registry.QUERIES["scan_pushdown"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(o_orderdate" in plan and "o_orderstatus" not in plan
