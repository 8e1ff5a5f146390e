"""The experiment workloads on the given tables, each held against SQL."""

from __future__ import annotations

from math import ceil
from time import perf_counter, sleep
from urllib.parse import unquote

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from exkit import train
from exkit.book import Book, Tables
from exkit.operators import online, randomize, resilience, skew
from exkit.plans import cost, metrics
from exkit.plans.partitioning import by_hash, by_range, portable_hash, virtual_map
from exkit.plans.planner import merge_factor, push_layout
from exkit.plans.spec import ShuffleSpec
from exkit.sources import records
from exkit.staging import new_path
from exkit.strategies import push, shuffle

BOOK = Book()
M, R, WORKERS, FACTOR, PER_ROUND = 16, 8, 4, 4, 4

# ---------------------------------------------------------------- record sort

KEYED = "SELECT substr(md5(o_orderkey::VARCHAR), 1, 20) AS key, ('0x' || substr(md5(o_orderkey::VARCHAR), 1, 8))::BIGINT AS h, o_orderkey FROM orders"


def _positions(df: DataFrame) -> DataFrame:
    pos = F.row_number().over(W.partitionBy("reduce_id").orderBy("key", "o_orderkey")).cast("long")
    return df.select("reduce_id", pos.alias("pos"), "key", "o_orderkey")


def sort_spec(r: int = R) -> ShuffleSpec:
    return ShuffleSpec(r, lambda d: by_range(d, "key", r), M, sort_keys=("key", "o_orderkey"), reduce_fn=_positions, merge_factor=FACTOR, workers=WORKERS, round_maps=PER_ROUND)


def order_records(t: Tables) -> DataFrame:
    keyed = virtual_map(t.orders.select("o_orderkey"), "o_orderkey", M)
    return keyed.select(records.hex_key(F.col("o_orderkey")).alias("key"), "o_orderkey", "map_id")


SORTED = f"""SELECT CAST(h * {R} // 4294967296 AS INTEGER) AS reduce_id,
  row_number() OVER (PARTITION BY h * {R} // 4294967296 ORDER BY key, o_orderkey) AS pos, key, o_orderkey FROM ({KEYED})"""
for _name in ("pull", "premerge", "push_durable", "push_lean", "push_inline", "stream_rounds"):
    BOOK.add(f"record_sort_{_name}", lambda t, s=_name: shuffle(order_records(t), sort_spec().with_(strategy=s)), SORTED)


@BOOK.query(SORTED)
def record_sort_inmemory(t):
    held = order_records(t).persist()
    return shuffle(held, sort_spec())


SWEEP = " UNION ALL ".join(
    f"SELECT {r} AS r_total, CAST(h * {r} // 4294967296 AS INTEGER) AS reduce_id, count(*) AS n_rows, min(key) AS min_key, max(key) AS max_key FROM ({KEYED}) GROUP BY 1, 2" for r in (2, 4, 8, 16)
)


@BOOK.query(SWEEP)
def record_sort_partition_sweep(t):
    base, out = order_records(t), None
    for r in (2, 4, 8, 16):
        one = shuffle(base, ShuffleSpec(r, lambda d, r=r: by_range(d, "key", r), M))
        one = one.groupBy("reduce_id").agg(F.count(F.lit(1)).alias("n_rows"), F.min("key").alias("min_key"), F.max("key").alias("max_key")).select(F.lit(r).alias("r_total"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@BOOK.query(f"SELECT count(*) AS n, 0::BIGINT AS inversions, count(DISTINCT h * {R} // 4294967296) AS partitions FROM ({KEYED})")
def record_sort_validate(t):
    return records.validate(shuffle(order_records(t), sort_spec().with_(strategy="push_inline"))).select("n", "inversions", "partitions")


LINE_ORDER = "l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus"
SHIP_RANGE = "CAST(greatest(0, least(7, date_diff('day', DATE '1992-01-01', l_shipdate::DATE) // 365)) AS INTEGER)"


@BOOK.query(f"""SELECT {SHIP_RANGE} AS reduce_id, row_number() OVER (PARTITION BY {SHIP_RANGE} ORDER BY {LINE_ORDER}) AS pos, l_orderkey, l_linenumber,
  CAST(l_shipdate AS VARCHAR)[1:10] AS ship FROM lineitem""")
def lineitem_sort_shipdate(t):
    days = F.datediff(F.to_date("l_shipdate"), F.lit("1992-01-01").cast("date"))
    rid = F.greatest(F.lit(0), F.least(F.lit(7), F.floor(days / 365))).cast("int")
    order = [c.strip() for c in LINE_ORDER.split(",")]
    pos = F.row_number().over(W.partitionBy("reduce_id").orderBy(*order)).cast("long")
    spec = ShuffleSpec(R, lambda d: d.withColumn("reduce_id", rid), M, sort_keys=tuple(order), reduce_fn=lambda d: d.select("reduce_id", pos.alias("pos"), "l_orderkey", "l_linenumber", F.date_format("l_shipdate", "yyyy-MM-dd").alias("ship")))
    return shuffle(t.lineitem, spec)


# ---------------------------------------------------------------- block ledgers

HASH = "('0x' || substr(md5(l_suppkey::VARCHAR), 1, 8))::BIGINT"
LINES = f"SELECT CAST(l_orderkey % {M} AS INTEGER) AS map_id, CAST({HASH} % {R} AS INTEGER) AS reduce_id, 72 + strlen(l_returnflag) + strlen(l_linestatus) AS b FROM lineitem"


def _lines(t: Tables, m: int = M, r: int = R) -> DataFrame:
    line = t.lineitem
    return by_hash(virtual_map(line.withColumn("b", metrics.row_bytes(line)), "l_orderkey", m), ["l_suppkey"], r, portable=True)


def _placed(t: Tables, m: int = M, r: int = R) -> DataFrame:
    return _lines(t, m, r).withColumns({"merge_id": F.floor(F.col("map_id") / FACTOR).cast("int"), "round": F.floor(F.col("map_id") / PER_ROUND).cast("int"), "worker": F.floor(F.col("reduce_id") * WORKERS / r).cast("int")})


LEDGERS = {
    "pull": (None, "map_id", "reduce_id", "0", "map_id", "reduce_id"),
    "premerge": (None, "merge_id", "reduce_id", "0", f"map_id // {FACTOR}", "reduce_id"),
    "push_map": ("round", "map_id", "worker", f"map_id // {PER_ROUND}", "map_id", f"reduce_id * {WORKERS} // {R}"),
    "push_merge": ("round", "worker", "reduce_id", f"map_id // {PER_ROUND}", f"reduce_id * {WORKERS} // {R}", "reduce_id"),
}
LEDGER_SQL = {}
for _name, (_round, _src, _dst, _q_round, _q_src, _q_dst) in LEDGERS.items():
    LEDGER_SQL[_name] = f"""SELECT '{_name}' AS stage, CAST({_q_round} AS INTEGER) AS round, CAST({_q_src} AS INTEGER) AS src, CAST({_q_dst} AS INTEGER) AS dst,
      count(*) AS n_rows, CAST(sum(b) AS BIGINT) AS n_bytes FROM ({LINES}) GROUP BY 1, 2, 3, 4"""
    BOOK.add(f"ledger_{_name}", lambda t, n=_name, a=_round, b=_src, c=_dst: metrics.ledger(_placed(t), n, b, c, a, F.col("b")), LEDGER_SQL[_name])


@BOOK.query(f"SELECT stage, count(*) AS n_blocks, round(avg(n_rows), 6) AS avg_rows, max(n_rows) AS max_rows, CAST(sum(n_bytes) AS BIGINT) AS n_bytes FROM ({' UNION ALL '.join(LEDGER_SQL.values())}) GROUP BY stage")
def ledger_summary(t):
    placed, out = _placed(t), None
    for n, (a, b, c, *_) in LEDGERS.items():
        one = metrics.ledger(placed, n, b, c, a, F.col("b"))
        out = one if out is None else out.unionByName(one)
    return metrics.ledger_summary(out)


GROWTH = ((4, 4, 2), (2, 8, 4), (1, 16, 8))


@BOOK.query(" UNION ALL ".join(f"""SELECT {s} AS part, count(*) AS n_blocks, round(avg(n), 6) AS avg_rows FROM (SELECT l_orderkey % {m} AS a, {HASH} % {r} AS b, count(*) AS n FROM lineitem
  WHERE ('0x' || substr(md5(l_orderkey::VARCHAR), 1, 8))::BIGINT % {s} = 0 GROUP BY 1, 2)""" for s, m, r in GROWTH))
def block_growth(t):
    out = None
    for s, m, r in GROWTH:
        own = _lines(t, m, r).where(portable_hash(F.col("l_orderkey")) % s == 0)
        one = own.groupBy("map_id", "reduce_id").agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)).alias("n_blocks"), F.round(F.avg("n"), 6).alias("avg_rows")).select(F.lit(s).alias("part"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@BOOK.query(f"""WITH d AS (SELECT CAST(sum(b) AS BIGINT) AS d FROM ({LINES})),
t(min_bytes) AS (VALUES (1000), (50000), (200000), (100000000)),
f AS (SELECT min_bytes, CAST(least({M}, greatest(1, ceil(min_bytes * {M}::DOUBLE * {R} / d))) AS INTEGER) AS f FROM t, d)
SELECT min_bytes, f, CAST(ceil({M}::DOUBLE / f) * {R} AS INTEGER) AS n_blocks FROM f""")
def merge_factor_dynamic(t):
    total = _lines(t).agg(F.sum("b").alias("d")).first()["d"]
    rows = [(b, f := merge_factor(total, M, R, b), ceil(M / f) * R) for b in (1000, 50_000, 200_000, 100_000_000)]
    return t.spark.createDataFrame(rows, "min_bytes int, f int, n_blocks int")


def _by_supplier(t: Tables) -> DataFrame:
    money = F.col("l_extendedprice").cast("decimal(18,2)")
    return virtual_map(t.lineitem.select("l_orderkey", "l_suppkey", F.col("l_quantity").cast("decimal(18,2)").alias("qty"), money.alias("price"), F.lit(1).cast("long").alias("n")), "l_orderkey", M).drop("l_orderkey")


def _combine(d: DataFrame) -> DataFrame:
    # the map id stays with un-merged rows only
    return d.groupBy("reduce_id", "l_suppkey").agg(F.sum("n").alias("n"), F.sum("qty").cast("decimal(18,2)").alias("qty"), F.sum("price").cast("decimal(18,2)").alias("price"))


def agg_spec() -> ShuffleSpec:
    done = lambda d: _combine(d).select(F.col("l_suppkey").alias("k"), "n", F.col("qty").cast("double").alias("qty"))
    return ShuffleSpec(R, lambda d: by_hash(d, ["l_suppkey"], R, portable=True), M, merge_fn=_combine, reduce_fn=done, merge_factor=FACTOR, workers=WORKERS, round_maps=PER_ROUND)


GROUPED = "SELECT l_suppkey AS k, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS qty FROM lineitem GROUP BY 1"
for _name in ("pull", "premerge", "push_durable", "push_lean", "push_inline", "stream_rounds"):
    BOOK.add(f"supplier_totals_{_name}", lambda t, s=_name: shuffle(_by_supplier(t), agg_spec().with_(strategy=s, merge_fn=None if s == "pull" else _combine)), GROUPED)


@BOOK.query(f"""SELECT CAST(map_id // {FACTOR} AS INTEGER) AS merge_id, reduce_id, k, count(*) AS n, CAST(sum(q) AS DOUBLE) AS qty
FROM (SELECT CAST(l_orderkey % {M} AS INTEGER) AS map_id, CAST({HASH} % {R} AS INTEGER) AS reduce_id, l_suppkey AS k, CAST(l_quantity AS DECIMAL(18,2)) AS q FROM lineitem) GROUP BY 1, 2, 3""")
def premerge_combine(t):
    own = by_hash(_by_supplier(t), ["l_suppkey"], R, portable=True)
    by = [F.floor(F.col("map_id") / FACTOR).cast("int").alias("merge_id"), "reduce_id", F.col("l_suppkey").alias("k")]
    return own.groupBy(*by).agg(F.sum("n").alias("n"), F.sum("qty").cast("double").alias("qty"))


@BOOK.query(f"""SELECT CAST(map_id // {PER_ROUND} AS INTEGER) AS round, CAST(reduce_id * {WORKERS} // {R} AS INTEGER) AS worker,
  count(DISTINCT map_id) AS fan_in, count(DISTINCT reduce_id) AS n_out, count(*) AS n_rows FROM ({LINES}) GROUP BY 1, 2""")
def push_rounds_layout(t):
    return _placed(t).groupBy("round", "worker").agg(F.countDistinct("map_id").alias("fan_in"), F.countDistinct("reduce_id").alias("n_out"), F.count(F.lit(1)).alias("n_rows"))


@BOOK.query(f"""WITH d AS (SELECT CAST(sum(b) AS BIGINT) AS d FROM ({LINES}))
SELECT v AS variant, d AS input_bytes, CAST(d * a AS BIGINT) AS intermediate_bytes, a::DOUBLE AS amplification FROM d, (VALUES ('push_durable', 2), ('push_lean', 1)) x(v, a)""")
def push_retention_cost(t):
    total = _lines(t).agg(F.sum("b").alias("d")).first()["d"] or 0
    rows = [(v, total, int(c["intermediate"]), c["amplification"]) for v in ("push_durable", "push_lean") for c in [cost.disk_traffic(v, total)]]
    return t.spark.createDataFrame(rows, "variant string, input_bytes long, intermediate_bytes long, amplification double")


def _pushed(t: Tables, strategy: str) -> dict:
    """What a push shuffle of the line items really wrote."""
    ledger: dict = {}
    lines = virtual_map(t.lineitem.select("l_orderkey", "l_suppkey", "l_quantity"), "l_orderkey", M)
    spec = ShuffleSpec(R, lambda d: by_hash(d, ["l_suppkey"], R, portable=True), M, workers=WORKERS, round_maps=PER_ROUND, keep_map_output=strategy == "push_durable")
    push(lines, spec, ledger=ledger)
    return ledger


@BOOK.query(f"SELECT CAST(map_id // {PER_ROUND} AS INTEGER) AS round, reduce_id, CAST(1 AS BIGINT) AS n_blocks, count(*) AS n_rows FROM ({LINES}) GROUP BY 1, 2")
def source_blocks(t):
    """Blocks and rows of each round and reduce partition, counted in the files that the merges committed."""
    files = [path for _, _, path in _pushed(t, "push_lean")["blocks"]]
    part = lambda name: F.regexp_extract("path", rf"/{name}=(\d+)/", 1).cast("int").alias(name)
    held = t.spark.read.parquet(*map(unquote, files)).select(F.col("_metadata.file_path").alias("path"))
    return held.groupBy(part("round"), part("reduce_id")).agg(F.countDistinct("path").alias("n_blocks"), F.count(F.lit(1)).alias("n_rows"))


@BOOK.query()
def push_bytes_measured(t):
    """Bytes on storage when the last round is merged: merged blocks, and the map output that is still kept."""
    rows = [(s, x["map_bytes"], x["block_bytes"], (x["map_bytes"] + x["block_bytes"]) / max(1, x["block_bytes"])) for s in ("push_durable", "push_lean") for x in [_pushed(t, s)]]
    return t.spark.createDataFrame(rows, "variant string, map_bytes long, block_bytes long, amplification double")


# ---------------------------------------------------------------- stragglers, failures, skew


@BOOK.query(GROUPED)
def best_effort_merge_groupby(t):
    spec = agg_spec()
    merged, raw = resilience.best_effort_merge(_by_supplier(t), spec, late=F.col("round") == 2)
    return resilience.reduce_best_effort(merged, raw, spec)


@BOOK.query(f"""SELECT reduce_id, count(DISTINCT CASE WHEN map_id // {PER_ROUND} <> 2 THEN map_id // {PER_ROUND} END) AS merged_blocks,
  count(DISTINCT CASE WHEN map_id // {PER_ROUND} = 2 THEN map_id END) AS raw_blocks FROM ({LINES}) GROUP BY 1""")
def best_effort_sources(t):
    late = F.col("round") == 2
    return _placed(t).groupBy("reduce_id").agg(F.countDistinct(F.when(~late, F.col("round"))).alias("merged_blocks"), F.countDistinct(F.when(late, F.col("map_id"))).alias("raw_blocks"))


@BOOK.query("SELECT o_orderpriority AS k, count(*) AS n, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DOUBLE) AS total FROM orders GROUP BY 1")
def speculative_agg(t):
    from exkit.staging import stage

    agg = t.orders.groupBy(F.col("o_orderpriority").alias("k")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("total"))
    return resilience.first_of(t.spark, lambda i: stage(agg, f"attempt-{i}"), patience_s=5.0)


@BOOK.query("SELECT event_id, value, round(threshold, 6) AS threshold FROM events, (SELECT 1.5 * quantile_cont(value, 0.5) AS threshold FROM events) WHERE value > threshold")
def straggler_suspects(t):
    return resilience.suspects(t.events.select("event_id", "value"), "value").select("event_id", "value", F.round("threshold", 6).alias("threshold"))


@BOOK.query("SELECT l_returnflag AS k, count(*) AS n FROM lineitem GROUP BY 1")
def failure_recovery_agg(t):
    """Masters without task retries can not lose a task, so the injected failure is retried as a whole there."""
    agg = lambda d: d.groupBy(F.col("l_returnflag").alias("k")).agg(F.count(F.lit(1)).alias("n"))
    line = t.lineitem.select("l_returnflag")

    def broken():
        raise RuntimeError("injected failure")

    return resilience.retried(t.spark, [broken, lambda: agg(line)])


HOT_SQL = "CASE WHEN ('0x' || substr(md5(l_orderkey::VARCHAR || ',' || l_partkey::VARCHAR), 1, 8))::BIGINT % 10 < 6 THEN 0 ELSE l_suppkey END"
ROW_SQL = "('0x' || substr(md5(l_orderkey::VARCHAR || ',' || l_partkey::VARCHAR || ',' || l_linenumber::VARCHAR), 1, 8))::BIGINT"


def hot_lines(t: Tables) -> DataFrame:
    hot = portable_hash(F.col("l_orderkey"), F.col("l_partkey")) % 10 < 6
    return t.lineitem.withColumn("hk", F.when(hot, F.lit(0).cast("long")).otherwise(F.col("l_suppkey")))


def _row(*more: str):
    return F.concat_ws(",", "l_orderkey", "l_partkey", "l_linenumber", *more)


def _split_sql(base: str, key: str, measure: str, limit: str, depth: int = 3) -> str:
    """Fixed-depth form of the recursive split: parts over the limit with several keys get another digit."""
    out, now = [f"WITH p0 AS ({base})"], "p0"
    out.append(f"lim AS ({limit})")
    for d in range(1, depth + 1):
        out.append(f"h{d} AS (SELECT part_path FROM {now} GROUP BY 1 HAVING sum({measure}) > (SELECT x FROM lim) AND min({key}) < max({key}))")
        out.append(f"""p{d} AS (SELECT p.* EXCLUDE (part_path, depth), CASE WHEN h.part_path IS NULL THEN p.part_path
          ELSE p.part_path || '.' || (('0x' || substr(md5('{d},' || CAST({key} AS VARCHAR)), 1, 8))::BIGINT % 2)::VARCHAR END AS part_path,
          CASE WHEN h.part_path IS NULL THEN p.depth ELSE {d} END AS depth FROM {now} p LEFT JOIN h{d} h ON p.part_path = h.part_path)""")
        now = f"p{d}"
    return ", ".join(out) + f" SELECT part_path, CAST(depth AS INTEGER) AS depth, count(*) AS n_rows, CAST(sum(b) AS BIGINT) AS n_bytes FROM {now} GROUP BY 1, 2"


@BOOK.query(_split_sql(f"SELECT l_suppkey AS k, 1 AS one, 72 + strlen(l_returnflag) + strlen(l_linestatus) AS b, CAST(CASE WHEN {HASH} % 10 < 6 THEN 0 ELSE {HASH} % {R} END AS VARCHAR) AS part_path, 0 AS depth FROM lineitem", "k", "one", f"SELECT 1.5 * count(*) / {R} AS x FROM lineitem"))
def skew_split_rows(t):
    h = portable_hash(F.col("l_suppkey"))
    line = t.lineitem
    base = line.select(F.col("l_suppkey").alias("k"), metrics.row_bytes(line).alias("b"), F.when(h % 10 < 6, 0).otherwise(h % R).cast("int").alias("part"))
    limit = 1.5 * line.count() / R
    return skew.split_oversized(base, "part", "k", limit, max_depth=3).groupBy("part_path", "depth").agg(F.count(F.lit(1)).alias("n_rows"), F.sum("b").alias("n_bytes"))


@BOOK.query(_split_sql("SELECT doc_id AS k, n_chars AS b, lang AS part_path, 0 AS depth FROM documents", "k", "b", "SELECT 1.5 * sum(n_chars) / count(DISTINCT lang) AS x FROM documents"))
def skew_split_bytes(t):
    docs = t.documents.select(F.col("doc_id").alias("k"), F.col("n_chars").alias("b"), "lang")
    limit = docs.agg((1.5 * F.sum("b") / F.countDistinct("lang")).alias("x")).first()["x"] or 0
    return skew.split_oversized(docs, "lang", "k", limit, measure=F.col("b"), max_depth=3).groupBy("part_path", "depth").agg(F.count(F.lit(1)).alias("n_rows"), F.sum("b").alias("n_bytes"))


HOT_TOTALS = f"SELECT {HOT_SQL} AS k, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS total FROM lineitem GROUP BY 1"


def _sums() -> dict:
    return {"n": F.count(F.lit(1)), "total": F.sum(F.col("l_quantity").cast("decimal(18,2)"))}


def _named(d: DataFrame) -> DataFrame:
    return d.select(F.col("hk").alias("k"), "n", F.col("total").cast("double").alias("total"))


@BOOK.query(HOT_TOTALS)
def skew_split_agg(t):
    base = hot_lines(t).withColumn("part", (portable_hash(F.col("hk")) % R).cast("int"))
    limit = 1.5 * t.lineitem.count() / R
    split = skew.split_oversized(base, "part", "hk", limit, max_depth=3, row_id=_row())
    parts = split.groupBy("hk", "part_path").agg(*[c.alias(n) for n, c in _sums().items()])
    return _named(skew.recombine(parts, ["hk"], ["n", "total"]))


@BOOK.query(HOT_TOTALS)
def salted_agg(t):
    return _named(skew.salted_agg(hot_lines(t), ["hk"], _sums(), _row()))


@BOOK.query(f"SELECT s.s_nationkey AS k, count(*) AS n, CAST(sum(CAST(l.l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS total FROM (SELECT *, {HOT_SQL.replace(' ELSE l_suppkey', ' ELSE l_suppkey')} AS hk FROM lineitem) l JOIN (SELECT s_suppkey AS hk, s_nationkey FROM supplier UNION ALL SELECT 0, 0) s ON l.hk = s.hk GROUP BY 1")
def salted_join(t):
    right = t.supplier.select(F.col("s_suppkey").alias("hk"), "s_nationkey").union(t.spark.createDataFrame([(0, 0)], "hk long, s_nationkey int"))
    both = skew.salted_join(hot_lines(t), right, "hk", _row())
    return both.groupBy(F.col("s_nationkey").alias("k")).agg(*[c.alias(n) for n, c in _sums().items()]).withColumn("total", F.col("total").cast("double"))


@BOOK.query("SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
def rebalance_report(t):
    return skew.rebalance_table(t.events).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("event_id").alias("ids"))


@BOOK.query(f"""SELECT count(*) AS parts, max(n) AS max_rows, round(avg(n), 6) AS mean_rows, round(max(n) / avg(n), 6) AS ratio, round(stddev_pop(n) / avg(n), 6) AS cv,
  CAST(sum(CASE WHEN n > 1000 THEN 1 ELSE 0 END) AS BIGINT) AS over_limit FROM (SELECT {HOT_SQL} AS hk, count(*) AS n FROM lineitem GROUP BY 1)""")
def skew_report(t):
    return metrics.skew_report(hot_lines(t), "hk", 1000)


# ---------------------------------------------------------------- online aggregation

DAY = "CAST(date_diff('day', DATE '2024-01-01', ts::DATE) AS INTEGER)"
CENTS = "CAST(value AS DECIMAL(18,2))"


def _running_sql(by_round: str, keys: str) -> str:
    return f"""WITH p AS (SELECT {by_round} AS round, {keys}, count(*) AS n, sum({CENTS}) AS v FROM events GROUP BY ALL),
r AS (SELECT DISTINCT round FROM p), s AS (SELECT {keys}, min(round) AS lo FROM p GROUP BY ALL),
g AS (SELECT r.round, s.* EXCLUDE (lo) FROM r JOIN s ON r.round >= s.lo),
run AS (SELECT g.round, {', '.join('g.' + k.strip() for k in keys.split(','))},
  CAST(sum(coalesce(p.n, 0)) OVER w AS BIGINT) AS n, sum(coalesce(p.v, 0)) OVER w AS v
  FROM g LEFT JOIN p ON g.round = p.round AND {' AND '.join(f'g.{k.strip()} = p.{k.strip()}' for k in keys.split(','))}
  WINDOW w AS (PARTITION BY {', '.join('g.' + k.strip() for k in keys.split(','))} ORDER BY g.round))"""


def _cents() -> dict:
    return {"n": F.count(F.lit(1)), "v": F.sum(F.col("value").cast("decimal(18,2)"))}


@BOOK.query(_running_sql(DAY, "event_type") + " SELECT round, event_type, n, CAST(v AS DOUBLE) AS total FROM run")
def online_agg_rounds(t):
    run = online.aggregate(online.rounds_by_time(t.events, "ts"), ["event_type"], _cents())
    return run.select("round", "event_type", "n", F.col("v").cast("double").alias("total"))


@BOOK.query(_running_sql(DAY, "event_type, user_id") + """ SELECT * FROM (SELECT round, event_type AS lang, user_id AS page, CAST(v AS DOUBLE) AS views,
  CAST(row_number() OVER (PARTITION BY round, event_type ORDER BY v DESC, user_id) AS INTEGER) AS rnk FROM run) WHERE rnk <= 3""")
def online_top_by_lang(t):
    run = online.aggregate(online.rounds_by_time(t.events, "ts"), ["event_type", "user_id"], _cents())
    top = online.top_by(run, ["round", "event_type"], "user_id", "v", 3)
    return top.select("round", F.col("event_type").alias("lang"), F.col("user_id").alias("page"), F.col("v").cast("double").alias("views"), "rnk")


@BOOK.query("""WITH p AS (SELECT CAST(doc_id % 10 AS INTEGER) AS round, lang, source, sum(n_chars) AS v FROM documents GROUP BY ALL),
s AS (SELECT lang, source, min(round) AS lo FROM p GROUP BY ALL), r AS (SELECT DISTINCT round FROM p),
run AS (SELECT r.round, s.lang, s.source, CAST(sum(coalesce(p.v, 0)) OVER (PARTITION BY s.lang, s.source ORDER BY r.round) AS BIGINT) AS views
  FROM r JOIN s ON r.round >= s.lo LEFT JOIN p ON p.round = r.round AND p.lang = s.lang AND p.source = s.source)
SELECT * FROM (SELECT round, lang, source, views, CAST(row_number() OVER (PARTITION BY round, lang ORDER BY views DESC, source) AS INTEGER) AS rnk FROM run) WHERE rnk <= 3""")
def online_top_docs(t):
    docs = t.documents.select((F.col("doc_id") % 10).cast("int").alias("round"), "lang", "source", "n_chars")
    return online.top_by(online.aggregate(docs, ["lang", "source"], {"views": F.sum("n_chars")}), ["round", "lang"], "source", "views", 3)


def _kl_sql(by_round: str, keys: str) -> str:
    join = " AND ".join(f"f.{k.strip()} = x.{k.strip()}" for k in keys.split(","))
    return _running_sql(by_round, keys) + f""", fin AS (SELECT {keys}, CAST(sum({CENTS}) AS DOUBLE) AS f FROM events GROUP BY ALL),
  ft AS (SELECT sum(f) AS ft FROM fin), xt AS (SELECT round, CAST(sum(v) AS DOUBLE) AS xt FROM run GROUP BY 1),
  k AS (SELECT r.round, sum(CASE WHEN x.v > 0 THEN f.f / ft.ft * ln((f.f / ft.ft) / (CAST(x.v AS DOUBLE) / xt.xt)) END) AS s,
    CAST(sum(CASE WHEN x.v > 0 THEN 0 ELSE 1 END) AS BIGINT) AS unseen
    FROM r CROSS JOIN fin f CROSS JOIN ft LEFT JOIN run x ON x.round = r.round AND {join} LEFT JOIN xt ON xt.round = r.round WHERE f.f > 0 GROUP BY 1)
  SELECT round, CASE WHEN unseen > 0 THEN 'Infinity'::DOUBLE ELSE round(s, 6) END AS kl, unseen FROM k"""


def _divergence(t: Tables, by_hash_rounds: bool, keys: list[str]) -> DataFrame:
    events = online.rounds_by_hash(t.events, "event_id", 20) if by_hash_rounds else online.rounds_by_time(t.events, "ts")
    run = online.aggregate(events, keys, _cents())
    final = t.events.groupBy(*keys).agg(F.sum(F.col("value").cast("decimal(18,2)")).alias("v"))
    return metrics.kl(final, run, keys, "v", ["round"])


HASH_ROUND = "CAST(('0x' || substr(md5(event_id::VARCHAR), 1, 8))::BIGINT % 20 AS INTEGER)"
BOOK.add("online_kl", lambda t: _divergence(t, False, ["event_type"]), _kl_sql(DAY, "event_type"))
BOOK.add("online_kl_hash", lambda t: _divergence(t, True, ["event_type"]), _kl_sql(HASH_ROUND, "event_type"))
BOOK.add("online_kl_hash_users", lambda t: _divergence(t, True, ["event_type", "user_id"]), _kl_sql(HASH_ROUND, "event_type, user_id"))
BOOK.add("online_time_to_error", lambda t: metrics.first_round_below(_divergence(t, True, ["event_type"])), f"SELECT min(round) AS round FROM ({_kl_sql(HASH_ROUND, 'event_type')}) WHERE kl <= 0.08")


@BOOK.query(f"SELECT event_type AS k, count(*) AS n, CAST(sum({CENTS}) AS DOUBLE) AS total FROM events GROUP BY 1")
def online_final_equals_batch(t):
    part = lambda d: d.groupBy("reduce_id", "event_type").agg(F.sum("n").alias("n"), F.sum("v").cast("decimal(18,2)").alias("v"))
    rows = t.events.select("event_type", F.lit(1).cast("long").alias("n"), F.col("value").cast("decimal(18,2)").alias("v"), F.pmod("event_id", F.lit(M)).cast("int").alias("map_id"))
    spec = ShuffleSpec(4, lambda d: by_hash(d, ["event_type"], 4, portable=True), M, merge_fn=part, round_maps=PER_ROUND, strategy="stream_rounds")
    return shuffle(rows, spec).select(F.col("event_type").alias("k"), "n", F.col("v").cast("double").alias("total"))


# ---------------------------------------------------------------- random shuffles and training


def _perm(seed: int, epoch: str, pk: str = "vec_id") -> str:
    return f"md5('{seed}-' || {epoch} || '-' || {pk}::VARCHAR)"


@BOOK.query(f"SELECT CAST(e AS INTEGER) AS epoch, row_number() OVER (PARTITION BY e ORDER BY {_perm(1, 'e')}, vec_id) - 1 AS pos, vec_id FROM embeddings, (VALUES (0), (1)) x(e)")
def random_shuffle_full(t):
    ids = t.embeddings.select("vec_id")
    one = lambda e: randomize.full_positions(ids, "vec_id", 1, e).select(F.lit(e).alias("epoch"), "pos", "vec_id")
    return one(0).unionByName(one(1))


def stored_order(t: Tables) -> DataFrame:
    """Embeddings in the hard order: by label, then id."""
    return randomize.numbered(t.embeddings.select("vec_id", "label"), ["vec_id"], "label", "ordinal")


WINDOWED = f"""WITH o AS (SELECT vec_id, label, row_number() OVER (ORDER BY label, vec_id) - 1 AS ordinal FROM embeddings),
s AS (SELECT CAST(floor(0.09 * count(*)) AS BIGINT) AS size FROM embeddings),
w AS (SELECT o.*, ordinal // size AS win, size FROM o, s)
SELECT 0 AS epoch, CAST(win AS INTEGER) AS "window", win * size + row_number() OVER (PARTITION BY win ORDER BY {_perm(1, "'0'")}, vec_id) - 1 AS pos, vec_id, ordinal, label FROM w"""


@BOOK.query(WINDOWED)
def random_shuffle_windowed(t):
    size = int(0.09 * t.embeddings.count())
    out = randomize.windowed(stored_order(t), "vec_id", 1, 0, "ordinal", size)
    return out.select(F.lit(0).alias("epoch"), "window", "pos", "vec_id", "ordinal", "label")


PARTIAL = f"""WITH o AS (SELECT vec_id, label, row_number() OVER (ORDER BY label, vec_id) - 1 AS ordinal FROM embeddings)
SELECT 0 AS epoch, CAST(ordinal // 32 AS INTEGER) AS batch, (ordinal // 32) * 32 + row_number() OVER (PARTITION BY ordinal // 32 ORDER BY {_perm(1, "'0'")}, vec_id) - 1 AS pos, vec_id, ordinal, label FROM o"""


@BOOK.query(PARTIAL)
def random_shuffle_partial(t):
    out = randomize.windowed(stored_order(t), "vec_id", 1, 0, "ordinal", 32)
    return out.select(F.lit(0).alias("epoch"), F.col("window").alias("batch"), "pos", "vec_id", "ordinal", "label")


@BOOK.query()
def random_shuffle_buffered(t):
    ordered = stored_order(t).repartitionByRange(2, "ordinal").sortWithinPartitions("ordinal")
    return randomize.buffered(ordered, 1, 0, 64).select("vec_id", "ordinal", "label")


FULL = f"SELECT row_number() OVER (ORDER BY {_perm(1, chr(39) + '0' + chr(39))}, vec_id) - 1 AS pos, ordinal, label FROM (SELECT vec_id, label, row_number() OVER (ORDER BY label, vec_id) - 1 AS ordinal FROM embeddings)"


def _mix_sql(mode: str, rows: str) -> str:
    return f"""SELECT '{mode}' AS mode, round(avg(abs(ordinal - pos)) / count(*), 6) AS displacement,
      round(CAST(sum(CASE WHEN nxt = ordinal + 1 THEN 1 ELSE 0 END) AS DOUBLE) / count(*), 6) AS adjacent_kept, CAST(sum(CASE WHEN lnext <> label THEN 1 ELSE 0 END) + 1 AS BIGINT) AS label_runs
      FROM (SELECT *, lead(ordinal) OVER (ORDER BY pos) AS nxt, lead(label) OVER (ORDER BY pos) AS lnext FROM ({rows}))"""


@BOOK.query(" UNION ALL ".join([_mix_sql("full", FULL), _mix_sql("windowed", f"SELECT pos, ordinal, label FROM ({WINDOWED})"), _mix_sql("partial", f"SELECT pos, ordinal, label FROM ({PARTIAL})")]))
def mixing_quality(t):
    base, n = stored_order(t), t.embeddings.count()
    modes = {
        "full": randomize.full_positions(base, "vec_id", 1, 0),
        "windowed": randomize.windowed(base, "vec_id", 1, 0, "ordinal", int(0.09 * n)),
        "partial": randomize.windowed(base, "vec_id", 1, 0, "ordinal", 32),
    }
    out = None
    for mode, df in modes.items():
        one = metrics.mixing(df, "ordinal", "pos", "label").select(F.lit(mode).alias("mode"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def training_rows(t: Tables) -> tuple[DataFrame, DataFrame]:
    """(train, test): class = place of the largest of the first ten components, features = 8 times the vector, stored by class."""
    first = F.slice("embedding", 1, 10)
    y = (F.array_position(first, F.array_max(first)) - 1).cast("int")
    rows = t.embeddings.select("vec_id", y.alias("y"), F.transform("embedding", lambda x: (x * 8).cast("double")).alias("features"))
    own = randomize.numbered(rows.where(F.col("vec_id") % 5 != 0), ["vec_id"], "y", "ordinal")
    return own, rows.where(F.col("vec_id") % 5 == 0)


def quality_rows(t: Tables) -> tuple[DataFrame, DataFrame]:
    """(train, test): document quality from the share of symbols, distinct lines, word length and language."""
    text, lines, words = F.col("text"), F.split("text", "\n"), F.split("text", r"\s+")
    symbols = F.length(F.regexp_replace(text, r"[\p{L}\s]", "")) / F.greatest(F.length(text), F.lit(1))
    feats = F.array(symbols * 5, F.size(F.array_distinct(lines)) / F.size(lines), F.length(F.regexp_replace(text, r"\s", "")) / F.size(words) / 10, *[(F.col("lang") == x).cast("double") for x in ("en", "fr", "de", "es")])
    rows = t.documents.join(t.labels, "doc_id").select("doc_id", F.col("quality").alias("y"), feats.alias("features"))
    own = randomize.numbered(rows.where(F.col("doc_id") % 5 != 0), ["doc_id"], "y", "ordinal")
    return own, rows.where(F.col("doc_id") % 5 == 0)


#: Shuffle modes that training is compared by, and passes over the rows.
MODES, EPOCHS = ("full", "windowed", "partial", "buffered"), 20


def _history(t: Tables, rows: tuple[DataFrame, DataFrame], pk: str, modes: tuple[str, ...], epochs: int) -> DataFrame:
    own, held = rows[0].persist(), train.to_arrays(rows[1].select("features", "y").collect())  # the held-out rows of the given tables
    n, out = own.count(), []
    for mode in modes:
        _, h = train.fit(own, held, pk, mode, epochs, window_rows=max(1, int(0.09 * n)), buffer_rows=max(1, int(0.09 * n)))
        out += [(mode, e, a) for e, a in enumerate(h.accuracy)]
    own.unpersist()
    return t.spark.createDataFrame(out, "mode string, epoch int, accuracy double")


@BOOK.query()
def train_embeddings(t):
    return _history(t, training_rows(t), "vec_id", MODES, EPOCHS)


@BOOK.query()
def train_doc_quality(t):
    return _history(t, quality_rows(t), "doc_id", MODES, EPOCHS)


@BOOK.query()
def train_distributed(t):
    own, test = training_rows(t)
    own, held, out = own.persist(), train.to_arrays(test.select("features", "y").collect()), []
    for mode in ("full", "partial"):
        h = train.fit_distributed(own, held, "vec_id", mode, WORKERS, EPOCHS)
        out += [(mode, e, a) for e, a in enumerate(h.accuracy)]
    own.unpersist()
    return t.spark.createDataFrame(out, "mode string, epoch int, accuracy double")


# ---------------------------------------------------------------- cost


EVENT_BYTES = """SELECT event_type, CAST(8 * (count(event_id) + count(ts) + count(user_id) + count(value))
  + coalesce(sum(strlen(event_type)), 0) + coalesce(sum(strlen(props)), 0) AS BIGINT) AS bytes FROM events GROUP BY 1"""


def event_bytes(t: Tables) -> DataFrame:
    """Bytes of each type's events: four numbers of eight bytes and two texts, nulls left out."""
    text = lambda c: F.coalesce(F.sum(F.octet_length(c)), F.lit(0))
    numbers = F.count("event_id") + F.count("ts") + F.count("user_id") + F.count("value")
    return t.events.groupBy("event_type").agg((8 * numbers + text("event_type") + text("props")).alias("bytes"))


@BOOK.query(f"""SELECT event_type, bytes, config, usd_per_tb, bytes * usd_per_tb / 1e6::DOUBLE AS micro_usd, saved_percent FROM ({EVENT_BYTES}),
  (VALUES ('record of 2016', 1.44::DOUBLE, 32.6::DOUBLE), ('2016 resources at 2022 prices', 1.15, 15.7), ('reference of 2022', 0.97, 0.0), ('network floor', 0.74, -31.1)) x(config, usd_per_tb, saved_percent)""")
def cost_sort_model(t):
    """What sorting the events of each type costs at the published prices."""
    ours = cost.SORT_USD_PER_TB["reference of 2022"]
    rows = [(k, v, round(100 * (v - ours) / v, 1)) for k, v in cost.SORT_USD_PER_TB.items()]
    prices = t.spark.createDataFrame(rows, "config string, usd_per_tb double, saved_percent double")
    return event_bytes(t).crossJoin(F.broadcast(prices)).select("event_type", "bytes", "config", "usd_per_tb", (F.col("bytes") * F.col("usd_per_tb") / F.lit(1e6)).alias("micro_usd"), "saved_percent")


NODES = (("10 HDD nodes", cost.HDD, 10), ("10 SSD nodes", cost.SSD, 10), ("100 HDD nodes", cost.HDD, 100))


def _floors(t: Tables, seconds) -> DataFrame:
    one = lambda c, hw, n: F.struct(F.lit(c).alias("config"), (seconds(F.col("bytes"), hw, n) * 1000).alias("milliseconds"))
    return event_bytes(t).select("event_type", "bytes", F.inline(F.array(*[one(*x) for x in NODES])))


@BOOK.query(f"""SELECT event_type, bytes, config, 4 * bytes / bandwidth * 1000 AS milliseconds FROM ({EVENT_BYTES}),
  (VALUES ('10 HDD nodes', 11e9::DOUBLE), ('10 SSD nodes', 7.2e9), ('100 HDD nodes', 110e9)) x(config, bandwidth)""")
def disk_floor_table(t):
    """The least time of the disks for an external sort of the events of each type."""
    return _floors(t, lambda d, hw, n: cost.disk_floor_seconds(d, hw.seq_bytes_s * n))


@BOOK.query(f"""SELECT event_type, bytes, config, bytes / bandwidth * 1000 AS milliseconds FROM ({EVENT_BYTES}),
  (VALUES ('10 HDD nodes', 18.75e9::DOUBLE), ('10 SSD nodes', 12.5e9), ('100 HDD nodes', 187.5e9)) x(config, bandwidth)""")
def network_floor_table(t):
    """The least time of the network to move the events of each type once."""
    return _floors(t, lambda d, hw, n: cost.network_floor_seconds(d, hw.nic_bytes_s, n))


PLACED = f"SELECT o_orderkey % {M} AS map_id, h * {R} // 4294967296 AS reduce_id FROM ({KEYED})"


@BOOK.query(f"""WITH p AS ({PLACED}), x AS (SELECT CAST(count(DISTINCT map_id) AS INTEGER) AS m, CAST(count(DISTINCT reduce_id) AS INTEGER) AS r FROM p)
  SELECT 'pull' AS strategy, m * r AS n_blocks, m AS fan_in, (SELECT count(DISTINCT (map_id, reduce_id)) FROM p) AS n_found FROM x
  UNION ALL SELECT 'premerge', (m + {FACTOR - 1}) // {FACTOR} * r, (m + {FACTOR - 1}) // {FACTOR}, (SELECT count(DISTINCT (map_id // {FACTOR}, reduce_id)) FROM p) FROM x
  UNION ALL SELECT 'push', (m + {PER_ROUND - 1}) // {PER_ROUND} * r, (m + {PER_ROUND - 1}) // {PER_ROUND}, (SELECT count(DISTINCT (map_id // {PER_ROUND}, reduce_id)) FROM p) FROM x""")
def predicted_blocks(t):
    """Blocks and fan-in that the model predicts for the maps and reducers of the order records, and the blocks there are."""

    def predict(m, r, pull, premerge, push_):
        p = push_layout(m, r, WORKERS, PER_ROUND) if m else None
        return [
            ("pull", cost.block_counts("pull", m, r)["map"], cost.fan_in("pull", m), pull),
            ("premerge", cost.block_counts("premerge", m, r, f=FACTOR)["merged"], cost.fan_in("premerge", m, f=FACTOR), premerge),
            ("push", cost.block_counts("push_lean", m, r, WORKERS, round_maps=PER_ROUND)["merged"], p.rounds if p else 0, push_),
        ]

    merged = lambda n: F.struct(F.floor(F.col("map_id") / n), "reduce_id")
    blocks = by_range(order_records(t), "key", R).select("map_id", "reduce_id").distinct()
    pairs = [F.countDistinct("map_id"), F.countDistinct("reduce_id"), F.count(F.lit(1)), F.countDistinct(merged(FACTOR)), F.countDistinct(merged(PER_ROUND))]
    found = blocks.agg(*[c.alias(f"c{i}") for i, c in enumerate(pairs)])
    kind = "array<struct<strategy:string, n_blocks:int, fan_in:int, n_found:bigint>>"
    return found.select(F.inline(F.udf(predict, kind)(*found.columns)))


def _timed(t: Tables, rows: int, settings: dict) -> DataFrame:
    out = []
    for name, thunk in settings.items():
        start = perf_counter()
        thunk()
        out.append((name, rows, round(perf_counter() - start, 3)))
    return t.spark.createDataFrame(out, "setting string, rows long, seconds double")


@BOOK.query()
def store_fuse_bench(t):
    """The same rows as many small files and as a few fused ones."""
    docs = t.documents
    write = lambda n: docs.repartition(n).write.parquet(new_path(t.spark, "fuse"))
    return _timed(t, docs.count(), {"unfused": lambda: write(40), "fused": lambda: write(2)})


@BOOK.query()
def prefetch_bench(t):
    """A consumer whose next partition is fetched while it works, or only when it asks."""
    ids = t.embeddings.select("vec_id").repartition(8, "vec_id")

    def consume(ahead: bool) -> None:
        for i, _ in enumerate(ids.toLocalIterator(prefetchPartitions=ahead)):
            if i % 50 == 0:
                sleep(0.01)

    return _timed(t, ids.count(), {"prefetch": lambda: consume(True), "no prefetch": lambda: consume(False)})


@BOOK.query()
def loc_table(t):
    """Texts of each source and their lines that hold code, by the rule of ``metrics.loc``."""
    lines = F.udf(lambda text: metrics.loc_of(text or ""), "long")
    return t.documents.select("source", lines("text").alias("loc")).groupBy("source").agg(F.count(F.lit(1)).alias("n_texts"), F.sum("loc").alias("loc"))
