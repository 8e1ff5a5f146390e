"""Every strategy gives the same rows in the same reduce partitions."""

import pytest
from pyspark.sql import functions as F

from exkit import workloads as w
from exkit.operators import resilience
from exkit.plans import metrics
from exkit.plans.partitioning import by_hash, by_range
from exkit.plans.spec import ShuffleSpec
from exkit.strategies import STRATEGIES, shuffle


def rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


@pytest.fixture(scope="module")
def recs(tables):
    return w.order_records(tables)


@pytest.mark.parametrize("strategy", STRATEGIES[1:])
def test_sorts_agree(recs, strategy):
    assert rows(shuffle(recs, w.sort_spec().with_(strategy=strategy))) == rows(shuffle(recs, w.sort_spec()))


@pytest.mark.parametrize(("r", "workers", "per_round"), [(1, 4, 16), (7, 3, 5), (2, 8, 1)])
def test_odd_layouts_agree(recs, r, workers, per_round):
    spec = w.sort_spec(r).with_(workers=workers, round_maps=per_round, merge_factor=3)
    want = rows(shuffle(recs, spec))
    assert rows(shuffle(recs, spec.with_(strategy="push_inline"))) == want == rows(shuffle(recs, spec.with_(strategy="premerge")))
    assert rows(shuffle(recs, spec.with_(strategy="push_lean"))) == want


@pytest.mark.parametrize("strategy", STRATEGIES)
def test_empty_and_single_key(spark, recs, strategy):
    assert shuffle(recs.where(F.lit(False)), w.sort_spec().with_(strategy=strategy)).count() == 0
    same = spark.createDataFrame([(i % 4, "k", 1) for i in range(40)] + [(0, None, 1)], "map_id int, k string, n int")
    spec = ShuffleSpec(4, lambda d: by_hash(d, ["k"], 4, portable=True), 4, round_maps=2, workers=2, strategy=strategy)
    got = shuffle(same, spec)
    assert got.count() == 41 and got.select("reduce_id").distinct().count() <= 2


def test_partial_aggregates_agree(tables):
    want = rows(shuffle(w._by_supplier(tables), w.agg_spec().with_(merge_fn=None)))
    for s in STRATEGIES[1:]:
        assert rows(shuffle(w._by_supplier(tables), w.agg_spec().with_(strategy=s))) == want


def exchanges(df):
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange ")


def test_exchange_counts(recs, spark):
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        spec = w.sort_spec().with_(reduce_fn=None)
        assert exchanges(shuffle(recs, spec)) == 1
        assert exchanges(shuffle(recs, spec.with_(strategy="premerge"))) == 1
        assert exchanges(shuffle(recs, spec.with_(strategy="push_inline"))) == 2
        assert exchanges(shuffle(recs, spec.with_(strategy="push_lean"))) == 0
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")


def test_micro_ledger(spark):
    base = spark.range(12).select((F.col("id") / 3).cast("int").alias("map_id"), (F.col("id") % 3).cast("int").alias("reduce_id"))
    placed = base.withColumns({"merge_id": (F.col("map_id") / 2).cast("int"), "round": (F.col("map_id") / 2).cast("int"), "worker": (F.col("reduce_id") * 2 / 3).cast("int")})
    size = lambda *a, **k: sorted(r["n_rows"] for r in metrics.ledger(placed, "s", *a, size=F.lit(1), **k).collect())
    assert size("map_id", "reduce_id") == [1] * 12
    assert size("merge_id", "reduce_id") == [2] * 6
    assert size("map_id", "worker", round_col="round") == [1] * 4 + [2] * 4
    assert size("worker", "reduce_id", round_col="round") == [2] * 6


def test_ranges_are_disjoint_and_ordered(recs):
    got = by_range(recs, "key", 5).groupBy("reduce_id").agg(F.min("key").alias("lo"), F.max("key").alias("hi")).orderBy("reduce_id").collect()
    assert all(a["hi"] < b["lo"] for a, b in zip(got, got[1:], strict=False))
    bounds = ["4", "8", "c"]
    assert {r["reduce_id"] for r in by_range(recs, "key", 4, bounds).select("reduce_id").distinct().collect()} == {0, 1, 2, 3}


def test_stream_rounds_publishes_and_stops(tables):
    seen = []
    spec = w.agg_spec().with_(strategy="stream_rounds")
    from exkit.strategies import stream_rounds

    stream_rounds(w._by_supplier(tables), spec, on_partial=lambda i, s: seen.append((i, s.agg(F.sum("n")).first()[0])), until=lambda i, s: i == 2)
    assert [i for i, _ in seen] == [0, 1, 2] and seen[0][1] < seen[1][1] < seen[2][1]


def test_timed_best_effort_merge_loses_nothing(tables):
    spec, src = w.agg_spec(), w._by_supplier(tables)
    want = rows(shuffle(src, spec))
    for timeout in (0.0, 60.0):
        merged, raw = resilience.best_effort_merge(src, spec, timeout_s=timeout)
        assert rows(resilience.reduce_best_effort(merged, raw, spec)) == want


def test_missing_round_is_found(spark):
    manifest = spark.createDataFrame([(0, 1, "a"), (2, 1, "b")], "round int, reduce_id int, path string")
    assert resilience.missing_rounds(manifest, 4) == [1, 3]


def test_maps_run_while_the_round_before_is_merged(spark, recs, tmp_path):
    """With an input for each round, and a merge slowed down, the next maps start before the merge ends; every input row is read once."""
    from time import monotonic, sleep

    from exkit.strategies.push import push

    spec = w.sort_spec().with_(strategy="push_lean")
    want = rows(shuffle(recs, spec.with_(strategy="pull")))
    recs.withColumn("own", F.floor(F.col("map_id") / spec.round_maps)).write.partitionBy("own").parquet(f"{tmp_path}/in")
    said, seen = [], spark.sparkContext.accumulator(0)

    def tell(what, i):
        said.append((monotonic(), what, i))
        if what == "merge":
            sleep(0.3)

    def read(i):
        seen.add(spark.read.parquet(f"{tmp_path}/in/own={i}").count())
        return spark.read.schema(recs.schema).parquet(f"{tmp_path}/in/own={i}")

    assert rows(push(recs, spec.with_(round_input=read), on_event=tell)) == want and seen.value == len(want)
    at = {(what, i): t for t, what, i in said}
    rounds = -(-spec.m // spec.round_maps)
    assert all(at["map", i + 1] < at["merged", i] for i in range(rounds - 1))
    assert all(at["merged", i] < at["merge", i + 1] for i in range(rounds - 1))  # one merge is out at a time


def test_rounds_read_their_input_once(spark, recs):
    """Without it, one job maps all: the input is scanned once, whatever the number of rounds."""
    read = spark.sparkContext.accumulator(0)

    def counted(batches):
        for b in batches:
            read.add(b.num_rows)
            yield b

    once = recs.mapInArrow(counted, recs.schema)
    assert shuffle(once, w.sort_spec().with_(strategy="push_lean")).count() == read.value
    read.value = 0
    assert shuffle(once, w.sort_spec().with_(strategy="stream_rounds")).count() == read.value
