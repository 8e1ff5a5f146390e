import time
from concurrent.futures import CancelledError

import pytest
from pyspark.sql import functions as F

from exkit.operators import online, randomize, resilience, skew
from exkit.plans import control
from exkit.plans.partitioning import sampled_bounds
from exkit.sources import records


def slow(spark, seconds):
    def run(batches):
        time.sleep(seconds)
        yield from batches

    return spark.range(0, 4, 1, 1).mapInArrow(run, "id long")


def test_submit_wait_then_fetch(spark):
    a, b = control.submit(spark, lambda: spark.range(5)), control.submit(spark, lambda: spark.range(7))
    done, pending = control.wait([a, b], k=2, timeout=30)
    assert len(done) == 2 and not pending
    assert control.fetch(a.then(lambda df: df.where("id > 2")), "rows") and control.fetch(b).num_rows == 7
    assert len(list(control.fetch(control.FrameFuture(spark.range(3)).then(lambda d: d.where("id < 2")), "iter"))) == 2


def test_cancel_stops_a_job(spark):
    f = control.submit(spark, lambda: slow(spark, 30).count())
    time.sleep(2)
    start = time.time()
    assert control.cancel(spark, f)
    with pytest.raises(CancelledError):
        f.result(20)
    assert time.time() - start < 20


def test_first_of_takes_the_faster_copy(spark):
    def attempt(i):
        return (i, slow(spark, 25 if i == 0 else 0).count())

    start = time.time()
    assert resilience.first_of(spark, attempt, patience_s=1.0) == (1, 4)
    assert time.time() - start < 20


def test_rounds_keep_one_merge_in_flight(spark):
    live, most = [], []

    def merge(i, mapped):
        live.append(i)
        most.append(len(live))
        time.sleep(0.2)
        live.remove(i)
        return mapped

    assert control.Rounds(spark).run(range(4), lambda i: i * 10, merge) == [0, 10, 20, 30]
    assert max(most) == 1


def test_loop_and_limiter():
    assert list(control.loop(lambda s: (s or 0) + 1, lambda s: s == 3)) == [1, 2, 3]
    assert control.Limiter(1).run(lambda: 5) == 5


def test_split_respects_limit_or_is_one_key(spark):
    df = spark.range(2000).select((F.col("id") % 50).alias("k"), F.lit("0").alias("part")).union(spark.range(500).select(F.lit(999).cast("long"), F.lit("1")))
    got = skew.split_oversized(df, "part", "k", 300).groupBy("part_path").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("k").alias("keys")).collect()
    assert sum(r["n"] for r in got) == 2500
    assert all(r["n"] <= 300 or r["keys"] == 1 for r in got)
    rows = skew.split_oversized(df.withColumn("id", F.monotonically_increasing_id()), "part", "k", 300, row_id=F.col("id"))
    assert max(r["n"] for r in rows.groupBy("part_path").agg(F.count(F.lit(1)).alias("n")).collect()) <= 300


def test_salting_equals_plain(tables):
    sums = {"n": F.count(F.lit(1))}
    line = tables.lineitem
    plain = sorted(map(tuple, line.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n")).collect()))
    assert sorted(map(tuple, skew.salted_agg(line, ["l_returnflag"], sums, F.col("l_orderkey")).collect())) == plain


def test_permutations(tables):
    ids = tables.embeddings.select("vec_id", "label")
    order = lambda e, s=1: [r["vec_id"] for r in randomize.full_positions(ids, "vec_id", s, e).orderBy("pos").collect()]
    a, b = order(0), order(1)
    assert sorted(a) == sorted(b) == sorted(r["vec_id"] for r in ids.collect()) and a != b and a == order(0)
    numbered = randomize.numbered(ids, ["vec_id"], "label", "ordinal")
    w = randomize.windowed(numbered, "vec_id", 1, 0, "ordinal", 45).collect()
    assert all(r["ordinal"] // 45 == r["pos"] // 45 for r in w) and len({r["pos"] for r in w}) == len(w)
    buffered = randomize.buffered(numbered.coalesce(1), 1, 0, 20).select("vec_id").collect()
    assert sorted(r["vec_id"] for r in buffered) == sorted(a)


def test_online_partials_end_in_the_batch_answer(tables):
    run = online.aggregate(online.rounds_by_hash(tables.events, "event_id", 10), ["event_type"], {"n": F.count(F.lit(1))})
    last = run.agg(F.max("round")).first()[0]
    got = sorted((r["event_type"], r["n"]) for r in run.where(F.col("round") == last).collect())
    assert got == sorted(map(tuple, tables.events.groupBy("event_type").count().collect()))


def test_records(spark):
    df = records.generate(spark, 100, parts=2)
    r = df.first()
    assert len(r["key"]) == 10 and len(r["payload"]) == 90
    assert len(sampled_bounds(spark.range(1000), "id", 4)) == 3
