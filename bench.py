"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one JSON line.

``python bench.py --shapes`` prints the ratios and counts that stand for the
published shapes instead: blocks, retention, partial answers, mixing, writes.
``python bench.py --systems`` runs what needs sessions of its own: compression,
processes against threads, stores on disk and in memory, and a lost task.
"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

HEADLINE = [
    "record_sort_pull", "record_sort_premerge", "record_sort_push_inline", "record_sort_push_lean", "record_sort_push_durable", "record_sort_stream_rounds", "record_sort_inmemory",
    "supplier_totals_pull", "supplier_totals_premerge", "supplier_totals_push_lean", "ledger_summary", "salted_agg", "salted_join", "skew_split_rows",
    "online_agg_rounds", "online_kl_hash_users", "random_shuffle_full", "random_shuffle_windowed", "mixing_quality", "join_multiway_star", "join_asof", "win_sessionize",
]


def session() -> SparkSession:
    cpus = os.environ.get("BENCH_CPUS", "8")
    conf = {"spark.sql.shuffle.partitions": cpus, "spark.driver.memory": "8g", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.session.timeZone": "UTC"}
    spark = SparkSession.builder.master(f"local[{cpus}]").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def timed(thunk) -> float:
    start = time.perf_counter()
    thunk()
    return round(time.perf_counter() - start, 3)


def run(df) -> None:
    df.write.format("noop").mode("overwrite").save()


def fuse(spark, sf: str) -> dict:
    """Small writes against fused ones: the same rows as many files or as few."""
    from exkit.staging import new_path

    docs = spark.read.parquet(f"{sf}/documents.parquet").persist()
    docs.count()
    many = timed(lambda: docs.repartition(200).write.parquet(new_path(spark, "many")))
    few = timed(lambda: docs.repartition(4).write.parquet(new_path(spark, "few")))
    return {"unfused_s": many, "fused_s": few, "ratio": round(many / few, 2)}


def prefetch(spark, sf: str) -> dict:
    """A consumer that works while the next partition is fetched, or not."""
    rows = spark.read.parquet(f"{sf}/embeddings.parquet").repartition(16, "vec_id")

    def consume(ahead: bool) -> None:
        for i, _ in enumerate(rows.toLocalIterator(prefetchPartitions=ahead)):
            if i % 100 == 0:
                time.sleep(0.02)

    consume(True)
    on, off = timed(lambda: consume(True)), timed(lambda: consume(False))
    return {"on_s": on, "off_s": off, "gain": round(1 - on / off, 3)}


def shapes(spark, sf: str) -> dict:
    from exkit import registry
    from exkit.plans import cost

    q = lambda name: registry.QUERIES[name](spark, sf)
    growth = {r["part"]: r["n_blocks"] for r in q("block_growth").collect()}
    regular = timed(lambda: run(q("supplier_totals_pull")))
    rounds = timed(lambda: run(q("supplier_totals_stream_rounds")))
    accuracy = [r.asDict() for r in q("train_embeddings").where(F.col("epoch").isin(0, 19)).collect()]
    return {
        "blocks_when_scale_doubles": round(growth[1] / growth[2], 2),
        "blocks_by_strategy": {r["stage"]: r["n_blocks"] for r in q("ledger_summary").collect()},
        "durable_over_lean": cost.disk_traffic("push_durable", 1.0)["amplification"] / cost.disk_traffic("push_lean", 1.0)["amplification"],
        "streaming_over_regular": round(rounds / regular, 2),
        "first_round_under_8_percent": q("online_time_to_error").first()["round"],
        "mixing": [r.asDict() for r in q("mixing_quality").collect()],
        "accuracy_first_and_last_epoch": accuracy,
        "small_writes": fuse(spark, sf),
        "prefetch": prefetch(spark, sf),
    }


#: A sort in a session of its own: prints seconds and, from the event log, shuffle bytes.
CHILD = """
import json, sys, tempfile, time
from pathlib import Path
sys.path.insert(0, {root!r})
from pyspark.sql import SparkSession
from exkit import profiles
from exkit.operators.resilience import flaky
from exkit.plans import metrics
from exkit.sources.records import generate
logs = tempfile.mkdtemp()
conf = dict(profiles.EVENT_LOG, **{conf!r}) | {{"spark.eventLog.dir": "file://" + logs, "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.shuffle.partitions": "16"}}
spark = SparkSession.builder.master({master!r}).config(map=conf).getOrCreate()
spark.sparkContext.setLogLevel("ERROR")
df = generate(spark, {n}, parts=16)
if {level!r}:
    from exkit.plans.control import LEVELS
    df = df.persist(LEVELS[{level!r}])
df.limit(10).count()
start = time.perf_counter()
out = df.repartitionByRange(16, "key").sortWithinPartitions("key")
out = flaky(out) if {fail} else out
out.write.format("noop").mode("overwrite").save()
seconds = time.perf_counter() - start
spark.stop()
print(json.dumps({{"seconds": round(seconds, 2), **metrics.event_totals(p for p in Path(logs).iterdir() if p.is_file())}}))
"""


def child(master: str = "local[4]", conf: dict | None = None, n: int = 300_000, level: str = "", fail: bool = False) -> dict:
    import subprocess

    code = CHILD.format(root=os.path.dirname(os.path.abspath(__file__)), master=master, conf=conf or {}, n=n, level=level, fail=fail)
    done = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, timeout=180)
    lines = done.stdout.strip().splitlines()
    return json.loads(lines[-1]) if done.returncode == 0 and lines else {"error": done.stderr[-300:]}


def systems() -> dict:
    from exkit import profiles

    on, off = child(conf=profiles.NATIVE_PULL), child(conf=profiles.NATIVE_PULL_UNCOMPRESSED)
    calm, hurt = child("local[4,4]"), child("local[4,4]", fail=True)
    return {
        "compression": {"saved": round(1 - on["shuffle_written"] / off["shuffle_written"], 3), "on_s": on["seconds"], "off_s": off["seconds"]},
        "recovery": {"without_s": calm["seconds"], "with_lost_task_s": hurt["seconds"], "failed_tasks": hurt["failed"]},
        "topology": {m: child(m, {"spark.executor.memory": "800m"})["seconds"] for m in ("local[4]", "local-cluster[2,2,1024]", "local-cluster[4,1,1024]")},
        "store": {level: child(level=level)["seconds"] for level in ("memory", "memory_disk", "disk")},
        "prefetch": {"on_s": on["seconds"], "off_s": child(conf=profiles.NATIVE_PULL | profiles.NO_PREFETCH)["seconds"]},
    }


def main() -> None:
    if "--systems" in sys.argv:
        print(json.dumps(systems()))
        return
    spark, sf = session(), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    if "--shapes" in sys.argv:
        print(json.dumps(shapes(spark, sf)))
        return
    from exkit import registry

    run(registry.QUERIES["scan_parquet"](spark, sf))  # warm-up
    seconds = {name: timed(lambda name=name: run(registry.QUERIES[name](spark, sf))) for name in HEADLINE}
    print(json.dumps({"metric": "headline queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": sf}))


if __name__ == "__main__":
    main()
