"""Session settings that stand for a baseline or a remedy which lives in Spark itself.

They are fixed when a session starts; give them to the builder or to
``spark-submit``. Nothing in the package changes a running session.
"""

from __future__ import annotations

#: Spark's own sort shuffle, as the native pull baseline runs it; ``off`` sends blocks uncompressed.
NATIVE_PULL = {"spark.sql.adaptive.enabled": "false", "spark.shuffle.compress": "true"}
NATIVE_PULL_UNCOMPRESSED = NATIVE_PULL | {"spark.shuffle.compress": "false", "spark.shuffle.spill.compress": "false"}

#: The external push service: needs YARN and the external shuffle service with its merge manager.
PUSH_SERVICE = {
    "spark.shuffle.push.enabled": "true",
    "spark.shuffle.service.enabled": "true",
    "spark.serializer": "org.apache.spark.serializer.KryoSerializer",
    "spark.io.encryption.enabled": "false",
}

#: Duplicates of late tasks; not active on local masters, where ``resilience.first_of`` duplicates jobs.
SPECULATION = {"spark.speculation": "true", "spark.speculation.multiplier": "1.5", "spark.speculation.quantile": "0.75"}

#: Shuffle files outlive their executor.
DECOMMISSION = {"spark.decommission.enabled": "true", "spark.storage.decommission.enabled": "true", "spark.storage.decommission.shuffleBlocks.enabled": "true"}

#: Rounds and merges of ``plans.control`` in pools of their own.
FAIR_POOLS = {"spark.scheduler.mode": "FAIR"}

#: Splitting of skewed joins and rebalances by Spark.
AQE_SKEW = {"spark.sql.adaptive.skewJoin.enabled": "true", "spark.sql.adaptive.optimizeSkewsInRebalancePartitions.enabled": "true"}

#: Fewest bytes in flight: a reducer that hardly prefetches.
NO_PREFETCH = {"spark.reducer.maxSizeInFlight": "1m", "spark.reducer.maxReqsInFlight": "1"}

#: Event logs that ``metrics.event_totals`` reads.
EVENT_LOG = {"spark.eventLog.enabled": "true", "spark.eventLog.compress": "false", "spark.eventLog.rolling.enabled": "false"}
