"""SQL surface: the tables as views and the partitioner as a SQL function."""

from __future__ import annotations

from pyspark.sql import SparkSession

from exkit.tables import NAMES, table

BUCKET = "CREATE OR REPLACE TEMPORARY FUNCTION exkit_bucket(k STRING, r INT) RETURNS INT RETURN CAST(CAST(conv(substr(md5(k), 1, 8), 16, 10) AS BIGINT) % r AS INT)"


def register(spark: SparkSession, sf_dir: str) -> None:
    """Temporary views of all tables, and ``exkit_bucket(key, r)``: the reduce partition of a key, inlined by the optimizer."""
    for name in NAMES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)
    spark.sql(BUCKET)
