"""Records for sorting: fixed-length keys, generated, written, read and validated."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

KEY_BYTES, RECORD_BYTES = 10, 100


def hex_key(pk: Column) -> Column:
    """Ten bytes as twenty hexadecimal digits, uniform over the key space."""
    return F.substring(F.md5(pk.cast("string")), 1, 2 * KEY_BYTES)


def record_keys(df: DataFrame, pk: str) -> DataFrame:
    return df.select(hex_key(F.col(pk)).alias("key"), F.col(pk))


def generate(spark: SparkSession, n: int, seed: int = 0, parts: int | None = None) -> DataFrame:
    """``n`` binary records: key of 10 bytes, payload of 90; a function of the row number and seed only."""
    ids = spark.range(0, n, 1, parts) if parts else spark.range(n)
    text = F.md5(F.concat_ws(":", F.lit(seed), "id"))
    body = F.concat(text, F.md5(F.concat(text, F.lit("a"))), F.md5(F.concat(text, F.lit("b"))))
    return ids.select(F.unhex(F.substring(text, 1, 20)).alias("key"), F.encode(F.substring(body, 1, 90), "UTF-8").alias("payload"))


def validate(sorted_df: DataFrame, key: str = "key", checksum_of: str | None = None) -> DataFrame:
    """n, checksum, inversions and partitions of a sorted result that has ``reduce_id``.

    Order is checked inside each partition by its neighbours and between
    partitions by their least and greatest keys, one row a partition.
    """
    from pyspark.sql import Window as W

    ordered = W.partitionBy("reduce_id").orderBy("pos")
    total = F.crc32((F.col(checksum_of) if checksum_of else F.col(key)).cast("string"))
    inside = sorted_df.withColumn("bad", (F.lag(key).over(ordered) > F.col(key)).cast("int"))
    parts = inside.groupBy("reduce_id").agg(F.count(F.lit(1)).alias("n"), F.sum(total).alias("s"), F.coalesce(F.sum("bad"), F.lit(0)).alias("bad"), F.min(key).alias("lo"), F.max(key).alias("hi"))
    parts = parts.withColumn("cross", F.coalesce((F.lag("hi").over(W.orderBy("reduce_id")) > F.col("lo")).cast("int"), F.lit(0)))
    return parts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.coalesce(F.sum("s"), F.lit(0)).alias("checksum"), F.coalesce(F.sum(F.col("bad") + F.col("cross")), F.lit(0)).alias("inversions"), F.count(F.lit(1)).alias("partitions"))


def read_binary(spark: SparkSession, path: str) -> DataFrame:
    """Files of 100-byte records; whole-file reads, so files should be of block size."""
    files = spark.read.format("binaryFile").load(path).select("content")
    at = F.explode(F.sequence(F.lit(0), (F.length("content") / RECORD_BYTES).cast("int") - 1)).alias("i")
    rows = files.where(F.length("content") >= RECORD_BYTES).select("content", at)
    cut = lambda start, n: F.substring(F.col("content"), F.col("i") * RECORD_BYTES + start, F.lit(n))
    return rows.select(cut(1, KEY_BYTES).alias("key"), cut(1 + KEY_BYTES, RECORD_BYTES - KEY_BYTES).alias("payload"))


class _Range(InputPartition):
    def __init__(self, start: int, end: int):
        super().__init__(start)
        self.start, self.end = start, end


class _RecordReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.parts = int(options.get("rows", "1000")), int(options.get("parts", "4"))

    def partitions(self):
        step = -(-self.n // self.parts) or 1
        return [_Range(i, min(i + step, self.n)) for i in range(0, max(1, self.n), step)]

    def read(self, part):
        import hashlib

        import pyarrow as pa

        for i in range(part.start, part.end, 8192):
            ids = range(i, min(i + 8192, part.end))
            keys = [hashlib.md5(str(k).encode()).hexdigest()[:20] for k in ids]
            yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(list(ids), pa.int64())], names=["key", "pk"])


class RecordSource(DataSource):
    """``spark.read.format("exkit_records").option("rows", n)``: generated keys, one task per range."""

    @classmethod
    def name(cls) -> str:
        return "exkit_records"

    def schema(self):
        return "key string, pk bigint"

    def reader(self, schema) -> DataSourceReader:
        return _RecordReader(self.options)
