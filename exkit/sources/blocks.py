"""Merged blocks on shared storage, and a reader with one task per reduce partition.

A block is a Parquet file below ``round=<i>/reduce_id=<k>``. Writers add their
file names to a manifest only when their job has committed; readers trust the
manifest alone, so attempts that were lost, cancelled or repeated leave nothing
behind that counts.
"""

from __future__ import annotations

import json
import os
import re
import uuid
from collections.abc import Iterator
from functools import reduce
from urllib.parse import unquote

import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from exkit.staging import new_path

FORMAT = "exkit_blocks"


#: Up to this many reduce partitions are read by a scan each, inside the JVM; more by ``BlockSource``.
SCANS = 128
Block = tuple[int, int, str]


def write_blocks(df: DataFrame, root: str, round_id: int) -> list[Block]:
    """Write one round's merged rows by reduce partition, each attempt in a folder of its own; returns its manifest (round, reduce_id, path), an entry a file.

    The entries are what the file system lists once the job has committed; no data are read for them.
    """
    path = f"{root}/round={round_id}/attempt={uuid.uuid4().hex}"
    df.write.partitionBy("reduce_id").parquet(path)
    files = df.sparkSession.read.schema(df.schema).parquet(path).inputFiles()
    return [(round_id, int(re.search(r"/reduce_id=(\d+)/", f)[1]), f) for f in sorted(files)]


class _Block(InputPartition):
    def __init__(self, reduce_id: int, paths: list[str]):
        super().__init__(reduce_id)
        self.reduce_id, self.paths = reduce_id, paths


class _BlockReader(DataSourceReader):
    def __init__(self, options: dict, schema):
        self.manifest, self.schema = options["manifest"], schema

    def partitions(self) -> list[InputPartition]:
        with open(self.manifest) as f:
            held = json.load(f)
        return [_Block(int(k), v) for k, v in sorted(held.items(), key=lambda x: int(x[0]))] or [_Block(-1, [])]

    def read(self, part: _Block) -> Iterator:
        want = to_arrow_schema(self.schema)
        for path in part.paths:
            for batch in pq.ParquetFile(path).iter_batches(batch_size=8192):
                ids = pa.array([part.reduce_id] * batch.num_rows, pa.int32())
                columns = [ids if f.name == "reduce_id" else batch.column(batch.schema.get_field_index(f.name)).cast(f.type) for f in want]
                yield pa.RecordBatch.from_arrays(columns, schema=want)


class BlockSource(DataSource):
    """Reads the blocks of a manifest, a reduce partition per task and without an exchange."""

    @classmethod
    def name(cls) -> str:
        return FORMAT

    def schema(self):
        raise ValueError("give the schema of the blocks")

    def reader(self, schema) -> DataSourceReader:
        return _BlockReader(self.options, schema)


def read_blocks(spark: SparkSession, manifest: list[Block], schema: StructType) -> DataFrame:
    """Rows of the manifest's blocks, a task for each reduce partition and no exchange.

    Up to SCANS partitions are scans of Spark's own reader; more, on a mounted
    file system, come through ``BlockSource``; on other stores they take one exchange.
    """
    held: dict[int, list[str]] = {}
    for _, k, path in manifest:
        held.setdefault(k, []).append(unquote(path))
    if not held:
        return spark.createDataFrame([], schema)
    inner = StructType([f for f in schema if f.name != "reduce_id"])
    names = [f.name for f in schema]
    if len(held) <= SCANS:
        scans = [spark.read.schema(inner).parquet(*paths).coalesce(1).withColumn("reduce_id", F.lit(k).cast("int")).select(*names) for k, paths in sorted(held.items())]
        return reduce(DataFrame.union, scans)
    if all(p.startswith("file:") for paths in held.values() for p in paths):
        spark.dataSource.register(BlockSource)
        listing = re.sub("^file:(//)?", "", new_path(spark, "manifest"))
        os.makedirs(os.path.dirname(listing), exist_ok=True)
        with open(listing, "w") as f:
            json.dump({k: [re.sub("^file:/*", "/", p) for p in paths] for k, paths in held.items()}, f)
        return spark.read.format(FORMAT).schema(schema).option("manifest", listing).load()
    by_file = spark.createDataFrame([(k, p) for k, paths in held.items() for p in paths], "reduce_id int, path string")
    rows = spark.read.schema(inner).parquet(*[p for paths in held.values() for p in paths]).withColumn("path", F.input_file_name())
    return rows.join(by_file.hint("shuffle_hash"), "path").select(*names).repartitionById(max(held) + 1, "reduce_id")
