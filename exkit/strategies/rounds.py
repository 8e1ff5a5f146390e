"""Map outputs by round, each input row read and mapped once.

A spec that can name the input of a round (``round_input``, say its files) gets a
map job per round, so that the maps of one round run while the one before is
merged. Otherwise one job maps everything and writes a folder per round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from exkit.plans.spec import ShuffleSpec
from exkit.staging import delete, new_path


class MapRounds:
    """Rows whose map_id is null or outside the rounds belong to no round's input and count with the last."""

    def __init__(self, df: DataFrame, spec: ShuffleSpec, rounds: int):
        self.spark, self.spec, self.rounds = df.sparkSession, spec, rounds
        self.root, self.mapped, self._written = new_path(self.spark, "maps"), spec.mapped(df), False

    def _path(self, i: int) -> str:
        return f"{self.root}/exkit_round={i}"

    def __call__(self, i: int) -> DataFrame:
        """The map output of round ``i``, written before this returns."""
        if self.spec.round_input:
            self.spec.mapped(self.spec.round_input(i)).write.parquet(self._path(i))
        elif not self._written:
            of = F.floor(F.col(self.spec.map_col) / self.spec.round_maps).cast("int")
            own = F.when(of.between(0, self.rounds - 1), of).otherwise(F.lit(self.rounds - 1))
            self.mapped.withColumn("exkit_round", own).write.partitionBy("exkit_round").parquet(self.root)
            self._written = True
        files = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self._path(i))
        if not files.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(files):
            return self.spark.createDataFrame([], self.mapped.schema)
        return self.spark.read.schema(self.mapped.schema).parquet(self._path(i))

    def drop(self, i: int | None = None) -> None:
        """Forget a round's map output, or all of it."""
        delete(self.spark, [self.root if i is None else self._path(i)])
