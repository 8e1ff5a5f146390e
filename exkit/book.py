"""Registers queries together with the SQL they are held against."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from exkit.tables import NAMES, table


class Tables:
    """The given tables as attributes: ``t.orders``."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    def __getattr__(self, name: str) -> DataFrame:
        if name not in NAMES:
            raise AttributeError(name)
        return table(self.spark, self.sf_dir, name)

    def sql(self, text: str, **frames: DataFrame) -> DataFrame:
        """Spark SQL over the tables named in braces."""
        used = {n: getattr(self, n) for n in NAMES if "{" + n + "}" in text}
        return self.spark.sql(text, **used, **frames)


class Book:
    def __init__(self):
        self.queries: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
        self.sql: dict[str, str] = {}

    def add(self, name: str, fn: Callable[[Tables], DataFrame], sql: str | None = None) -> None:
        self.queries[name] = lambda spark, sf_dir: fn(Tables(spark, sf_dir))
        if sql:
            self.sql[name] = sql

    def query(self, sql: str | None = None, name: str | None = None):
        def keep(fn):
            self.add(name or fn.__name__, fn, sql)
            return fn

        return keep

    def both(self, name: str, text: str, spark_text: str | None = None) -> None:
        """One statement that both engines understand; table names stand in braces."""
        plain = text
        for n in NAMES:
            plain = plain.replace("{" + n + "}", n)
        self.add(name, lambda t: t.sql(spark_text or text), plain)
