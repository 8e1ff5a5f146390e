"""User-defined functions of every kind, used where the methods would use them. Arrow forms throughout."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import functions as F

from exkit.book import Book
from exkit.plans.partitioning import portable_hash
from exkit.sql import BUCKET

BOOK = Book()
query = BOOK.query


@query("SELECT o_orderkey, CAST(o_orderkey % 7 AS INTEGER) AS part FROM orders")
def udf_scalar(t):
    """A custom partitioner."""
    part = F.udf(lambda k: k % 7, "int", useArrow=True)
    return t.orders.select("o_orderkey", part("o_orderkey").alias("part"))


@query("SELECT p_partkey, upper(trim(p_name)) AS key FROM part")
def udf_arrow(t):
    """A key normaliser on whole columns."""

    def norm(x: pa.Array) -> pa.Array:
        return pc.utf8_upper(pc.utf8_trim_whitespace(x))

    return t.part.select("p_partkey", F.arrow_udf(norm, "string")("p_name").alias("key"))


@query("SELECT l_returnflag, max(l_quantity) - min(l_quantity) AS spread FROM lineitem GROUP BY 1")
def udaf_grouped(t):
    def spread(v: pd.Series) -> float:
        return float(v.max() - v.min())

    return t.lineitem.groupBy("l_returnflag").agg(F.pandas_udf(spread, "double")("l_quantity").alias("spread"))


@query("SELECT l_orderkey, l_quantity * 2 AS q FROM lineitem")
def udf_map_arrow(t):
    def twice(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pc.multiply(b.column(1), 2.0)], names=["l_orderkey", "q"])

    return t.lineitem.select("l_orderkey", "l_quantity").mapInArrow(twice, "l_orderkey long, q double")


@query("SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1")
def udf_grouped_arrow(t):
    def count(rows: pa.Table) -> pa.Table:
        return pa.table({"o_custkey": rows.column("o_custkey").slice(0, 1), "n": [rows.num_rows]})

    return t.orders.select("o_custkey").groupBy("o_custkey").applyInArrow(count, "o_custkey long, n long")


@query("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def udf_cogroup(t):
    def meet(a: pa.Table, b: pa.Table) -> pa.Table:
        return pa.table({"c_custkey": a.column("c_custkey"), "n": pa.array([b.num_rows] * a.num_rows, pa.int64())})

    left = t.customer.select("c_custkey").groupBy("c_custkey")
    return left.cogroup(t.orders.select("o_custkey").groupBy("o_custkey")).applyInArrow(meet, "c_custkey long, n long")


@query("SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents")
def udtf_split(t):
    @F.udtf(returnType="doc_id bigint, line string")
    class Lines:
        def eval(self, row):
            for line in row["text"].split("\n"):
                yield row["doc_id"], line

    t.spark.udtf.register("exkit_lines", Lines)
    return t.sql("SELECT * FROM exkit_lines(TABLE(SELECT doc_id, text FROM {documents}))")


@query("SELECT o_orderkey, CAST(('0x' || substr(md5(o_orderkey::VARCHAR), 1, 8))::BIGINT % 8 AS INTEGER) AS reduce_id FROM orders")
def udf_sql(t):
    """A SQL function, inlined by the optimizer: no Python at run time."""
    t.spark.sql(BUCKET)
    return t.sql("SELECT o_orderkey, exkit_bucket(CAST(o_orderkey AS STRING), 8) AS reduce_id FROM {orders}")


@query("SELECT o_orderkey, CAST(('0x' || substr(md5(o_orderkey::VARCHAR), 1, 8))::BIGINT % 8 AS INTEGER) AS reduce_id FROM orders")
def fn_portable_bucket(t):
    return t.orders.select("o_orderkey", (portable_hash(F.col("o_orderkey")) % 8).cast("int").alias("reduce_id"))
