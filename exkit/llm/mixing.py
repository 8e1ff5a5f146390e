"""Mixing sources to target weights.

Every document gets a hash-random key; inside its source the documents are
ordered by that key. The order is never materialised by one task: the first
digits of the key form range buckets, the bucket totals are summed into
offsets, and a running sum inside each (source, bucket) completes the prefix
sum of word counts. A document's share of its source's budget then follows from
its prefix alone, epochs included. Only DataFrame functions are used.

Defined results: null or empty text has size 0 and takes 0 words; a null source
is a source of its own, last in order; repeated rows are separate documents
(rows alike in id and size may swap places, which changes no result); an empty
table gives an empty plan; other columns are ignored, or carried by
``mixed_documents``. Names that start with ``mix_`` are reserved in the input
of ``mixed_documents``.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from exkit.llm.text import WORD, count_words
from exkit.staging import stage

#: Hex digits of the key that name a range bucket: 4096 buckets in each source.
BUCKET_DIGITS = 3


def _group(source: Column) -> Column:
    """A key without nulls that keeps the null source apart from every text."""
    return F.coalesce(F.concat(F.lit("="), source), F.lit(""))


def _keyed(docs: DataFrame, seed: str) -> DataFrame:
    key = F.md5(F.concat(F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    return docs.withColumns({"mix_group": _group(F.col("source")), "mix_key": key, "mix_bucket": F.substring(key, 1, BUCKET_DIGITS)})


def source_targets(sizes: DataFrame, weights: Sequence[int] = (3, 1, 2), share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """Targets of (mix_group, source, source_size): one row per source, the catalogue of sources.

    ``share`` times all words is dealt by weight; no target passes ``cap`` times
    its source's size. The level of that water filling is found in closed form:
    in order of size per weight the saturated sources are a prefix.
    """
    order = W.orderBy(F.col("source").asc_nulls_last())
    cycle = F.array(*[F.lit(int(w)) for w in weights])
    by_ratio = W.orderBy("mix_ratio", "mix_rank")
    ahead, behind = by_ratio.rowsBetween(W.unboundedPreceding, -1), by_ratio.rowsBetween(0, W.unboundedFollowing)
    everything = W.partitionBy()
    level = (share * F.sum("source_size").over(everything) - F.coalesce(F.sum("mix_cap").over(ahead), F.lit(0.0))) / F.sum("mix_weight").over(behind)
    return (
        sizes.withColumn("mix_rank", F.row_number().over(order))
        .withColumn("mix_weight", F.element_at(cycle, ((F.col("mix_rank") - 1) % len(weights) + 1).cast("int")))
        .withColumn("mix_cap", F.lit(float(cap)) * F.col("source_size"))
        .withColumn("mix_ratio", F.col("mix_cap") / F.col("mix_weight"))
        .withColumn("mix_level", level)
        .withColumn("mix_level", F.max(F.when(F.col("mix_ratio") > F.col("mix_level"), F.col("mix_level"))).over(everything))
        .withColumn("target", F.when(F.col("mix_ratio") > F.col("mix_level"), F.col("mix_level") * F.col("mix_weight")).otherwise(F.col("mix_cap")))
        .select("mix_group", "source_size", "target")
    )


def _offsets(sized: DataFrame, **targets) -> DataFrame:
    """For each (mix_group, mix_bucket): the words before it in its source, and the source's size and target."""
    buckets = sized.groupBy("mix_group", "mix_bucket", "source").agg(F.sum("size").alias("mix_words"))
    sources = buckets.groupBy("mix_group", "source").agg(F.sum("mix_words").alias("source_size"))
    before = W.partitionBy("mix_group").orderBy("mix_bucket").rowsBetween(W.unboundedPreceding, -1)
    return (
        buckets.withColumn("mix_before", F.coalesce(F.sum("mix_words").over(before), F.lit(0)))
        .drop("mix_words", "source")
        .join(source_targets(sources, **targets), "mix_group")
    )


def _taken(keyed: DataFrame, offsets: DataFrame) -> DataFrame:
    """Adds source_size, target, mix_epochs (whole repeats) and mix_rest (words of one more, cut repeat)."""
    within = W.partitionBy("mix_group", "mix_bucket").orderBy("mix_key", "doc_id", "size").rowsBetween(W.unboundedPreceding, -1)
    budget = F.floor("target")
    start = F.col("mix_before") + F.col("mix_start")
    over = F.when(F.col("source_size") > 0, budget - F.col("mix_epochs") * F.col("source_size")).otherwise(0)
    return (
        keyed.withColumn("mix_start", F.coalesce(F.sum("size").over(within), F.lit(0)))
        .join(offsets, ["mix_group", "mix_bucket"])
        .withColumn("mix_epochs", F.when(F.col("source_size") > 0, F.floor(budget / F.greatest(F.col("source_size"), F.lit(1)))).otherwise(0).cast("long"))
        .withColumn("mix_rest", F.greatest(F.lit(0), F.least(F.col("size"), over - start)).cast("long"))
    )


def mixing_plan(docs: DataFrame, seed: str = "mix-", **targets) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, epochs, rest, taken.

    ``taken`` = ``epochs`` whole repeats plus ``rest`` words of a last repeat
    that the source's budget cuts; summed over a source it is floor(target).
    """
    sized = stage(_keyed(docs.select("doc_id", "source", count_words(F.col("text")).alias("size")), seed), "mix-sizes")
    return _taken(sized, _offsets(sized, **targets)).select(
        "doc_id", "source", "size", "source_size", "target",
        F.col("mix_epochs").alias("epochs"), F.col("mix_rest").alias("rest"),
        (F.col("mix_epochs") * F.col("size") + F.col("mix_rest")).alias("taken"),
    )


def mixed_documents(docs: DataFrame, seed: str = "mix-", **targets) -> DataFrame:
    """The mix itself, with the columns of ``docs``: a row for each repeat; the repeat that a budget cuts ends after its last word taken.

    ``n_chars``, where present, follows a cut text.
    """
    columns = docs.columns
    held = [c for c in columns if c not in ("doc_id", "source")]
    packed = docs.select("doc_id", "source", count_words(F.col("text")).alias("size"), F.struct(*[F.col(c) for c in held]).alias("mix_row"))
    offsets = stage(_offsets(_keyed(packed.select("doc_id", "source", "size"), seed), **targets), "mix-offsets")
    copies = F.col("mix_epochs").cast("int") + (F.col("mix_rest") > 0).cast("int")
    cut = (F.col("mix_rest") > 0) & (F.col("mix_rest") < F.col("size")) & (F.col("mix_copy") > F.col("mix_epochs"))
    out = _taken(_keyed(packed, seed), offsets).where(copies > 0).select("*", F.explode(F.sequence(F.lit(1), copies)).alias("mix_copy"))
    words = F.slice(F.regexp_extract_all("mix_row.text", F.lit(f"(?s)(.*?{WORD})"), 1), F.lit(1), F.col("mix_rest").cast("int"))
    out = out.withColumn("mix_text", F.when(cut, F.array_join(words, "")).otherwise(F.col("mix_row.text")))
    own = {"doc_id": F.col("doc_id"), "source": F.col("source"), "text": F.col("mix_text")}
    if "n_chars" in columns:
        own["n_chars"] = F.when(cut, F.length("mix_text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("mix_row.n_chars"))
    return out.select(*[own.get(c, F.col("mix_row").getField(c)).alias(c) for c in columns])


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return mixing_plan(docs).select("doc_id", "size", "source_size", "target", "taken", "epochs", "rest")


SQL = r"""
WITH sized AS (
  SELECT doc_id, source, md5('mix-' || coalesce(CAST(doc_id AS VARCHAR), '')) AS k,
         coalesce(CAST(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) AS BIGINT), 0) AS size
  FROM documents),
per_source AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source),
ranked AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) AS rnk FROM per_source),
weighted AS (
  SELECT *, CASE (rnk - 1) % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS w, 2.0::DOUBLE * source_size AS cap FROM ranked),
rated AS (SELECT *, cap / w AS ratio FROM weighted),
levels AS (
  SELECT *, (1.5::DOUBLE * (SELECT sum(source_size) FROM per_source)
     - coalesce(sum(cap) OVER (ORDER BY ratio, rnk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0))
     / sum(w) OVER (ORDER BY ratio, rnk ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS lv
  FROM rated),
level AS (SELECT max(lv) AS lv FROM levels WHERE ratio > lv),
targets AS (
  SELECT l.source, l.source_size, CASE WHEN l.ratio > v.lv THEN v.lv * l.w ELSE l.cap END AS target
  FROM levels l CROSS JOIN level v),
placed AS (
  SELECT s.doc_id, s.size, t.source_size, t.target, CAST(floor(t.target) AS BIGINT) AS budget,
    coalesce(CAST(sum(s.size) OVER (PARTITION BY s.source ORDER BY s.k, s.doc_id, s.size
      ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS BIGINT), 0) AS start
  FROM sized s JOIN targets t ON s.source IS NOT DISTINCT FROM t.source),
dealt AS (
  SELECT *, CASE WHEN source_size > 0 THEN budget // source_size ELSE 0 END AS epochs FROM placed),
cut AS (
  SELECT *, CASE WHEN source_size > 0 THEN greatest(0, least(size, budget - epochs * source_size - start)) ELSE 0 END AS rest FROM dealt)
SELECT doc_id, size, source_size, CAST(target AS DOUBLE) AS target, CAST(epochs * size + rest AS BIGINT) AS taken,
  CAST(epochs AS BIGINT) AS epochs, CAST(rest AS BIGINT) AS rest
FROM cut
"""
