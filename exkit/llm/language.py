"""Language identification by fusing evidence.

Four kinds of evidence meet in one posterior: the likelihood of the text under
hashed byte trigrams of each language, the language that markup declares, the
language that the address suggests, and the prior of the host. Host priors come
from a grouped aggregation of the texts' own posteriors, smoothed from the host
to its domain, to its suffix, to all. A noise hypothesis (all trigrams alike)
competes too; documents that it wins, that hold no letters, or whose best
language stays under ``min_confidence`` are rejected.

The text model is fitted on a bounded sample of labelled rows (``per_language``
texts of every label, chosen by hash); everything else covers all rows. What
reaches the driver is a row a label and at most BUCKETS counts for each.

Defined results: null and empty texts have no evidence and are rejected, their
language is the host's likeliest; null hosts share one prior; declarations and
addresses outside the known languages say nothing; texts of any length count
whole; repeated rows get equal rows; an empty table, or one without labels,
gives no languages: ``identify`` then returns no rows, and
``identified_documents`` all; other columns are carried untouched, whatever
their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, StructType

from exkit.staging import stage

BUCKETS = 1 << 15
#: Hosts up to this many are broadcast with their priors (8 bytes for each language); more are joined by a shuffle.
BROADCAST_HOSTS = 50_000


@dataclass(frozen=True)
class Fusion:
    per_language: int = 2000  # texts in the fitting sample
    weight: int = 64  # trigrams that a text's evidence is worth at most
    smoothing: float = 20.0  # documents that a parent's prior is worth
    declared_trust: float = 0.9
    address_trust: float = 0.8
    noise_prior: float = 1e-3
    min_confidence: float = 0.5


#: Letters of ASCII and all bytes of other characters; everything else counts as a space.
LETTER = np.array([97 <= i <= 122 or i >= 128 for i in range(256)])


def _grams(text: str) -> np.ndarray:
    """Hashes of the trigrams that hold two letters or more."""
    b = np.frombuffer(f" {text.lower()} ".encode("utf-8", "surrogatepass"), np.uint8)
    letter = LETTER[b]
    two = letter[:-2].astype(np.int8) + letter[1:-1] + letter[2:] >= 2
    b = np.where(letter, b, 32).astype(np.uint32)
    return ((b[:-2] * np.uint32(961) + b[1:-1] * np.uint32(31) * np.uint32(7) + b[2:] * np.uint32(8191)) & np.uint32(BUCKETS - 1))[two]


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    sums: dict[str, np.ndarray] = {}
    for b in batches:
        for lang, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
            one = sums.setdefault(lang, np.zeros(BUCKETS, np.int64))
            one += np.bincount(_grams(text.as_py() or ""), minlength=BUCKETS)
    for lang, one in sums.items():
        at = np.flatnonzero(one)
        yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at), pa.array(one[at])], names=["lang", "bucket", "n"])


@dataclass
class TextModel:
    languages: list[str]
    table: np.ndarray  # log likelihood of each bucket (rows) in each language


def fit_text_model(labelled: DataFrame, how: Fusion = Fusion()) -> TextModel:
    """Fit on (doc_id, text, lang); null labels are left out. Reads at most about ``per_language`` texts a language."""
    known = labelled.where("lang IS NOT NULL AND lang <> ''")
    sizes = known.groupBy("lang").count().collect()
    if not sizes:
        return TextModel([], np.zeros((BUCKETS, 0), np.float32))
    share = F.element_at(F.create_map(*[F.lit(v) for r in sizes for v in (r["lang"], min(1.0, how.per_language / r["count"]))]), F.col("lang"))
    draw = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) / float(1 << 20)
    sample = known.where(draw < share)
    counts = sample.select("lang", "text").mapInArrow(_counted, "lang string, bucket long, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toArrow()
    names = sorted(r["lang"] for r in sizes)
    table = np.full((BUCKETS, len(names)), 0.5)
    where = {x: i for i, x in enumerate(names)}
    np.add.at(table, (counts["bucket"].to_numpy(), np.array([where[x] for x in counts["lang"].to_pylist()], np.int64)), counts["n"].to_numpy())
    return TextModel(names, np.log(table / table.sum(0)).astype(np.float32))


def _scored(model: TextModel, weight: int, text: int, drop: bool):
    """Adds text evidence to each row; ``text`` is the place of the text column, which goes with ``drop``."""
    table, k = model.table, len(model.languages)

    def one(text: str | None) -> tuple[list[float], float, bool]:
        g = _grams(text or "")
        if not len(g):
            return [0.0] * k, 0.0, any(map(str.isalpha, text or ""))
        total = np.zeros(k)
        for i in range(0, len(g), 1 << 18):
            total += table[g[i : i + (1 << 18)]].sum(0, dtype=np.float64)
        w = min(len(g), weight) / len(g)
        return (total * w).tolist(), -np.log(BUCKETS) * min(len(g), weight), any(map(str.isalpha, text))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 512):
                part = b.slice(i, 512)
                found = [one(t.as_py()) for t in part.column(text)]
                cells = [pa.array([r[j] for r in found], t) for j, t in enumerate((pa.list_(pa.float64()), pa.float64(), pa.bool_()))]
                kept = [c for j, c in enumerate(part.columns) if not (drop and j == text)]
                names = [n for j, n in enumerate(part.schema.names) if not (drop and j == text)]
                yield pa.RecordBatch.from_arrays([*kept, *cells], names=[*names, "_text_ll", "_noise_ll", "_letters"])

    return run


def _softmax(ll: Column) -> Column:
    top = F.array_max(ll)
    grown = F.transform(ll, lambda x: F.exp(x - top))
    total = F.aggregate(grown, F.lit(0.0), lambda a, x: a + x)
    return F.transform(grown, lambda x: x / total)


def _said(code: Column, languages: list[str], trust: float) -> Column:
    """Log likelihood of a declaration in each language; all zero where it names none of them."""
    miss = (1 - trust) / max(1, len(languages) - 1)
    code = F.lower(F.split(F.trim(code), "[-_]")[0])
    each = F.array(*[F.when(code == x, F.log(F.lit(trust))).otherwise(F.log(F.lit(max(miss, 1e-9)))) for x in languages])
    return F.when(code.isin(languages), each).otherwise(F.array(*[F.lit(0.0) for _ in languages]))


def address_language(url: Column) -> Column:
    """The language an address suggests: its first path part of two letters, else its country suffix."""
    path = F.regexp_extract(url, r"^[^/]*://[^/?#]*/([A-Za-z]{2})(?:[/?#]|$)", 1)
    suffix = F.regexp_extract(url, r"^[^/]*://[^/?#:]*\.([A-Za-z]{2})(?:[:/?#]|$)", 1)
    return F.lower(F.when(path != "", path).otherwise(F.when(suffix != "", suffix)))


def declared_language(html: Column) -> Column:
    """The ``lang`` attribute of the html element."""
    found = F.regexp_extract(html, r"(?is)<html\b[^>]*?\slang\s*=\s*[\"']?([A-Za-z]{2,3}(?:[-_][A-Za-z0-9]+)*)", 1)
    return F.when(found != "", found)


def host_priors(soft: DataFrame, k: int, smoothing: float) -> DataFrame:
    """(_host, _prior) from (_host, _p: posterior by text alone): counts smoothed host < domain < suffix < all."""
    sums = lambda df, *by: df.groupBy(*by).agg(*[F.sum(f"_s{i}").alias(f"_s{i}") for i in range(k)])
    host = stage(soft.groupBy("_host").agg(*[F.sum(F.col("_p")[i]).alias(f"_s{i}") for i in range(k)]), "host-counts")
    labels = F.split("_host", r"\.")
    host = host.withColumns({"_suffix": F.element_at(labels, -1), "_domain": F.array_join(F.slice(labels, F.greatest(F.lit(1), F.size(labels) - 1), 2), ".")})

    def smooth(df: DataFrame, parent: Column) -> DataFrame:
        total = reduce(lambda a, b: a + b, [F.col(f"_s{i}") for i in range(k)])
        return df.withColumn("_prior", F.array(*[(F.col(f"_s{i}") + smoothing * parent[i]) / (total + smoothing) for i in range(k)]))

    every = smooth(sums(host), F.array(*[F.lit(1.0 / k) for _ in range(k)])).select(F.col("_prior").alias("_up"))
    suffix = stage(smooth(sums(host, "_suffix").join(F.broadcast(every)), F.col("_up")).select("_suffix", F.col("_prior").alias("_up")), "suffix-priors")
    domain = smooth(_to(sums(host, "_domain", "_suffix"), suffix, "_suffix"), F.col("_up"))
    domain = stage(domain.select("_domain", F.col("_prior").alias("_up")), "domain-priors")
    return stage(smooth(_to(host, domain, "_domain"), F.col("_up")).select("_host", "_prior"), "host-priors")


def _to(rows: DataFrame, priors: DataFrame, key: str, how: str = "inner") -> DataFrame:
    """Rows with the staged prior of their key: sent to all tasks while those are few, else sorted, where Spark splits a key that many rows have."""
    return rows.join(F.broadcast(priors) if priors.count() <= BROADCAST_HOSTS else priors.hint("merge"), key, how)


def _column(name: str) -> Column:
    return F.col("`" + name.replace("`", "``") + "`")


RESULT = {"language": "string", "confidence": "double", "text_language": "string", "kept": "boolean"}


def _fused(rows: DataFrame, model: TextModel, how: Fusion, text: str, host: str | None, declared: Column | None, address: Column | None, carry: list[str]) -> DataFrame:
    """The columns ``carry`` as _c0, _c1, ... and the result's columns behind a ``_``. Every text is scored once; what was found is staged."""
    names, k, nothing = model.languages, len(model.languages), F.lit(None).cast("string")
    drop = text not in carry
    base = rows.select(
        *[_column(c).alias(f"_c{i}") for i, c in enumerate(carry)], *([_column(text).alias("_text")] if drop else []),
        F.coalesce(F.lower(_column(host)) if host else nothing, F.lit("")).alias("_host"),
        (nothing if declared is None else declared).alias("_declared"), (nothing if address is None else address).alias("_address"),
    )
    made = StructType([f for f in base.schema if f.name != "_text"])
    made = made.add("_text_ll", ArrayType(DoubleType())).add("_noise_ll", "double").add("_letters", "boolean")
    scored = stage(base.mapInArrow(_scored(model, how.weight, len(carry) if drop else carry.index(text), drop), made), "language-scored")
    priors = host_priors(scored.where("_letters").select("_host", _softmax(F.col("_text_ll")).alias("_p")), k, how.smoothing)
    flat = F.array(*[F.lit(1.0 / k) for _ in names])
    joined = _to(scored, priors, "_host", "left").withColumn("_prior", F.coalesce("_prior", flat))
    total = F.zip_with("_text_ll", F.transform("_prior", lambda p: F.log(p)), lambda a, b: a + b)
    for code, trust in (("_declared", how.declared_trust), ("_address", how.address_trust)):
        total = F.zip_with(total, _said(F.col(code), names, trust), lambda a, b: a + b)
    noise = F.col("_noise_ll") + float(np.log(how.noise_prior))
    label = F.array(*[F.lit(x) for x in names])
    named = joined.withColumn("_post", _softmax(F.concat(total, F.array(noise)))).withColumn("_best", F.slice("_post", 1, k))
    best, alone = F.array_max("_best"), F.col("_text_ll")
    return named.select(
        *[f"_c{i}" for i in range(len(carry))],
        F.element_at(label, F.array_position("_best", best).cast("int")).alias("_language"),
        best.alias("_confidence"),
        F.when(F.col("_letters"), F.element_at(label, F.array_position(alone, F.array_max(alone)).cast("int"))).alias("_text_language"),
        (F.col("_letters") & (best >= how.min_confidence)).alias("_kept"),
    )


def identify(rows: DataFrame, model: TextModel, how: Fusion = Fusion(), text: str = "text", host: str | None = None, declared: Column | None = None, address: Column | None = None, carry: list[str] | None = None) -> DataFrame:
    """The columns ``carry`` of ``rows`` (all, if not said) and, after them, language, confidence, text_language and kept; columns of these names in ``rows`` stay where they are carried."""
    carry = rows.columns if carry is None else carry
    if not model.languages:
        return rows.select(*map(_column, carry), *[F.lit(None).cast(t).alias(c) for c, t in RESULT.items()]).where(F.lit(False))
    found = _fused(rows, model, how, text, host, declared, address, carry)
    return found.select(*[F.col(f"_c{i}").alias(c) for i, c in enumerate(carry)], *[F.col(f"_{c}").alias(c) for c in RESULT])


def identified_documents(docs: DataFrame, how: Fusion = Fusion()) -> DataFrame:
    """The documents whose language is identified; columns as in ``docs``, whatever their names. Without any label nothing can be judged, and all stay."""
    model = fit_text_model(docs, how)
    if not model.languages:
        return docs
    found = _fused(docs, model, how, "text", "source", None, None, docs.columns).where("_kept")
    return found.select(*[F.col(f"_c{i}").alias(c) for i, c in enumerate(docs.columns)])


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return identify(docs, fit_text_model(docs), host="source", carry=["doc_id"])


def query_pages(spark, sf_dir: str) -> DataFrame:
    """Pages: all four kinds of evidence; the text is the html without scripts, styles, comments and tags."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    bare = F.regexp_replace("html", r"(?is)<(script|style)\b.*?</\1>|<!--.*?-->|<[^>]*>", " ")
    rows = pages.select("page_id", bare.alias("text"), F.regexp_extract("url", r"://([^/?#:]*)", 1).alias("host"), declared_language(F.col("html")).alias("declared"), address_language(F.col("url")).alias("address"))
    return identify(rows, fit_text_model(docs), host="host", declared=F.col("declared"), address=F.col("address"), carry=["page_id", "declared", "address"])
