"""A corpus pipeline of five stages, each an operator of ``exkit.llm``.

``STAGES`` lists (name, function); a function takes (spark, docs, sf_dir) and
returns a DataFrame, all but the last with the columns of ``documents``.
``run`` writes what each stage keeps as Parquet in the shared folder and gives
it to the next.

A stage's documents are a written table, so what the stage before staged on its
way is not read again: a stage deletes it when it begins, unless ``docs`` reads
it. Write a stage's result before the next stage is called.

Defined results: each stage's are those of its operator. Null and empty texts
leave with the first stage; a null doc_id stays; rows alike in every column
stay once; an empty table gives an empty result; columns beside those of
``documents`` are carried by all stages but the last, whatever their names
(names that start with ``mix_`` are reserved).
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession

from exkit.llm import language, mixing, packing, quality, shingle_join
from exkit.staging import delete, recorded, stage

Step = Callable[[SparkSession, DataFrame, str], DataFrame]
_left: list[str] = []


def tidy(step: Step) -> Step:
    """Deletes what earlier stages staged and ``docs`` does not read, then runs the stage."""

    @wraps(step)
    def run_step(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        if _left:
            read = docs.inputFiles()
            gone = [p for p in _left if not any(p.split("/")[-1] in f for f in read)]
            delete(spark, gone)
            _left[:] = [p for p in _left if p not in gone]
        with recorded(_left):
            return step(spark, docs, sf_dir)

    return run_step


@tidy
def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the fused evidence settles; noise and texts without letters go."""
    return language.identified_documents(docs)


@tidy
def clean_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without their failing lines; documents that fail the base rules or lose too much go."""
    return quality.cleaned_documents(docs)


@tidy
def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of near-duplicates: five-word shingles, similarity 0.8 or more."""
    return shingle_join.distinct_documents(docs, shingle_join.Similarity(words=5, percent=80))


@tidy
def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources brought to their target weights; repeated and cut documents are rows of their own."""
    return mixing.mixed_documents(docs)


@tidy
def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The place of every piece of every document in sequences of 1024 tokens."""
    return packing.pack_documents(docs)


STAGES = [
    ("language_id", identify_language),
    ("quality_rules", clean_lines),
    ("near_copies", drop_near_copies),
    ("source_mixing", mix_sources),
    ("best_fit_packing", pack_sequences),
]

#: The text model of the first stage and the tokenizer of the last are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, step) in enumerate(STAGES):
        docs = step(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = stage(docs, f"stage-{name}")
    return docs
