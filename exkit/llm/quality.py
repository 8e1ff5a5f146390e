"""Quality rules: line-first cleaning.

Every line is judged by punctuation, navigation, boilerplate and repetition
rules; failing lines go, and a document that loses more than ``max_loss`` of its
word characters is rejected. Base rules on the whole text come first: too few
words, or too many words inside repeated five-word windows.

Defined results: null and empty texts have no words, fail the base rules and
keep no lines; texts of any length are judged whole, a line at a time; blank lines
are kept as they are; repeated rows get equal rows; an empty table gives an
empty result; other columns are ignored, or carried by ``cleaned_documents``,
whose input must not have the column ``_kept``.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SYMBOLS = b"#*$%&|<>"
WINDOW = 5
MIN_WORDS, MAX_REPEAT_PERCENT = 10, 20
SPACE = b" \t\n\r\x0b\x0c"


@dataclass(frozen=True)
class LineRules:
    max_symbol_share: float = 0.1  # of a line's characters
    max_unended_words: int = 40  # a longer line must hold a sentence end
    max_bars: int = 2  # separators of a navigation line
    max_notice_words: int = 25  # a longer line is prose even if it holds a notice's phrase
    min_distinct_share: float = 0.35  # of the words of a line of ten or more
    max_capital_share: float = 0.8  # of the letters of a line of five words or more
    max_loss: float = 0.5  # of a document's word characters


ODD = re.compile(r"[#*$%&|<>{}\[\]\\^~=_@]|!!")
BARS = re.compile(r"\s[|»›>•·]\s|\s[|»›•·]$")
NOTICE = re.compile(
    r"\b(?:accept (?:all )?cookies|cookie policy|privacy policy|terms of (?:use|service)|all rights reserved|(?:released|licensed) under"
    r"|click here|sign up|log ?in|subscribe to|share this|enable javascript|follow us|skip to content|copyright (?:\(c\)|©))\b",
    re.I,
)


def line_fault(line: str, words: list[str], rules: LineRules) -> str | None:
    """Name of the first rule that a line with words fails."""
    n = len(words)
    if len(BARS.findall(line)) > rules.max_bars:
        return "navigation"
    if n <= rules.max_notice_words and NOTICE.search(line):
        return "boilerplate"
    if len(ODD.findall(line)) > rules.max_symbol_share * len(line):
        return "symbols"
    if n >= 10 and len(set(words)) < rules.min_distinct_share * n:
        return "repetition"
    if n > rules.max_unended_words and not re.search(r"[.!?…。]", line):
        return "unended"
    if n >= 5 and line.upper() == line and line.lower() != line:
        letters = sum(map(str.isalpha, line))
        if sum(map(str.isupper, line)) > rules.max_capital_share * letters:
            return "capitals"
    return None


def repeated_words(words: list[bytes]) -> int:
    """Words that lie in a five-word window which the text holds twice or more."""
    if len(words) <= WINDOW:
        return 0
    number = defaultdict(count().__next__)
    ids = np.fromiter(map(number.__getitem__, words), np.int64, len(words))
    base = len(number)
    if base == len(words):
        return 0
    two = ids[:-1] * base + ids[1:]
    if base**WINDOW < 1 << 62:
        five = (two[:-2] * base**2 + two[2:])[:-1] * base + ids[4:]
    else:
        two = np.unique(two, return_inverse=True)[1]
        four = np.unique(two[:-2] * (int(two.max()) + 1) + two[2:], return_inverse=True)[1]
        five = four[:-1] * base + ids[4:]
    _, which, times = np.unique(five, return_inverse=True, return_counts=True)
    starts = np.flatnonzero(times[which] > 1)
    if not len(starts):
        return 0
    edge = np.zeros(len(words) + 1, np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + WINDOW, -1)
    return int((np.cumsum(edge) > 0).sum())


def judge(raw: bytes, rules: LineRules) -> dict:
    """All measures of one text, its verdict and its cleaned form."""
    words = raw.split()
    text = raw.decode("utf-8", "surrogatepass")
    solid = sum(map(len, words))
    chars = len(text) - (len(raw) - solid)
    repeat = repeated_words(words)
    n = len(words)
    seen: set[str] = set()
    kept, dup, lost, removed = [], 0, 0, 0
    for line in text.split("\n"):
        own = line.split()
        if not line.strip(" \t\r\x0b\x0c"):
            kept.append(line)
            continue
        again = line in seen
        dup += again
        seen.add(line)
        if again or line_fault(line, own, rules):
            lost += sum(map(len, own))
            removed += 1
        else:
            kept.append(line)
    failed = n < MIN_WORDS or 100 * repeat > MAX_REPEAT_PERCENT * n
    return {
        "n_words": n, "word_chars": chars, "n_symbols": len(raw) - len(raw.translate(None, SYMBOLS)), "n_dup_lines": dup, "n_repeat_words": repeat,
        "base_failed": failed, "kept": not failed and lost <= rules.max_loss * max(1, chars), "n_removed_lines": removed, "lost_chars": lost, "cleaned": "\n".join(kept),
    }


MEASURES = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, n_removed_lines long, lost_chars long, cleaned string"


def _judged(rules: LineRules, text: bool):
    fields = [f.split() for f in MEASURES.split(", ")][: None if text else -1]
    kinds = {"long": pa.int64(), "boolean": pa.bool_(), "string": pa.string()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.schema.get_field_index("_text")
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                rows = [judge(t.as_py() or b"", rules) for t in part.column(at).cast(pa.binary())]
                rest = [c for k, c in enumerate(part.columns) if k != at]
                names = [c for k, c in enumerate(part.schema.names) if k != at]
                yield pa.RecordBatch.from_arrays(rest + [pa.array([r[c] for r in rows], kinds[k]) for c, k in fields], names=names + [c for c, _ in fields])

    return run


def line_quality(docs: DataFrame, rules: LineRules = LineRules(), cleaned: bool = True) -> DataFrame:
    """doc_id, the measures, the verdict ``kept`` and, if asked for, the ``cleaned`` text."""
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, " + (MEASURES if cleaned else MEASURES.rpartition(", ")[0])
    return docs.select("doc_id", F.col("text").alias("_text")).mapInArrow(_judged(rules, cleaned), schema)


def cleaned_documents(docs: DataFrame, rules: LineRules = LineRules()) -> DataFrame:
    """The documents that stay, with cleaned text; columns as in ``docs``, ``n_chars`` (if there) follows the text."""
    columns = docs.columns
    row = docs.select(F.struct(*[F.col(c) for c in columns if c != "text"]).alias("_row"), F.col("text").alias("_text"))
    kinds = ", ".join(f"`{f.name}`: {f.dataType.simpleString()}" for f in docs.schema if f.name != "text")
    judged = row.mapInArrow(_judged(rules, True), f"_row struct<{kinds}>, {MEASURES}").where("kept")
    own = {"text": F.col("cleaned")}
    if "n_chars" in columns:
        own["n_chars"] = F.length("cleaned").cast(docs.schema["n_chars"].dataType)
    return judged.select(*[own.get(c, F.col("_row").getField(c)).alias(c) for c in columns])


def query(spark, sf_dir: str) -> DataFrame:
    return line_quality(spark.read.parquet(f"{sf_dir}/documents.parquet"), cleaned=False)
