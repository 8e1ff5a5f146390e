"""Toxicity: a linear-chain conditional random field tags toxic words.

Word labels come from document labels: in toxic documents the words (or word
beginnings) that clean documents do not have are toxic, the others are not. On
windows around such words a two-state chain is fitted by the gradient of its
likelihood (forward-backward). Scoring runs forward-backward over every whole
text; marginals of single words aggregate to a document score by a logistic
function of the largest marginal, the expected number of toxic words, the tagged words and the length, and
runs of words with a marginal of one half or more give the offending offsets.

The chain is fitted on a bounded sample of labelled rows: at most about
``per_class`` toxic and ``clean`` other documents, each of at most ``longest`` characters. Scores
use the text alone.

Defined results: null and empty texts, and texts without words, get the score of
no toxic words; texts of any length are scored whole; rows that repeat get equal
rows; null labels are not learnt from; where a class has no labels, the fit is
empty and every score is the share of toxic labels; an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD = re.compile(r"\w+")
STEPS = 64


@dataclass(frozen=True)
class Fit:
    per_class: int = 1500  # toxic documents, and
    clean: int = 6000  # others
    longest: int = 12_000
    precision: float = 0.9  # of a feature that marks toxic words, among documents that have it, classes weighed alike
    support: int = 6  # toxic documents that have it, and
    share: float = 0.02  # of the toxic documents
    reach: int = 12  # words kept on either side of a labelled word
    rounds: int = 80
    rate: float = 0.3
    decay: float = 1e-3
    seed: int = 7


def features(word: str) -> tuple[str, ...]:
    w = word.lower()
    return (w, "^4" + w[:4], "^5" + w[:5]) if len(w) > 5 else (w, "^4" + w[:4]) if len(w) > 4 else (w,)


@dataclass
class Crf:
    weights: dict[str, float] = field(default_factory=dict)
    bias: float = -4.0
    move: np.ndarray = field(default_factory=lambda: np.zeros((2, 2)))  # log weight from state (row) to state (column)
    scale: tuple[float, ...] = (0.0,) * 6  # of ``evidence``, in the logistic function of a document

    def emission(self, word: str) -> float:
        return self.bias + sum(self.weights.get(f, 0.0) for f in features(word))


def _block_scan(m: np.ndarray, first: float) -> np.ndarray:
    """r[t] = (m00 r + m01) / (m10 r + m11) for all t, from r[-1] = ``first``; m is (2, 2, n).

    Steps are laid out in blocks that run side by side; the products of the
    blocks' matrices carry the exact state from one block to the next.
    """
    n = m.shape[2]
    k = -(-n // STEPS)
    full = np.zeros((2, 2, k * STEPS))
    full[0, 0], full[1, 1] = 1.0, 1.0
    full[:, :, :n] = m
    full = full.reshape(2, 2, k, STEPS)
    a, b, c, d = np.ones(k), np.zeros(k), np.zeros(k), np.ones(k)
    for s in range(STEPS):
        (p, q), (u, v) = full[0, :, :, s], full[1, :, :, s]
        a, b, c, d = p * a + q * c, p * b + q * d, u * a + v * c, u * b + v * d
        top = np.maximum(np.maximum(a, b), np.maximum(c, d))
        a, b, c, d = a / top, b / top, c / top, d / top
    starts, r = np.empty(k), first
    for i, (x, y, z, w) in enumerate(zip(a.tolist(), b.tolist(), c.tolist(), d.tolist(), strict=True)):
        starts[i] = r
        r = (x * r + y) / (z * r + w)
    out, r = np.empty((k, STEPS)), starts
    for s in range(STEPS):
        r = (full[0, 0, :, s] * r + full[0, 1, :, s]) / (full[1, 0, :, s] * r + full[1, 1, :, s])
        out[:, s] = r
    return out.reshape(-1)[:n]


def marginals(e: np.ndarray, begins: np.ndarray, move: np.ndarray) -> np.ndarray:
    """Probability of the toxic state at every word of texts laid end to end; ``begins`` marks first words."""
    if not len(e):
        return e
    t, x = np.exp(move), np.exp(np.clip(e, -30, 30))
    one = np.ones(len(e))
    m = np.array([[x * t[1, 1], x * t[0, 1]], [one * t[1, 0], one * t[0, 0]]])
    m[:, :, begins] = np.array([[np.zeros(begins.sum()), x[begins]], [np.zeros(begins.sum()), one[begins]]])
    forward = _block_scan(m, 1.0)
    # backward: word i looks at word i + 1, and a last word looks at nothing
    nxt = np.append(x[1:], 1.0)
    last = np.append(begins[1:], True)
    m = np.array([[t[1, 1] * nxt, one * t[1, 0]], [t[0, 1] * nxt, one * t[0, 0]]])
    m[:, :, last] = np.array([[0.0, 1.0], [0.0, 1.0]])[:, :, None]
    backward = _block_scan(np.ascontiguousarray(m[:, :, ::-1]), 1.0)[::-1]
    both = forward * backward
    return both / (1 + both)


def _chain_gradient(e: np.ndarray, y: np.ndarray, mask: np.ndarray, move: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Observed minus expected toxic states (rows are windows), and the same for moves."""
    n, length = e.shape
    em = np.stack([np.zeros_like(e), e], -1) * mask[..., None]
    lse = lambda z, axis: (m := z.max(axis, keepdims=True)).squeeze(axis) + np.log(np.exp(z - m).sum(axis))
    alpha, beta = np.zeros((n, length, 2)), np.zeros((n, length, 2))
    alpha[:, 0] = em[:, 0]
    for t in range(1, length):
        step = lse(alpha[:, t - 1, :, None] + move[None], 1) + em[:, t]
        alpha[:, t] = np.where(mask[:, t, None] > 0, step, alpha[:, t - 1])
    for t in range(length - 2, -1, -1):
        step = lse(move[None] + (em[:, t + 1] + beta[:, t + 1])[:, None, :], 2)
        beta[:, t] = np.where(mask[:, t + 1, None] > 0, step, 0)
    z = lse(alpha[:, -1], 1)
    p = np.exp(alpha[..., 1] + beta[..., 1] - z[:, None]) * mask
    pair = np.exp(alpha[:, :-1, :, None] + move[None, None] + (em[:, 1:] + beta[:, 1:])[:, :, None, :] - z[:, None, None, None]) * mask[:, 1:, None, None]
    hot = np.stack([1 - y, y], -1)
    seen = hot[:, :-1, :, None] * hot[:, 1:, None, :] * mask[:, 1:, None, None]
    return (y - p) * mask, (seen - pair).sum((0, 1))


def fit(texts: list[str], toxic: list[int], how: Fit = Fit()) -> Crf:
    pool: dict[str, str] = {}
    words = [[pool.setdefault(w, w) for w in WORD.findall(t)] for t in texts]  # each word is held once
    n1 = sum(toxic)
    n0 = len(toxic) - n1
    if not n1 or not n0:
        share = (n1 + 0.5) / (len(toxic) + 1)
        return Crf(scale=(float(np.log(share / (1 - share))), *(0.0,) * 5))
    bad, good = Counter(), Counter()
    for ws, x in zip(words, toxic, strict=True):
        (bad if x else good).update({f for w in set(ws) for f in features(w)})
    marks = {f for f, n in bad.items() if n >= max(how.support, how.share * n1) and n / n1 >= how.precision * (n / n1 + (good[f] + 0.5) / n0)}
    number: dict[str, int] = {}
    rng, rows = np.random.default_rng(how.seed), []
    for ws, x in zip(words, toxic, strict=True):
        y = [int(x and any(f in marks for f in features(w))) for w in ws]
        hits = [i for i, v in enumerate(y) if v][:6]
        if x and not hits or not ws:
            continue
        for i in hits or rng.integers(0, len(ws), 1).tolist():
            span = slice(max(0, i - how.reach), i + how.reach + 1)
            rows.append((ws[span], y[span]))
    size = 2 * how.reach + 1
    y, mask = np.zeros((len(rows), size)), np.zeros((len(rows), size))
    ids = np.zeros((len(rows), size, 3), np.int64)
    for r, (ws, ys) in enumerate(rows):
        y[r, : len(ys)], mask[r, : len(ys)] = ys, 1
        for t, w in enumerate(ws):
            own = [number.setdefault(f, len(number) + 1) for f in features(w)]
            ids[r, t, : len(own)] = own
    weights, bias, move = np.zeros(len(number) + 1), -2.0, np.zeros((2, 2))
    seen = [np.full(len(weights), 1e-8), 1e-8, np.full((2, 2), 1e-8)]
    for _ in range(how.rounds):
        e = bias + weights[ids].sum(-1)
        g, gm = _chain_gradient(e, y, mask, move)
        gw = np.bincount(ids.reshape(-1), np.repeat(g.reshape(-1), 3), len(weights)) - how.decay * len(rows) * weights / 10
        gw[0] = 0
        gb = g.sum() - how.decay * bias
        gm = gm - how.decay * move
        seen = [seen[0] + gw**2, seen[1] + gb**2, seen[2] + gm**2]
        weights, bias, move = weights + how.rate * gw / np.sqrt(seen[0]), bias + how.rate * gb / np.sqrt(seen[1]), move + how.rate * gm / np.sqrt(seen[2])
    crf = Crf({f: float(weights[i]) for f, i in number.items() if abs(weights[i]) > 1e-3}, float(bias), move)
    known = _Emissions(crf)
    p, at = _laid_out(words, crf, known)
    x = np.array([evidence(ws, p[i:j]) for ws, i, j in zip(words, at[:-1], at[1:], strict=True)])
    target, w = np.array(toxic, float), np.zeros(x.shape[1])
    ridge = np.diag([1e-3, *(0.2,) * (x.shape[1] - 1)])
    for _ in range(25):  # Newton steps; the ridge bounds the weights of separable classes
        q = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        w = w + np.linalg.solve(x.T @ (x * (q * (1 - q))[:, None]) + ridge, x.T @ (target - q) - ridge @ w)
    crf.scale = tuple(map(float, w))
    return crf


class _Emissions(dict):
    def __init__(self, crf: Crf, limit: int = 400_000):
        super().__init__()
        self.crf, self.limit = crf, limit

    def __missing__(self, word: str) -> float:
        if len(self) >= self.limit:
            self.clear()
        v = self[word] = self.crf.emission(word)
        return v


def _laid_out(words: list[list[str]], crf: Crf, known: dict | None = None) -> tuple[np.ndarray, np.ndarray]:
    known = _Emissions(crf) if known is None else known
    sizes = np.array([len(w) for w in words], np.int64)
    e = np.fromiter((v for ws in words for v in map(known.__getitem__, ws)), np.float64, int(sizes.sum()))
    begins = np.zeros(len(e), bool)
    ends = np.cumsum(sizes)
    begins[(ends - sizes)[sizes > 0]] = True
    return marginals(e, begins, crf.move), np.append(0, ends)


def evidence(words: list[str], p: np.ndarray) -> tuple[float, ...]:
    """What a document's marginals come to: one; the largest; expected toxic words among all and among the tagged; distinct tagged words; words."""
    if not len(p):
        return (1.0, 0.0, 0.0, 0.0, 0.0, 0.0)
    tagged = np.flatnonzero(p >= 0.5)
    distinct = len({words[i].lower() for i in tagged}) if len(tagged) else 0
    return (1.0, float(p.max()), float(np.log1p(p.sum())), float(np.log1p(p[tagged].sum())), float(np.log1p(distinct)), float(np.log1p(len(p))))


def spans_of(text: str, p: np.ndarray) -> list[dict]:
    """Offsets (code points) of runs of words with a marginal of one half or more."""
    out, open_run = [], False
    for m, q in zip(WORD.finditer(text), p, strict=True):
        if q < 0.5:
            open_run = False
        elif open_run:
            out[-1]["end"] = m.end()
        else:
            out.append({"start": m.start(), "end": m.end()})
            open_run = True
    return out


SCORES = "score double, spans array<struct<start: long, end: long>>"


def _scored(crf: Crf):
    span = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = _Emissions(crf)
        for b in batches:
            start = 0
            while start < b.num_rows:  # a slice: 128 texts, or fewer if they are long
                texts, size, end = [], 0, start
                while end < b.num_rows and len(texts) < 128 and (not texts or size < 1 << 20):
                    texts.append(b.column(1)[end].as_py() or "")
                    size, end = size + len(texts[-1]), end + 1
                words = [WORD.findall(t) for t in texts]
                p, at = _laid_out(words, crf, known)
                scores, spans = [], []
                for t, ws, i, j in zip(texts, words, at[:-1], at[1:], strict=True):
                    seen = evidence(ws, p[i:j])
                    z = sum(c * v for c, v in zip(crf.scale, seen, strict=True))
                    scores.append(1 / (1 + np.exp(-min(30.0, max(-30.0, z)))))
                    spans.append(spans_of(t, p[i:j]) if seen[1] >= 0.5 else [])
                yield pa.RecordBatch.from_arrays([b.column(0).slice(start, end - start), pa.array(scores, pa.float64()), pa.array(spans, span)], names=["doc_id", "score", "spans"])
                start = end

    return run


def fit_toxicity(docs: DataFrame, labels: DataFrame, learn: Column, how: Fit = Fit()) -> Crf:
    """Fit on the rows of ``labels`` (doc_id, toxic) where ``learn`` holds and whose text is in ``docs``."""
    own = labels.where(learn & F.col("toxic").isin(0, 1)).select("doc_id", "toxic").distinct()
    sizes = {r["toxic"]: r["n"] for r in own.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    draw = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) / float(1 << 20)
    share = {x: min(1.0, n / max(1, sizes.get(x, 0))) for x, n in ((1, how.per_class), (0, how.clean))}
    drawn = own.where(draw < F.when(F.col("toxic") == 1, share[1]).otherwise(share[0]))
    sample = docs.where(F.length("text") <= how.longest).select("doc_id", "text").join(F.broadcast(drawn), "doc_id").toArrow()
    rows = sorted(zip(sample["text"].to_pylist(), sample["toxic"].to_pylist(), strict=True))
    return fit([t for t, _ in rows], [int(x) for _, x in rows], how)


def score_toxicity(docs: DataFrame, crf: Crf) -> DataFrame:
    """doc_id, score and offending spans of every text."""
    return docs.select("doc_id", "text").mapInArrow(_scored(crf), f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, {SCORES}")


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    held_out = F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), F.lit(3)) == 1
    found = score_toxicity(docs, fit_toxicity(docs, labels, ~held_out))
    return found.select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"), F.size("spans").alias("n_spans"), "spans")
