"""Best-fit packing by bin completion.

How well a packing can be depends on the lengths alone, so the whole corpus is
reduced to one count per length (at most ``size`` rows, however many documents
there are). On these counts a best-fit-decreasing packing is the first
incumbent; branch and bound then completes bins around the largest length left
with undominated fillings, a whole multiple at a time, and gives up a branch
once its waste exceeds what a better packing could still waste. The result is a
list of bin patterns with multiplicities. Pieces get their place from their rank
among pieces of equal length, a rank made of bucket offsets and ranks inside a
bucket, so that no length has to fit one task.

Defined results: null and empty texts are one piece of the end id alone;
documents longer than a sequence are cut into full pieces, the first takes the
remainder; rows with a repeated doc_id are packed as documents of their own;
texts of any length are encoded whole; an empty table gives an empty packing;
other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from exkit.llm.tokens import byte_bpe
from exkit.staging import stage

SIZE, END_ID = 1024, 2
#: Branch and bound looks at this many nodes at most, dominated fillings included; the incumbent stands beyond that.
NODES, RANK_BUCKETS = 3000, 256

Pattern = tuple[int, tuple[int, ...]]


def pieces_of(n: int, size: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of ``n`` ids."""
    first = n % size or min(n, size)
    return [(0, first), *((s, size) for s in range(first, n, size))]


def best_fit_decreasing(counts: dict[int, int], size: int) -> list[Pattern]:
    """Bins as (how many alike, lengths), filled from the longest length down, tightest room first."""
    open_bins: dict[int, list[list]] = {}
    done: list[Pattern] = []
    put = lambda room, n, held: done.append((n, held)) if room == 0 else open_bins.setdefault(room, []).append([n, held])
    for length in sorted(counts, reverse=True):
        left = counts[length]
        for room in sorted(r for r in open_bins if r >= length):
            each = room // length
            while left and open_bins.get(room):
                group = open_bins[room][-1]
                if group[0] * each <= left:
                    open_bins[room].pop()
                    left -= group[0] * each
                    put(room - each * length, group[0], group[1] + (length,) * each)
                else:
                    whole, rest = divmod(left, each)
                    left = 0
                    group[0] -= whole + (rest > 0)
                    if whole:
                        put(room - each * length, whole, group[1] + (length,) * each)
                    if rest:
                        put(room - rest * length, 1, group[1] + (length,) * rest)
                    if not group[0]:
                        open_bins[room].pop()
            if not open_bins.get(room):
                open_bins.pop(room, None)
            if not left:
                break
        if left:
            each = size // length
            whole, rest = divmod(left, each)
            if whole:
                put(size - each * length, whole, (length,) * each)
            if rest:
                put(size - rest * length, 1, (length,) * rest)
    return done + [(n, held) for groups in open_bins.values() for n, held in groups]


def _dominated(held: dict[int, int], counts: dict[int, int], slack: int) -> bool:
    """Whether a piece left over could take the place of some pieces in ``held`` that are together no longer, ``slack`` shorter at most."""
    for x in counts:
        if counts[x] <= held.get(x, 0):
            continue
        sums = 1
        for y, n in held.items():
            if y < x:
                for _ in range(min(n, x // y)):
                    sums |= sums << y
        if sums >> max(0, x - slack) & ((1 << (min(slack, x) + 1)) - 1):
            return True
    return False


def fillings(counts: dict[int, int], room: int, spare: int) -> Iterator[tuple[int, ...] | None]:
    """Undominated ways to fill ``room`` up to ``spare``, with any number of pieces, least waste first; None for each dominated one.

    Sums that the shorter lengths reach are kept as bits of a number for each
    length, so that every step of the walk leads to a filling.
    """
    lengths = sorted((x for x, n in counts.items() if n and x <= room), reverse=True)
    if not lengths:
        yield ()
        return
    if lengths[0] == room:
        yield (room,)
        return
    fits = (1 << (room + 1)) - 1
    reached = [1]
    for x in reversed(lengths):
        sums, left, step = reached[-1], min(counts[x], room // x), 1
        while left:
            step = min(step, left)
            sums |= sums << (step * x) & fits
            left, step = left - step, 2 * step
        reached.append(sums)
    reached.reverse()
    for total in range(room, max(lengths[0], room - spare) - 1, -1):
        walk = [(0, total, ())] if reached[0] >> total & 1 else []
        while walk:
            i, left, held = walk.pop()
            if not left:
                yield None if _dominated(dict(held), counts, room - total) else tuple(x for x, n in held for _ in range(n))
                continue
            while not counts[lengths[i]] or lengths[i] > left:
                i += 1
            x = lengths[i]
            for n in range(min(counts[x], left // x) + 1):
                if reached[i + 1] >> (left - n * x) & 1:
                    walk.append((i + 1, left - n * x, (*held, (x, n)) if n else held))


def _completions(left: dict[int, int], bins: int, waste: int, made, size: int, spare: int) -> Iterator[tuple | None]:
    """What is left after bins around the longest piece: each filling as often as it goes first, then once."""
    longest = max(left)
    rest = {**left, longest: left[longest] - 1}
    for often in (True, False):
        for more in fillings(rest, size - longest, spare):
            if more is None:
                yield None
                continue
            held = (longest, *more)
            need = {x: held.count(x) for x in held}
            most = min(left[x] // n for x, n in need.items())
            if often or most > 1:
                m = most if often else 1
                yield {x: n for x, n in ((x, n - m * need.get(x, 0)) for x, n in left.items()) if n}, bins + m, waste + m * (size - sum(held)), (made, (m, held))


def bin_completion(counts: dict[int, int], size: int = SIZE, nodes: int = NODES) -> list[Pattern]:
    """Bin patterns for ``counts`` pieces of each length, in as few bins as the search finds."""
    counts = {x: n for x, n in counts.items() if n}
    best = best_fit_decreasing(counts, size)
    total = sum(x * n for x, n in counts.items())
    least, used = -(-total // size), sum(n for n, _ in best)
    stack = [iter([(counts, 0, 0, None)])]
    while stack and used > least and nodes:
        nodes -= 1
        node = next(stack[-1], stack)
        if node is stack:
            stack.pop()
        if node is stack or node is None or node[2] > (used - 1) * size - total:
            continue
        left, bins, waste, made = node
        if left:
            stack.append(_completions(left, bins, waste, made, size, (used - 1) * size - total - waste))
            continue
        used, best = bins, []
        while made:
            made, pattern = made
            best.append(pattern)
    return best


def places(patterns: list[Pattern]) -> np.ndarray:
    """Rows (length, first rank, pieces of that length in a bin, offset of the first, first sequence), by length and rank."""
    rows, ranks, sequence = [], {}, 0
    for n, held in sorted(patterns, key=lambda p: (p[1], p[0])):
        offset = 0
        for length in sorted(set(held), reverse=True):
            each = held.count(length)
            rows.append((length, ranks.get(length, 0), each, offset, sequence))
            ranks[length] = ranks.get(length, 0) + n * each
            offset += each * length
        sequence += n
    return np.array(sorted(rows), np.int64).reshape(-1, 5)


PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def _cut(size: int, vocabulary: str | None):
    names = [c.split()[0] for c in PIECES.split(", ")]
    kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe, end = byte_bpe(vocabulary), END_ID.to_bytes(4, "little")
        for b in batches:
            rows = []
            for doc, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = bpe.encode(text.as_py() or "") + end
                rows += [(doc, k, s, n, zlib.crc32(ids[4 * s : 4 * (s + n)])) for k, (s, n) in enumerate(pieces_of(len(ids) // 4, size))]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)

    return run


def _placed(table: np.ndarray):
    keys = table[:, 0] << 44 | table[:, 1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            *rest, rank = b.columns
            length, rank = b.column(3).to_numpy(), rank.to_numpy()
            at = table[np.searchsorted(keys, length << 44 | rank, side="right") - 1]
            copy, slot = np.divmod(rank - at[:, 1], at[:, 2])
            yield pa.RecordBatch.from_arrays([*rest, pa.array(at[:, 4] + copy), pa.array(at[:, 3] + slot * length)], names=[*b.schema.names[:-1], "sequence_id", "offset"])

    return run


def pack_documents(docs: DataFrame, size: int = SIZE, vocabulary: str | None = None, nodes: int = NODES) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, and its sequence_id and offset there."""
    pieces = stage(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_cut(size, vocabulary), PIECES), "pieces")
    bucket = F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(RANK_BUCKETS))
    own = pieces.withColumn("bucket", bucket)
    sums = own.groupBy("length", "bucket").agg(F.count(F.lit(1)).alias("n"))
    before = W.partitionBy("length").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)
    offsets = stage(sums.withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0))), "piece-ranks")
    counts = {r["length"]: r["n"] for r in offsets.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most ``size`` rows
    inside = F.row_number().over(W.partitionBy("length", "bucket").orderBy("doc_id", "piece", "ids_crc32")) - 1
    ranked = own.withColumn("inside", inside).join(offsets.drop("n"), ["length", "bucket"])
    ranked = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("before") + F.col("inside")).cast("long").alias("rank"))
    return ranked.mapInArrow(_placed(places(bin_completion(counts, size, nodes))), f"{PIECES}, sequence_id long, offset long")


def _slices(vocabulary: str | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe, end = byte_bpe(vocabulary), END_ID.to_bytes(4, "little")
        for b in batches:
            for text, doc, start, length, sequence, offset in zip(*(c.to_pylist() for c in b.columns), strict=True):
                ids = np.frombuffer(bpe.encode(text or "") + end, "<u4")[start : start + length].astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array([sequence]), pa.array([offset]), pa.array([doc], pa.int64()), pa.array([ids], pa.list_(pa.int32()))], names=["sequence_id", "offset", "doc_id", "ids"])

    return run


def token_sequences(docs: DataFrame, layout: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """The packed sequences of a layout whose doc_ids are unique: sequence_id, ids, and the doc_id and length of each piece in order."""
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(layout, "doc_id").select("text", "doc_id", "start", "length", "sequence_id", "offset")
    parts = own.mapInArrow(_slices(vocabulary), "sequence_id long, offset long, doc_id long, ids array<int>")
    held = parts.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "doc_id", "ids"))).alias("p"))  # a sequence holds at most ``size`` ids
    return held.select("sequence_id", F.flatten("p.ids").alias("ids"), F.col("p.doc_id").alias("doc_ids"), F.transform("p.ids", F.size).alias("lengths"))


def query(spark, sf_dir: str) -> DataFrame:
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
