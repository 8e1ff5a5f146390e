"""N-gram Jaccard join by parity sketches.

A document is the set of its word shingles. Shingles are XOR-ed into a sketch of
bits: two sketches differ in at most as many bits as the sets have different
members. In a band of set sizes that allows ``t`` differences the sketch has
``t + 1 + e`` blocks, so similar sets agree on ``e + 1`` blocks at least, and one
of them is not empty unless a set has more than ``e`` empty blocks (only then are
empty blocks used too). Blocks are join keys; a set near the upper end of its band also enters
the next one, so no pair is missed.

Equal sets are one class from the start, and buckets of equal blocks that hold
the same ids are one bucket. Ids that share fewer blocks than a link guarantees
drop out, and so do the most frequent blocks that a link can do without. Inside
a bucket no pairs are formed: members are verified against the bucket's least
id, verified links are contracted into components, and only buckets that still
hold several components are looked at again. The sets of such a bucket meet in
chunks of bounded size, where sketches of all members are compared as bit
arrays (the Hamming distance prunes), survivors are verified, and only links
that connect two components leave the task. Nothing is capped.

Defined results: null and empty texts have no shingles, their component is their
own id; texts with fewer words than a shingle are one shingle of all their
words; texts of any length are whole; rows that share a doc_id belong together;
a null doc_id is never linked to; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from exkit.llm.components import components
from exkit.llm.text import LOWER, UPPER
from exkit.staging import stage

DOWN = bytes.maketrans(UPPER.encode(), LOWER.encode())
#: Ids up to this many are broadcast (8 bytes each) to fetch their texts; more are joined by a shuffle.
BROADCAST_IDS = 300_000
#: Sets of a chunk, and members of all its sets, about; pivots are copied for this many shares of their members.
CHUNK, MEMBERS, SHARES = 512, 1 << 20, 16
#: Keys are dealt to this many groups at least; more where the session has more shuffle partitions.
GROUPS = 64
#: Bytes of text that are shingled before their sets leave the task.
PIECE = 1 << 21
#: Least and most width of whole sketches; a narrow sketch prunes less and loses nothing.
BIT_WORDS, MOST_BITS = 64, 1 << 20


@dataclass(frozen=True)
class Similarity:
    """Sets of ``words``-word shingles are linked when 100 * intersection >= ``percent`` * union."""

    words: int = 5
    percent: int = 80

    def differences(self, sizes: int) -> int:
        """Most members in which linked sets with ``sizes`` members together can differ."""
        return (100 - self.percent) * sizes // (100 + self.percent)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(32))


class _Words(dict):
    def __missing__(self, w: bytes) -> int:
        if len(self) > 100_000:
            self.clear()
        h = self[w] = xxhash.xxh64_intdigest(w)
        return h


_words = _Words()


def shingles(raw: bytes, words: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles of a text."""
    found = raw.translate(DOWN).split()
    if not found:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(_words.__getitem__, found), np.uint64, len(found))
    n = min(words, len(h))
    total = np.full(len(h) - n + 1, len(found) if len(found) < words else 0, np.uint64)
    for i in range(n):
        total = _mix(total * np.uint64(0x9E3779B97F4A7C15) + h[i : len(h) - n + 1 + i])
    return np.unique(total)


@lru_cache(maxsize=8)
def bands(percent: int, most: int = 1 << 40) -> np.ndarray:
    """Least set size of each band. Bands grow a little more than linked sets can, so partners are in one band or the next."""
    out = [1]
    while out[-1] < most:
        out.append(max(out[-1] + 1, out[-1] * 104 // percent + 1))
    return np.array(out, np.int64)


@lru_cache(maxsize=1024)
def block_count(t: int, smallest: int) -> int:
    """Blocks of a band that allows ``t`` differences: t + 1, and as many more as sets of its least size are likely to leave empty."""
    spare = 1
    for _ in range(8):
        empty = (t + 1 + spare) * np.exp(-smallest / (t + 1 + spare))
        spare = 1 + int(np.ceil(empty + 4 * np.sqrt(empty)))
    return t + 1 + spare


def block_keys(s: np.ndarray, like: Similarity) -> tuple[np.ndarray, int]:
    """Join keys of a set, and how many of them a linked set must share: the blocks of its parity sketch in its own band, and in the next one if a partner may be there.

    Of t + 1 + e blocks similar sets share e + 1. A set with more than e empty
    blocks uses its empty blocks as keys too, but a partner with e of them may
    not, which leaves one; otherwise at least as many as the empty ones leave of
    e + 1 are shared and not empty.
    """
    low, n, out, need = bands(like.percent), len(s), [], 1 << 30
    own = int(np.searchsorted(low, n, side="right")) - 1
    for band in range(own, own + 1 + int(n * 100 // like.percent >= low[own + 1])):
        t = like.differences(2 * int(low[band + 1] - 1))
        if t == 0:
            continue
        blocks = block_count(t, int(low[band]))
        place = _mix(s + np.uint64(band + 1))
        # the upper half of a place names the block, the lower one of its 2**32 bits
        block = ((place >> np.uint64(32)) * np.uint64(blocks) >> np.uint64(32)).astype(np.int64)
        order = np.argsort(block, kind="stable")
        at = np.flatnonzero(np.diff(block[order], prepend=-1))
        # the XOR of a value per bit: equal for equal blocks, and toggled twice a bit vanishes
        parity = np.zeros(blocks, np.uint64)
        parity[block[order][at]] = np.bitwise_xor.reduceat(_mix((place[order] & np.uint64(0xFFFFFFFF)) + np.uint64(1 << 50)), at)
        empty = int((parity == 0).sum())
        use = np.arange(blocks) if empty > blocks - t - 1 else np.flatnonzero(parity)
        need = min(need, 1 if empty > blocks - t - 1 else blocks - t - empty)
        out.append(_mix(parity[use] + _mix(use.astype(np.uint64) + np.uint64(band << 40))))
    return (np.concatenate(out).view(np.int64), need) if out else (np.empty(0, np.int64), 0)


def parity_bits(s: np.ndarray) -> np.ndarray:
    """The whole parity sketch as 64-bit words: two to four bits a member, a power of two, at most MOST_BITS."""
    width = min(MOST_BITS, 1 << max(6, (2 * len(s) - 1).bit_length()))
    odd = np.bincount((_mix(s) & np.uint64(width - 1)).astype(np.int64), minlength=width) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.uint64)


def sketch_distance(a: np.ndarray, b: np.ndarray) -> int:
    """Hamming distance once the wider sketch is folded to the other's width; at most the symmetric difference of the sets."""
    while len(a) > len(b):
        a = a[: len(a) // 2] ^ a[len(a) // 2 :]
    while len(b) > len(a):
        b = b[: len(b) // 2] ^ b[len(b) // 2 :]
    return int(np.bitwise_count(a ^ b).sum())


def _pieces(batch: pa.RecordBatch, column: int) -> Iterator[pa.RecordBatch]:
    """The batch in slices of at most 512 rows and, but for single rows, PIECE bytes of a column."""
    size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    at, before = 0, 0
    while at < batch.num_rows:
        end = max(at + 1, min(at + 512, int(np.searchsorted(size, before + PIECE, side="right"))))
        yield batch.slice(at, end - at)
        at, before = end, int(size[end - 1])


def _sketched(like: Similarity):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part in _pieces(b, 1):
                sizes, names, keys, needs, bits = [], [], [], [], []
                for text in part.column(1).cast(pa.binary()):
                    s = shingles(text.as_py() or b"", like.words)
                    sizes.append(len(s))
                    names.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None)
                    own, need = block_keys(s, like) if len(s) else (np.empty(0, np.int64), 0)
                    keys.append(own), needs.append(need)
                    bits.append(parity_bits(s).tobytes() if len(keys[-1]) else None)
                ends = np.cumsum([0, *map(len, keys)]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(keys)))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64()), pa.array(names, pa.binary()), lists, pa.array(needs, pa.int32()), pa.array(bits, pa.binary())], names=["doc_id", "n_shingles", "set_id", "keys", "need", "bits"])

    return run


def _dealt(parts: int):
    """Keys of a set grouped by the shuffle partition they go to, so that an id travels once for all of them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 512):
                part = b.slice(i, 512)
                lists = part.column(1)
                keys = lists.flatten().to_numpy(zero_copy_only=False)
                sizes = np.diff(lists.offsets.to_numpy())
                row = np.repeat(np.arange(part.num_rows), sizes)
                to = (keys.view(np.uint64) % np.uint64(parts)).astype(np.int64)
                order = np.lexsort((to, row))
                row, to, keys = row[order], to[order], keys[order]
                at = np.flatnonzero(np.diff(row * parts + to, prepend=-1))
                ends = np.append(at, len(keys)).astype(np.int32)
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(row[at])), pa.array(to[at].astype(np.int32)), pa.ListArray.from_arrays(pa.array(ends), pa.array(keys))], names=["rep", "part", "keys"])

    return run


def _named(spread) -> list:
    """n, lo and a number that stands for the ids of a bucket; ``spread`` makes an aggregate a window or leaves it alone."""
    return [spread(F.count(F.lit(1))).alias("n"), spread(F.min("rep")).alias("lo"), spread(F.sum(F.shiftright(F.xxhash64("rep"), 20))).alias("ids")]


def _merged(rows: DataFrame) -> DataFrame:
    """(bucket, n, lo, rep, w) of rows (n, lo, ids, rep): buckets with the same ids are one, which stands for w of them."""
    return rows.groupBy(F.xxhash64("n", "lo", "ids").alias("bucket"), "n", "lo", "rep").agg(F.sum("w").alias("w"))


def _buckets(reps: DataFrame) -> DataFrame:
    """(bucket, n, lo, rep, w): ids that have the same w keys, n of them, lo the least.

    Copies share most of their keys, so buckets with the same ids are merged as
    soon as they are known: the rows then follow the families of documents, not their keys.
    """
    spark = reps.sparkSession
    parts = max(GROUPS, int(spark.conf.get("spark.sql.shuffle.partitions")))
    sent = reps.select("doc_id", "keys").mapInArrow(_dealt(parts), "rep long, part int, keys array<long>").repartitionById(parts, "part")
    own = W.partitionBy("part", "key")
    met = sent.select("part", "rep", F.explode("keys").alias("key")).select("rep", *_named(lambda c: c.over(own)))
    return _merged(met.where("n > 1").withColumn("w", F.lit(1).cast("long")))


def _shared(left: DataFrame) -> DataFrame:
    """(bucket, n, lo, rep, w) of staged rows (bucket, rep, w), without ids that are alone in theirs."""
    rows = left.groupBy("bucket").agg(*_named(lambda c: c)).where("n > 1")
    return _merged(_with_buckets(left.select("bucket", "rep", "w"), stage(rows, "join-named")))


def _with_buckets(rows: DataFrame, facts: DataFrame) -> DataFrame:
    """Rows joined to a staged row for each bucket: sent to all tasks while those are few, else sorted, where Spark splits a bucket that holds too much."""
    return rows.join(F.broadcast(facts) if facts.count() <= BROADCAST_IDS else facts.hint("merge"), "bucket")


def _enough(members: DataFrame, reps: DataFrame, rounds: int = 2) -> DataFrame:
    """Staged buckets without ids that share fewer keys than any link needs, without keys that no link needs, and without what that leaves alone.

    Loses no link: two linked sets share ``need`` keys at least, of either, so
    the least of them in any one order is not among the ``need`` - 1 greatest of
    either set. The order is by the number of ids, so what goes are the keys of
    passages that many documents have.
    """
    need = reps.select(F.col("doc_id").alias("rep"), "need")
    for _ in range(rounds):
        strong = members.groupBy("rep").agg(F.sum("w").alias("t")).join(need, "rep").where("t >= need").select("rep")
        members = stage(_shared(stage(members.join(_broadcast_if_small(stage(strong, "join-strong")), "rep", "left_semi"), "join-left")), "join-buckets")
    own = W.partitionBy("rep").orderBy(F.desc("n"), F.desc("bucket"))
    rare = members.join(need, "rep").withColumn("above", F.sum("w").over(own)).where("above >= need")
    return stage(_shared(stage(rare.select("bucket", "rep", "w"), "join-left")), "join-buckets")


def _hashed(like: Similarity):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part in _pieces(b, 1):
                sets = [shingles(t.as_py() or b"", like.words) for t in part.column(1).cast(pa.binary())]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(map(len, sets), pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], names=["id", "n", "hashes"])

    return run


def _linked(a: np.ndarray, b: np.ndarray, like: Similarity) -> bool:
    both = len(a) + len(b) - len(np.union1d(a, b))
    return 100 * both >= like.percent * (len(a) + len(b) - both)


def _views(column: pa.Array) -> list[np.ndarray]:
    """The numbers in each value of a binary column, as views of its buffer."""
    if not len(column):
        return []
    ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
    whole = column.buffers()[2] or b""
    return [np.frombuffer(whole, np.uint64, (int(b) - int(a)) // 8, int(a)) for a, b in zip(ends, ends[1:], strict=False)]


def _near_pivot(like: Similarity):
    """Pairs (pivot, member) whose sketches are near enough for a link."""
    near = lambda n, a, m, b: 100 * min(n, m) >= like.percent * max(n, m) and sketch_distance(a, b) <= like.differences(n + m)
    return _to_pivots(lambda n, a, pivots: any(near(n, a, m, b) for m, b in pivots), ["lo", "rep"])


def _against_pivot(like: Similarity):
    """Links (pivot, member)."""
    return _to_pivots(lambda n, a, pivots: any(_linked(a, b, like) for _, b in pivots), ["u", "v"])


def _to_pivots(fits, names: list[str]):
    """Pairs of a pivot and a member that ``fits`` it, of rows (pivot, share, member, size, numbers) by share, the pivot's own first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pivots: list = []
        at = None
        for b in batches:
            u, v = [], []
            for pivot, share, member, n, own in zip(*(c.to_pylist() for c in b.columns[:4]), _views(b.column(4)), strict=True):
                if (pivot, share) != at:
                    at, pivots = (pivot, share), []
                if member is None:
                    pivots.append((n, own.copy()))
                elif fits(n, own, pivots):
                    u.append(pivot), v.append(member)
            yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], names=names)

    return run


def _bits(sets: list[np.ndarray]) -> np.ndarray:
    """Parity sketches of equal width; more bits than any bound on differences of ordinary sets."""
    words = BIT_WORDS
    while words < 1024 and words * 8 < max(map(len, sets)):
        words *= 2
    out = np.zeros((len(sets), words), np.uint64)
    for row, s in zip(out, sets, strict=True):
        odd = np.bincount((_mix(s) % np.uint64(words * 64)).astype(np.int64), minlength=words * 64) & 1
        row[:] = np.packbits(odd.astype(np.uint8)).view(np.uint64)
    return out


def connecting_links(rows: list[tuple], cross: bool, like: Similarity) -> list[tuple[int, int]]:
    """Links among ``rows`` (id, component, side, set) that join two components; with ``cross`` only from side 0 to side 1."""
    rows = sorted(rows, key=lambda r: len(r[3]))
    sets, sizes = [r[3] for r in rows], np.array([len(r[3]) for r in rows], np.int64)
    names, label = np.unique([r[1] for r in rows], return_inverse=True)
    side, sketch, links = np.array([r[2] for r in rows]), _bits(sets), []
    for i in range(len(rows) - 1):
        end = int(np.searchsorted(sizes, sizes[i] * 100 // like.percent, side="right"))
        rest = np.arange(i + 1, end)
        rest = rest[(label[rest] != label[i]) & ((side[rest] != side[i]) if cross else True)]
        if not len(rest):
            continue
        far = np.bitwise_count(sketch[rest] ^ sketch[i]).sum(1, dtype=np.int64)
        for j in rest[far <= (100 - like.percent) * (sizes[rest] + sizes[i]) // (100 + like.percent)]:
            if label[j] != label[i] and _linked(sets[i], sets[j], like):
                links.append((rows[i][0], rows[j][0]))
                label[label == label[j]] = label[i]
    return links


def near_others(rows: list[tuple], cross: bool, like: Similarity) -> list[int]:
    """Ids among ``rows`` (id, component, side, size, sketch) that are near one of another component by their sketches."""
    rows = sorted(rows, key=lambda r: r[3])
    sizes, side = np.array([r[3] for r in rows], np.int64), np.array([r[2] for r in rows])
    label, width = np.array([r[1] for r in rows]), min(len(r[4]) for r in rows)
    sketch = np.stack([np.bitwise_xor.reduce(r[4].reshape(-1, width), axis=0) for r in rows])
    near = np.zeros(len(rows), bool)
    for i in range(len(rows) - 1):
        end = int(np.searchsorted(sizes, sizes[i] * 100 // like.percent, side="right"))
        rest = np.arange(i + 1, end)
        rest = rest[(label[rest] != label[i]) & ((side[rest] != side[i]) if cross else True)]
        if len(rest):
            far = np.bitwise_count(sketch[rest] ^ sketch[i]).sum(1, dtype=np.int64)
            hit = rest[far <= (100 - like.percent) * (sizes[rest] + sizes[i]) // (100 + like.percent)]
            near[hit] = True
            near[i] |= len(hit) > 0
    return [r[0] for r, x in zip(rows, near, strict=True) if x]


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, bool, list[tuple]]]:
    """Runs of rows (bucket, i, j, own, rep, component, n, numbers): the bucket, whether two chunks meet, and (rep, component, side, n, numbers)."""
    at, rows = None, []
    for b in batches:
        for bucket, i, j, own, rep, component, n, numbers in zip(*(c.to_pylist() for c in b.columns[:7]), _views(b.column(7)), strict=True):
            if (bucket, i, j) != at:
                if len(rows) > 1:
                    yield at[0], at[1] != at[2], rows
                at, rows = (bucket, i, j), []
            rows.append((rep, component, int(own != i), n, numbers))
    if len(rows) > 1:
        yield at[0], at[1] != at[2], rows


def _near_in_chunks(like: Similarity):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for bucket, cross, rows in _runs(batches):
            near = near_others(rows, cross, like)
            if near:
                yield pa.RecordBatch.from_arrays([pa.array([bucket] * len(near), pa.int64()), pa.array(near, pa.int64())], names=["bucket", "rep"])

    return run


def _chunk_pairs(like: Similarity):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, cross, rows in _runs(batches):
            links = connecting_links([(*r[:3], r[4]) for r in rows], cross, like)
            if links:
                yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in links], pa.int64()) for i in (0, 1)], names=["u", "v"])

    return run


def _broadcast_if_small(rows: DataFrame) -> DataFrame:
    return F.broadcast(rows) if rows.count() <= BROADCAST_IDS else rows


def _sets_of(ids: DataFrame, docs: DataFrame, like: Similarity) -> DataFrame:
    wanted = docs.join(_broadcast_if_small(stage(ids.distinct(), "join-ids")), docs["doc_id"] == F.col("id"), "left_semi")
    return stage(wanted.select("doc_id", "text").mapInArrow(_hashed(like), "id long, n long, hashes binary"), "join-sets")


def _with_pivots(pairs: DataFrame, facts: DataFrame, columns: list[str]) -> DataFrame:
    """Members of staged (lo, rep) pairs with their facts, by (lo, share) and behind the pivot's own facts.

    The pairs go to the facts while they are few, so that facts travel once.
    """
    shared = pairs.withColumn("share", F.pmod(F.xxhash64("rep"), F.lit(SHARES)))
    few = pairs.count() <= BROADCAST_IDS
    sent = lambda df: F.broadcast(df) if few else df
    pivots = facts.join(sent(shared.select("lo", "share").distinct()), F.col("lo") == F.col("id")).select("lo", "share", F.lit(None).cast("long").alias("rep"), *columns)
    others = facts.join(sent(shared), F.col("rep") == F.col("id")).select("lo", "share", "rep", *columns)
    return pivots.unionByName(others).repartition("lo", "share").sortWithinPartitions("lo", "share", F.col("rep").asc_nulls_first())


def _sketches(reps: DataFrame) -> DataFrame:
    return reps.select(F.col("doc_id").alias("id"), F.col("n_shingles").alias("n"), "bits")


def _phase_one(members: DataFrame, reps: DataFrame, docs: DataFrame, like: Similarity) -> DataFrame:
    """Links between each bucket's least id and its other members: sketches first, then the sets of what is near."""
    pairs = stage(members.where("rep <> lo").select("lo", "rep").distinct(), "join-pairs")
    near = _with_pivots(pairs, _sketches(reps), ["n", "bits"])
    near = stage(near.mapInArrow(_near_pivot(like), "lo long, rep long").distinct(), "join-near")
    sets = _sets_of(near.select(F.explode(F.array("lo", "rep")).alias("id")), docs, like)
    return stage(_with_pivots(near, sets, ["n", "hashes"]).mapInArrow(_against_pivot(like), "u long, v long"), "join-links")


def _in_chunks(own: DataFrame, facts: DataFrame, column: str) -> DataFrame:
    """Staged (bucket, rep, component) with facts, so that each two chunks of a bucket meet in one run of rows (bucket, i, j).

    A chunk is bounded by its sets and by their members; only a bucket beyond that has several.
    """
    few = _broadcast_if_small(own)
    sized = stage(facts.select("id", "n").join(few, F.col("rep") == F.col("id")).select("bucket", "rep", "component", "n"), "join-sized")
    chunks = sized.groupBy("bucket").agg(F.least(F.count(F.lit(1)), F.greatest(F.ceil(F.count(F.lit(1)) / CHUNK), F.ceil(F.sum("n") / MEMBERS))).cast("int").alias("chunks"))
    dealt = _with_buckets(sized.drop("n"), stage(chunks, "join-chunks")).withColumn("own", F.pmod(F.xxhash64("rep", F.lit(7)), F.col("chunks")).cast("int"))
    dealt = facts.join(_broadcast_if_small(stage(dealt, "join-dealt")), F.col("rep") == F.col("id"))
    dealt = dealt.select("bucket", "own", "rep", "component", "n", column, F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("with"))
    dealt = dealt.select("bucket", F.least("own", "with").alias("i"), F.greatest("own", "with").alias("j"), "own", "rep", "component", "n", column)
    return dealt.repartition("bucket", "i", "j").sortWithinPartitions("bucket", "i", "j")


def _mixed(own: DataFrame) -> DataFrame:
    """Staged rows (bucket, rep, component) of buckets with several components; of buckets with the same ids, one."""
    facts = own.groupBy("bucket").agg(F.min("component").alias("a"), F.max("component").alias("b"), *_named(lambda c: c)).where("a < b")
    named = facts.groupBy("n", "lo", "ids").agg(F.min("bucket").alias("bucket")).select("bucket")
    return stage(_with_buckets(own, stage(named, "join-mixed")), "join-mixed")


def _phase_two(members: DataFrame, first: DataFrame, reps: DataFrame, docs: DataFrame, like: Similarity) -> DataFrame | None:
    """Links between components that still share a bucket, or None if there are none. The pivots have met all others of their buckets already."""
    first = _broadcast_if_small(first.withColumnRenamed("id", "rep"))
    own = members.where("rep <> lo").join(first, "rep", "left").select("bucket", "rep", F.coalesce("component", "rep").alias("component"))
    own = _mixed(stage(own, "join-members"))
    if own.isEmpty():
        return None
    near = _in_chunks(own, _sketches(reps), "bits").mapInArrow(_near_in_chunks(like), "bucket long, rep long").distinct()
    own = _mixed(stage(own.join(_broadcast_if_small(stage(near, "join-near")), ["bucket", "rep"], "left_semi"), "join-members"))
    if own.isEmpty():
        return None
    met = _in_chunks(own, _sets_of(own.select(F.col("rep").alias("id")), docs, like), "hashes")
    return stage(met.mapInArrow(_chunk_pairs(like), "u long, v long"), "join-links")


def similar_components(docs: DataFrame, like: Similarity = Similarity()) -> DataFrame:
    """doc_id, n_shingles and component_id (least doc_id reachable by links) for each row."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    made = stage(docs.mapInArrow(_sketched(like), "doc_id long, n_shingles long, set_id binary, keys array<long>, need int, bits binary"), "join-sketches")
    sizes = made.where("n_shingles > 0").groupBy("set_id").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("n"))
    copies = stage(sizes.where("n > 1").select("set_id", "rep"), "join-copies")
    few = _broadcast_if_small(copies)
    reps = made.where("size(keys) > 0 AND doc_id IS NOT NULL").join(few, "set_id", "left").where("rep IS NULL OR rep = doc_id")
    members = _enough(stage(_buckets(reps), "join-buckets"), reps)
    links = _phase_one(members, reps, docs, like)
    found = stage(components(links), "join-components")
    more = _phase_two(members, found, reps, docs, like)
    if more is not None and not more.isEmpty():
        found = stage(components(links.unionByName(more)), "join-components")
    named = made.select("doc_id", "n_shingles", "set_id").join(few, "set_id", "left").withColumn("rep", F.coalesce("rep", "doc_id"))
    return named.join(found.distinct(), F.col("rep") == F.col("id"), "left").select("doc_id", "n_shingles", F.coalesce("component", "rep").alias("component_id"))


def _unlike(rows: DataFrame) -> DataFrame:
    """Rows alike in every column once; columns may have any type and any name, equal maps count as alike if their entries are in one order."""
    digest = "digest"
    while digest in rows.columns:
        digest += "_"
    exact = {"timestampFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSSXXX", "timestampNTZFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSS"}
    own = F.to_json(F.struct(*[F.col("`" + c.replace("`", "``") + "`") for c in rows.columns]), exact)
    return rows.withColumn(digest, F.sha2(own, 256)).dropDuplicates(["doc_id", digest]).drop(digest)


def distinct_documents(docs: DataFrame, like: Similarity = Similarity()) -> DataFrame:
    """One document of each component stays, the one whose doc_id names it; rows alike in every column stay once; documents without words all stay."""
    found = similar_components(docs, like).where("doc_id IS NULL OR doc_id = component_id OR n_shingles = 0")
    keep = _broadcast_if_small(stage(found.select(F.col("doc_id").alias("kept_id")).distinct(), "join-kept"))
    kept = docs.join(keep, docs["doc_id"].eqNullSafe(keep["kept_id"]), "left_semi")
    again = stage(docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col("doc_id").alias("again_id")), "join-again")
    if again.isEmpty():
        return kept
    again = _broadcast_if_small(again)
    same = kept["doc_id"].eqNullSafe(again["again_id"])
    return kept.join(again, same, "left_anti").unionByName(_unlike(kept.join(again, same, "left_semi")))


#: The query's own similarity: three words, nine tenths.
QUERY_LIKE = Similarity(words=3, percent=90)


def query(spark, sf_dir: str) -> DataFrame:
    return similar_components(spark.read.parquet(f"{sf_dir}/documents.parquet"), QUERY_LIKE)
