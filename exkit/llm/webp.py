"""Media columns: lossless WebP (VP8L) written and read without an imaging library.

``decode`` is a whole VP8L decoder: prefix codes, meta prefix groups, back-references
with the near-distance map, colour cache, and the predictor, cross-colour,
subtract-green and palette transforms; it returns the pixel array (rows,
columns, RGBA). Streams of one prefix group are read by looking up the symbols at
every bit of a block at once and following the steps from symbol to symbol; streams
of several groups are read symbol by symbol. ``encode`` writes palettes, predictors,
back-references, colour cache and prefix codes as they suit an image (``level=2``);
levels 0 and 1 are plain forms: flat eight-bit codes, and green subtracted with
codes by frequency.

``media_digests`` stores a text column as RGB rows of 64 pixels and reads it
back. Defined results: null and empty texts are one row of 192 spaces; texts of
any length are whole (an image has at most 16,384 rows, longer ones become
several images, one after the other); repeated rows give equal rows; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import gc
import hashlib
import struct
import zlib
from collections import Counter
from collections.abc import Iterator
from functools import cached_property, lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

WIDTH, MAX_SIDE, ROW = 64, 16_384, 192

# Fixed values of the format: order of code-length codes, and the offsets that near distance codes stand for.
LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
NEAR = (
    (0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0), (1, 2), (-1, 2), (2, 1), (-2, 1), (2, 2), (-2, 2), (0, 3), (3, 0), (1, 3), (-1, 3), (3, 1), (-3, 1), (2, 3), (-2, 3),
    (3, 2), (-3, 2), (0, 4), (4, 0), (1, 4), (-1, 4), (4, 1), (-4, 1), (3, 3), (-3, 3), (2, 4), (-2, 4), (4, 2), (-4, 2), (0, 5), (3, 4), (-3, 4), (4, 3), (-4, 3), (5, 0),
    (1, 5), (-1, 5), (5, 1), (-5, 1), (2, 5), (-2, 5), (5, 2), (-5, 2), (4, 4), (-4, 4), (3, 5), (-3, 5), (5, 3), (-5, 3), (0, 6), (6, 0), (1, 6), (-1, 6), (6, 1), (-6, 1),
    (2, 6), (-2, 6), (6, 2), (-6, 2), (4, 5), (-4, 5), (5, 4), (-5, 4), (3, 6), (-3, 6), (6, 3), (-6, 3), (0, 7), (7, 0), (1, 7), (-1, 7), (5, 5), (-5, 5), (7, 1), (-7, 1),
    (4, 6), (-4, 6), (6, 4), (-6, 4), (2, 7), (-2, 7), (7, 2), (-7, 2), (3, 7), (-3, 7), (7, 3), (-7, 3), (5, 6), (-5, 6), (6, 5), (-6, 5), (8, 0), (4, 7), (-4, 7), (7, 4),
    (-7, 4), (8, 1), (8, 2), (6, 6), (-6, 6), (8, 3), (5, 7), (-5, 7), (7, 5), (-7, 5), (8, 4), (6, 7), (-6, 7), (7, 6), (-7, 6), (8, 5), (7, 7), (-7, 7), (8, 6), (8, 7),
)
CACHE_FACTOR = 0x1E35A7BD
#: Bits looked up at once; pixels that a back-reference has to cover and its longest copy; the farthest distance that has a code.
BLOCK, SHORTEST, LONGEST, FARTHEST = 1 << 15, 3, 4096, (1 << 20) - 120
SHIFTS, PLACES = np.arange(8), np.arange(BLOCK)
#: Pixels that show whether an image has more colours than a palette.
MANY = 600
#: Longest prefix that is written; the format allows 15, and shorter ones need smaller tables to read.
MOST_LENGTH = 11
#: Lengths of the code that code lengths up to MOST_LENGTH are written in, by their frequency in prose.
STEP_LENGTHS = {0: 2, 1: 7, 2: 7, 3: 5, 4: 4, 5: 4, 6: 4, 7: 4, 8: 4, 9: 4, 10: 4, 11: 4, 16: 6, 17: 4, 18: 3}
#: Bits of code lengths that are held as one number.
HEADER = 1024
#: Extra bits of a length or distance prefix, and the value it starts from.
EXTRA = np.array([0] * 4 + [(p - 2) >> 1 for p in range(4, 40)], np.int64)
BASE = np.array([1, 2, 3, 4] + [((2 + (p & 1)) << ((p - 2) >> 1)) + 1 for p in range(4, 40)], np.int64)
FLIPPED = np.array([int(f"{i:08b}"[::-1], 2) for i in range(256)], dtype=np.uint8)


#: What a decoder counts: events of each kind, and transforms by their number in the format.
SEEN = ("literals", "copies", "cache_hits", "predictors", "cross_colours", "green_sums", "palettes")


class Bits:
    """Reads and writes bits, lowest first; ``seen`` counts what was read by SEEN."""

    def __init__(self, data: bytes = b"", at: int = 0):
        self.data, self.at, self.out, self.n = data, at, 0, 0
        self.seen = [0] * len(SEEN)

    def read(self, k: int) -> int:
        first = self.at >> 3
        v = int.from_bytes(self.data[first : first + (k + 14) // 8 + 1], "little") >> (self.at & 7)
        self.at += k
        return v & ((1 << k) - 1)

    def write(self, value: int, k: int) -> None:
        self.out |= value << self.n
        self.n += k

    def write_all(self, values: np.ndarray, sizes: np.ndarray) -> None:
        """Writes many values of at most 22 bits each."""
        ends = np.cumsum(sizes)
        total = int(ends[-1]) if len(ends) else 0
        at = ends - sizes
        # Bits of one word never overlap, so that their sum, below 2**53, is exact as a float.
        words = np.bincount(at >> 5, weights=(values << (at & 31)).astype(np.float64), minlength=(total >> 5) + 2).astype(np.uint64)
        low = (words & 0xFFFFFFFF).astype(np.uint32)
        low[1:] |= (words[:-1] >> np.uint64(32)).astype(np.uint32)
        self.write(int.from_bytes(low.astype("<u4").tobytes(), "little"), total)

    def bytes(self) -> bytes:
        return self.out.to_bytes((self.n + 7) // 8, "little")


@lru_cache(maxsize=16)
def _turned(width: int) -> np.ndarray:
    """The numbers of ``width`` bits with their bits in reverse order."""
    out = np.zeros(1, np.int64)
    for _ in range(width):
        out = np.concatenate([out * 2, out * 2 + 1])
    return out


class Code:
    """A canonical prefix code: table from the next ``width`` bits to (symbol, length)."""

    def __init__(self, lengths: list[int] | np.ndarray):
        sizes = np.asarray(lengths, np.int64)
        used = sizes.nonzero()[0]
        own = sizes[used]
        self.only = int(used[0]) if len(used) == 1 else None
        self.width = 0 if self.only is not None else int(own.max(initial=0))
        self.symbols, self.sizes = used[own.argsort(kind="stable")], sizes

    @cached_property
    def flat(self) -> bool:
        return len(self.sizes) >= 256 and bool((self.sizes[:256] == 8).all()) and not self.sizes[256:].any()

    @cached_property
    def codes(self) -> dict[int, tuple[int, int]]:
        values, sizes = self.written
        return {s: (int(values[s]), int(sizes[s])) for s in self.symbols.tolist()}

    @cached_property
    def written(self) -> tuple[np.ndarray, np.ndarray]:
        """Bits and number of bits to write for each symbol."""
        values = np.zeros(len(self.sizes), np.int64)
        if self.only is not None:
            return values, values
        share = 1 << (self.width - self.sizes[self.symbols])
        values[self.symbols] = _turned(self.width)[np.cumsum(share) - share]
        return values, self.sizes

    @cached_property
    def lookup(self) -> tuple[np.ndarray, np.ndarray]:
        """Symbol and number of bits by the next ``width`` bits."""
        if self.only is not None:
            return np.array([self.only]), np.array([0])
        own = self.sizes[self.symbols]
        share = 1 << (self.width - own)
        symbols, sizes = np.zeros(1 << self.width, np.int64), np.full(1 << self.width, self.width)
        n = min(int(share.sum()), 1 << self.width)
        symbols[:n], sizes[:n] = np.repeat(self.symbols, share)[:n], np.repeat(own, share)[:n]
        turned = _turned(self.width)
        return symbols[turned], sizes[turned]

    @cached_property
    def table(self) -> list[tuple[int, int]]:
        return list(zip(*(a.tolist() for a in self.lookup), strict=True))

    def read(self, bits: Bits) -> int:
        if self.only is not None:
            return self.only
        at = bits.at
        symbol, n = self.table[bits.read(self.width)]
        bits.at = at + n
        return symbol


@lru_cache(maxsize=256)
def _code(lengths: bytes) -> Code:
    return Code(list(lengths))


@lru_cache(maxsize=256)
def _small_table(lengths: tuple[int, ...]) -> tuple[list[tuple[int, int]], int]:
    """What ``Code.table`` has for a few symbols, and the bits that it is looked up by."""
    used = sorted([(n, s) for s, n in enumerate(lengths) if n])
    if len(used) == 1:
        return [(used[0][1], 0)], 0
    width = used[-1][0] if used else 0
    table, turned, at = [(0, width)] * (1 << width), _turned(width).tolist(), 0
    for n, s in used:
        for i in turned[at : at + (1 << width - n)]:
            table[i] = (s, n)
        at += 1 << width - n
    return table, width


def _read_code(bits: Bits, size: int) -> Code:
    lengths = [0] * size
    if bits.read(1):
        two, wide = bits.read(1), bits.read(1)
        lengths[bits.read(8 if wide else 1)] = 1
        if two:
            lengths[bits.read(8)] = 1
        return _code(bytes(lengths))
    small, n = [0] * 19, 4 + bits.read(4)
    found = bits.read(3 * n)
    for i in range(n):
        small[LENGTH_ORDER[i]] = found >> 3 * i & 7
    (table, width), left = _small_table(tuple(small)), size
    if bits.read(1):
        left = 2 + bits.read(2 + 2 * bits.read(3))
    mask, start = (1 << width) - 1, bits.at
    held = lambda: int.from_bytes(bits.data[start >> 3 : (start + HEADER >> 3) + 1], "little") >> (start & 7)
    now, gone, at, before = held(), 0, 0, 8
    while at < size and left:
        if gone > HEADER - 14:  # a symbol and its extra bits take 14 at most
            start += gone
            now, gone = held(), 0
        left -= 1
        s, n = table[now & mask]
        now, gone = now >> n, gone + n
        if s < 16:
            lengths[at] = s
            before, at = s or before, at + 1
            continue
        more, k, v = (2, 3, before) if s == 16 else (3, 3, 0) if s == 17 else (7, 11, 0)
        k += now & ((1 << more) - 1)
        now, gone = now >> more, gone + more
        if v:
            lengths[at : at + k] = [v] * k
        at += k
    bits.at = start + gone
    return _code(bytes(lengths[:size]))


def _spread(bits: Bits, prefix: int) -> int:
    if prefix < 4:
        return prefix + 1
    extra = (prefix - 2) >> 1
    return ((2 + (prefix & 1)) << extra) + bits.read(extra) + 1


def _codes(bits: Bits, cache_bits: int) -> list[Code]:
    codes: list[Code] = []
    start, before = 0, 0
    for n in (280 + (1 << cache_bits if cache_bits else 0), 256, 256, 256, 40):
        at, k = bits.at, bits.at - start
        if len(codes) > 1 and n == before and Bits(bits.data, at).read(k) == Bits(bits.data, start).read(k):  # the same bits are the same code
            codes.append(codes[-1])
            bits.at += k
        else:
            codes.append(_read_code(bits, n))
        start, before = at, n
    return codes


def _image(bits: Bits, width: int, height: int, main: bool) -> np.ndarray:
    """Pixels as ARGB numbers, row by row."""
    cache_bits = bits.read(4) if bits.read(1) else 0
    groups, tiles, tile_bits = 1, None, 0
    if main and bits.read(1):
        tile_bits = bits.read(3) + 2
        across = -(-width >> tile_bits) if width & ((1 << tile_bits) - 1) == 0 else (width >> tile_bits) + 1
        tiles = (_image(bits, across, -(-height // (1 << tile_bits)), False) >> 8 & 0xFFFF).reshape(-1, across)
        groups = int(tiles.max()) + 1
    sets = [_codes(bits, cache_bits) for _ in range(groups)]
    green, red, blue, alpha, far = sets[0]
    if groups == 1 and green.flat and red.flat and blue.flat and alpha.only is not None and not cache_bits:
        n = 3 * width * height
        raw = np.frombuffer(bits.data, np.uint8, count=-1)[bits.at >> 3 :][: n + 1].astype(np.uint16)
        raw = np.append(raw, np.zeros(max(0, n + 1 - len(raw)), np.uint16))
        shift = bits.at & 7
        g = FLIPPED[((raw[:-1] >> shift) | (raw[1:] << (8 - shift))) & 255].reshape(-1, 3).astype(np.uint32)
        bits.at += 8 * n
        bits.seen[0] += width * height
        return alpha.only << 24 | g[:, 1] << 16 | g[:, 0] << 8 | g[:, 2]
    if groups == 1 and green.only is None:
        return _events(bits, sets[0], cache_bits, width, width * height)
    out: list[int] = []
    cache, total = [0] * (1 << cache_bits), width * height
    keep = lambda p: cache.__setitem__((CACHE_FACTOR * p & 0xFFFFFFFF) >> (32 - cache_bits), p) if cache_bits else None
    while len(out) < total:
        if tiles is not None:
            green, red, blue, alpha, far = sets[tiles[(len(out) // width) >> tile_bits][(len(out) % width) >> tile_bits]]
        s = green.read(bits)
        bits.seen[(s >= 256) + (s >= 280)] += 1
        if s < 256:
            r, b = red.read(bits), blue.read(bits)
            out.append(alpha.read(bits) << 24 | r << 16 | s << 8 | b)
            keep(out[-1])
        elif s < 280:
            n, d = _spread(bits, s - 256), _spread(bits, far.read(bits))
            if d > 120:
                d -= 120
            else:
                x, y = NEAR[d - 1]
                d = max(1, x + y * width)
            for _ in range(min(n, total - len(out))):
                out.append(out[-d])
                keep(out[-1])
        else:
            out.append(cache[s - 280])
            keep(out[-1])
    return np.array(out, dtype=np.uint32)


def _events(bits: Bits, codes: list[Code], cache_bits: int, width: int, total: int) -> np.ndarray:
    """``total`` pixels of one prefix group: literals, copies and cache hits, a block of bits at a time."""
    blocks = _blocks(bits, codes, total)
    return _filled_by_cache(blocks, cache_bits, width, total) if cache_bits else _filled(blocks, width, total)


def _followed(ends: np.ndarray, start: int) -> np.ndarray:
    """``start`` and what follows it when each place leads to its later place in ``ends``, as far as there are places; eight at a step."""
    n = len(ends)
    one = np.append(np.minimum(ends, n), n)
    two = one.take(one, mode="clip")
    four = two.take(two, mode="clip")
    leads, eighths, p = four.take(four, mode="clip").data, [], start
    while p < n:
        eighths.append(p)
        p = leads[p]
    out = np.empty((len(eighths), 8), np.int64)
    out[:, 0] = eighths
    out[:, 4] = four[out[:, 0]]
    out[:, 2::4] = two[out[:, ::4]]
    out[:, 1::2] = one[out[:, ::2]]
    out = out.reshape(-1)
    return out[: int(np.searchsorted(out, n))]


def _blocks(bits: Bits, codes: list[Code], total: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Green symbols, values (pixel, distance code or place in the cache) and lengths of the events of a block of bits."""
    (gs, gn), (rs, rn), (bs, bn), (as_, an), (ds, dn) = (c.lookup for c in codes)
    gm, rm, bm, am, dm = ((1 << c.width) - 1 for c in codes)
    gs = gs.astype(np.uint16)
    while total > 0:
        first, left = bits.at >> 3, bits.at & 7
        raw = bits.data[first : first + BLOCK // 8 + 24]
        usable = min(BLOCK, 8 * len(raw))
        if left >= usable:
            raise ValueError("VP8L stream ends early")
        eight = np.ndarray(len(raw) + 22, "<i8", raw + bytes(29), strides=(1,))  # the eight bytes that begin at each
        windows = (eight[:, None] >> SHIFTS).reshape(-1)  # of which 57 bits are sure to be there
        own = windows[:usable] & gm
        g, ends = gs.take(own, mode="clip"), gn.take(own, mode="clip")  # a step as if each bit began a literal, mended for the others
        ends += PLACES[:usable]
        after = ends
        further = {}  # bits of the code that begins at each bit, once for codes that are the same
        for n, m in ((rn, rm), (bn, bm), (an, am)):
            if m:
                if id(n) not in further:
                    further[id(n)] = n.take(windows & m, mode="clip")
                ends = ends + further[id(n)].take(ends, mode="clip")
        other = (g >= 256).nonzero()[0]
        if after is not ends:
            ends[other] = after[other]
        copies = other[g[other] < 280]
        p = after[copies] + EXTRA[g[copies] - 256]
        far = windows[p] & dm
        p = p + dn[far]
        if after is ends:
            ends = ends.copy()
        ends[copies] = p + EXTRA[np.minimum(ds[far], 39)]
        where = _followed(ends, left)
        kind, p = g[where].astype(np.int64), after[where]
        sizes = np.ones(len(where), np.int64)
        values = kind - 280
        literal, copy = np.flatnonzero(kind < 256), np.flatnonzero((kind >= 256) & (kind < 280))
        q = p[literal]
        r = windows[q] & rm
        q = q + rn[r]
        b = windows[q] & bm
        q = q + bn[b]
        values[literal] = as_[windows[q] & am] << 24 | rs[r] << 16 | kind[literal] << 8 | bs[b]
        q, prefix = p[copy], kind[copy] - 256
        more = lambda q, k: windows[q] & ((1 << k) - 1)
        sizes[copy] = BASE[prefix] + more(q, EXTRA[prefix])
        q = q + EXTRA[prefix]
        far = windows[q] & dm
        prefix = ds[far]
        values[copy] = BASE[prefix] + more(q + dn[far], EXTRA[prefix])
        sums = np.cumsum(sizes)
        n = min(int(np.searchsorted(sums, total)) + 1, len(where))
        bits.at = 8 * first + int(ends[where[n - 1]])
        total -= int(sums[n - 1])
        other = kind[:n][kind[:n] >= 256]
        cached = int((other >= 280).sum())
        for i, k in enumerate((n - len(other), len(other) - cached, cached)):
            bits.seen[i] += k
        yield kind[:n], values[:n], sizes[:n]


def _distance(code: int, width: int, held: int) -> int:
    if code > 120:
        code -= 120
    else:
        x, y = NEAR[code - 1]
        code = max(1, x + y * width)
    if code > held:
        raise ValueError("copy from before the image")
    return code


def _filled(blocks: Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]], width: int, total: int) -> np.ndarray:
    """Pixels of events without a cache: all literals at once, then the copies in order."""
    out, done = np.zeros(total, np.uint32), 0
    for kind, values, sizes in blocks:
        ends = done + np.cumsum(sizes)
        at = ends - sizes
        literal = kind < 256
        out[at[literal]] = values[literal]
        copies = np.flatnonzero(~literal)
        for p, code, k in zip(at[copies].tolist(), values[copies].tolist(), sizes[copies].tolist(), strict=True):
            d, k = _distance(code, width, p), min(k, total - p)
            out[p : p + k] = out[p - d : p - d + k] if k <= d else np.resize(out[p - d : p], k)
        done = int(ends[-1])
    return out


def _filled_by_cache(blocks: Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]], cache_bits: int, width: int, total: int) -> np.ndarray:
    """Pixels of events with a cache, which holds the last pixel of each hash."""
    out: list[int] = []
    cache = [0] * (1 << cache_bits)
    shift = 32 - cache_bits
    for kind, values, sizes in blocks:
        n, keys = len(kind), ((CACHE_FACTOR * values & 0xFFFFFFFF) >> shift).tolist()
        special = np.flatnonzero(kind >= 256).tolist() + [n]
        values, sizes, own = values.tolist(), sizes.tolist(), kind.tolist()
        before = 0
        for i in special:
            if i > before:
                out += values[before:i]
                for k in range(before, i):  # mostly one or two, where a cache pays
                    cache[keys[k]] = values[k]
            before = i + 1
            if i == n:
                break
            if own[i] >= 280:
                out.append(cache[values[i]])
                continue
            d, k = _distance(values[i], width, len(out)), min(sizes[i], total - len(out))
            pixels = out[-d : len(out) - d + k] if k < d else (out[-d:] * (k // d + 1))[:k]
            out += pixels
            for p in pixels:
                cache[(CACHE_FACTOR * p & 0xFFFFFFFF) >> shift] = p
    return np.array(out, dtype=np.uint32)


def _channels(argb: np.ndarray, width: int) -> np.ndarray:
    return argb.astype("<u4").view(np.uint8).reshape(-1, width, 4)[..., [2, 1, 0, 3]]


def _predicted(mode: int, left, top, top_right, top_left):
    half = lambda a, b: (a + b) >> 1
    if mode == 11:
        toward = int(np.abs(left + top - top_left - left).sum()) < int(np.abs(left + top - top_left - top).sum())
        return left if toward else top
    return {
        1: lambda: left, 2: lambda: top, 3: lambda: top_right, 4: lambda: top_left,
        5: lambda: half(half(left, top_right), top), 6: lambda: half(left, top_left), 7: lambda: half(left, top),
        8: lambda: half(top_left, top), 9: lambda: half(top, top_right),
        10: lambda: half(half(left, top_left), half(top, top_right)),
        12: lambda: np.clip(left + top - top_left, 0, 255),
        13: lambda: np.clip((m := half(left, top)) + np.trunc((m - top_left) / 2).astype(int), 0, 255),
    }.get(mode, lambda: np.array([0, 0, 0, 255]))()


def _undo_predictor(px: np.ndarray, size_bits: int, modes: np.ndarray) -> np.ndarray:
    height, width, _ = px.shape
    if modes.min() == modes.max() and modes[0, 0] in (1, 2):
        out = px.astype(np.uint8)
        out[:1, :1, 3] -= 1  # black is opaque: 255 is -1
        edge = out[:, :1] if modes[0, 0] == 1 else out[:1]
        edge[:] = np.cumsum(edge, axis=int(modes[0, 0] == 2), dtype=np.uint8)
        return np.cumsum(out, axis=int(modes[0, 0] == 1), dtype=np.uint8)
    out = px.astype(np.int64)
    for y in range(height):
        for x in range(width):
            if x == 0 or y == 0:
                guess = np.array([0, 0, 0, 255]) if x == y else out[y, x - 1] if y == 0 else out[y - 1, x]
            else:
                right = out[y - 1, x + 1] if x + 1 < width else out[y, 0]
                guess = _predicted(int(modes[y >> size_bits, x >> size_bits]), out[y, x - 1], out[y - 1, x], right, out[y - 1, x - 1])
            out[y, x] = (out[y, x] + guess) & 255
    return out.astype(np.uint8)


def _undo_cross_colour(px: np.ndarray, size_bits: int, parts: np.ndarray) -> np.ndarray:
    height, width, _ = px.shape
    own = parts[np.arange(height)[:, None] >> size_bits, np.arange(width)[None, :] >> size_bits].astype(np.int8).astype(int)
    signed = lambda a: a.astype(np.uint8).astype(np.int8).astype(int)
    green = signed(px[..., 1])
    red = (px[..., 0] + (own[..., 2] * green >> 5)) & 255
    blue = (px[..., 2] + (own[..., 1] * green >> 5) + (own[..., 0] * signed(red) >> 5)) & 255
    return np.stack([red, px[..., 1], blue, px[..., 3]], -1).astype(np.uint8)


def _undo_palette(px: np.ndarray, width: int, pack_bits: int, colours: np.ndarray) -> np.ndarray:
    index, per = px[..., 1], 1 << pack_bits
    if pack_bits:
        deep = 8 >> pack_bits
        index = np.stack([index >> (deep * i) & ((1 << deep) - 1) for i in range(per)], -1).reshape(px.shape[0], -1)[:, :width]
    table = np.zeros((256, 4), np.uint8)
    table[: len(colours)] = colours
    return table[index]


def _one(chunk: bytes, seen: list[int] | None = None) -> np.ndarray:
    bits = Bits(chunk, 8)
    bits.seen = bits.seen if seen is None else seen
    if chunk[0] != 0x2F:
        raise ValueError("not a VP8L stream")
    width, height = bits.read(14) + 1, bits.read(14) + 1
    bits.at += 1
    if bits.read(3):
        raise ValueError("unknown VP8L version")
    undo, now = [], width
    while bits.read(1):
        kind = bits.read(2)
        bits.seen[3 + kind] += 1
        if kind in (0, 1):
            b = bits.read(3) + 2
            across, down = -(-now // (1 << b)), -(-height // (1 << b))
            tiles = _channels(_image(bits, across, down, False), across)
            undo.append((lambda px, b=b, t=tiles: _undo_predictor(px, b, t[..., 1])) if kind == 0 else (lambda px, b=b, t=tiles: _undo_cross_colour(px, b, t)))
        elif kind == 2:
            undo.append(lambda px: np.stack([px[..., 0] + px[..., 1], px[..., 1], px[..., 2] + px[..., 1], px[..., 3]], -1))
        else:
            n = bits.read(8) + 1
            colours = np.cumsum(_channels(_image(bits, n, 1, False), n)[0], axis=0, dtype=np.uint8)
            pack = 3 if n <= 2 else 2 if n <= 4 else 1 if n <= 16 else 0
            undo.append(lambda px, w=now, p=pack, c=colours: _undo_palette(px, w, p, c))
            now = -(-now // (1 << pack))
    px = _channels(_image(bits, now, height, True), now)
    for f in reversed(undo):
        px = f(px)
    return px


def decode(media: bytes, seen: list[int] | None = None) -> list[np.ndarray]:
    """The images in ``media``, each (rows, columns, RGBA); ``seen`` gets the counts of SEEN."""
    out, at = [], 0
    while at < len(media):
        tag, size, kind = struct.unpack_from("<4sI4s", media, at)
        if tag != b"RIFF" or kind != b"WEBP":
            raise ValueError("not a WebP file")
        end, chunk = at + 8 + size, at + 12
        while chunk < end:
            name, n = struct.unpack_from("<4sI", media, chunk)
            if name == b"VP8L":
                out.append(_one(media[chunk + 8 : chunk + 8 + n], seen))
            chunk += 8 + n + (n & 1)
        at = end
    return out


def _depths(weights: list[int]) -> list[int]:
    """Depth of each of the ascending weights when the two least are merged again and again."""
    made = len(weights)
    weights, parent = [*weights, 1 << 60], [0] * (2 * made)
    merged, leaf, inner, least = [], 0, 0, 1 << 60  # the least merged weight not yet used, if any
    for node in range(made, 2 * made - 1):
        if weights[leaf] <= least:
            one = weights[leaf]
            parent[leaf] = node
            leaf += 1
        else:
            one = least
            parent[made + inner] = node
            inner += 1
            least = merged[inner] if inner < len(merged) else 1 << 60
        if weights[leaf] <= least:
            one += weights[leaf]
            parent[leaf] = node
            leaf += 1
        else:
            one += least
            parent[made + inner] = node
            inner += 1
        merged.append(one)
        least = merged[inner]
    deep = [0] * (2 * made)
    for node in range(2 * made - 3, -1, -1):
        deep[node] = deep[parent[node]] + 1
    return deep[:made]


def _sizes(counts: np.ndarray, limit: int = MOST_LENGTH) -> np.ndarray:
    """Code length of each symbol by its count, 0 where it has none; counts are flattened until no length is above ``limit``."""
    used = counts.nonzero()[0]
    own, out = counts[used], np.zeros(len(counts), np.int64)
    order = own.argsort(kind="stable")
    symbols, weights = used[order], own[order].tolist()
    deep = _depths(weights) if len(weights) > 1 else [1] * len(weights)
    while len(deep) > 1 and max(deep) > limit:
        weights = [n // 2 + 1 for n in weights]
        deep = _depths(weights)
    out[symbols] = deep
    return out


def _lengths(counts: dict[int, int], limit: int = MOST_LENGTH) -> dict[int, int]:
    """Code lengths of symbols by their counts; a single symbol has length 0."""
    leaves = sorted([(n, s) for s, n in counts.items()])
    weights = [n for n, _ in leaves]
    while max(deep := _depths(weights)) > limit:
        weights = [n // 2 + 1 for n in weights]
    return {s: d for (_, s), d in zip(leaves, deep, strict=True)}


def _canonical(lengths: dict[int, int]) -> dict[int, tuple[int, int]]:
    """Bits to write and their number for a few symbols of at most seven bits; a single symbol takes none."""
    if len(lengths) == 1:
        return {s: (0, 0) for s in lengths}
    out, at, turned = {}, 0, _turned(7)
    for s, n in sorted(lengths.items(), key=lambda x: (x[1], x[0])):
        out[s] = (int(turned[at]), n)
        at += 1 << (7 - n)
    return out


def _steps(v: int, n: int) -> list[tuple[int, int, int]]:
    """Symbols, extra bits and their number that stand for ``n`` symbols of length ``v``."""
    steps: list[tuple[int, int, int]] = []
    while n:
        k = min(n, 138) if v == 0 and n >= 3 else min(n, 7) if v and n >= 4 else 1
        if k == 1:
            steps.append((v, 0, 0))
        elif v:
            steps += [(v, 0, 0), (16, k - 4, 2)]
        else:
            steps.append((17, k - 3, 3) if k <= 10 else (18, k - 11, 7))
        n -= k
    return steps


#: Code of the code lengths up to MOST_LENGTH, and its bits ahead of them.
_STEP_CODE = _canonical(STEP_LENGTHS)
_STEP_HEAD = (15 << 1 | sum(STEP_LENGTHS.get(s, 0) << 5 + 3 * i for i, s in enumerate(LENGTH_ORDER)), 5 + 3 * 19 + 1)


@lru_cache(maxsize=8192)
def _run(v: int, n: int) -> tuple[int, int]:
    """The bits of ``n`` symbols of length ``v``, and their number."""
    out = at = 0
    for s, extra, k in _steps(v, n):
        value, width = _STEP_CODE[s]
        out |= (value | extra << width) << at
        at += width + k
    return out, at


def _write_code(bits: Bits, lengths: list[int] | np.ndarray) -> Code:
    sizes = np.asarray(lengths, np.int64)
    used = np.flatnonzero(sizes)
    if len(used) <= 1 and (not len(used) or used[0] < 256):
        only = int(used[0]) if len(used) else 0
        bits.write(5 | only << 3, 11)
        sizes = np.zeros(len(sizes), np.int64)
        sizes[only] = 1
        return Code(sizes)
    starts = [0, *((sizes[1:] != sizes[:-1]).nonzero()[0] + 1).tolist()]
    if sizes.max() <= MOST_LENGTH:
        out, at = _STEP_HEAD
        for v, start, end in zip(sizes[starts].tolist(), starts, [*starts[1:], len(sizes)], strict=True):
            value, n = _run(v, end - start)
            out |= value << at
            at += n
        bits.write(out, at)
        return Code(sizes)
    steps: list[tuple[int, int, int]] = []
    for v, at, end in zip(sizes[starts].tolist(), starts, [*starts[1:], len(sizes)], strict=True):
        steps += _steps(v, end - at)
    kinds = _lengths(Counter([s for s, _, _ in steps]), 7)
    if len(kinds) == 1:
        kinds = dict.fromkeys(kinds, 1)
    out, at = 15 << 1, 5
    for s in LENGTH_ORDER:
        out |= kinds.get(s, 0) << at
        at += 3
    at += 1
    by = _canonical(kinds)
    for s, extra, k in steps:
        value, n = by[s]
        out |= (value | extra << n) << at
        at += n + k
    bits.write(out, at)
    return Code(sizes)


@lru_cache(maxsize=4096)
def _flat_start(width: int, height: int) -> tuple[int, int]:
    """The stream up to the first pixel where every literal code has eight bits: value and number of bits."""
    bits = _start(width, height)
    bits.write(0, 3)
    for n in (280, 256, 256):
        _write_code(bits, [8] * 256 + [0] * (n - 256))
    _write_code(bits, [0] * 255 + [1])
    _write_code(bits, [1] + [0] * 39)
    return bits.out, bits.n


def _start(width: int, height: int) -> Bits:
    bits = Bits()
    bits.write(0x2F, 8), bits.write(width - 1, 14), bits.write(height - 1, 14), bits.write(0, 4)
    return bits


def _riff(stream: bytes) -> bytes:
    body = stream + b"\0" * (len(stream) & 1)
    return struct.pack("<4sI4s4sI", b"RIFF", 12 + len(body), b"WEBP", b"VP8L", len(stream)) + body


@lru_cache(maxsize=64)
def _near(width: int) -> dict[int, int]:
    """The smallest code of each near distance."""
    out: dict[int, int] = {}
    for i, (x, y) in enumerate(NEAR):
        if x + y * width >= 1:
            out.setdefault(x + y * width, i + 1)
    return out


def _prefixed(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Prefix and extra bits of lengths or distance codes."""
    prefix = np.searchsorted(BASE, values, side="right") - 1
    return prefix, values - BASE[prefix]


def _copies(argb: np.ndarray) -> list[tuple[int, int, int]]:
    """(start, length, distance) of copies from the last place where the same pixels began, first come first taken."""
    n = len(argb)
    if n <= SHORTEST:
        return []
    wide = argb.astype(np.uint64)
    key = (wide[:-2] * np.uint64(0x9E3779B97F4A7C15)) ^ (wide[1:-1] * np.uint64(0xC2B2AE3D27D4EB4F)) ^ (wide[2:] * np.uint64(0x165667B19E3779F9))
    low = np.uint64((1 << n.bit_length()) - 1)  # the place takes the lowest bits, so that one sort brings like keys together in order
    found = np.sort(key & ~low | np.arange(n - 2, dtype=np.uint64))
    order = (found & low).astype(np.int64)
    alike = ((found[1:] & ~low) == (found[:-1] & ~low)).nonzero()[0]
    if not len(alike):
        return []
    last = np.zeros(n, np.int64)
    last[order[alike + 1]] = order[alike] + 1
    pixels, starts = argb.tolist(), last.tolist()
    out, end = [], 0
    for i in np.flatnonzero(last).tolist():
        p = starts[i] - 1
        if i < end or i - p > FARTHEST:
            continue
        k, most = 0, min(n - i, LONGEST)
        while k < most and pixels[p + k] == pixels[i + k]:
            k += 1
        if k >= SHORTEST:
            out.append((i, k, i - p))
            end = i + k
    return out


def _write_image(bits: Bits, argb: np.ndarray, width: int, main: bool, colours: int = 0) -> None:
    """An image as one prefix group: copies, cache hits where they pay, and literals. ``colours``: it has that many at least."""
    n = len(argb)
    copies = np.array(_copies(argb), np.int64).reshape(-1, 3)
    covered = np.zeros(n + 1, np.int64)
    covered[copies[:, 0]] += 1
    covered[copies[:, 0] + copies[:, 1]] -= 1  # copies do not overlap
    event = np.cumsum(covered[:n]) == 0
    event[copies[:, 0]] = True
    cache_bits, hit = 0, None
    if n >= 64 and 2 * (n - colours) >= int(np.count_nonzero(event)):  # a colour's first pixel is no hit
        tried = min(9, n.bit_length() - 2)
        slots = (argb.astype(np.uint64) * np.uint64(CACHE_FACTOR) & np.uint64(0xFFFFFFFF)) >> np.uint64(32 - tried)
        order = np.argsort(slots.astype(np.uint16), kind="stable")
        again = (slots[order[1:]] == slots[order[:-1]]) & (argb[order[1:]] == argb[order[:-1]])
        hit = np.zeros(n, bool)
        hit[order[1:][again]] = True
        hit &= event
        hit[copies[:, 0]] = False
        if 2 * int(hit.sum()) >= int(event.sum()):
            cache_bits = tried
    where = np.flatnonzero(event)
    colour = argb[where].astype(np.int64)
    symbol = colour >> 8 & 255
    literal = np.ones(len(where), bool)
    if cache_bits:
        hits = np.flatnonzero(hit[where])
        symbol[hits] = 280 + slots[where[hits]].astype(np.int64)
        literal[hits] = False
    at = np.searchsorted(where, copies[:, 0])
    literal[at] = False
    near = _near(width)
    far = np.array([near.get(d, d + 120) for d in copies[:, 2].tolist()], np.int64)
    (length, length_more), (distance_prefix, distance_more) = _prefixed(copies[:, 1]), _prefixed(far)
    symbol[at] = 256 + length
    at_literal = np.flatnonzero(literal)
    red, blue, alpha = (colour[at_literal] >> k & 255 for k in (16, 0, 24))
    bits.write(int(cache_bits > 0), 1)
    if cache_bits:
        bits.write(cache_bits, 4)
    if main:
        bits.write(0, 1)
    written = []
    sides = np.bincount(red, minlength=256), np.bincount(blue, minlength=256)
    if all(np.count_nonzero(c) > 1 for c in sides):  # one code for both, written twice: its lengths are then known better
        sides = (sides[0] + sides[1],) * 2
    counts = [np.bincount(symbol, minlength=280 + (1 << cache_bits if cache_bits else 0)), *sides, np.bincount(alpha, minlength=256), np.bincount(distance_prefix, minlength=40)]
    last = None
    for own, count in zip((symbol, red, blue, alpha, distance_prefix), counts, strict=True):
        if last is None or count is not last[0]:
            before = bits.n
            code, n_bits = _write_code(bits, _sizes(count)).written
            last = (count, code, n_bits, bits.out >> before, bits.n - before)
        else:
            _, code, n_bits, head, n = last
            bits.write(head, n)
        written.append((code.take(own), n_bits.take(own)))
    (green, n_green), (red, n_red), (blue, n_blue), (alpha, n_alpha), (distance, n_distance) = written
    # Literals are green, red with blue, alpha; copies are length with its extra bits, distance, its extra bits.
    values, sizes = np.zeros((len(where), 3), np.int64), np.zeros((len(where), 3), np.int64)
    green[at] |= length_more << n_green[at]
    n_green[at] += EXTRA[length]
    values[:, 0], sizes[:, 0] = green, n_green
    values[at_literal, 1], sizes[at_literal, 1] = red | blue << n_red, n_red + n_blue
    if n_alpha.any():
        values[at_literal, 2], sizes[at_literal, 2] = alpha, n_alpha
    values[at, 1], sizes[at, 1] = distance, n_distance
    values[at, 2], sizes[at, 2] = distance_more, EXTRA[distance_prefix]
    bits.write_all(values.reshape(-1), sizes.reshape(-1))


def _spread_of(px: np.ndarray) -> float:
    """What the bits of all samples by the frequency of their values are less by than those of a constant number."""
    counts = np.bincount(px.reshape(-1), minlength=1)
    counts = counts[counts > 1].astype(np.float64)
    return -float(counts @ np.log2(counts))


def _guessed(px: np.ndarray, mode: int) -> np.ndarray:
    """What is left of RGB samples when each is predicted by its left (1) or upper (2) neighbour."""
    out = px.copy()
    if mode == 1:
        out[:, 1:] -= px[:, :-1]
        out[1:, 0] -= px[:-1, 0]
    else:
        out[1:] -= px[:-1]
        out[0, 1:] -= px[0, :-1]
    return out


def _joined(px: np.ndarray, alpha: int) -> np.ndarray:
    """RGB samples as ARGB numbers."""
    out = np.full((*px.shape[:2], 4), alpha, np.uint8)
    out[..., 2::-1] = px
    return out.view("<u4")[..., 0]


def _packed(px: np.ndarray) -> bytes:
    """The VP8L stream with the palette or predictor that suits the image."""
    height, width, _ = px.shape
    bits = _start(width, height)
    argb = _joined(px, 255)
    colours, found = np.unique(argb.reshape(-1)[:MANY]), 0
    if len(colours) <= 256 and argb.size > MANY:
        colours = np.unique(argb)
    if len(colours) <= 256 and 2 * len(colours) <= argb.size:
        bits.write(1, 1), bits.write(3, 2), bits.write(len(colours) - 1, 8)
        table = colours.view(np.uint8).reshape(-1, 4).copy()
        table[1:] -= table[:-1].copy()
        _write_image(bits, table.view(np.uint32).reshape(-1), len(colours), False)
        pack = 3 if len(colours) <= 2 else 2 if len(colours) <= 4 else 1 if len(colours) <= 16 else 0
        per, deep = 1 << pack, 8 >> pack
        across = -(-width // per)
        index = np.pad(np.searchsorted(colours, argb), ((0, 0), (0, across * per - width))).reshape(height, across, per)
        argb = (index << deep * np.arange(per)).sum(-1).astype(np.uint32) << 8 | np.uint32(255 << 24)
        width = across
    else:
        green = px[..., 1:2]  # decides for all channels
        bitwise = {mode: _spread_of(_guessed(green, mode)) for mode in (1, 2)}
        mode = min(bitwise, key=bitwise.get)
        found = len(colours)
        if bitwise[mode] < _spread_of(green):
            bits.write(1, 1), bits.write(0, 2), bits.write(7, 3)
            across, down = -(-width // 512), -(-height // 512)
            _write_image(bits, np.full(across * down, 255 << 24 | mode << 8, np.uint32), across, False)
            argb, found = _joined(_guessed(px, mode), 0), 0
    bits.write(0, 1)
    _write_image(bits, argb.reshape(-1), width, True, found)
    return bits.bytes()


def encode(px: np.ndarray, level: int = 2) -> bytes:
    """A lossless WebP file of (rows, columns, RGB). Level 0: codes of eight bits; 1: green subtracted, prefix codes by frequency; 2: all that makes the image smaller."""
    height, width, _ = px.shape
    if level == 2:
        return _riff(_packed(px))
    if level == 0:
        value, n = _flat_start(width, height)
        shift = n & 7
        body = FLIPPED[px[..., [1, 0, 2]].reshape(-1)].astype(np.uint16)
        tail = np.zeros(len(body) + 1, np.uint16)
        tail[:-1] = body << shift
        tail[1:] |= body >> (8 - shift)
        tail[0] |= value >> (n - shift)
        return _riff(value.to_bytes((n + 7) // 8, "little")[: n // 8] + tail.astype(np.uint8).tobytes())
    bits = _start(width, height)
    bits.write(1, 1), bits.write(2, 2), bits.write(0, 3)
    flat = px.reshape(-1, 3)
    g, r, b = flat[:, 1], flat[:, 0] - flat[:, 1], flat[:, 2] - flat[:, 1]
    made = []
    for values, size in ((g, 280), (r, 256), (b, 256)):
        depth = _lengths(Counter(values.tolist()))
        made.append(_write_code(bits, [depth.get(s, 0) or int(len(depth) == 1 and s in depth) for s in range(size)]))
    _write_code(bits, [0] * 255 + [1])
    _write_code(bits, [1] + [0] * 39)
    for row in zip(g.tolist(), r.tolist(), b.tolist(), strict=True):
        for code, s in zip(made, row, strict=True):
            bits.write(*code.codes[s])
    return _riff(bits.bytes())


def padded(text: bytes) -> bytes:
    """Spaces up to a positive multiple of a row's 192 bytes."""
    return text.ljust(max(ROW, -(-len(text) // ROW) * ROW), b" ")


def to_media(payload: bytes, level: int = 2) -> bytes:
    """Images of 64 pixels a row that hold ``payload`` as RGB samples."""
    px = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH, 3)
    return b"".join(encode(px[i : i + MAX_SIDE], level) for i in range(0, len(px), MAX_SIDE))


def from_media(media: bytes, seen: list[int] | None = None) -> np.ndarray:
    """The RGB rows of all images in ``media``."""
    images = decode(media, seen)
    return np.ascontiguousarray(images[0][..., :3]) if len(images) == 1 else np.concatenate([px[..., :3] for px in images])


def feature(px: np.ndarray) -> str:
    """Size, mean of each channel, and mean step between neighbours along a row, all exact to a thousandth."""
    n = px.shape[0] * px.shape[1]
    means = [int(v) * 1000 // n for v in px.reshape(-1, 3).sum(0, dtype=np.int64)]
    flat = px.reshape(len(px), -1).astype(np.int16)
    step = int(np.abs(np.diff(flat, axis=1)).sum(dtype=np.int64)) * 1000 // max(1, flat[:, 1:].size)
    return f"{px.shape[1]}x{px.shape[0]} rgb={means[0]},{means[1]},{means[2]} step={step}"


DIGEST = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, " + ", ".join(f"n_{k} long" for k in SEEN)


def _digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    gc.disable()  # nothing here makes cycles, and looking for them among the many small lists takes time
    try:
        yield from map(_digested, batches)
    finally:
        gc.enable()


def _digested(batch: pa.RecordBatch) -> pa.RecordBatch:
    rows = []
    for i, text in zip(batch.column(0), batch.column(1).cast(pa.binary()), strict=True):
        raw = text.as_py() or b""
        media = to_media(padded(raw))
        seen = [0] * len(SEEN)
        px = from_media(media, seen)
        back = px.tobytes()
        rows.append((i.as_py(), len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-16:]), len(media), hashlib.sha256(media).hexdigest(), feature(px), *seen))
    kinds = [pa.string() if k == "string" else pa.int64() for _, k in (f.split() for f in DIGEST.split(", "))]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows, strict=True)) or [[]] * len(kinds), kinds, strict=True)], names=[f.split()[0] for f in DIGEST.split(", ")])


def media_digests(docs: DataFrame) -> DataFrame:
    """Per document: sizes and digests of its payload as read back from the stored images, and of the images."""
    return docs.select("doc_id", "text").mapInArrow(_digests, DIGEST)


def _stored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        media = [to_media(padded(t.as_py() or b"")) for t in batch.column(1).cast(pa.binary())]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(media, pa.binary())], names=["doc_id", "media"])


def media_column(docs: DataFrame) -> DataFrame:
    """doc_id and media: the text's UTF-8 bytes as lossless WebP."""
    return docs.select("doc_id", "text").mapInArrow(_stored, "doc_id long, media binary")


def _pixels(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, media in zip(batch.column(0), batch.column(1), strict=True):
            for k, px in enumerate(decode(media.as_py()) if media.is_valid else []):
                cells = [pa.array([v]) for v in (k, px.shape[1], px.shape[0])]
                yield pa.RecordBatch.from_arrays([pa.array([i.as_py()], pa.int64()), *cells, pa.array([px.tobytes()], pa.binary())], names=["doc_id", "image", "width", "height", "rgba"])


def pixel_arrays(media: DataFrame) -> DataFrame:
    """One row for each image in (doc_id, media): width, height and RGBA samples row by row; null media has no image."""
    return media.select("doc_id", "media").mapInArrow(_pixels, "doc_id long, image long, width long, height long, rgba binary")


def query(spark, sf_dir: str) -> DataFrame:
    return media_digests(spark.read.parquet(f"{sf_dir}/documents.parquet"))
