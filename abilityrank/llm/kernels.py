"""Vectorised byte and word hashing over Arrow batches of texts.

Every routine works on a block: the concatenated UTF-8 bytes of some consecutive rows with their
offsets.  Hashes are polynomials modulo 2**64 taken from one cumulative sum, then finalised, so a
hash of any substring costs a subtraction and a multiplication.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa

U64 = np.uint64
_MASK = (1 << 64) - 1
BASES = (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)
_BYTE_VALUES = [np.random.default_rng(s).integers(1, 1 << 63, 256, dtype=np.uint64) * U64(2) + U64(1) for s in (11, 12, 13)]

SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True

_powers: dict[int, np.ndarray] = {}
#: Called before a worker reads texts by blocks: stores that another operator filled in this worker.
RELEASE: list = []


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64, kept between calls."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        size = max(n, 1 << 16)
        have = np.full(size, base & _MASK, U64)
        have[0] = 1
        np.multiply.accumulate(have, out=have)
        _powers[base] = have
    return have[:n]


def inverse(base: int) -> int:
    return pow(base, -1, 1 << 64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit integers."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


@dataclass
class Block:
    rows: slice
    data: np.ndarray
    offsets: np.ndarray

    def text(self, i: int) -> bytes:
        return self.data[self.offsets[i] : self.offsets[i + 1]].tobytes()


def text_blocks(column: pa.Array, most_bytes: int = 1 << 18):
    """Consecutive rows of a string column in blocks of about ``most_bytes``; nulls are empty.
    A longer text is a block of its own."""
    for empty in RELEASE:
        empty()
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    if len(column) == 0:
        return
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    lo = 0
    while lo < len(column):
        hi = int(np.searchsorted(offsets, offsets[lo] + most_bytes, side="right")) - 1
        hi = min(max(hi, lo + 1), len(column))
        yield Block(slice(lo, hi), data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo])
        lo = hi


def cumulative(values: np.ndarray, base: int) -> np.ndarray:
    out = np.zeros(len(values) + 1, U64)
    np.cumsum(values * powers(base, len(values)), out=out[1:])
    return out


def spans_hash(cum: np.ndarray, start: np.ndarray, end: np.ndarray, base: int) -> np.ndarray:
    """Finalised hashes of values[start:end] from their cumulative sum."""
    inv = powers(inverse(base), len(cum))
    h = (cum[end] - cum[start]) * inv[start]
    return mix(h + (end - start).astype(U64) * U64(0xC2B2AE3D27D4EB4F))


@dataclass
class Words:
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray  # index of each row's first word, and the total at the end

    def hashes(self, block: Block, which: int = 0) -> np.ndarray:
        cum = cumulative(_BYTE_VALUES[which][block.data], BASES[which])
        return spans_hash(cum, self.start, self.end, BASES[which])


def words_of(block: Block, breaks: np.ndarray = SPACE) -> Words:
    """Maximal runs of bytes outside ``breaks``, never across rows."""
    n = len(block.data)
    if n == 0:
        zero = np.zeros(0, np.int64)
        return Words(zero, zero, np.zeros(len(block.offsets), np.int64))
    inside = ~breaks[block.data]
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = inside[:-1]
    edges = block.offsets[(block.offsets > 0) & (block.offsets < n)]
    before[edges] = False
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = inside[1:]
    after[edges - 1] = False
    start = np.flatnonzero(inside & ~before)
    end = np.flatnonzero(inside & ~after) + 1
    return Words(start, end, np.searchsorted(start, block.offsets))


def grams(values: np.ndarray, first: np.ndarray, n: int, base: int = BASES[0]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of n values, and whether each lies within one row; one for each start
    0..len-n."""
    count = len(values) - n + 1
    if count <= 0:
        return np.zeros(0, U64), np.zeros(0, bool)
    cum = cumulative(values, base)
    h = mix((cum[n:] - cum[:-n]) * powers(inverse(base), count))
    return h, within_rows(first, count, n)


def sliding_argmin(values: np.ndarray, width: int) -> np.ndarray:
    """For each window of ``width`` values the index of its smallest, the leftmost among equals."""
    n = len(values) - width + 1
    best = values.copy()
    at = np.arange(len(values), dtype=np.int32 if len(values) < 1 << 31 else np.int64)
    have = 1
    while have < width:  # windows of have and of have+step, doubled until wide enough
        step = min(have, width - have)
        m = len(best) - step
        worse = best[step:] < best[:m]
        at = np.where(worse, at[step:], at[:m])
        best = np.minimum(best[:m], best[step:])
        have += step
    return at[:n]


def concat_ranges(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """start[0]..start[0]+length[0]-1, start[1].. and so on, end to end."""
    total = int(length.sum())
    if not total:
        return np.zeros(0, np.int64)
    ends = np.cumsum(length)
    return np.arange(total) - np.repeat(ends - length - start, length)


def merge_intervals(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The union of half-open intervals as sorted disjoint maximal ones."""
    if not len(start):
        return start, end
    order = np.argsort(start, kind="stable")
    start, end = start[order], end[order]
    reach = np.maximum.accumulate(end)
    new = np.concatenate([[True], start[1:] > reach[:-1]])
    heads = np.flatnonzero(new)
    return start[heads], reach[np.concatenate([heads[1:] - 1, [len(reach) - 1]])]


@dataclass
class Anchors:
    """Runs of windows that share their smallest gram: for each its row, first window and their
    number, the gram's place from the first window on, the gram's hash and the hash of all it spans."""

    row: np.ndarray
    start: np.ndarray
    count: np.ndarray
    place: np.ndarray
    gram: np.ndarray
    span: np.ndarray


def within_rows(first: np.ndarray, count: int, n: int) -> np.ndarray:
    """Whether the n values from each of the starts 0..count-1 lie within one row."""
    row = np.repeat(np.arange(len(first) - 1), np.diff(first))[:count]
    return np.arange(count) + n <= first[row + 1]


def anchors(v0: np.ndarray, v1: np.ndarray, first: np.ndarray, gram: int, window: int) -> Anchors:
    """Anchors of all windows of a block.  Equal windows have equal anchors at equal places, whatever
    stands around them; v0 and v1 are two independent hashes of the values."""
    count = len(v0) - window + 1
    if count <= 0 or not (np.diff(first) >= window).any():
        none = np.zeros(0, np.int64)
        return Anchors(none, none, none, none, none.view(U64), none.view(U64))
    c0 = cumulative(v0, BASES[0])
    g = mix((c0[gram:] - c0[:-gram]) * powers(inverse(BASES[0]), len(v0) - gram + 1))
    at = sliding_argmin(g, window - gram + 1)
    valid = within_rows(first, count, window)
    new = valid.copy()
    new[1:] &= ~valid[:-1] | (at[1:] != at[:-1]) | np.isin(np.arange(1, count), first)
    start = np.flatnonzero(new)
    ends = np.flatnonzero(valid & np.concatenate([new[1:] | ~valid[1:], [True]])) + 1
    n = ends - start
    place = at[start] - start
    row = np.searchsorted(first, start, side="right") - 1
    c1 = cumulative(v1, BASES[1])
    span = mix(spans_hash(c1, start, start + n + window - 1, BASES[1]) + place.astype(U64))
    return Anchors(row, start - first[row], n, place, g[at[start]], span)


def byte_values(block: Block, which: int) -> np.ndarray:
    return _BYTE_VALUES[which][block.data]


def row_hashes(values: np.ndarray, first: np.ndarray, base: int = BASES[2]) -> np.ndarray:
    """One hash of all values of each row."""
    return spans_hash(cumulative(values, base), first[:-1], first[1:], base)
