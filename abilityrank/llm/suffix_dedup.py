"""Repeated byte strings by external induced sorting of suffixes.

A string of ``length`` bytes that stands twice has, at both places, the same anchor: the run of
``gram`` bytes inside it with the smallest hash.  So only anchors that occur more than once matter.
All text positions whose windows share an anchor form a context: the bytes those windows span.
Whole contexts that are equal are found by their 64-bit hash; only anchors with several different
contexts go through the induction, with one context of each hash.

The suffixes of an anchor's contexts are sorted by induction.  First the suffixes that begin at the
anchor are sorted with their longest common prefixes.  Then each round goes one byte to the left:
a suffix is its first byte and the rank of the suffix behind it, so tuples (byte, rank, common
prefix) pass through a priority queue over the 256 bytes, and the common prefix of two neighbours
with equal bytes is one more than the smallest one between their tails.  A window is repeated where
a neighbour shares ``length`` bytes.

Contexts that fit in memory go through a vectorised form of the queue, many anchors at once.  A
larger anchor's tuples and context bytes are kept in files of the task (as Spark keeps its own
spills), in one first-in-first-out file for each byte: pushes come in rank order, so that is the
queue's order.

Null and empty texts have no bytes.  Repeated rows are places of their own, so they remove each
other wherever they are long enough.  Rows with null doc_ids are judged like others, but under one
key.  Extra columns are ignored; empty tables give no rows.
"""

from __future__ import annotations

import hashlib
import heapq
import tempfile
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .shared import materialise

NO_ID = -(1 << 63)
ANCHORS = "gram long, span long, doc_id long, row_key long, start int, count int"
CONTEXTS = "gram long, span long, place int, count int, context binary"
HITS = "gram long, span long, first int, last int"


def _values(block: K.Block):
    return K.byte_values(block, 0), K.byte_values(block, 1)


def anchor_rows(docs: DataFrame, length: int, gram: int) -> DataFrame:
    def run(batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for block in K.text_blocks(batch.column(1)):
                v0, v1 = _values(block)
                found = K.anchors(v0, v1, block.offsets, gram, length)
                if len(found.row):
                    keys = K.signed(K.row_hashes(v1, block.offsets))
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(K.signed(found.gram)), pa.array(K.signed(found.span)), pa.array(ids[block.rows][found.row]), pa.array(keys[found.row]), pa.array(found.start.astype(np.int32)), pa.array(found.count.astype(np.int32))],
                        ["gram", "span", "doc_id", "row_key", "start", "count"],
                    )

    return docs.where(F.octet_length("text") >= length).mapInArrow(run, ANCHORS)


def context_rows(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """docs: doc_id, text, wanted spans.  The bytes of each wanted context."""

    def run(batches):
        for batch in batches:
            wanted = batch.column(2)
            for block in K.text_blocks(batch.column(1)):
                v0, v1 = _values(block)
                found = K.anchors(v0, v1, block.offsets, gram, length)
                rows = wanted.slice(block.rows.start, block.rows.stop - block.rows.start)
                asked = rows.flatten().to_numpy()
                asked_row = np.repeat(np.arange(len(rows)), rows.value_lengths().to_numpy())
                pair = lambda row, g: K.mix(g.view(np.uint64) + row.astype(np.uint64) * np.uint64(K.BASES[2]))
                hit = np.flatnonzero(np.isin(pair(found.row, found.span), pair(asked_row, asked)))
                at = block.offsets[found.row[hit]] + found.start[hit]
                raw = [block.data[s : s + n + length - 1].tobytes() for s, n in zip(at.tolist(), found.count[hit].tolist())]
                if raw:
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(K.signed(found.gram[hit])), pa.array(K.signed(found.span[hit])), pa.array(found.place[hit].astype(np.int32)), pa.array(found.count[hit].astype(np.int32)), pa.array(raw, pa.binary())],
                        ["gram", "span", "place", "count", "context"],
                    )

    return docs.mapInArrow(run, CONTEXTS)


def _range_min(values: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """min(values[lo:hi]) of each range; ranges are not empty."""
    if not len(lo):
        return np.zeros(0, values.dtype)
    flat = np.empty(2 * len(lo), np.int64)
    flat[0::2], flat[1::2] = lo, hi
    return np.minimum.reduceat(np.append(values, values[-1]), flat)[::2]


def _aligned(contexts: list[bytes], skip: np.ndarray, width: int) -> np.ndarray:
    """Rows of ``width`` bytes: each context from its skip on, zeros behind its end."""
    out = np.zeros((len(contexts), width), np.uint8)
    for i, (c, k) in enumerate(zip(contexts, skip.tolist())):
        out[i, : len(c) - k] = np.frombuffer(c, np.uint8, -1, k)
    return out


def _neighbour_prefixes(rows: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Common prefix of each row with the one before it; 0 for the first."""
    out = np.zeros(len(rows), np.int32)
    if len(rows) > 1:
        differ = rows[1:] != rows[:-1]
        first = np.where(differ.any(1), differ.argmax(1), rows.shape[1])
        out[1:] = np.minimum(first, np.minimum(sizes[1:], sizes[:-1]))
    return out


def induce(group: np.ndarray, contexts: list[bytes], place: np.ndarray, count: np.ndarray, length: int) -> np.ndarray:
    """For each context and window whether another context of its group has the window.

    group: numbers of the contexts' anchors, in any order; all contexts of a group differ.
    """
    n = len(contexts)
    sizes = count + length - 1 - place
    tails = _aligned(contexts, place, length)
    order = np.lexsort((sizes, tails.view(f"S{length}").ravel(), group))  # sizes: padding is no byte of its own
    lcp = _neighbour_prefixes(tails[order], sizes[order])
    lcp[1:][group[order][1:] != group[order][:-1]] = 0
    del tails
    most = int(place.max(initial=0))
    heads = np.zeros((n, max(1, most)), np.uint8)  # bytes to the left of the anchor, nearest first
    for i, (c, k) in enumerate(zip(contexts, place.tolist())):
        heads[i, :k] = np.frombuffer(c, np.uint8, k)[::-1]
    found = np.zeros((n, most + 1), bool)  # by distance to the anchor
    for back in range(most + 1):
        if back:
            stay = np.flatnonzero(place[order] >= back)
            if not len(stay):
                break
            if len(stay) < len(order):
                lcp = np.concatenate([[0], _range_min(lcp, stay[:-1] + 1, stay[1:] + 1)]).astype(np.int32)
                order = order[stay]
            key = group[order].astype(np.int64) * 256 + heads[order, back - 1]
            if (key[1:] < key[:-1]).any():
                by = np.argsort(key, kind="stable")
                key = key[by]
                same = np.flatnonzero(key[1:] == key[:-1]) + 1
                new = np.zeros(len(order), np.int32)
                new[same] = _range_min(lcp, by[same - 1] + 1, by[same] + 1) + 1
                order, lcp = order[by], new
            else:
                lcp = np.where(np.concatenate([[False], key[1:] == key[:-1]]), lcp + 1, 0).astype(np.int32)
        near = lcp >= length
        near[:-1] |= lcp[1:] >= length
        found[order[near], back] = True
    return found


class ByteQueue:
    """A priority queue of (byte, item, common prefix) that keeps equal bytes in the order of their
    pushes, in memory up to ``most`` tuples and in one file for each byte beyond."""

    TUPLE = np.dtype([("item", np.int64), ("lcp", np.int32)])

    def __init__(self, folder: str, most: int):
        self.folder, self.most, self.held = folder, most, 0
        self.memory: dict[int, list[np.ndarray]] = {}
        self.files: dict[int, object] = {}

    def push(self, byte: np.ndarray, item: np.ndarray, lcp: np.ndarray) -> None:
        """A block in rank order."""
        by = np.argsort(byte, kind="stable")
        rows = np.empty(len(by), self.TUPLE)
        rows["item"], rows["lcp"] = item[by], lcp[by]
        keys, at = np.unique(byte[by], return_index=True)
        for k, part in zip(keys.tolist(), np.split(rows, at[1:])):
            self.memory.setdefault(k, []).append(part)
        self.held += len(rows)
        if self.held > self.most:
            self._spill()

    def _spill(self) -> None:
        for k, parts in self.memory.items():
            if k not in self.files:
                self.files[k] = tempfile.TemporaryFile(dir=self.folder)
            for p in parts:
                self.files[k].write(p.tobytes())
        self.memory.clear()
        self.held = 0

    def pop_all(self, block: int = 1 << 16):
        """Blocks in order; the first tuple of each byte has common prefix 0."""
        for k in sorted({*self.memory, *self.files}):
            first = True
            f = self.files.pop(k, None)
            if f is not None:
                f.seek(0)
                while raw := f.read(block * self.TUPLE.itemsize):
                    rows = np.frombuffer(raw, self.TUPLE).copy()
                    if first:
                        rows["lcp"][0], first = 0, False
                    yield rows
                f.close()
            for rows in self.memory.pop(k, []):
                if first:
                    rows["lcp"][0], first = 0, False
                yield rows


class ExternalInduction:
    """``induce`` for one anchor whose contexts exceed memory: contexts are added one by one."""

    def __init__(self, length: int, most: int = 1 << 20, run: int = 1 << 14):
        self.length, self.most, self.run = length, most, run
        self.scratch = tempfile.TemporaryDirectory()
        self.store = tempfile.TemporaryFile(dir=self.scratch.name)  # contexts, rows of one width
        self.width = 2 * length
        self.place, self.count = array("i"), array("i")  # four bytes a context
        self.held: list[tuple[bytes, int]] = []
        self.sorted: list[tuple[object, int]] = []

    def add(self, context: bytes, place: int, count: int) -> None:
        self.store.write(context.ljust(self.width, b"\0"))
        self.held.append((context[place:], len(self.place)))
        self.place.append(place)
        self.count.append(count)
        if len(self.held) >= self.run:
            self._flush()

    def _flush(self) -> None:
        """A sorted run of the suffixes that begin at the anchor."""
        f = tempfile.TemporaryFile(dir=self.scratch.name)
        for tail, item in sorted(self.held):
            f.write(len(tail).to_bytes(4, "little") + item.to_bytes(8, "little") + tail)
        self.sorted.append(f)
        self.held = []

    @staticmethod
    def _read(f):
        f.seek(0)
        while head := f.read(12):
            yield f.read(int.from_bytes(head[:4], "little")), int.from_bytes(head[4:], "little")

    def _first_blocks(self, size: int = 1 << 14):
        rows, before = [], b""
        for tail, item in heapq.merge(*map(self._read, self.sorted)):
            m = min(len(tail), len(before))
            if tail[:m] == before[:m]:
                lcp = m
            else:
                lo, hi = 0, m
                while hi - lo > 1:
                    mid = (lo + hi) // 2
                    lo, hi = (mid, hi) if tail[:mid] == before[:mid] else (lo, mid)
                lcp = lo
            rows.append((item, lcp))
            before = tail
            if len(rows) == size:
                yield np.array(rows, ByteQueue.TUPLE)
                rows = []
        if rows:
            yield np.array(rows, ByteQueue.TUPLE)

    def finish(self):
        """(item, distance to the anchor) arrays of repeated windows, block by block."""
        self._flush()
        self.store.flush()
        data = np.memmap(self.store, np.uint8, "r", shape=(len(self.place), self.width)) if self.place else np.zeros((0, self.width), np.uint8)
        place = np.array(self.place, np.int64)
        blocks = self._first_blocks()
        for back in range(int(place.max(initial=0)) + 1):
            queue = ByteQueue(self.scratch.name, self.most)
            least = np.full(256, 1 << 30, np.int64)  # smallest common prefix since each byte's last push
            waiting = None  # the last tuple: its later neighbour is still to come
            for rows in blocks:
                item, lcp = rows["item"], rows["lcp"]
                near = lcp >= self.length
                near[:-1] |= lcp[1:] >= self.length
                if waiting is not None and lcp[0] >= self.length:
                    yield np.array([waiting]), back
                waiting = item[-1]
                if near.any():
                    yield item[near], back
                goes = np.flatnonzero(place[item] > back)
                byte = data[item[goes], place[item[goes]] - back - 1]
                new = np.zeros(len(goes), np.int32)
                by = np.argsort(byte, kind="stable")
                at, sorted_byte = goes[by], byte[by]
                head = np.concatenate([[True], sorted_byte[1:] != sorted_byte[:-1]]) if len(by) else np.zeros(0, bool)
                lo = np.where(head, 0, np.concatenate([[0], at[:-1] + 1]) if len(by) else at)
                fresh = _range_min(lcp, lo, at + 1).astype(np.int64)
                fresh[head] = np.minimum(fresh[head], least[sorted_byte[head]])
                new[by] = fresh + 1
                least = np.minimum(least, int(lcp.min()))
                if len(by):
                    tail = np.concatenate([head[1:], [True]])
                    last = at[tail]
                    suffix = np.minimum.accumulate(lcp[::-1])[::-1]
                    least[sorted_byte[tail]] = np.where(last + 1 < len(lcp), suffix[np.minimum(last + 1, len(lcp) - 1)], 1 << 30)
                queue.push(byte, item[goes], new)
            blocks = queue.pop_all()
        self.store.close()
        del data
        self.scratch.cleanup()


def repeated_in_contexts(rows: DataFrame, length: int, memory: int = 8_000) -> DataFrame:
    """HITS of contexts sorted by anchor and span; ``memory`` contexts are sorted at a time, and an
    anchor with more goes through files."""

    def ranges(gram, span, place, hit):
        """hit: repeated windows by context and distance to the anchor."""
        item, back = np.nonzero(hit)
        if not len(item):
            return
        at = place[item] - back
        order = np.lexsort((at, item))
        item, at = item[order], at[order]
        head = np.flatnonzero(np.concatenate([[True], (item[1:] != item[:-1]) | (at[1:] != at[:-1] + 1)]))
        last = np.concatenate([head[1:] - 1, [len(at) - 1]])
        yield pa.RecordBatch.from_arrays([pa.array(gram[item[head]]), pa.array(span[item[head]]), pa.array(at[head].astype(np.int32)), pa.array(at[last].astype(np.int32))], ["gram", "span", "first", "last"])

    def small(held):
        if len(held) > 1:
            gram, span, place, count, context = zip(*held)
            gram, span, place, count = (np.array(x, np.int64) for x in (gram, span, place, count))
            group = np.cumsum(np.concatenate([[0], gram[1:] != gram[:-1]]))
            yield from ranges(gram, span, place, induce(group, list(context), place, count, length))

    def large(gram, spans, external):
        with tempfile.TemporaryFile() as f:  # one byte for each context and distance
            hit = np.memmap(f, bool, "w+", shape=(len(spans), length + 1))
            for item, back in external.finish():
                hit[item, back] = True
            for lo in range(0, len(spans), memory):
                own = slice(lo, lo + memory)
                place = np.array(external.place[own], np.int64)
                yield from ranges(np.full(len(place), gram), np.array(spans[own]), place, np.array(hit[own]))
            del hit

    def run(batches):
        held: list[tuple] = []  # whole anchors and the one being read
        begin = 0  # where the latter begins
        external, spans, before = None, array("q"), None
        for batch in batches:
            for row in zip(*(batch.column(c).to_pylist() for c in range(5))):
                if before is not None and row[:2] == before[:2]:
                    continue  # another place of the same context
                if before is not None and row[0] != before[0]:
                    if external:
                        yield from large(before[0], spans, external)
                        external, spans = None, array("q")
                    if len(held) >= memory // 2:
                        yield from small(held)
                        held = []
                    begin = len(held)
                before = row
                if external is None and len(held) - begin >= memory:
                    external = ExternalInduction(length)
                    for old in held[begin:]:
                        external.add(old[4], old[2], old[3])
                        spans.append(old[1])
                    held = held[:begin]
                if external is not None:
                    external.add(row[4], row[2], row[3])
                    spans.append(row[1])
                else:
                    held.append(row)
        if external:
            yield from large(before[0], spans, external)
        yield from small(held)

    return rows.mapInArrow(run, HITS)


def repeated_ranges(docs: DataFrame, length: int = 400, gram: int = 100, memory: int = 8_000) -> DataFrame:
    """doc_id, row_key, start, end: byte ranges that windows standing twice cover."""
    docs = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id"), "text")
    mine = materialise(anchor_rows(docs, length, gram), "anchors")
    spans = materialise(mine.groupBy("gram", "span").agg(F.count("*").alias("places"), F.min("doc_id").alias("doc_id")), "spans")
    cover = lambda first, last: [F.col("doc_id"), F.col("row_key"), (F.col("start") + first).cast("int").alias("start"), (F.col("start") + last + length).cast("int").alias("end")]
    twice = mine.join(spans.where("places > 1").select("gram", "span"), ["gram", "span"]).select(*cover(F.lit(0), F.col("count") - 1))
    mixed = spans.groupBy("gram").agg(F.count("*").alias("n")).where("n > 1").select("gram")
    wanted = spans.join(mixed, "gram", "left_semi").groupBy("doc_id").agg(F.collect_set("span").alias("wanted"))
    asked = docs.where(F.octet_length("text") >= length).join(wanted, "doc_id").select("doc_id", "text", "wanted")
    contexts = context_rows(asked, length, gram).repartition("gram").sortWithinPartitions("gram", "span")
    hits = materialise(repeated_in_contexts(contexts, length, memory), "hits")
    once = spans.where("places = 1").select("gram", "span")
    partly = mine.join(once, ["gram", "span"], "left_semi").join(hits, ["gram", "span"]).select(*cover(F.col("first"), F.col("last")))
    return materialise(twice.unionByName(partly), "ranges")


OUT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def remove_ranges(docs: DataFrame, ranges: DataFrame, with_bytes: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and, if asked for, the bytes that are left."""
    per_doc = ranges.groupBy(F.col("doc_id").alias("key")).agg(F.collect_list(F.struct("row_key", "start", "end")).alias("_cuts"))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("key"), "text")
    joined = docs.join(per_doc, "key", "left").select("doc_id", "text", F.col("_cuts.row_key").alias("k"), F.col("_cuts.start").alias("s"), F.col("_cuts.end").alias("e"))

    def run(batches):
        for batch in batches:
            ids = batch.column(0)
            for block in K.text_blocks(batch.column(1)):
                lo, n = block.rows.start, block.rows.stop - block.rows.start
                any_cut = batch.column(2).slice(lo, n).is_valid().to_pylist()
                keys = K.signed(K.row_hashes(_values(block)[1], block.offsets)) if any(any_cut) else None
                removed, spans, sha, left = [], [], [], []
                for i in range(n):
                    raw = block.text(i)
                    cut = spanned = 0
                    if any_cut[i]:
                        own = np.array(batch.column(2)[lo + i].as_py()) == keys[i]
                        s, e = K.merge_intervals(np.array(batch.column(3)[lo + i].as_py())[own], np.array(batch.column(4)[lo + i].as_py())[own])
                        stay, at = [], 0
                        for a, b in zip(s.tolist(), e.tolist()):
                            stay.append(raw[at:a])
                            at = b
                        stay.append(raw[at:])
                        rest = b"".join(stay)
                        cut, spanned = len(raw) - len(rest), len(s)
                    else:
                        rest = raw
                    removed.append(cut)
                    spans.append(spanned)
                    sha.append(hashlib.sha256(rest).hexdigest())
                    left.append(rest if with_bytes else None)
                yield pa.RecordBatch.from_arrays([ids.slice(lo, n), pa.array(np.diff(block.offsets)), pa.array(removed, pa.int64()), pa.array(spans, pa.int64()), pa.array(sha, pa.string()), *([pa.array(left, pa.binary())] if with_bytes else [])], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", *(["kept"] if with_bytes else [])])

    return joined.mapInArrow(run, OUT + (", kept binary" if with_bytes else ""))


def dedup_bytes(docs: DataFrame, length: int = 400, gram: int = 100, memory: int = 8_000, with_bytes: bool = False) -> DataFrame:
    docs = docs.select("doc_id", "text")
    return remove_ranges(docs, repeated_ranges(docs, length, gram, memory), with_bytes)
