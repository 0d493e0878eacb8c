"""SentencePiece merge-type encoding with seeded merge dropout, and its decoding.

Encoding starts from characters and keeps an agenda of candidate merges, best score first, then
leftmost.  Each candidate popped is skipped with probability ``rate``, apart from all others: the
numbers of merges between two skips are geometric draws from a keyed hash of (seed, document, unit
in the text, number of the skip).  So segmentations vary from place to place but are the same on
every run, partition and retry.  With rate 0 the ids are those of the library.

Pieces never reach over the start of a run of spaces, so the agendas of units (spaces and the
characters after them) are independent.  Those of all units of a block run side by side in arrays:
a step pops one candidate from every agenda that has one left.  Nothing is kept between blocks, and
no unit's segmentation is reused at another place.  Units of more than ``LONG`` characters have an
agenda of their own in a heap.

Characters that no piece has, and the space symbol itself where a text holds it, are spelt in byte
pieces; decoding restores every text exactly.

Null texts are empty ones and have no ids.  Rows that repeat a doc_id and text repeat its ids;
a null doc_id counts as 0 in the hash.  Extra columns are ignored; empty tables give no rows.
"""

from __future__ import annotations

import heapq
import itertools
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .encode import vocabulary
from .kernels import concat_ranges, mix

SPACE = "▁"
LONG = 64
#: Characters of one block: texts are encoded together up to it, and longer texts in parts.
BLOCK = 1 << 18
COLUMN, COLUMN_BITS = 32, 6  # where a merge keeps the place of its pair in a unit
NONE = np.int64((1 << 63) - 1)
GONE = np.int32(-(1 << 31))
_SIZES = (3, 5, 7, 9, 12, 16, 24, 40, LONG)
_MASK = (1 << 64) - 1
_models: dict[str, "MergeModel"] = {}


def _hash(*parts: int) -> int:
    x = 0x9E3779B97F4A7C15
    for p in parts:
        x = ((x ^ p) * 0xBF58476D1CE4E5B9) & _MASK
        x ^= x >> 29
    x = (x * 0x94D049BB133111EB) & _MASK
    return x ^ (x >> 32)


class PairTable:
    """(left, right) symbols to the merge that they allow, one integer: its place in the order of
    merges, room for a column, and the symbol it gives."""

    def __init__(self, pairs: dict[tuple[int, int], tuple[int, int]]):
        bits = max(4, (4 * len(pairs)).bit_length())
        self.shift, self.last = np.uint32(32 - bits), (1 << bits) - 1
        self.keys = np.full(1 << bits, -1, np.int64)
        self.merges = np.full(1 << bits, NONE)
        keys = np.array([l << 32 | r for l, r in pairs], np.int64)
        values = np.array([order << COLUMN + COLUMN_BITS | merged for merged, order in pairs.values()], np.int64)
        at, todo = self._slot(keys), np.arange(len(keys))
        while len(todo):  # each free slot goes to the first of those that ask for it, the others move on
            todo = todo[np.argsort(at[todo], kind="stable")]
            slots, who = np.unique(at[todo], return_index=True)
            free = self.keys[slots] == -1
            own = todo[who[free]]
            self.keys[slots[free]], self.merges[slots[free]] = keys[own], values[own]
            todo = np.setdiff1d(todo, own)
            at[todo] = (at[todo] + 1) & self.last

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        x = (keys >> 32).astype(np.uint32) * np.uint32(0x9E3779B1) ^ keys.astype(np.uint32) * np.uint32(0x85EBCA77)
        return (x >> self.shift).astype(np.int64)

    def find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The merges of pairs; NONE where they do not merge, as with negative symbols."""
        keys = left.astype(np.int64) << 32 | right.astype(np.int64) & 0xFFFFFFFF
        at = self._slot(keys)
        there = self.keys[at]
        away = np.flatnonzero((there != keys) & (there != -1))
        while len(away):
            at[away] = (at[away] + 1) & self.last
            there = self.keys[at[away]]
            away = away[(there != keys[away]) & (there != -1)]
        return self.merges[at]


class MergeModel:
    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        n = self.size = model.get_piece_size()
        names = [model.id_to_piece(i) for i in range(n)]
        normal = [not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i)) for i in range(n)]
        self.pieces = {p: i for i, p in enumerate(names) if normal[i]}
        self.order = {p: -model.get_score(i) for p, i in self.pieces.items()}
        self.bytes = np.zeros(256, np.int64)
        self.bytes[[int(names[i][3:5], 16) for i in range(n) if model.is_byte(i)]] = [i for i in range(n) if model.is_byte(i)]
        self.breaks_alone = not any("\n" in p for p in self.pieces)
        text = [b""] * n
        for p, i in self.pieces.items():
            text[i] = p.replace(SPACE, " ").encode()
        for b, i in enumerate(self.bytes.tolist()):
            text[i] = bytes([b])
        self.text = text
        self.text_bytes = np.frombuffer(b"".join(text), np.uint8)
        self.text_size = np.array([len(x) for x in text], np.int64)
        self.text_start = np.cumsum(self.text_size) - self.text_size
        # symbols: pieces by id, then characters that are only parts of pieces; others are -1 - code point
        symbols = dict(self.pieces)
        for c in sorted({c for p in self.pieces for c in p} - set(symbols)):
            symbols[c] = n + len(symbols) - len(self.pieces)
        self.extra = np.array([ord(c) for c, s in symbols.items() if s >= n], np.int64)
        self.symbol_of = -1 - np.arange(0x110000, dtype=np.int32)
        for c, s in symbols.items():
            if len(c) == 1:
                self.symbol_of[ord(c)] = s
        self.symbol_of[ord(" ")], self.symbol_of[ord(SPACE)] = self.symbol_of[ord(SPACE)], -1 - ord(SPACE)
        place = {o: k for k, o in enumerate(sorted(set(self.order.values())))}
        self.pairs = PairTable({(symbols[p[:k]], symbols[p[k:]]): (i, place[self.order[p]]) for p, i in self.pieces.items() for k in range(1, len(p)) if p[:k] in symbols and p[k:] in symbols})

    @classmethod
    def get(cls, path: str) -> "MergeModel":
        if path not in _models:
            _models[path] = cls(path)
        return _models[path]

    def unit(self, unit: str, skips: Iterator[int] | tuple = ()) -> list[str]:
        """Symbols of one unit (spaces as the space symbol) when the popped candidates numbered
        ``skips`` (ascending) are skipped."""
        n = len(unit)
        order = self.order
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        end = list(range(1, n + 1))  # of the symbol that starts here; 0 once it is merged away
        agenda = []
        for i in range(n - 1):
            o = order.get(unit[i : i + 2])
            if o is not None:
                agenda.append((o, i, i + 2))
        heapq.heapify(agenda)
        popped, ahead = -1, iter(skips)
        skip = next(ahead, -1)
        while agenda:
            _, i, stop = heapq.heappop(agenda)
            j = after[i] if end[i] else n
            if not end[i] or j >= n or end[j] != stop:
                continue  # one of the two has changed
            popped += 1
            if popped == skip:
                skip = next(ahead, -1)
                continue
            end[i], end[j] = stop, 0
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                o = order.get(unit[i : end[k]])
                if o is not None:
                    heapq.heappush(agenda, (o, i, end[k]))
            h = before[i]
            if h >= 0:
                o = order.get(unit[h:stop])
                if o is not None:
                    heapq.heappush(agenda, (o, h, stop))
        return [unit[i : end[i]] for i in range(n) if end[i]]

    def decode(self, ids) -> str:
        """The text; the space put before its first character goes."""
        raw = b"".join(map(self.text.__getitem__, ids))
        return raw[1:].decode() if raw[:1] == b" " else raw.decode()


def _utf8(points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes as four columns, their number) of code points."""
    size = 1 + (points >= 0x80) + (points >= 0x800) + (points >= 0x10000)
    out = np.zeros((len(points), 4), np.int64)
    for n, lead in ((1, 0), (2, 0xC0), (3, 0xE0), (4, 0xF0)):
        own = size == n
        for b in range(n):
            part = points[own] >> 6 * (n - 1 - b)
            out[own, b] = part | lead if b == 0 else part & 0x3F | 0x80
    return out, size


class DropoutEncoder:
    def __init__(self, path: str | None = None, rate: float = 0.1, seed: int = 42):
        self.model = MergeModel.get(path or vocabulary("piece_bpe_32k.model"))
        self.rate, self.seed = rate, seed
        self.dtype = np.uint16 if self.model.size <= 1 << 16 else np.uint32

    def _gaps(self, keys: np.ndarray, number) -> np.ndarray:
        """How many candidates are popped between the skips ``number`` - 1 and ``number`` of each key."""
        x = keys + np.asarray(number).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
        u = ((mix(x) >> np.uint64(11)) + np.uint64(1)) * 2.0**-53
        with np.errstate(divide="ignore"):
            return np.minimum(np.log(u) / np.log1p(-min(self.rate, 1.0)), 1 << 30).astype(np.int32)

    def _skips(self, key: np.uint64) -> Iterator[int]:
        if self.rate <= 0:
            return
        at = -1
        for number in itertools.count():
            at += 1 + int(self._gaps(np.array([key], np.uint64), number)[0])
            yield at

    def _run(self, symbols: np.ndarray, size: np.ndarray, keys: np.ndarray) -> np.ndarray:
        """Agendas of units side by side.  symbols: one column a unit, filled up with GONE; merged
        symbols stand where the first of the pair did."""
        out, width, find = symbols, len(symbols), self.model.pairs.find
        unit = np.arange(symbols.shape[1])  # where each column belongs in ``out``
        column = np.arange(width)[:, None]
        agenda = np.full(symbols.shape, NONE)
        if width > 1:
            found = find(symbols[:-1].ravel(), symbols[1:].ravel()).reshape(width - 1, -1)
            agenda[:-1] = np.where(found != NONE, found | column[:-1] << COLUMN, NONE)
        after, before = np.repeat((column + 1).astype(np.int8), len(unit), 1), np.repeat((column - 1).astype(np.int8), len(unit), 1)
        drops, popped = self.rate > 0, -1
        if drops:
            skip, number = self._gaps(keys, np.uint64(0)), np.zeros(len(unit), np.uint64)
        while len(unit):
            best = agenda.min(0)
            row = np.flatnonzero(best != NONE)
            if len(row) < 0.8 * len(unit):
                done = np.flatnonzero(best == NONE)
                out[:, unit[done]] = symbols[:, done]
                if not len(row):
                    break
                symbols, agenda, after, before = (x.take(row, 1) for x in (symbols, agenda, after, before))
                unit, size, best = unit[row], size[row], best[row]
                if drops:
                    keys, skip, number = keys[row], skip[row], number[row]
                row = np.arange(len(unit))
            else:
                best = best[row]
            n = len(unit)
            popped += 1
            at = best >> COLUMN & (1 << COLUMN_BITS) - 1
            cell = at * n + row
            if drops:
                left = skip[row] == popped
                if left.any():
                    agenda.ravel()[cell[left]] = NONE
                    who = row[left]
                    number[who] += np.uint64(1)
                    skip[who] += 1 + self._gaps(keys[who], number[who])
                    row, at, cell, best = row[~left], at[~left], cell[~left], best[~left]
            flat, due, ahead, behind = symbols.ravel(), agenda.ravel(), after.ravel(), before.ravel()
            new = (best & 0xFFFFFFFF).astype(np.int32)
            gone = ahead[cell].astype(np.int64) * n + row
            k = ahead[gone]
            flat[cell], flat[gone], due[gone], ahead[cell] = new, GONE, NONE, k
            there = np.flatnonzero(k < size[row])
            due[cell] = NONE
            right, here = k[there].astype(np.int64) * n + row[there], cell[there]
            behind[right] = at[there]
            due[here] = self._placed(find(new[there], flat[right]), at[there])
            h = behind[cell].astype(np.int64)
            there = np.flatnonzero(h >= 0)
            h = h[there]
            left_of = h * n + row[there]
            due[left_of] = self._placed(find(flat[left_of], new[there]), h)
        return out

    @staticmethod
    def _placed(found: np.ndarray, at: np.ndarray) -> np.ndarray:
        return np.where(found != NONE, found | at << COLUMN, NONE)

    def block(self, points: np.ndarray, first: np.ndarray, keys: np.ndarray, before: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """points: code points of some texts end to end, each with its leading space; first: where each
        begins, and the end; keys: of each text; before: units of the text that came before this part.

        Returns ids end to end, where each text's begin, and the texts' numbers of units."""
        model = self.model
        n = len(points)
        space = points == 0x20
        head = np.zeros(n + 1, bool)
        head[1:n] = space[1:] & ~space[:-1]
        if model.breaks_alone:
            head[:n] |= points == 0x0A
        head[first] = True
        head = np.flatnonzero(head[:n])
        size = np.diff(np.append(head, n))
        row = np.searchsorted(first, head, side="right") - 1
        units = np.bincount(row, minlength=len(first) - 1)
        place = np.arange(len(head)) - np.repeat(np.cumsum(units) - units, units) + before[row]
        key = mix(keys[row] + place.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        symbols = model.symbol_of[points]
        owners, pieces = [], []
        low = 0
        for high in _SIZES:
            own = np.flatnonzero((size > low) & (size <= high))
            low = high
            if not len(own):
                continue
            column = np.arange(high)[:, None]
            grid = np.where(column < size[own], symbols[np.minimum(head[own] + column, n - 1)], GONE)
            grid = np.ascontiguousarray(self._run(grid, size[own], key[own]).T)
            kept = grid != GONE
            owners.append(np.repeat(own, kept.sum(1)))
            pieces.append(grid[kept])
        for u in np.flatnonzero(size > LONG).tolist():
            raw = points[head[u] : head[u] + size[u]]
            literal = raw == ord(SPACE)  # a private stand-in, so that it merges with nothing
            text = np.where(literal, 0x10FFFF, np.where(raw == 0x20, ord(SPACE), raw)).astype("<u4").tobytes().decode("utf-32-le")
            found = model.unit(text, self._skips(key[u]))
            ids = [model.pieces[s] if s in model.pieces else int(p) for s, p in zip(found, symbols[head[u] + np.cumsum([0, *map(len, found[:-1])])])]
            owners.append(np.full(len(ids), u))
            pieces.append(np.array(ids, np.int64))
        owner = np.concatenate(owners) if owners else np.zeros(0, np.int64)
        piece = np.concatenate(pieces).astype(np.int64) if pieces else np.zeros(0, np.int64)
        spelt = np.flatnonzero((piece < 0) | (piece >= model.size))
        width = np.ones(len(piece), np.int64)
        if len(spelt):
            point = np.where(piece[spelt] < 0, -1 - piece[spelt], model.extra[np.clip(piece[spelt] - model.size, 0, max(len(model.extra) - 1, 0))] if len(model.extra) else 0)
            raw, width[spelt] = _utf8(point)
        total = np.bincount(owner, weights=width, minlength=len(head)).astype(np.int64)
        start = np.cumsum(total) - total
        run = np.cumsum(width) - width  # within the order of groups; each unit's pieces stand together
        lead = np.flatnonzero(np.append(True, owner[1:] != owner[:-1])) if len(owner) else np.zeros(0, np.int64)
        at = start[owner] + run - np.repeat(run[lead], np.diff(np.append(lead, len(owner))))
        ids = np.zeros(int(total.sum()), self.dtype)
        whole = width == 1
        if len(spelt):
            whole[spelt] = False
            for b in range(4):
                has = np.flatnonzero(width[spelt] > b)
                ids[at[spelt[has]] + b] = model.bytes[raw[has, b]]
        ids[at[whole]] = piece[whole]
        begin = np.append(start, len(ids))[np.searchsorted(head, first)]
        return ids, begin, units

    def encode_texts(self, texts: list[str], docs: list[int]) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """Blocks (from text, to text, their ids, where each text's begin and the end)."""
        lo = 0
        while lo < len(texts):
            hi, held = lo, 0
            while hi < len(texts) and (hi == lo or held + len(texts[hi]) <= BLOCK):
                held += len(texts[hi]) + 1
                hi += 1
            keys = np.array([_hash(self.seed, d & _MASK) for d in docs[lo:hi]], np.uint64)
            if hi == lo + 1 and len(texts[lo]) > BLOCK:
                ids = self._long(texts[lo], keys)
                yield lo, hi, ids, np.array([0, len(ids)])
            else:
                led = [" " + t if t else "" for t in texts[lo:hi]]
                points = np.frombuffer("".join(led).encode("utf-32-le"), "<u4")
                first = np.cumsum([0, *map(len, led)])
                ids, begin, _ = self.block(points, first, keys, np.zeros(hi - lo, np.int64)) if len(points) else (np.zeros(0, self.dtype), np.zeros(hi - lo + 1, np.int64), None)
                yield lo, hi, ids, begin
            lo = hi

    def _long(self, text: str, keys: np.ndarray) -> np.ndarray:
        """A long text in parts that begin where units do."""
        text, at, before, out = " " + text, 0, np.zeros(1, np.int64), []
        while at < len(text):
            cut = text.find(" ", at + BLOCK)
            while cut > 0 and text[cut - 1] == " ":
                cut = text.find(" ", cut + 1)
            cut = len(text) if cut < 0 else cut
            points = np.frombuffer(text[at:cut].encode("utf-32-le"), "<u4")
            ids, _, units = self.block(points, np.array([0, len(points)]), keys, before)
            out.append(ids)
            at, before = cut, before + units
        return np.concatenate(out)

    def encode(self, text: str, doc: int) -> list[int]:
        return [i for _, _, ids, _ in self.encode_texts([text], [doc]) for i in ids.tolist()]

    def decode(self, ids) -> str:
        return self.model.decode(ids)

    def restores(self, ids: np.ndarray, begin: np.ndarray, texts: list[str]) -> list[bool]:
        """Whether the ids of each text decode to it."""
        model = self.model
        size = model.text_size[ids]
        raw = model.text_bytes[concat_ranges(model.text_start[ids], size)].tobytes()
        ends = np.append(0, np.cumsum(size))[begin].tolist()
        return [raw[a:b] == (" " + t if t else "").encode() for a, b, t in zip(ends, ends[1:], texts)]


def encode_documents(df: DataFrame, path: str | None = None, rate: float = 0.1, seed: int = 42, with_ids: bool = False) -> DataFrame:
    """doc_id, n_pieces, ids_crc32 (of 32-bit ids), restored (decoding gives the text back), and ids if asked for."""

    def run(batches):
        encoder = DropoutEncoder(path, rate, seed)
        for batch in batches:
            docs = [d or 0 for d in batch.column(0).to_pylist()]
            for lo in range(0, len(docs), 256):
                texts = [t or "" for t in batch.column(1).slice(lo, 256).to_pylist()]
                for a, b, ids, begin in encoder.encode_texts(texts, docs[lo : lo + 256]):
                    wide = ids.astype("<u4")
                    crc = [zlib.crc32(wide[s:e]) for s, e in zip(begin[:-1].tolist(), begin[1:].tolist())]
                    columns = [batch.column(0).slice(lo + a, b - a), pa.array(np.diff(begin)), pa.array(crc, pa.int64()), pa.array(encoder.restores(ids, begin, texts[a:b]))]
                    if with_ids:
                        columns.append(pa.ListArray.from_arrays(pa.array(begin, pa.int32()), pa.array(wide.astype(np.int32))))
                    yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_pieces", "ids_crc32", "restored", *(["ids"] if with_ids else [])])

    return df.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_pieces long, ids_crc32 long, restored boolean" + (", ids array<int>" if with_ids else ""))
