"""Whole-text token ids with the tokenizers library, with the ids of each space-separated piece kept.

A text is cut only where the tokenizer itself always cuts (a single space between two other
characters, for both public vocabularies, and a full stop or comma between a letter and a space), so
the ids are those of one call on the whole text; texts for which this is not certain are encoded whole.

Pieces are found, looked up and put together in arrays: a kept piece is known by two independent
64-bit hashes of its bytes.  Pieces of more than ``LONGEST`` bytes are encoded each time.
"""

from __future__ import annotations

import os
import unicodedata

import numpy as np

from . import kernels as K
from .kernels import RELEASE, concat_ranges

#: Characters that Python or the tokenizers take for white space, other than the space and line end.
_OTHER_SPACES = "\t\r\x0b\x0c\x1c\x1d\x1e\x1f", "\x85\xa0\u1680\u2028\u2029\u202f\u205f\u3000" + "".join(map(chr, range(0x2000, 0x200B)))
#: Bytes of the longest piece that is kept, and of the blocks in which pieces are looked up.
LONGEST, BLOCK = 64, 1 << 20
_STARTS = np.zeros(256, bool)
_STARTS[[0x00, 0x0A, 0x20]] = True
_LETTERS = np.zeros(256, bool)
_LETTERS[0x41:0x5B] = _LETTERS[0x61:0x7B] = True
_MARKS = np.zeros(256, bool)
_MARKS[[0x2C, 0x2E]] = True
_encoders: dict[tuple, "PieceEncoder"] = {}
RELEASE.append(_encoders.clear)


def vocabulary(name: str, folder: str | None = None) -> str:
    if folder:
        return os.path.join(folder, name)
    import public_tokenizers

    return public_tokenizers.path(name)


def plain_word(piece: str) -> bool:
    """Letters only, whatever composing and lower-casing do."""
    return piece.isalpha() and (piece.isascii() or unicodedata.is_normalized("NFC", piece) and piece.lower().isalpha())


class PieceStore:
    """Ids by the two hashes of a piece, with open addressing on the first."""

    def __init__(self, dtype):
        self.dtype = dtype
        self.clear()

    def clear(self) -> None:
        self.count, self.used = 0, 0
        self.slots = np.full(1 << 12, -1, np.int32)
        self.one, self.two = np.zeros(1 << 10, np.uint64), np.zeros(1 << 10, np.uint64)
        self.start, self.size = np.zeros(1 << 10, np.int64), np.zeros(1 << 10, np.int32)
        self.ids = np.zeros(1 << 12, self.dtype)

    @staticmethod
    def _grown(x: np.ndarray, need: int) -> np.ndarray:
        return x if need <= len(x) else np.concatenate([x, np.zeros(max(need, 2 * len(x)) - len(x), x.dtype)])

    def find(self, one: np.ndarray, two: np.ndarray) -> np.ndarray:
        """Numbers of pieces; -1 for those not kept."""
        mask = np.uint64(len(self.slots) - 1)
        at = (one & mask).astype(np.int64)
        got = self.slots[at]
        out = np.full(len(one), -1, np.int64)
        left = np.flatnonzero(got >= 0)
        got = got[left]
        while len(left):
            same = (self.one[got] == one[left]) & (self.two[got] == two[left])
            out[left[same]] = got[same]
            left = left[~same]
            at[left] = (at[left] + 1) & int(mask)
            got = self.slots[at[left]]
            there = got >= 0
            left, got = left[there], got[there]
        return out

    def append(self, raw: list[bytes]) -> np.ndarray:
        """Numbers of new pieces, not yet to be found."""
        n = len(raw)
        sizes = np.array([len(x) for x in raw], np.int64) // np.dtype(self.dtype).itemsize
        self.start, self.size = self._grown(self.start, self.count + n), self._grown(self.size, self.count + n)
        new = np.frombuffer(b"".join(raw), self.dtype)
        self.ids = self._grown(self.ids, self.used + len(new))
        self.ids[self.used : self.used + len(new)] = new
        own = np.arange(self.count, self.count + n)
        self.start[own], self.size[own] = self.used + np.cumsum(sizes) - sizes, sizes
        self.used, self.count = self.used + len(new), self.count + n
        return own

    def keep(self, own: np.ndarray, one: np.ndarray, two: np.ndarray) -> None:
        """Makes appended pieces, all different and not kept before, known by their hashes."""
        self.one, self.two = self._grown(self.one, self.count), self._grown(self.two, self.count)
        self.one[own], self.two[own] = one, two
        if 3 * self.count > len(self.slots):
            kept = self.slots[self.slots >= 0]
            self.slots = np.full(1 << (4 * self.count).bit_length(), -1, np.int32)
            own = np.concatenate([kept, own])
        mask = len(self.slots) - 1
        at = (self.one[own] & np.uint64(mask)).astype(np.int64)
        while len(own):  # a free slot goes to the last that asks for it, the others move on
            free = self.slots[at] == -1
            self.slots[at[free]] = own[free]
            stay = self.slots[at] != own
            own, at = own[stay], (at[stay] + 1) & mask


class PieceEncoder:
    """payloads(texts) -> the ids of each text in the narrowest width.

    Byte-level vocabularies keep the space with the word that follows it; word vocabularies drop it.
    The store of pieces is emptied when it holds ``most`` of them.
    """

    def __init__(self, path: str, byte_level: bool, most: int = 1_000_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.dtype = np.uint16 if self.tok.get_vocab_size() <= 1 << 16 else np.uint32
        self.byte_level, self.most, self.kept = byte_level, most, PieceStore(self.dtype)
        self.edge = np.zeros(self.tok.get_vocab_size(), bool)
        self.edge[[i for t, i in self.tok.get_vocab().items() if (t[:1] == "\u0120" if byte_level else t.endswith("</w>"))]] = True
        self.line_end = self.tok.token_to_id("\u010a")

    def cuttable(self, text: str) -> bool:
        """Whether the tokenizer surely cuts at every space of the text."""
        if "<|" in text or "\0" in text:
            return False
        if not self.byte_level:
            return True
        if text[:1] in ("", " ") or text[-1] == " " or "  " in text or " \n" in text or "\n " in text or "\n\n" in text or text[-1] == "\n" or text[0] == "\n":
            return False
        return not any(c in text for kinds in _OTHER_SPACES[: 1 if text.isascii() else 2] for c in kinds)

    @classmethod
    def get(cls, path: str, byte_level: bool, most: int = 1_000_000) -> "PieceEncoder":
        key = (path, byte_level, most)
        if key not in _encoders:
            _encoders.clear()  # one store a worker
            _encoders[key] = cls(path, byte_level, most)
        return _encoders[key]

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, self.dtype).tobytes() for e in self.tok.encode_batch(texts, add_special_tokens=False)]

    def _alike(self, pieces: list[str]) -> list[bytes]:
        """Of many pieces of one kind, in one call over all of them."""
        if self.byte_level and pieces[0][:1] in (" ", "\n"):  # only a piece's first id begins with its space or line end
            ids = np.array(self.tok.encode_batch_fast(["".join(pieces)], add_special_tokens=False)[0].ids, self.dtype)
            starts = np.flatnonzero(self.edge[ids] if pieces[0][0] == " " else ids == self.line_end)
        elif not self.byte_level and plain_word(pieces[0]):  # only a word's last id ends one
            ids = np.array(self.tok.encode_batch_fast([" ".join(pieces)], add_special_tokens=False)[0].ids, self.dtype)
            starts = np.concatenate([[0], np.flatnonzero(self.edge[ids])[:-1] + 1])
        else:
            got = self.tok.encode(pieces, is_pretokenized=True, add_special_tokens=False)
            ids = np.array(got.ids, self.dtype)
            counts = np.bincount(np.array(got.word_ids, np.int64), minlength=len(pieces))
            starts = np.cumsum(counts) - counts
        raw = ids.tobytes()
        starts = (starts * ids.itemsize).tolist()
        return [raw[a:b] for a, b in zip(starts, [*starts[1:], len(raw)])]

    def _pieces(self, pieces: list[str]) -> list[bytes]:
        """Ids of pieces; byte-level ones begin with their space or line end where they have one."""
        kind = (lambda p: p[:1] if p[:1] in (" ", "\n") else "") if self.byte_level else plain_word
        groups: dict = {}
        for i, p in enumerate(pieces):
            groups.setdefault(kind(p), []).append(i)
        out: list = [b""] * len(pieces)
        for own in groups.values():
            for lo in range(0, len(own), 4096):
                part = own[lo : lo + 4096]
                for i, raw in zip(part, self._alike([pieces[i] for i in part])):
                    out[i] = raw
        return out

    def _numbers(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Numbers in the store of the pieces data[start:end], encoding those that it has not."""
        base = int(start[0])
        block = data[base : int(end[-1])]
        at, to = start - base, end - base
        one, two = (K.spans_hash(K.cumulative(K._BYTE_VALUES[w][block], K.BASES[w]), at, to, K.BASES[w]) for w in (0, 1))
        short = to - at <= LONGEST
        out = np.full(len(at), -1, np.int64)
        out[short] = self.kept.find(one[short], two[short])
        gaps = np.flatnonzero(out < 0)
        if len(gaps):
            _, first, which = np.unique(one[gaps], return_index=True, return_inverse=True)
            alone = two[gaps] == two[gaps[first]][which]
            alone &= short[gaps]
            ask = np.concatenate([gaps[first], gaps[~alone]])  # each short piece once, and all others
            raw = [block[at[i] : to[i]].tobytes().decode() for i in ask.tolist()]
            own = self.kept.append(self._pieces([p[p[:1] == "\0" :] for p in raw]))
            out[ask] = own
            out[gaps[alone]] = own[which[alone]]
            first_short = short[ask[: len(first)]]
            keep = ask[: len(first)][first_short]
            self.kept.keep(own[: len(first)][first_short], one[keep], two[keep])
        return out

    def payloads(self, texts: list[str]) -> list[bytes]:
        """Little-endian ids of each text in the narrowest width."""
        if self.kept.count > self.most:
            self.kept.clear()
        out: list = [b""] * len(texts)
        cut, whole = [], []
        for i, text in enumerate(texts):
            (cut if self.cuttable(text) else whole).append(i)
        if cut:  # a zero byte stands before each text
            data = np.frombuffer(("\0" + "\0".join([texts[i] for i in cut])).encode(), np.uint8)
            n = len(data)
            starts = _STARTS[data]
            ends = np.append(starts[1:], True)  # a mark between a letter and the next start is a piece too
            mark = _MARKS[data] & ends
            mark[1:] &= _LETTERS[data[:-1]]
            mark[0] = False
            start = np.flatnonzero(starts | mark)
            end = np.append(start[1:], n)
            text_at = np.searchsorted(start, np.flatnonzero(data == 0))
            if not self.byte_level:  # the space before a word goes
                start = start + starts[start]
            numbers, lo = [], 0
            while lo < len(start):
                hi = max(lo + 1, int(np.searchsorted(end, start[lo] + BLOCK, side="right")))
                numbers.append(self._numbers(data, start[lo:hi], end[lo:hi]))
                lo = hi
            number = np.concatenate(numbers)
            size = self.kept.size[number].astype(np.int64)
            ids = self.kept.ids[concat_ranges(self.kept.start[number], size)]
            bounds = np.append(np.append(0, np.cumsum(size))[text_at], len(ids)).tolist()
            for i, a, b in zip(cut, bounds, bounds[1:]):
                out[i] = ids[a:b].tobytes()
        for i, b in zip(whole, self._whole([texts[i] for i in whole]) if whole else ()):
            out[i] = b
        return out
