"""Whole-text encoding with the tokenizers library, remembering the ids of pieces seen before.

A byte-level BPE never merges across its pre-tokens, so a text may be cut wherever one always begins and what stands
before it is split the same way alone: before a run of white space, after a newline that stands alone, and before ASCII
punctuation that follows a letter or digit. Pieces repeat far more than texts do. Texts stay bytes throughout: pieces
of up to 15 bytes are looked up as two integers, exactly, in a table that grows up to `most` of them and starts anew
beyond that; a batch's new pieces go through the library as one string. Longer pieces, and pieces with white space
inside, go through it one by one, and texts that hold a special token's string as a whole.
"""

from __future__ import annotations

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from .common import CACHES, ragged

MOST_PIECES, MOST_IDS, MOST_LONG, SHORT = 1_500_000, 8_000_000, 50_000, 15
_MASK = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
_ONE, _TWO = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)
_WORDLIKE, _PUNCTUATION = np.zeros(256, bool), np.zeros(256, bool)
for _c in range(33, 127):
    (_WORDLIKE if chr(_c).isalnum() else _PUNCTUATION)[_c] = True
#: Lead bytes of two-byte letters (all of U+0100 to U+017F and U+0400 to U+047F; U+00C0 to U+00FF but two).
_LEADS = np.zeros(256, bool)
_LEADS[[0xC3, 0xC4, 0xC5, 0xD0, 0xD1]] = True
#: White space of three bytes.
_WIDE = np.array([0xE19A80, *range(0xE28080, 0xE2808B), 0xE280A8, 0xE280A9, 0xE280AF, 0xE2819F, 0xE38080])


def _white(data: np.ndarray) -> np.ndarray:
    """Bytes of white space (control characters count, which only makes pieces longer)."""
    white = data <= 32
    two = np.flatnonzero(data[:-1] == 0xC2)
    two = two[(data[two + 1] == 0x85) | (data[two + 1] == 0xA0)]
    three = np.flatnonzero((data[:-2] >= 0xE1) & (data[:-2] <= 0xE3))
    code = (data[three].astype(np.int64) << 16) | (data[three + 1].astype(np.int64) << 8) | data[three + 2]
    three = three[np.isin(code, _WIDE)]
    for at, n in ((two, 2), (three, 3)):
        for k in range(n):
            white[at + k] = True
    return white


def cuts(data: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where the pieces of texts laid end to end begin (text k: bytes [bounds[k], bounds[k + 1])), and which bytes are white."""
    white = _white(data)
    cut = white.copy()
    cut[1:] &= ~white[:-1]
    line = np.flatnonzero(data[1:-1] == 10) + 1
    cut[line[~white[line - 1] & ~white[line + 1]] + 1] = True
    word = _WORDLIKE[data]
    lead = _LEADS[data]
    word[1:] |= lead[:-1]
    not_letters = np.flatnonzero((data[:-1] == 0xC3) & ((data[1:] == 0x97) | (data[1:] == 0xB7)))
    word[not_letters + 1] = False
    cut[1:] |= _PUNCTUATION[data[1:]] & word[:-1]
    cut[bounds[:-1][bounds[:-1] < bounds[1:]]] = True
    return np.flatnonzero(cut), white


class PieceEncoder:
    def __init__(self, path: str, by_piece: bool):
        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.special = [t.content.encode() for t in self.library.get_added_tokens_decoder().values()]
        self.most = MOST_PIECES
        self.newline = int(self.whole("\n")[0])
        self.by_piece = by_piece and len(self.whole("\n")) == 1
        self.clear()

    def clear(self) -> None:
        self.bits = 16
        self.slots = np.full(1 << self.bits, -1, np.int32)
        self.keys = np.zeros((1 << 15, 2), np.uint64)
        self.start, self.length = np.zeros(1 << 15, np.int32), np.zeros(1 << 15, np.int32)
        self.flat = np.zeros(1 << 16, np.uint32)
        self.n = self.used = 0
        self.long: dict[bytes, np.ndarray] = {}

    def whole(self, text: str) -> np.ndarray:
        return np.asarray(self.library.encode_batch_fast([text], add_special_tokens=False)[0].ids, np.uint32) if text else np.empty(0, np.uint32)

    def each(self, pieces: list[bytes]) -> list[np.ndarray]:
        got = self.library.encode_batch_fast([p.decode("utf-8", "surrogatepass") for p in pieces], add_special_tokens=False) if pieces else []
        return [np.asarray(g.ids, np.uint32) for g in got]

    # ---- the table

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        h = (keys[:, 0] ^ (keys[:, 1] * _TWO)) * _ONE
        h = (h ^ (h >> np.uint64(32))) * _ONE
        return (h >> np.uint64(64 - self.bits)).astype(np.int64)

    def _find(self, keys: np.ndarray) -> np.ndarray:
        """The numbers of keys, -1 for those that aren't known."""
        slot = self._slot(keys)
        number = self.slots[slot]
        have = self.keys.take(number, axis=0, mode="clip")
        same = (have[:, 0] == keys[:, 0]) & (have[:, 1] == keys[:, 1])
        left = np.flatnonzero(~same & (number >= 0))
        while len(left):
            slot[left] = (slot[left] + 1) & (len(self.slots) - 1)
            got = self.slots[slot[left]]
            number[left] = got
            left = left[(got >= 0) & (self.keys.take(got, axis=0, mode="clip") != keys[left]).any(axis=1)]
        return number

    def _put(self, numbers: np.ndarray) -> None:
        slot = self._slot(self.keys[numbers])
        while len(numbers):
            free = self.slots[slot] < 0
            self.slots[slot[free]] = numbers[free]
            lost = self.slots[slot] != numbers
            numbers, slot = numbers[lost], (slot[lost] + 1) & (len(self.slots) - 1)

    def _add(self, keys: np.ndarray, ids: np.ndarray, lengths: np.ndarray) -> None:
        """Distinct unknown keys with their ids end to end."""
        n, used = self.n + len(keys), self.used + len(ids)
        if n > len(self.start):
            more = max(n, 2 * len(self.start))
            self.keys = np.concatenate([self.keys[: self.n], np.zeros((more - self.n, 2), np.uint64)])
            self.start, self.length = (np.concatenate([x[: self.n], np.zeros(more - self.n, np.int32)]) for x in (self.start, self.length))
        if used > len(self.flat):
            self.flat = np.concatenate([self.flat[: self.used], np.zeros(max(used, 2 * len(self.flat)) - self.used, np.uint32)])
        self.keys[self.n : n], self.length[self.n : n] = keys, lengths
        self.start[self.n : n] = self.used + np.cumsum(lengths) - lengths
        self.flat[self.used : used] = ids
        before, self.n, self.used = self.n, n, used
        if 2 * n > len(self.slots):
            self.bits = int(2 * n - 1).bit_length()
            self.slots, before = np.full(1 << self.bits, -1, np.int32), 0
        self._put(np.arange(before, n, dtype=np.int32))

    def _learn(self, data: np.ndarray, white: np.ndarray, begin: np.ndarray, size: np.ndarray, keys: np.ndarray) -> None:
        """New pieces. Each that has no white space but a space before it stands on a line of its own: the newline's id shows where it begins."""
        inner = np.add.reduceat(white[ragged(begin, size)].astype(np.int64), np.cumsum(size) - size) - (data[begin] == 32)
        plain = inner == 0
        odd = ~plain
        b, s = begin[plain], size[plain]
        if len(b):
            joined = np.full(int(s.sum()) + len(b), 10, np.uint8)
            ends = np.cumsum(s + 1)
            joined[ragged(ends - s, s)] = data[ragged(b, s)]
            ids = self.whole(joined.tobytes().decode())
            at = np.flatnonzero(ids == self.newline)
            if len(at) == len(b):
                lengths = np.diff(at, append=len(ids)) - 1
                self._add(keys[plain], ids[ids != self.newline], lengths)
            else:
                odd = np.ones(len(begin), bool)
        if odd.any():
            raw = data.tobytes()
            got = self.each([raw[x : x + y] for x, y in zip(begin[odd].tolist(), size[odd].tolist(), strict=True)])
            self._add(keys[odd], np.concatenate(got), np.array([len(g) for g in got], np.int64))

    # ---- texts

    def _located(self, data: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Each piece's first byte, where its ids begin in `ids`, how many they are, and ids."""
        if self.n > self.most or self.used > MOST_IDS or len(self.long) > MOST_LONG:
            self.clear()
        begin, white = cuts(data, bounds)
        size = np.diff(begin, append=len(data))
        words = np.ndarray((len(data),), "<u8", np.concatenate([data, np.zeros(16, np.uint8)]).data, strides=(1,))
        keys = np.empty((len(begin), 2), np.uint64)
        keys[:, 0] = words[begin] & _MASK[np.minimum(size, 8)]
        rest = np.clip(size - 8, 0, 7)
        keys[:, 1] = words[np.minimum(begin + 8, len(data) - 1)] & _MASK[rest]  # past the end: masked to nothing
        keys[:, 1] |= size.astype(np.uint64) << np.uint64(56)
        short = size <= SHORT
        number = self._find(keys)
        miss = np.flatnonzero(short & (number < 0))
        if len(miss):
            order = miss[np.lexsort((keys[miss, 1], keys[miss, 0]))]
            first = np.append(True, (keys[order[1:]] != keys[order[:-1]]).any(axis=1))
            one = order[first]
            self._learn(data, white, begin[one], size[one], keys[one])
            number[miss] = self._find(keys[miss])
        at, length = self.start[number].astype(np.int64), self.length[number].astype(np.int64)
        ids, more = self.flat, np.flatnonzero(~short)
        if len(more):
            raw = data.tobytes()
            pieces = [raw[x : x + y] for x, y in zip(begin[more].tolist(), size[more].tolist(), strict=True)]
            own = {p: None for p in pieces}
            new = [p for p in own if p not in self.long]
            for p, g in zip(new, self.each(new), strict=True):
                own[p] = g
                if len(p) <= 256:
                    self.long[p] = g
            place, end, parts = {}, self.used, [self.flat[: self.used]]
            for p, g in own.items():
                g = self.long[p] if g is None else g
                place[p] = (end, len(g))
                parts.append(g)
                end += len(g)
            ids = np.concatenate(parts)
            found = np.array([place[p] for p in pieces], np.int64).reshape(-1, 2)
            at[more], length[more] = found[:, 0], found[:, 1]
        return begin, at, length, ids

    def _specials(self, data: np.ndarray, bounds: np.ndarray) -> np.ndarray:
        """Texts that hold a special token's string."""
        raw, hits = memoryview(data), []
        if self.special:
            raw = data.tobytes()
        for s in self.special:
            at = raw.find(s)
            while at >= 0:
                hits.append(int(np.searchsorted(bounds, at, "right")) - 1)
                at = raw.find(s, int(bounds[hits[-1] + 1]) - len(s) + 1)
        return np.unique(np.array(hits, np.int64))

    def encode_bytes(self, data: np.ndarray, bounds: np.ndarray, only_lengths: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """The ids of texts laid end to end, exactly those of the library for each whole text, and how many each has."""
        n = len(bounds) - 1
        whole = self._specials(data, bounds) if self.by_piece else np.arange(n)
        if not len(whole):
            if not len(data):
                return np.empty(0, np.uint32), np.zeros(n, np.int64)
            begin, at, length, ids = self._located(data, bounds)
            total = np.concatenate([[0], np.cumsum(length)])
            lengths = np.diff(total[np.searchsorted(begin, bounds)])
            return np.empty(0, np.uint32) if only_lengths else ids[ragged(at, length)], lengths
        out, lengths, a = [], np.zeros(n, np.int64), 0
        for k in [*whole.tolist(), n]:
            if k > a:
                part = data[bounds[a] : bounds[k]]
                got, lengths[a:k] = self.encode_bytes(part, bounds[a : k + 1] - bounds[a], only_lengths) if self.by_piece else (np.empty(0, np.uint32), 0)
                out.append(got)
            if k < n:
                got = self.whole(data[bounds[k] : bounds[k + 1]].tobytes().decode("utf-8", "surrogatepass"))
                lengths[k] = len(got)
                out.append(got)
            a = k + 1
        return np.concatenate(out), lengths

    def encode_all(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        raw = [t.encode("utf-8", "surrogatepass") for t in texts]
        return self.encode_bytes(np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)]))

    def encode(self, text: str) -> np.ndarray:
        return self.encode_all([text])[0]

    def count(self, text: str) -> int:
        return int(self.encode_all([text])[1][0])


_held: dict[str, PieceEncoder] = {}


def encoder(name: str, most: int = MOST_PIECES) -> PieceEncoder:
    """This process's encoder for a file of public_tokenizers (or a path); other pre-tokenizers than byte level go whole. most: pieces to remember."""
    import json
    import os

    path = name if os.path.exists(name) else public_tokenizers.path(name)
    if path not in _held:
        with open(path, encoding="utf-8") as f:
            said = json.load(f)
        pre = said.get("pre_tokenizer") or {}
        plain = pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True) and not said.get("normalizer") and said["model"].get("type") == "BPE"
        _held[path] = PieceEncoder(path, plain)
    _held[path].most = most
    return _held[path]


CACHES.append(_held.clear)
