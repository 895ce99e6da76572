"""Benchmark passages in training documents, found by spaced seeds that ignore some token positions.

Words are runs of letters and digits (any byte from 0x80 on counts as a letter), A-Z lower-cased, and hashed. A mask
picks four words of a short window; windows of documents and of benchmark items meet where the picked words are the
same. All masks share one table, so that an item's window may meet a document's window of another mask: a word stands
between in one of them only, which is an inserted or dropped word.

Around each meeting item and document are aligned word by word in a band of diagonals; a word that is changed, inserted
or dropped is one miss. An overlap begins and ends with equal words, takes at least `least` words of the document or of
the item, and `similarity` of equal words and misses are equal; or it is the whole item, however short, with `similarity` of its words equal. Of the overlaps of a document and
an item the one with the most (equal - MISS * misses) is reported.

No such overlap is missed at the fixed values: 12 words or more with a fifth missed always leave four equal words in a
row, or (15 words, 3 misses) four threes, which the second mask meets; the other two masks do the same for whole items
of 5 to 11 words. Overlaps of more than `MOST` misses are found by a part of them, and that part is what is reported.
Items under `SHORTEST` words can't be told from chance inside a text: they are found where they are the whole document,
word by word; items without words are nothing to find.

A meeting that goes on from the words before it, on the same diagonal, says nothing new: only where meetings begin are
they written out, so that repeated words cost what they are long, not the product. A long text is hashed in parts.

Items reach the tasks in blocks of at most `BLOCK_WORDS` words, a broadcast of bounded size; documents are scanned
once for each block and never shuffled. Null texts are empty; empty tables give no rows; repeated documents and items
are judged one by one; other columns aren't read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import CACHES, enter, laid, materialise, ragged, record, slices, texts, trim

#: The masks, 1 = compared.
MASKS, SHORT_MASKS = ("1111", "11101"), ("11011", "10111")
SHORTEST = 5
LEAST, SIMILARITY, MISS, MOST = 12, 0.8, 1, 16
BLOCK_WORDS, CELLS, HITS, PART = 1 << 21, 1 << 21, 1 << 20, 1 << 19
_MIX = np.uint64(0x9E3779B97F4A7C15)
_BASE = 0x100000001B3 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_LOWER = np.zeros(256, np.uint64)
for _c in [*range(48, 58), *range(97, 123), *range(128, 256)]:
    _LOWER[_c] = _c + 1
for _c in range(65, 91):
    _LOWER[_c] = _c + 33
_powers: dict[str, np.ndarray] = {}
CACHES.append(_powers.clear)


def _power(base: int, n: int, name: str) -> np.ndarray:
    if name not in _powers or len(_powers[name]) < n:
        out = np.full(max(n, 1 << 16), base, np.uint64)
        out[0] = 1
        _powers[name] = np.cumprod(out, dtype=np.uint64)
    return _powers[name][:n]


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * _MIX
    return x ^ (x >> np.uint64(29))


def words(data: np.ndarray, bounds: np.ndarray, part: int = PART) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of texts laid end to end (text k: bytes [bounds[k], bounds[k + 1])), and each text's first word.

    Bytes are taken `part` at a time, and as many more as a word that crosses the border has.
    """
    out, opens, a = [], [], 0
    while a < len(data):
        b = min(a + part, len(data))
        while b < len(data) and _LOWER[data[b]] and _LOWER[data[b - 1]] and (k := int(np.searchsorted(bounds, b))) < len(bounds) and bounds[k] != b:
            rest = _LOWER[data[b : b + 4096]] == 0
            b += int(np.argmax(rest)) if rest.any() else len(rest)
        inner = bounds[np.searchsorted(bounds, a, "right") : np.searchsorted(bounds, b, "left")] - a
        hashes, at = _words(data[a:b], inner)
        out.append(hashes)
        opens.append(at + a)
        a = b
    opens = np.concatenate([np.empty(0, np.int64), *opens])
    return np.concatenate([np.empty(0, np.uint64), *out]), np.searchsorted(opens, bounds)


def _words(data: np.ndarray, breaks_at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words and where they begin; a word ends at each of breaks_at."""
    code = _LOWER[data]
    live = code != 0
    breaks = np.zeros(len(data) + 1, bool)
    breaks[breaks_at] = True
    breaks[[0, -1]] = True
    opens = np.flatnonzero(live & (breaks[:-1] | ~np.append(False, live[:-1])))
    shuts = np.flatnonzero(live & (breaks[1:] | ~np.append(live[1:], False)))
    if not len(opens):
        return np.empty(0, np.uint64), opens
    total = np.cumsum(code * _power(_BASE, len(code), "up"), dtype=np.uint64)
    start = np.where(opens > 0, total[opens - 1], np.uint64(0))
    return _mixed((total[shuts] - start) * _power(_INVERSE, len(code), "down")[opens]), opens


def _windows(hashes: np.ndarray, mask: str) -> np.ndarray:
    n = len(hashes) - len(mask) + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for k, c in enumerate(mask):
        if c == "1":
            out = out * np.uint64(0xD6E8FEB86659FD93) + hashes[k : k + n]
    return _mixed(out ^ np.uint64(mask.count("1")))


def aligned(equal: np.ndarray, first: np.ndarray, lengths: np.ndarray, most: int, whole: bool, least: int, similarity: float) -> np.ndarray:
    """(equal words, misses, start, end) of each candidate's best overlap, no words where there is none.

    equal[c, i, k]: item word i of candidate c is the document's word first[c] + i + k (k < 128). `whole`: the overlap is the whole
    item; otherwise it begins and ends with equal words and takes `least` words of the document or of the item. The table
    holds, for each number of misses, the most equal words of an overlap that ends there, and of those the earliest start
    (counted from `first`, negated) and its diagonal.
    """
    n, rows, width = equal.shape
    one, none = np.int64(1) << 32, np.int64(-1) << 60
    diagonal = np.arange(width)
    opened = (((np.int64(1) << 24) - diagonal) << 7) + diagonal
    table = np.full((most + 1, n, width), none, np.int64)
    if whole:
        table[0] = opened
    best = np.zeros((n, 5), np.int64)
    best[:, 0] = np.iinfo(np.int64).min
    for i in range(rows):
        now, same = np.empty_like(table), equal[:, i]
        for e in range(most + 1):
            got = np.where(same, table[e] + one, none)
            if not whole:
                np.maximum(got, np.where(same, one + opened - (i << 7), none), out=got)
            if e:
                np.maximum(got, table[e - 1], out=got)
                np.maximum(got[:, :-1], table[e - 1][:, 1:], out=got[:, :-1])
                np.maximum(got[:, 1:], now[e - 1][:, :-1], out=got[:, 1:])
            now[e] = got
            stops = (lengths == i + 1)[:, None] if whole else same
            words, start = got >> 32, (np.int64(1) << 24) - ((got & (one - 1)) >> 7)
            fits = stops & (words > 0) & (words >= similarity * (words + e) - 1e-9)
            if not whole:
                fits &= i + 1 - start + np.maximum(diagonal, got & 127) >= least
            if fits.any():
                rank = np.where(fits, got - e * MISS * one, np.iinfo(np.int64).min)
                k = np.argmax(rank, axis=1)
                c = np.flatnonzero(rank[np.arange(n), k] > best[:, 0])
                k = k[c]
                best[c] = np.stack([rank[c, k], words[c, k], np.full(len(c), e), first[c] + start[c, k], first[c] + i + k + 1], axis=1)
        table = now
    return best[:, 1:]


def _distinct(rows: np.ndarray) -> np.ndarray:
    rows = rows[np.lexsort(rows.T[::-1])]
    return rows[np.append(True, (rows[1:] != rows[:-1]).any(axis=1))] if len(rows) else rows


class Items:
    """A block of benchmark items, ready to be met.

    Keys of item windows are numbered in ascending order; a row of the table is (number of a window's key, number of the
    key one word before under the same mask, plus one; or 0), sorted, so that what goes on from an equal window before
    it is one range of a key's rows.
    """

    def __init__(self, rows: list[tuple], masks: tuple = MASKS, least: int = LEAST):
        self.ids, self.hashes, key, of, at, before = [], [], [], [], [], []
        self.tiny: dict[tuple, list] = {}
        short = False
        for item, text in rows:
            data = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)
            h, _ = words(data, np.array([0, len(data)]))
            if len(h) < SHORTEST:
                if len(h):
                    self.tiny.setdefault(tuple(h.tolist()), []).append(item)
                continue
            short |= len(h) < least
            for mask in (*masks, *SHORT_MASKS) if len(h) < least else masks:
                w = _windows(h, mask)
                before.append(np.append(False, np.ones(max(0, len(w) - 1), bool))[: len(w)])
                key.append(w)
                of.append(np.full(len(w), len(self.ids)))
                at.append(np.arange(len(w)))
            self.ids.append(item)
            self.hashes.append(h)
        self.masks = (*masks, *SHORT_MASKS) if short else masks
        none = np.empty(0, np.int64)
        key, of, at = np.concatenate([np.empty(0, np.uint64), *key]), np.concatenate([none, *of]), np.concatenate([none, *at])
        before = np.concatenate([np.empty(0, bool), *before])
        self.keys, number = np.unique(key, return_inverse=True)
        last = np.where(before, np.append(0, number[:-1] + 1)[: len(number)], 0)
        order = np.lexsort((last, number))
        self.table = number[order] * (len(self.keys) + 1) + last[order]
        self.of, self.at = of[order], at[order]
        self.bits = np.zeros(1 << 22, bool)
        self.bits[(key >> np.uint64(42)).astype(np.int64)] = True
        self.lengths = np.array([len(h) for h in self.hashes], np.int64)
        self.starts = np.cumsum(self.lengths) - self.lengths
        self.words = np.concatenate([np.empty(0, np.uint64), *self.hashes])

    def _numbers(self, keys: np.ndarray) -> np.ndarray:
        """A key's number plus one, 0 where no item has it."""
        if not len(self.keys):
            return np.zeros(len(keys), np.int64)
        at = np.searchsorted(self.keys, keys)
        return np.where(self.keys[np.minimum(at, len(self.keys) - 1)] == keys, at + 1, 0)

    def found(self, hashes: np.ndarray, firsts: np.ndarray, similarity: float) -> Iterator[np.ndarray]:
        """(text, item, first diagonal) where meetings begin, `drift` diagonals taken as one: the item's first word stands at that word of all the texts."""
        drift, radix = np.maximum(self.drift(similarity), 1), len(self.keys) + 1
        for mask in self.masks:
            got = _windows(hashes, mask)
            if not len(got):
                continue
            maybe = np.flatnonzero(self.bits[(got >> np.uint64(42)).astype(np.int64)])
            text = np.searchsorted(firsts, maybe, "right") - 1
            maybe, text = (x[maybe + len(mask) <= np.append(firsts, len(hashes))[text + 1]] for x in (maybe, text))
            number = self._numbers(got[maybe])
            maybe, text, number = maybe[number > 0], text[number > 0], number[number > 0] - 1
            last = np.where(maybe > firsts[text], self._numbers(got[np.maximum(maybe - 1, 0)]), 0)
            a, b = np.searchsorted(self.table, number * radix, "left"), np.searchsorted(self.table, (number + 1) * radix, "left")
            # rows that go on from an equal window: one range in the middle, left out
            x, y = (np.where(last > 0, np.searchsorted(self.table, number * radix + last, side), b) for side in ("left", "right"))
            for lo, hi in ((a, x), (y, b)):
                many = np.maximum(hi - lo, 0)
                part = np.cumsum(many) // HITS  # so many at a time
                cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), len(maybe)]
                for c, d in zip(cuts, cuts[1:], strict=False):
                    hit = ragged(lo[c:d], many[c:d])
                    if len(hit):
                        item, diagonal = self.of[hit], np.repeat(maybe[c:d], many[c:d]) - self.at[hit]
                        yield _distinct(np.stack([np.repeat(text[c:d], many[c:d]), item, diagonal // drift[item] * drift[item]], axis=1))

    def drift(self, similarity: float) -> np.ndarray:
        """The most misses of an overlap of each item."""
        return np.minimum(np.floor(self.lengths * (1 - similarity) / similarity + 1e-9).astype(np.int64), MOST)

    def overlaps(self, hashes: np.ndarray, firsts: np.ndarray, ends: np.ndarray, least: int, similarity: float) -> Iterator[tuple]:
        """(text, item, equal words, misses, start, end) of overlaps, places counted from the first of all words."""
        spots = _distinct(np.concatenate([np.empty((0, 3), np.int64), *self.found(hashes, firsts, similarity)]))
        spots = spots[np.argsort(self.lengths[spots[:, 1]], kind="stable")]
        drifts, at, done = self.drift(similarity), 0, set()
        while at < len(spots):
            if done:  # a whole item without a miss can't be bettered, and spots come from the left
                spots = np.concatenate([spots[:at], spots[at:][[(t, i) not in done for t, i in spots[at:, :2].tolist()]]])
                done = set()
                if at == len(spots):
                    break
            # the items of a chunk have nearly the same number of words
            small = int(self.lengths[spots[at, 1]])
            upto = int(np.searchsorted(self.lengths[spots[:, 1]], small + 4 + small // 8, "right"))
            rows, most = small + 4 + small // 8, int(drifts[spots[at:upto, 1]].max())
            width = 3 * most + 1
            upto = min(upto, at + max(1, CELLS // (rows * width)))
            text, item, diagonal = spots[at:upto].T
            at = upto
            rows = int(self.lengths[item].max())
            first = diagonal - most
            i = np.arange(rows)[:, None]
            place = first[:, None, None] + i + np.arange(width)
            inside = (place >= firsts[text][:, None, None]) & (place < ends[text][:, None, None]) & (i < self.lengths[item][:, None, None])
            own = self.words[np.minimum(self.starts[item][:, None] + np.arange(rows), len(self.words) - 1)]
            equal = inside & (hashes[np.clip(place, 0, len(hashes) - 1)] == own[:, :, None])
            need = similarity * np.minimum(least, self.lengths[item])
            left = np.flatnonzero(equal.any(axis=2).sum(axis=1) >= need - 1e-9)
            for whole in (False, True):
                n = self.lengths[item[left]]
                some = left[similarity * n < least] if whole else left[n >= least]
                if not len(some):
                    continue
                got = aligned(equal[some], first[some], self.lengths[item[some]], most, whole, least, similarity)
                for c, (n_equal, misses, start, end) in zip(some.tolist(), got.tolist(), strict=True):
                    if n_equal == self.lengths[item[c]] and not misses:
                        done.add((int(text[c]), int(item[c])))
                    if n_equal:
                        yield int(text[c]), int(item[c]), n_equal, misses, max(start, int(firsts[text[c]])), min(end, int(ends[text[c]]))


def contaminated(docs: DataFrame, benchmark: DataFrame, least: int = LEAST, similarity: float = SIMILARITY, masks: tuple = MASKS) -> DataFrame:
    """(doc_id, item_id, start, n_words, n_equal, item_words): the best overlap of each contaminated document and item.

    An overlap needs `least` words, inserted or dropped ones among them, however long the item is (an item shorter
    than that: all its words; one of fewer than SHORTEST words: the whole document).
    n_words counts the document's words. Masks other than the fixed ones may miss overlaps.
    """
    spark = docs.sparkSession
    schema = pa.schema([("doc_id", pa.int64()), ("item_id", pa.int64()), ("start", pa.int64()), ("n_words", pa.int64()), ("n_equal", pa.int64()), ("item_words", pa.int64())])
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.coalesce("text", F.lit("")).alias("text"))
    size = items.agg(F.sum(F.length("text"))).first()[0] or 0
    blocks = max(1, math.ceil(size / (4 * BLOCK_WORDS)))
    rows, out = texts(docs), None
    for k in range(blocks):
        block = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == k) if blocks > 1 else items
        sent = spark.sparkContext.broadcast(Items([tuple(r) for r in block.collect()], masks, least))

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            enter("seeds")
            items = sent.value
            for batch in slices(batches, most=2 << 20):
                hashes, firsts = words(*laid(batch.column(1)))
                firsts, ends = firsts[:-1], np.append(firsts[1:-1], len(hashes))
                best: dict[tuple[int, int], tuple] = {}
                for text, item, n, misses, start, end in items.overlaps(hashes, firsts, ends, least, similarity):
                    now = (n - MISS * misses, n, firsts[text] - start, end - start)
                    if (text, item) not in best or now > best[text, item]:
                        best[text, item] = now
                if items.tiny:
                    out = [(batch.column(0)[t].as_py(), i, 0, n, n, n) for t in np.flatnonzero((ends - firsts < SHORTEST) & (ends > firsts)).tolist() for n in [int(ends[t] - firsts[t])] for i in items.tiny.get(tuple(hashes[firsts[t] : ends[t]].tolist()), ())]
                    if out:
                        yield record(schema, *map(list, zip(*out, strict=True)))
                if best:
                    keys, vals = list(best), list(best.values())
                    yield record(schema, [batch.column(0)[t].as_py() for t, _ in keys], [items.ids[i] for _, i in keys], [int(-v[2]) for v in vals], [int(v[3]) for v in vals], [int(v[1]) for v in vals], [len(items.hashes[i]) for _, i in keys])

            trim()

        part = rows.mapInArrow(run, "doc_id long, item_id long, start long, n_words long, n_equal long, item_words long")
        if blocks > 1:  # one block at a time in driver and tasks
            part = materialise(part, "contaminated")
            sent.unpersist()
        out = part if out is None else out.unionByName(part)
    return out


def clean(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The documents that no item contaminates; rows with a null doc_id are judged by their text too."""
    numbered = docs.where("doc_id is null")
    known = docs.where("doc_id is not null")
    gone = contaminated(known, benchmark, **options).select(F.col("doc_id").alias("_gone")).distinct()
    kept = known.join(gone, known["doc_id"].cast("long") == gone["_gone"], "left_anti")
    keyed = numbered.withColumn("doc_id", F.xxhash64("text"))
    bad = contaminated(keyed, benchmark, **options).select(F.col("doc_id").alias("_gone")).distinct()
    rest = keyed.join(bad, keyed["doc_id"] == bad["_gone"], "left_anti").withColumn("doc_id", F.lit(None).cast(docs.schema["doc_id"].dataType))
    return kept.unionByName(rest)
