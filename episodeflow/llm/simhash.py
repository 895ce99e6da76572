"""Near-duplicates by fingerprint: links at a small Hamming distance, found through segment popcounts.

A fingerprint's embedding holds the bit counts of its 32 two-bit segments. The Manhattan distance of two embeddings is
never above the Hamming distance of the fingerprints, so links lie within 3 in it, and one of the two halves of their
embeddings lies within 1. The grid's cells are the halves' count vectors: each distinct fingerprint stands in its two
cells and probes the cells one step up in one count (one direction is enough, the other is the partner's). What meets
in a cell is compared exactly, and a cell hands on a spanning forest of its links, never all pairs. A cell of more than
`SPLIT` rows is split by the other half: links lie within 3 there, so that one of its two quarters lies within 1, and
the same step is taken again with the quarters' counts. No task holds more of a crowded cell than such a part.

Equal fingerprints are one node from the start, so copies cost nothing. Null texts are empty; a text without words has
fingerprint zero and links like any other; repeated rows keep their rows; other columns aren't read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import enter, materialise, ragged, record, slices, texts, trim
from .components import components

SHINGLE, DISTANCE, SEED = 3, 3, 42
MANY, SPLIT = 64, 1 << 15
_PAIRS = np.uint64(0x5555555555555555)


def fingerprint(text: str, shingle: int = SHINGLE) -> int:
    """Bit k is 1 where it is set in over half of the XXH64 hashes of the word shingles."""
    words = text.encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z alone is lowered, ASCII white space alone splits
    if not words:
        return 0
    joined = b" ".join(words)
    n = max(1, len(words) - shingle + 1)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    starts = (ends - lengths)[:n].tolist()
    ends = ends[min(shingle, len(words)) - 1 :].tolist()
    digest = xxhash.xxh64_digest
    hashes = np.frombuffer(b"".join([digest(joined[a:b], SEED) for a, b in zip(starts, ends, strict=True)]), np.uint8).reshape(-1, 8)
    counts = np.zeros(64, np.int64)
    for at in range(0, n, 1 << 16):
        counts += np.unpackbits(hashes[at : at + (1 << 16)], axis=1).sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(counts * 2 > n).tobytes(), "big")


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """doc_id and fp, the fingerprint as a signed long."""
    schema = pa.schema([("doc_id", pa.int64()), ("fp", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("simhash")
        for batch in slices(batches):
            prints = np.array([fingerprint(t, shingle) for t in batch.column(1).to_pylist()], np.uint64)
            yield record(schema, batch.column(0), prints.view(np.int64))
        trim()

    return texts(docs).mapInArrow(run, "doc_id long, fp long")


def embedding(fp: np.ndarray) -> np.ndarray:
    """Popcounts of the two-bit segments, each in its own two bits."""
    return (fp & _PAIRS) + ((fp >> np.uint64(1)) & _PAIRS)


def manhattan(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Distance of two embeddings, field by field; every field holds 0 to 2."""
    low = np.uint64(0x3333333333333333)
    total = np.zeros(np.broadcast(a, b).shape, np.int64)
    for shift in (np.uint64(0), np.uint64(2)):
        x, y = (a >> shift) & low, (b >> shift) & low
        d = (x | np.uint64(0x4444444444444444)) - y  # 4 + difference: 2 to 6, so 1 where odd, else 2 where bit 1 is set
        odd = d & np.uint64(0x1111111111111111)
        total += np.bitwise_count(odd) + 2 * np.bitwise_count((d & np.uint64(0x2222222222222222)) & ~(odd << np.uint64(1)))
    return total


def _cells(prints: DataFrame) -> DataFrame:
    """(cell, probe, fp): each half's own cell, and the cells one count up."""
    counts = "(({0} & 1431655765L) + (shiftrightunsigned({0}, 1) & 1431655765L))"  # of the 16 segments of 32 bits
    low, high = counts.format("(fp & 4294967295L)"), counts.format("shiftrightunsigned(fp, 32)")
    halves = prints.selectExpr("fp", f"inline(array(struct(0L as half, {low} as c), struct(1L as half, {high} as c)))")
    # A two-bit count takes 32 bits, so the half's number goes above them.
    up = "transform(filter(sequence(0, 15), i -> (shiftright(c, 2 * i) & 3L) < 2L), i -> struct(half * 4294967296L + c + shiftleft(1L, 2 * i) as cell, true as probe))"
    return halves.selectExpr("fp", f"inline(concat(array(struct(half * 4294967296L + c as cell, false as probe)), {up}))").select("cell", "probe", "fp")


def _parts(rows: DataFrame) -> DataFrame:
    """(cell, probe, fp) of crowded cells, split by the quarters of the other half.

    Own rows meet each other, so one direction is enough for them; probes meet own rows only and go both ways.
    """
    counts = "(({0} & 1431655765L) + (shiftrightunsigned({0}, 1) & 1431655765L))"
    other = F.when(F.col("cell") < (1 << 32), F.expr(counts.format("shiftrightunsigned(fp, 32)"))).otherwise(F.expr(counts.format("(fp & 4294967295L)")))
    quarters = rows.withColumn("_o", other).selectExpr("cell", "probe", "fp", "inline(array(struct(0L as _q, _o & 65535L as c), struct(1L as _q, shiftrightunsigned(_o, 16) as c)))")
    up = "transform(filter(sequence(0, 7), i -> (shiftright(c, 2 * i) & 3L) < 2L), i -> struct(c + shiftleft(1L, 2 * i) as c2, true as p2))"
    down = "if(probe, transform(filter(sequence(0, 7), i -> (shiftright(c, 2 * i) & 3L) > 0L), i -> struct(c - shiftleft(1L, 2 * i) as c2, true as p2)), array())"
    each = quarters.selectExpr("cell", "_q", "fp", f"inline(concat(array(struct(c as c2, probe as p2)), {up}, {down}))")
    return each.select(F.xxhash64("cell", "_q", "c2").alias("cell"), F.col("p2").alias("probe"), "fp")  # cells that share a hash cost a comparison


def _forest(fps: np.ndarray, distance: int) -> tuple[list, list]:
    """Links that join what is linked among fps: each is reached once, from the one that found it."""
    left, a, b = np.unique(fps), [], []
    while len(left):
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            p = queue.pop()
            near = np.bitwise_count(left ^ p) <= distance
            if near.any():
                got = left[near]
                left = left[~near]
                a.extend([p] * len(got))
                b.extend(got.tolist())
                queue.extend(got)
    return a, b


def _links(cell: np.ndarray, probe: np.ndarray, fp: np.ndarray, distance: int) -> tuple[np.ndarray, np.ndarray]:
    """Links within whole cells; rows are sorted by cell, own rows before probes."""
    opens = np.flatnonzero(np.diff(cell, prepend=cell[0] - 1 if len(cell) else 0))
    size = np.diff(opens, append=len(cell))
    own = np.add.reduceat(~probe, opens).astype(np.int64) if len(opens) else np.empty(0, np.int64)
    live = (own > 0) & (size > 1)
    a, b = [np.empty(0, np.uint64)], [np.empty(0, np.uint64)]
    few = live & (size <= MANY)
    # Row k of a cell with its own rows before it: each pair once, no pair of two probes.
    rows = ragged(opens[few], size[few])
    at = rows - np.repeat(opens[few], size[few])
    count = np.minimum(at, np.repeat(own[few], size[few]))
    first = np.repeat(opens[few], size[few])
    step = 1 << 17
    for k in range(0, len(rows), step):
        x = np.repeat(rows[k : k + step], count[k : k + step])
        y = ragged(first[k : k + step], count[k : k + step])
        p, q = fp[x], fp[y]
        near = (p != q) & (np.bitwise_count(p ^ q) <= distance)
        a.append(p[near])
        b.append(q[near])
    for k in np.flatnonzero(live & (size > MANY)):
        p, q = _forest(fp[opens[k] : opens[k] + size[k]], distance)
        a.append(np.array(p, np.uint64))
        b.append(np.array(q, np.uint64))
    return np.concatenate(a), np.concatenate(b)


def links(prints: DataFrame, distance: int = DISTANCE, split: int = SPLIT) -> DataFrame:
    """(a, b): links that join all fingerprints (distinct, column fp) at `distance` (3 at most) or fewer differing bits."""
    if not 0 <= distance <= 3:
        raise ValueError("two halves with a step of one find distances up to 3")
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("simhash")
        held: list[tuple[np.ndarray, ...]] = []

        def out(parts: list) -> pa.RecordBatch:
            a, b = _links(*(np.concatenate(x) for x in zip(*parts, strict=True)), distance)
            return record(schema, a.view(np.int64), b.view(np.int64))

        for batch in batches:
            if not batch.num_rows:
                continue
            cell, probe, fp = (np.asarray(batch.column(k).to_numpy(zero_copy_only=False)) for k in range(3))
            cut = int(np.searchsorted(cell, cell[-1], "left"))  # the last cell may go on in the next batch
            parts = (cell, probe.astype(bool), fp.view(np.uint64))
            if cut:
                held.append(tuple(x[:cut] for x in parts))
                yield out(held)
                held = []
            elif held and held[-1][0][-1] != cell[0]:
                yield out(held)
                held = []
            held.append(tuple(x[cut:] for x in parts))
        if held:
            yield out(held)
        held = []
        trim()

    n = int(prints.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cells = _cells(prints)
    crowded = materialise(cells.groupBy("cell").count().where(F.col("count") > split).select("cell"), "crowded")
    if crowded.limit(1).count():
        cells = cells.join(crowded, "cell", "left_anti").unionByName(_parts(cells.join(crowded, "cell", "left_semi")))
    dealt = cells.repartition(n, "cell").sortWithinPartitions("cell", "probe")
    return dealt.mapInArrow(run, "a long, b long").distinct()


def near_duplicates(docs: DataFrame, shingle: int = SHINGLE, distance: int = DISTANCE) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id: the smallest doc_id reachable over links, itself included."""
    prints = materialise(fingerprints(docs, shingle), "fingerprints")
    nodes = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct-fingerprints")
    joined = components(links(nodes.select("fp"), distance))
    smallest = nodes.join(joined, nodes.fp == joined.node, "left").select("fp", "least", F.coalesce("component", "fp").alias("c"))
    groups = smallest.groupBy("c").agg(F.min("least").alias("component_id"))
    of = smallest.join(groups, "c").select("fp", "component_id")
    return prints.join(of, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, shingle: int = SHINGLE, distance: int = DISTANCE) -> DataFrame:
    """The documents that have the smallest doc_id of their group; rows with a null doc_id stay. Of repeated doc_ids all rows stay or go."""
    groups = near_duplicates(docs.where("doc_id is not null"), shingle, distance)
    gone = groups.where("doc_id <> component_id").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, docs["doc_id"].cast("long") == gone["_gone"], "left_anti")
