"""Nearest neighbours by inner product over one-bit codes of randomly rotated vectors.

A vector is centred, scaled to unit length and rotated by a random orthogonal matrix; its code keeps the signs, packed,
and two scalars: the length of what was coded and how much of it the code holds (the inner product of code and unit
vector, which corrects the estimate). A query is rotated as it is. The estimate of an inner product comes with an error
bound that holds with high probability; in each block of rows, vectors whose upper bound reaches the query's k-th best
lower bound (or k-th best score so far) are scored exactly in double precision, the others aren't touched.

The centre is the mean of a bounded sample (`SAMPLE` rows by smallest hash); all rows are indexed. Queries come in
blocks of about `QUERIES` vectors, a broadcast of bounded size that is let go of before the next one; each block runs
against all rows and its result is written, and every task hands on k rows for a query at most. Estimates and bounds
are double; one that isn't finite excludes nothing, so that vectors of any finite length are found.

The code stands beside its vector: at 64 components the bounds still let through a tenth of all pairs, too many to fetch
by a join. Vectors that are null, zero, or hold null or non-finite components take no part, nor do those of another
length than `dim` (None: the length that most have; ties: the larger). Ties go to the smaller vec_id; repeated rows
count as rows; a vec_id that repeats asks once, with its smallest vector; a null vec_id takes no part; other columns
aren't read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import materialise, record

SAMPLE, QUERIES, BLOCK, ROWS_A_TASK, SIGMAS, SEED, DENSE = 4096, 4096, 4096, 32768, 2.6, 11, 1 / 16


def valid(df: DataFrame, dim: int | None = None) -> DataFrame:
    """vec_id, v (array of doubles) of the vectors that take part."""
    v = F.col("embedding").cast("array<double>")
    fine = F.col("embedding").isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    if dim:
        fine = fine & (F.size(v) == dim)
    return df.where("vec_id is not null").where(fine).select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v"))


def matrix(column: pa.Array, dim: int) -> np.ndarray:
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(-1, dim)


def rotation(dim: int, seed: int = SEED) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(dim, dim)))
    return q * np.sign(np.diag(r))


def lengths(x: np.ndarray) -> np.ndarray:
    """Lengths of rows, of any finite components."""
    top = np.abs(x).max(axis=1, initial=0)
    return np.linalg.norm(x / np.where(top > 0, top, 1)[:, None], axis=1) * top


def encode(x: np.ndarray, centre: np.ndarray, turn: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Packed signs, the centred lengths, and how much of each unit vector its code holds."""
    rest = x - centre
    norm = lengths(rest)
    unit = rest / np.where(norm > 0, norm, 1)[:, None] @ turn.T
    held = np.abs(unit).sum(axis=1) / np.sqrt(x.shape[1])
    return np.packbits(unit > 0, axis=1), norm, np.where(norm > 0, held, 1)


def estimates(codes: np.ndarray, norm: np.ndarray, held: np.ndarray, queries: np.ndarray, turn: np.ndarray, sigmas: float = SIGMAS) -> tuple[np.ndarray, np.ndarray]:
    """Of query times centred vector: the estimate, and the bound of its error (queries in rows)."""
    dim = queries.shape[1]
    signs = (np.unpackbits(codes, axis=1, count=dim).astype(np.float32) * 2 - 1) / np.float32(np.sqrt(dim))
    size = lengths(queries)
    turned = (queries / np.where(size > 0, size, 1)[:, None] @ turn.T).astype(np.float32)
    share = (turned @ signs.T) / held.astype(np.float32)  # of the product of both lengths
    bound = np.sqrt(np.maximum(0, 1 - held**2)) / held * sigmas / np.sqrt(max(1, dim - 1)) + 1e-5  # and single precision's
    with np.errstate(over="ignore", invalid="ignore"):
        return share * norm * size[:, None], norm * bound * size[:, None]


def exact(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Inner products of rows, summed in the order of the components, so that they don't depend on what else is in the block."""
    return np.cumsum(x * q, axis=1)[:, -1]


class Best:
    """The k best rows of each query so far."""

    def __init__(self, ids: np.ndarray, q: np.ndarray, k: int):
        self.ids, self.q, self.k = ids, q, k
        self.scores, self.rows = [np.empty(0)] * len(ids), [np.empty(0, np.int64)] * len(ids)
        self.bar, self.size = np.full(len(ids), -np.inf), lengths(q)

    def take(self, vec: np.ndarray, x: np.ndarray, size: np.ndarray, a: int, guess: np.ndarray, error: np.ndarray) -> None:
        """Rows vec with vectors x of lengths size for the queries from the a-th on: those that the bounds can't exclude are scored.

        Where the bounds let through more than `DENSE` of a tile, all its products cost less than picking rows; the few
        that reach the bar are summed again in order.
        """
        k, ids, q = self.k, self.ids[a : a + len(guess)], self.q[a : a + len(guess)]
        bar, own = self.bar[a : a + len(guess)], vec[None, :] == ids[:, None]
        high = guess + error
        high[~np.isfinite(high)] = np.inf
        high[own] = -np.inf
        if len(vec) >= k and np.isinf(bar).any():
            low = guess - error
            low[own | ~np.isfinite(low)] = -np.inf
            bar = np.maximum(bar, np.partition(low, len(vec) - k, axis=1)[:, len(vec) - k])
        some, at = np.nonzero((high >= bar[:, None]) & ~own)
        if len(some) > DENSE * high.size:
            rough = (q @ x.T)[some, at]
        else:
            rough = np.empty(len(some))
            for c in range(0, len(some), 1 << 14):
                part = slice(c, c + (1 << 14))
                rough[part] = np.einsum("ij,ij->i", x[at[part]], q[some[part]])
        slack = 1e-12 * self.size[a + some] * size[at]
        keep = ~(rough + slack < bar[some])
        some, at = some[keep], at[keep]
        score = np.concatenate([np.empty(0), *[exact(x[at[c : c + 4096]], q[some[c : c + 4096]]) for c in range(0, len(some), 4096)]])
        cuts = np.flatnonzero(np.diff(some, prepend=-1))
        for c, d in zip(cuts, np.append(cuts[1:], len(some)), strict=True):
            j = a + int(some[c])
            s, v = np.concatenate([self.scores[j], score[c:d]]), np.concatenate([self.rows[j], vec[at[c:d]]])
            order = np.lexsort((v, -s))[:k]
            self.scores[j], self.rows[j] = s[order], v[order]
            if len(order) == k:
                self.bar[j] = self.scores[j][-1]


def index(df: DataFrame, dim: int) -> tuple[DataFrame, np.ndarray]:
    """One coded row for each vector that takes part, and the centre."""
    rows = valid(df, dim)
    few = rows.orderBy(F.xxhash64("vec_id"), "vec_id", "v").limit(SAMPLE).collect()
    centre = (np.array([r["v"] for r in few]) / len(few)).sum(axis=0) if few else np.zeros(dim)
    turn = rotation(dim)
    schema = pa.schema([("vec_id", pa.int64()), ("code", pa.binary()), ("norm", pa.float64()), ("held", pa.float64()), ("vector", pa.list_(pa.float64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                codes, norm, held = encode(matrix(batch.column(1), dim), centre, turn)
                yield record(schema, batch.column(0), [c.tobytes() for c in codes], norm, held, batch.column(1).cast(pa.list_(pa.float64())))

    return materialise(rows.mapInArrow(run, "vec_id long, code binary, norm double, held double, vector array<double>"), "one-bit-index"), centre


def search(df: DataFrame, queries: DataFrame, k: int = 20, dim: int | None = None, sigmas: float = SIGMAS) -> DataFrame:
    """(query_id, rank, vec_id, score): the k nearest found of each query among the rows of df with another vec_id."""
    spark = df.sparkSession
    if dim is None:
        sizes = valid(df).groupBy(F.size("v").alias("dim")).count().orderBy(F.desc("count"), F.desc("dim")).first()
        dim = sizes["dim"] if sizes else 1
    coded, centre = index(df, dim)
    n, turn = coded.count(), rotation(dim)
    tasks = max(-(-n // ROWS_A_TASK), min(spark.sparkContext.defaultParallelism, -(-n // BLOCK)), 1)
    asked = materialise(valid(queries, dim).groupBy("vec_id").agg(F.min("v").alias("v")), "queries")
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])
    n_blocks = max(1, -(-asked.count() // QUERIES))
    found = None
    for b in range(n_blocks):
        block = asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(n_blocks)) == b).collect()
        sent = spark.sparkContext.broadcast((np.array([r[0] for r in block], np.int64), np.array([r[1] for r in block], np.float64).reshape(-1, dim)))

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            ids, q = sent.value
            best = Best(ids, q, k)
            offset = exact(q, centre[None, :])
            for batch in batches:
                for at in range(0, batch.num_rows, BLOCK):
                    part = batch.slice(at, BLOCK)
                    vec = part.column(0).to_numpy()
                    x = matrix(part.column(4), dim)
                    codes = np.frombuffer(b"".join(part.column(1).to_pylist()), np.uint8).reshape(len(vec), -1)
                    norm, held, size = *(part.column(c).to_numpy() for c in (2, 3)), lengths(x)
                    for a in range(0, len(ids), 128):
                        guess, error = estimates(codes, norm, held, q[a : a + 128], turn, sigmas)
                        own = offset[a : a + 128, None]
                        best.take(vec, x, size, a, guess + own, error + 1e-9 * np.abs(own))
            many = [len(s) for s in best.scores]
            if sum(many):
                yield record(schema, np.repeat(ids, many), np.concatenate(best.rows), np.concatenate(best.scores))

        part = coded.coalesce(tasks).mapInArrow(run, "query_id long, vec_id long, score double")
        order = W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
        part = part.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
        if n_blocks > 1:
            part = materialise(part, "neighbours")
            sent.unpersist()
        found = part if found is None else found.unionByName(part)
    return found
