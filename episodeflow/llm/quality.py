"""Quality by a byte-level convolutional network in numpy, over overlapping chunks that cover the whole document.

A filter of width `WIDTH` over one-hot bytes is a table (position, byte) -> weight, so convolving is looking up and
adding. A chunk's features are each filter's largest response in it (max pooling, floored at zero); a document's are
the mean and the maximum of its chunks' features; a logistic layer makes them one probability. Chunks overlap by
`WIDTH` - 1 bytes, so every window of the document lies in one.

Fitting (Adam on the driver, gradients through the pooled positions alone) is bounded by three parameters: `sample`
labelled rows, half of each label, by the smallest hash; `each` bytes a text, from its begin; and `most` bytes of them
altogether. Scoring reads whole texts, a megabyte at a time. Null and empty texts have one empty chunk (all features
zero) and thus the bias as their score; so have texts that are shorter than a filter is wide. With labels of one kind only, or
none, the score is their share (0.5). Repeated rows are scored one by one; repeated labels of a doc_id: the smallest.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import enter, held_out, laid, modest_batches, record, slices, smallest

FILTERS, WIDTH, CHUNK = 16, 4, 256
SAMPLE, BYTES, EACH, PASSES, STEPS, BATCH, RATE = 1500, 3 << 20, 48 << 10, 6, 150, 64, 0.01
PAD = 256


def chunks(bounds: np.ndarray, chunk: int = CHUNK) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where the chunks of texts laid end to end begin, where their texts end, and which texts these are."""
    lengths = np.diff(bounds)
    many = np.maximum(1, -(-lengths // chunk))
    of = np.repeat(np.arange(len(lengths)), many)
    first = np.cumsum(many) - many
    return bounds[:-1][of] + (np.arange(len(of)) - first[of]) * chunk, bounds[1:][of], of


def windows(data: np.ndarray, start: np.ndarray, end: np.ndarray, chunk: int = CHUNK, width: int = WIDTH) -> np.ndarray:
    """The chunks' codes and `width` - 1 more, PAD past a text's end."""
    at = start[:, None] + np.arange(chunk + width - 1)
    codes = np.full(at.shape, PAD, np.int32)  # PAD is no byte
    inside = at < end[:, None]
    codes[inside] = data[at[inside]]
    return codes


def chunked(data: np.ndarray, bounds: np.ndarray, chunk: int = CHUNK, width: int = WIDTH) -> tuple[np.ndarray, np.ndarray]:
    """Windows of texts laid end to end: (chunks, chunk + width - 1) codes, PAD past a text's end; and each chunk's text."""
    start, end, of = chunks(bounds, chunk)
    return windows(data, start, end, chunk, width), of


class Network:
    def __init__(self, filters: int = FILTERS, width: int = WIDTH, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.table = rng.normal(0, 0.3, (width, PAD + 1, filters)).astype(np.float32)
        self.table[:, PAD] = -4  # windows past the end don't win
        self.bias, self.out, self.shift = np.zeros(filters, np.float32), rng.normal(0, 0.1, 2 * filters).astype(np.float32), np.float32(0)
        self.constant: float | None = None

    def pooled(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Each chunk's largest response to each filter, and where it is."""
        width = len(self.table)
        n = codes.shape[1] - width + 1
        response = self.table[0][codes[:, :n]]
        for k in range(1, width):
            response += self.table[k][codes[:, k : k + n]]
        at = response.argmax(axis=1)
        return np.take_along_axis(response, at[:, None], 1)[:, 0] + self.bias, at

    def largest(self, codes: np.ndarray) -> np.ndarray:
        width = len(self.table)
        n = codes.shape[1] - width + 1
        response = self.table[0][codes[:, :n]]
        for k in range(1, width):
            response += self.table[k][codes[:, k : k + n]]
        return response.max(axis=1) + self.bias

    def combined(self, pooled: np.ndarray, of: np.ndarray, texts: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        first = np.searchsorted(of, np.arange(texts))
        live = np.maximum(pooled, 0)
        count = np.bincount(of, minlength=texts).astype(np.float32)[:, None]
        return np.concatenate([np.add.reduceat(live, first) / count, np.maximum.reduceat(live, first)], axis=1), live, count

    def score(self, data: np.ndarray, bounds: np.ndarray) -> np.ndarray:
        texts = len(bounds) - 1
        if self.constant is not None:
            return np.full(texts, self.constant)
        start, end, of = chunks(bounds)
        pooled = []
        for k in range(0, len(of), 4096):
            codes = windows(data, start[k : k + 4096], end[k : k + 4096])
            pooled += [self.largest(codes[j : j + 128]) for j in range(0, len(codes), 128)]
        pooled = np.concatenate(pooled)
        z = self.combined(pooled, of, texts)[0].astype(np.float64) @ self.out.astype(np.float64) + float(self.shift)
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))

    def fit(self, texts: list[bytes], labels: np.ndarray, passes: int = PASSES, batch: int = BATCH, rate: float = RATE, seed: int = 7) -> None:
        """Rows of either label weigh the same altogether, by the square root of the ratio."""
        if len(set(labels.tolist())) < 2:
            self.constant = float(labels.mean()) if len(labels) else 0.5
            return
        share = labels.mean()
        weight = np.where(labels == 1, np.sqrt(0.5 / share), np.sqrt(0.5 / (1 - share))).astype(np.float32)
        rng, step = np.random.default_rng(seed), 0
        params = [self.table, self.bias, self.out]
        first, second = [np.zeros_like(p) for p in params] + [np.float32(0)], [np.zeros_like(p) for p in params] + [np.float32(0)]
        width = len(self.table)
        for _ in range(max(passes, STEPS * batch // len(texts))):
            order = rng.permutation(len(texts))
            for k in range(0, len(order), batch):
                own = order[k : k + batch]
                lengths = np.array([len(texts[i]) for i in own])
                data = np.frombuffer(b"".join(texts[i] for i in own), np.uint8)
                codes, of = chunked(data, np.concatenate([[0], np.cumsum(lengths)]))
                got = [self.pooled(codes[c : c + 256]) for c in range(0, len(codes), 256)]
                pooled, at = (np.concatenate(x) for x in zip(*got, strict=True))
                x, live, count = self.combined(pooled, of, len(own))
                z = x @ self.out + self.shift
                d = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - labels[own]) * weight[own] / len(own)
                f = len(self.bias)
                to = np.outer(d, self.out)
                back = (to[:, :f] / count)[of] + np.where(live == x[:, f:][of], to[:, f:][of], 0)
                back *= pooled > 0
                table = np.zeros_like(self.table)
                rows, cols = np.nonzero(back)
                for j in range(width):
                    np.add.at(table[j], (codes[rows, at[rows, cols] + j], cols), back[rows, cols])
                table[:, PAD] = 0
                step += 1
                for i, g in enumerate((table, back.sum(axis=0), x.T @ d, d.sum())):
                    first[i] = 0.9 * first[i] + 0.1 * g
                    second[i] = 0.999 * second[i] + 0.001 * g * g
                    move = rate * (first[i] / (1 - 0.9**step)) / (np.sqrt(second[i] / (1 - 0.999**step)) + 1e-8)
                    if i < 3:
                        params[i] -= move.astype(np.float32)
                    else:
                        self.shift = np.float32(self.shift - move)


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", sample: int = SAMPLE, most: int = BYTES, each: int = EACH) -> Network:
    """A network that has learned from a bounded sample of the labelled rows that aren't held out."""
    marks = labels.where(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull()).where(~held_out("doc_id")).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min(label).cast("int").alias("y"))
    few = smallest(marks, "y", sample // 2).limit(sample)  # its size is known: two labels
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.substring("text", 1, each).alias("text")).join(F.broadcast(few), "doc_id").where("text is not null")
    got = rows.groupBy("doc_id").agg(F.min("y").alias("y"), F.min("_k").alias("k"), F.min("text").alias("text")).orderBy("k", "y", "doc_id").collect()
    texts, ys, held = [], [], 0
    for r in got:
        data = r["text"].encode("utf-8", "surrogatepass")[:each]
        if held + len(data) > most:
            break
        texts.append(data)
        ys.append(r["y"])
        held += len(data)
    net = Network()
    net.fit(texts, np.array(ys, np.float32))
    return net


def score(docs: DataFrame, net: Network, threshold: float = 0.7) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every whole text."""
    modest_batches(docs)
    sent = docs.sparkSession.sparkContext.broadcast(net)
    schema = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("score", pa.float64()), ("predicted", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("quality")
        net = sent.value
        for batch in slices(batches, most=1 << 20):
            p = net.score(*laid(batch.column(2)))
            yield record(schema, batch.column(0), batch.column(1), p, (p >= threshold).astype(np.int32))

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out("doc_id").alias("held_out"), F.coalesce("text", F.lit("")).alias("text"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")
