"""Language by compression: the dictionary of the right language makes a text smallest.

For each language a raw-content zstandard dictionary is laid together from a bounded sample of its training texts. A
text is cut into chunks, so that its own repetitions don't hide the dictionary's help; each chunk is compressed with
each dictionary, and the language with the smallest sum wins. The margin, (second - first) / second, is the score's
source; a text whose margin is below `margin` is rejected, as is one with no letter.

Fitting is bounded by three parameters: `sample` texts of each language (by the smallest hash of the doc_id, so that the
choice doesn't depend on partitions), of each the first `each` characters, and `content` bytes of each dictionary;
prediction reads whole texts and nothing else. A language
has to be non-null and non-empty to be learned. Null, empty and letterless texts are `und` with score 0; with no
training rows everything is; ties go to the language first in the alphabet; repeated rows are judged one by one.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import enter, held_out, modest_batches, record, slices, smallest, trim

SAMPLE, EACH, CONTENT, CHUNK, MARGIN, LEVEL = 1200, 1365, 400 << 10, 4096, 0.02, 6
_NO_LETTERS = re.compile(r"[\W\d_]+")


def normal(text: str) -> bytes:
    """Lower case, with one space for what isn't letters: neither shouting nor junk marks tell a language."""
    return _NO_LETTERS.sub(" ", text.lower()).encode("utf-8", "surrogatepass")


def fit(docs: DataFrame, sample: int = SAMPLE, content: int = CONTENT, each: int = EACH) -> dict[str, bytes]:
    """A dictionary's content for each language of the rows that aren't held out, from `sample` texts, `each` characters of one."""
    known = docs.where("lang is not null and lang <> '' and doc_id is not null").where(~held_out("doc_id"))
    ids = known.select("lang", F.col("doc_id").cast("long").alias("doc_id")).distinct()  # chosen without their texts
    chosen = smallest(ids, "lang", sample)
    few = known.select("lang", F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(chosen), ["lang", "doc_id"]).where("text is not null")
    out: dict[str, list[bytes]] = {}
    one = few.groupBy("lang", "_k").agg(F.min(F.substring("text", 1, each)).alias("text"))  # a doc_id may repeat
    for r in one.orderBy("lang", "_k").collect():
        out.setdefault(r["lang"], []).append(normal(r["text"]))
    return {k: b" ".join(v)[:content] for k, v in sorted(out.items())}


class Judge:
    def __init__(self, contents: dict[str, bytes], level: int = LEVEL, chunk: int = CHUNK):
        self.names, self.chunk, self.presses = list(contents), chunk, []
        for data in contents.values():
            made = zstandard.ZstdCompressionDict(data, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            made.precompute_compress(level=level)
            self.presses.append(zstandard.ZstdCompressor(dict_data=made, level=level, write_checksum=False, write_content_size=False, write_dict_id=False))

    def sizes(self, text: str) -> list[int]:
        data = normal(text)
        parts = [data[a : a + self.chunk] for a in range(0, len(data), self.chunk)]
        return [sum([len(press.compress(p)) for p in parts]) for press in self.presses]

    def __call__(self, text: str | None) -> tuple[str, float, float]:
        """(language, score, margin)."""
        if not text or not self.names or not any(map(str.isalpha, text)):
            return "und", 0.0, 0.0
        sizes = self.sizes(text)
        order = sorted(range(len(sizes)), key=lambda k: (sizes[k], k))
        if len(order) == 1:
            return self.names[0], 1.0, 1.0
        first, second = sizes[order[0]], sizes[order[1]]
        margin = (second - first) / second
        return self.names[order[0]], 0.5 + 0.5 * math.tanh(8 * margin), margin


def identify(docs: DataFrame, contents: dict[str, bytes] | None = None, margin: float = MARGIN) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, margin, rejected); contents: None fits on docs themselves."""
    modest_batches(docs)
    spark = docs.sparkSession
    sent = spark.sparkContext.broadcast(fit(docs) if contents is None else contents)
    schema = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("lang_pred", pa.string()), ("score", pa.float64()), ("margin", pa.float64()), ("rejected", pa.bool_())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("language")
        judge = Judge(sent.value)
        for batch in slices(batches):
            said = [judge(t) for t in batch.column(2).to_pylist()]
            names, scores, margins = zip(*said, strict=True)
            yield record(schema, batch.column(0), batch.column(1), list(names), list(scores), list(margins), [n == "und" or m < margin for n, m in zip(names, margins, strict=True)])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out("doc_id").alias("held_out"), "text")
    return rows.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double, margin double, rejected boolean")


def known_language(docs: DataFrame, margin: float = MARGIN) -> DataFrame:
    """The documents that aren't rejected, with all their columns."""
    modest_batches(docs)
    sent = docs.sparkSession.sparkContext.broadcast(fit(docs))
    kinds = docs.schema
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("language")
        judge = Judge(sent.value)
        for batch in slices(batches):
            said = [judge(t) for t in batch.column(at).to_pylist()]
            yield batch.filter(pa.array([n != "und" and m >= margin for n, _, m in said]))
        trim()

    return docs.mapInArrow(run, kinds)
