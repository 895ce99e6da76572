"""A corpus cleaned and packed: language, near-duplicates, benchmark passages, personal data, sequences.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of documents, whatever
columns these are. What a stage keeps is written as Parquet and is the next stage's docs; what the one before it had
written is then removed. Empty tables give empty results at every stage; repeated rows are judged alike.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from episodeflow.llm import decontaminate, language, packing, pii, simhash
from episodeflow.llm.common import table
from episodeflow.storage import new_path, remove


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of a recognised language; those that language ID rejects go, null, empty and letterless texts among them.

    It learns from docs themselves; without a row to learn from all go.
    """
    return language.known_language(docs)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest doc_id of each group of near-duplicates.

    Null texts count as empty ones; rows with a null doc_id stay; of a doc_id that repeats all rows stay or go.
    """
    return simhash.keep_one(docs)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark passage, null and empty texts among them; null and empty items are nothing to find."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def redacted(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal data in their texts replaced by its kind; n_chars follows the text where there is one.

    Null texts stay null; where spans overlap the first counts.
    """
    out = pii.redact(docs, docs.columns)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text")).cast(docs.schema["n_chars"].dataType))
    return out


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every piece of every document and its place in a sequence; a null or empty text is its end id alone.

    It remembers fewer pieces than it would alone: what the stages before it hold in an executor stays there.
    """
    return packing.pack(docs, remembered=200_000, batch_bytes=1 << 20)


STAGES = [("language", known_language), ("near_duplicates", one_of_each), ("decontamination", decontaminated), ("personal_data", redacted), ("packing", packed)]
#: Compression, fingerprints, seeds and the tokenizer are beyond SQL: tests hold the pipeline against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        path = new_path(spark, f"stage-{name}")
        kept = stage(spark, docs, sf_dir)
        kept.write.parquet(path)
        docs = spark.read.schema(kept.schema).parquet(path)
        if before:
            remove(spark, before)
        before = path
    return STAGES[-1][1](spark, docs, sf_dir)
