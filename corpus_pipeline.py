"""A corpus pipeline of five stages, each written as Parquet and reread by the next.

Every function takes ``(spark, docs, sf_dir)``; all but the last return the
columns of ``documents``, and the last the packed token ids.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hubloom.llm.bpe import bpe_documents
from hubloom.llm.common import saved, sha256_hex, table, texts
from hubloom.llm.decontamination import contaminated_texts, text_key
from hubloom.llm.line_templates import drop_recurring_lines
from hubloom.llm.near_copies import near_copy_components, row_key
from hubloom.llm.quality import resample
from hubloom.llm.simhash import sampled_bands

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Near-duplicates: sets of five-word shingles of a Jaccard similarity of 0.8 at least, verified.  Candidates are 256-bit
#: fingerprints of which up to 64 bits differ, met in sampled bands; with binomial bit differences a pair is a candidate
#: with probability 0.998 at a similarity of 0.8 and 0.9998 at 0.85.
NEAR = {"shingle": 5, "lanes": 4, "radius": 64, "least": 0.8}
BAND_WIDTH, BAND_TABLES = 14, 96
#: Wider bands of the first pass, which joins most copies before every pair is tried.
FIRST_WIDTH, FIRST_TABLES = 18, 16


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that importance resampling rejects go.

    Null texts are empty, which speaks neither for nor against; repeated rows stay or go together, null ids are judged like others.
    """
    kept = saved(resample(texts(docs), table(spark, sf_dir, "labels")).select("row").distinct(), "kept")
    return docs.withColumn("row", row_key()).join(kept.hint("merge"), "row", "left_semi").select(COLUMNS)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines of recurring templates go, but for their first place; every row stays.

    Rows are told apart by id and text: repeated rows lose the same lines; null ids come first; null texts have no lines and stay null.
    """
    shorter = saved(drop_recurring_lines(texts(docs)).where("n_dropped > 0").select("row", F.col("text").alias("left")).distinct(), "shorter")
    joined = docs.withColumn("row", row_key()).join(shorter.hint("merge"), "row", "left").withColumn("text", F.coalesce("left", "text"))
    return joined.withColumn("n_chars", F.when(F.col("left").isNull(), F.col("n_chars")).otherwise(F.char_length("text"))).select(COLUMNS)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each near-duplicate group stays: that of the smallest id, null ids last.

    Different texts under one id are different rows; of repeated rows one stays; null and empty texts are one group.
    """
    bands, first = sampled_bands(256, BAND_WIDTH, BAND_TABLES), sampled_bands(256, FIRST_WIDTH, FIRST_TABLES, seed=8)
    grouped = near_copy_components(texts(docs), bands=bands, first_bands=first, **NEAR)
    stay = saved(grouped.where("stays").select("row").distinct(), "stay")
    return docs.withColumn("row", row_key()).join(stay.hint("merge"), "row", "left_semi").dropDuplicates(["row"]).select(COLUMNS)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text holds a benchmark item go, whatever their id; null texts hold none."""
    items = table(spark, sf_dir, "benchmark").select(F.col("item_id").cast("long").alias("item_id"), F.coalesce("text", F.lit("")).alias("text"))
    leaks = saved(contaminated_texts(texts(docs), items).select("row").distinct(), "leaks")
    return docs.withColumn("row", text_key()).join(leaks.hint("merge"), "row", "left_anti").select(COLUMNS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each row, packed as little-endian unsigned 32-bit integers; null texts are empty and have none."""
    path = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    coded = bpe_documents(texts(docs), path, public_tokenizers.PATTERN)
    return coded.select("doc_id", "n_tokens", "ids", sha256_hex(F.col("decoded")).alias("decoded_sha256"))


STAGES = [
    ("quality classifier", quality_filter),
    ("line dedup", line_dedup),
    ("SimHash near-dedup", near_dedup),
    ("benchmark decontamination", decontaminate),
    ("byte-level BPE", encode),
]

# Joins of a stage take a side that grows with the documents, so they merge at every size and never broadcast.

#: The models of the first stage and the fingerprints of the third are beyond SQL; tests hold stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(COLUMNS)
    for name, stage in STAGES:
        docs = saved(stage(spark, docs, sf_dir), name.split()[0].lower())
    return docs
