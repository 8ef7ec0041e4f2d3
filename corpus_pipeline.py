"""Corpus pipeline: toxicity, line dedup, near duplicates, decontamination, byte-level BPE.

Each stage takes (spark, docs, sf_dir) and returns a frame, which is written as
Parquet in the shared folder and read again as the next stage's ``docs``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsehop.llm import bpe, common, decontaminate, lines, neardup, toxicity

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier holds toxic go; empty texts are not toxic words and stay by their score."""
    scored = toxicity.toxicity(docs.select(*COLUMNS), common.load(spark, sf_dir, "labels"))
    return scored.filter("predicted = 0").select(*COLUMNS)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that stand earlier in the corpus leave the texts, at any length if equal, long ones to within the edit threshold; n_chars follows."""
    done = lines.dedup_lines(docs.select(*COLUMNS), least=1)
    return done.withColumn("n_chars", F.char_length(common.text_of()).cast("long")).select(*COLUMNS)


def keep_one_of_each_class(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the least doc_id of each near-duplicate class stays; rows that repeat it are one row."""
    judged = neardup.near_duplicates(docs.select("doc_id", "text"))
    first = judged.filter(F.col("doc_id").eqNullSafe(F.col("class_id"))).groupBy(F.col("doc_id").alias("kept")).agg(F.count("*").alias("rows"))
    kept = docs.select(*COLUMNS).join(first, F.col("doc_id").eqNullSafe(F.col("kept")), "inner")
    # only rows whose doc_id repeats are compared with each other
    single, repeated = kept.filter("rows = 1").select(*COLUMNS), kept.filter("rows > 1").select(*COLUMNS).distinct()
    return single.unionByName(repeated)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose benchmark share reaches the contract's rule go; all others stay whole."""
    found = decontaminate.benchmark_hits(docs.select(*COLUMNS), common.load(spark, sf_dir, "benchmark"))
    return found.filter(~decontaminate.contaminated()).select(*COLUMNS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each remaining document, with digests of the ids and of the bytes they stand for."""
    path, pattern = bpe.default_vocabulary()
    return bpe.bpe_encode(docs.select("doc_id", "text"), path, pattern).select("doc_id", "n_tokens", "ids", "ids_sha256", "decoded_sha256")


STAGES = [("toxicity", drop_toxic), ("line_dedup", drop_repeated_lines), ("near_duplicates", keep_one_of_each_class), ("decontaminate", drop_contaminated), ("bpe", encode)]

#: Several stages (classifier, signatures, byte pairs) have no SQL form; tests hold each against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows; a stage's table goes as soon as the next stage's is written."""
    docs, written = common.load(spark, sf_dir, "documents"), None
    for _, stage in STAGES[:-1]:
        docs = common.persist_shared(stage(spark, docs, sf_dir))
        if written is not None:
            common.forget_shared(written)
        written = docs
    return STAGES[-1][1](spark, docs, sf_dir)
