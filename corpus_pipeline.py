"""A training corpus from ``documents``: five stages, each written and read again before the next.

Language identification drops texts without a language; exact dedup and near-dedup keep one document of each
group; decontamination drops documents that hold a benchmark item; the last stage encodes what is left in
sampled subword segmentations and decodes them again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from conflate.llm import decontam, exact, langid, probminhash, sampling
from conflate.llm.common import for_learning, table, text_key
from conflate.plans.tables import broadcast_if_small, materialise

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the documents whose text has a language; profiles are learned from the rows for learning."""
    profiles = langid.learn(docs.where(for_learning(F.col("doc_id"))).select("doc_id", "text", "lang"))
    # judged by text, so that a null or shared doc_id takes no other row with it
    hashed = docs.select(text_key(F.col("text")).alias("doc_id"), "text")
    rejected = langid.predict(hashed, profiles).where(~langid.accepted(F.col("lang_pred")))
    bad = materialise(rejected.select(F.col("doc_id").alias("__th")).distinct(), "rejected")
    keyed = docs.withColumn("__th", text_key(F.col("text")))
    return keyed.join(broadcast_if_small(bad), "__th", "left_anti").select(*COLUMNS)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact.dedup(docs).select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return probminhash.dedup(docs).select(*COLUMNS)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontam.decontaminate(docs, table(spark, sf_dir, "benchmark")).select(*COLUMNS)


def encode_samples(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, sample, ids, n_pieces, log_prob, inclusion and decodes (the ids give the text back)."""
    return sampling.encode(docs)


STAGES = [
    ("language ID", identify_language),
    ("exact dedup", drop_copies),
    ("near-dedup", drop_near_copies),
    ("benchmark decontamination", drop_benchmark),
    ("subword encoding", encode_samples),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(*COLUMNS)
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)


#: Profiles, signatures and sampling can't be put in SQL; tests hold run() against brute force.
ORACLE_SQL = None
