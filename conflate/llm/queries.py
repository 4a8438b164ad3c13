"""Registered queries of the corpus operators, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from conflate.llm import decontam, exact, fuzzylines, langid, passages, pii, probminhash, sampling, toxicity, urls
from conflate.llm.common import for_learning, held_out, table

#: The rule list of the URL query: (host, path, verdict).
URL_RULES = [("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block")]


def op1_language_profiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    profiles = langid.learn(docs.where(for_learning(F.col("doc_id"))))
    got = langid.predict(docs.select("doc_id", "text"), profiles)
    return got.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def op2_probability_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return probminhash.classes_of(table(spark, sf_dir, "documents"))


def op3_disclosure_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find(table(spark, sf_dir, "documents"), texts=True)
    return found.withColumn("clean_sha256", F.sha2(F.encode("clean", "UTF-8"), 256)).drop("clean")


def op4_weak_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels").select("doc_id", "toxic")
    scorer = toxicity.learn(docs.where(for_learning(F.col("doc_id"))), labels.where(for_learning(F.col("doc_id"))))
    got = toxicity.score(docs, scorer)
    return got.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= toxicity.CUT).cast("int").alias("predicted"))


def op5_fuzzy_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fuzzylines.report(table(spark, sf_dir, "documents"))


def op6_phrase_automata(spark: SparkSession, sf_dir: str) -> DataFrame:
    return passages.remove(table(spark, sf_dir, "documents"), texts=False).withColumnRenamed("kept", "kept_sha256")


def op7_simhash_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op8_gumbel_segmentations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampling.encode(table(spark, sf_dir, "documents"), ids=False).withColumnRenamed("ids", "ids_sha256")


def op9_progressive_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.decisions(table(spark, sf_dir, "documents"))


def op10_host_path_trie(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(table(spark, sf_dir, "pages"), URL_RULES)


QUERIES = {"op1_language_profiles": op1_language_profiles, "op2_probability_minhash": op2_probability_minhash, "op3_disclosure_pii": op3_disclosure_pii, "op4_weak_toxicity": op4_weak_toxicity, "op5_fuzzy_lines": op5_fuzzy_lines, "op6_phrase_automata": op6_phrase_automata, "op7_simhash_windows": op7_simhash_windows, "op8_gumbel_segmentations": op8_gumbel_segmentations, "op9_progressive_dedup": op9_progressive_dedup, "op10_host_path_trie": op10_host_path_trie}

ORACLES = {
    "op9_progressive_dedup": r"""
WITH t AS (SELECT doc_id, length(coalesce(text, '')) AS n, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', '', 'g')) AS h FROM documents),
g AS (SELECT doc_id, h, count(*) OVER (PARTITION BY h) AS group_size, first_value(doc_id) OVER w AS keep_id, row_number() OVER w AS k FROM t WINDOW w AS (PARTITION BY h ORDER BY n DESC, doc_id NULLS LAST))
SELECT doc_id, keep_id, group_size, k = 1 AS kept, h AS text_sha256 FROM g""",
    "op10_host_path_trie": r"""
WITH u AS (SELECT page_id, coalesce(regexp_extract(url, '^.*?://([^/?#]*)', 1), '') AS h, coalesce(regexp_extract(url, '^.*?://[^/?#]*([^?#]*)', 1), '') AS path FROM pages),
v AS (SELECT page_id, translate(h, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, path FROM u),
r(rh, rp, verdict) AS (VALUES ('org','/','allow'), ('example.org','/es/','block'), ('example.org','/en/1','block'), ('com','/fr/','allow'), ('com','/de/','block')),
m AS (SELECT page_id, rh || rp AS rule, verdict, row_number() OVER (PARTITION BY page_id ORDER BY length(rh) DESC, length(rp) DESC) AS k
      FROM v JOIN r ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp))
SELECT v.page_id, v.host, v.path, m.rule, coalesce(m.verdict, 'allow') AS verdict FROM v LEFT JOIN m ON m.page_id = v.page_id AND m.k = 1""",
}
