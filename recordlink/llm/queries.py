"""The thin queries op1-op10 over the documents table, and DuckDB's SQL where it can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, crf, licenses, linededup, lm, mixing, quality_rules, simhash, tiff, warc
from .common import documents

#: A mixture with uneven weights at each level; up to four epochs of a leaf.
TARGET = mixing.Target(
    weights={"domain": {"d0": 4.0, "d1": 3.0, "d2": 2.0, "d3": 1.0}, "lang": {"en": 5.0, "de": 2.0, "fr": 2.0, "es": 1.0}},
    budget_share=1.0,
    max_epochs=4,
)


def domain_of_source():
    """The documents table has no domain: its sources' trailing numbers fall into four."""
    number = F.regexp_extract("source", r"(\d+)$", 1)
    return F.when(number != "", F.concat(F.lit("d"), F.pmod(number.cast("long"), F.lit(4)).cast("string")))


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.select(documents(spark, sf_dir), TARGET, domain_of_source())[0]


def op2_tiff(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tiff.text_media(documents(spark, sf_dir))


def op3_lm_trie(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    scored = lm.TrieModel(docs, train=(10, {0})).score(docs)
    held = lm.held_out_column(scored, 10, {0}).alias("held_out")
    return scored.select("doc_id", held, "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(documents(spark, sf_dir), shingle=3)
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = warc.pages_as_warc(spark.read.parquet(f"{sf_dir}/pages.parquet"))
    made = warc.derivatives(pages, ["page_id"])
    return made.withColumn("record_sha256", F.sha2("record", 256)).drop("record")


def op6_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_documents(documents(spark, sf_dir), with_ids=False)


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.digests(documents(spark, sf_dir), min_docs=10)


def op8_quality_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = crf.fit(*crf.labelled_sample(docs, labels, crf.train_rows(4, {2}), max_docs=4000))
    scored = crf.score(docs, model)
    return scored.select("doc_id", lm.held_out_column(scored, 4, {2}).alias("held_out"), "score", "predicted", "n_lines", "n_bad_lines")


def op9_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(documents(spark, sf_dir))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return quality_rules.score(docs, quality_rules.Rules(quality_rules.fit(docs)), ["doc_id"])


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_mixing, op2_tiff, op3_lm_trie, op4_simhash, op5_warc, op6_bpe, op7_line_dedup, op8_quality_crf, op9_licenses, op10_quality_rules)}


def oracle_sql() -> dict[str, str]:
    return {"op7_line_dedup": linededup.ORACLE_SQL}
