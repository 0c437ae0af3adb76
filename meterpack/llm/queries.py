"""The queries of the training-data operators, each over its whole table, and the pipeline."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meterpack.llm import decontaminate, lm_score, mixing, near_dedup, pii, quality, secret_scan, sharding, token_counts, url_filter
from meterpack.llm.common import sf_table, shared_dir
from meterpack.llm.oracles import SQL

URL_RULES = [("block", "com/en/"), ("allow", "example.com/en/7"), ("allow", "net/de/"), ("block", "example.net/de/8"), ("block", "org/es/")]
SHARDS = 24


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge_urls(sf_table(spark, sf_dir, "pages").select("page_id", "url"), URL_RULES).drop("url")


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(sf_table(spark, sf_dir, "documents"), SHARDS)


def op3_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.personal_report(sf_table(spark, sf_dir, "documents"))


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_report(sf_table(spark, sf_dir, "documents"), sf_table(spark, sf_dir, "labels"))


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.leak_report(sf_table(spark, sf_dir, "documents"), sf_table(spark, sf_dir, "benchmark"))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents come in with counts estimated from n_chars, get their true counts by a revision (committed twice over,
    as after a crash), are counted by a second tokenizer, and the toxic ones go again."""
    docs = sf_table(spark, sf_dir, "documents")
    toxic = sf_table(spark, sf_dir, "labels").where("toxic = 1").select("doc_id").distinct()
    ledger = token_counts.TokenLedger(spark, f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}")
    guess = F.floor(F.coalesce("n_chars", F.lit(0)) / 6)
    words, pieces = token_counts.words_v1(F.col("text")), token_counts.pieces_v1(F.col("text"))
    # counted before the join, so that no text is shuffled; a semi join would be moved below the count
    gone = docs.select("doc_id", "source", "lang", words.alias("words"), pieces.alias("pieces")).join(toxic, "doc_id")
    ledger.commit("1-inserts", token_counts.changes(docs, "words-1", guess))
    for _ in range(2):
        ledger.commit("2-revisions", token_counts.revisions(docs, "words-1", guess, words))
    ledger.commit("3-second-tokenizer", token_counts.changes(docs, "pieces-1", pieces))
    ledger.commit("4-deletes", token_counts.changes(gone, "words-1", F.col("words"), -1).union(token_counts.changes(gone, "pieces-1", F.col("pieces"), -1)))
    return ledger.totals()


def op7_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_score.score_documents(sf_table(spark, sf_dir, "documents"))


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(sf_table(spark, sf_dir, "documents"))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(sf_table(spark, sf_dir, "documents"))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A document's source owns it; its language within the source is its repository."""
    return secret_scan.scan_secrets(sf_table(spark, sf_dir, "documents"), repository=F.concat_ws("/", "source", "lang")).drop("found")


OPERATORS = (op1_url_filter, op2_sharding, op3_personal_data, op4_quality_rules, op5_decontamination, op6_token_counts, op7_lm_scores, op8_near_duplicates, op9_mixing, op10_secret_scan)


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (*OPERATORS, pipeline)}


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
