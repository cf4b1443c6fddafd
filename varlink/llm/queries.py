"""Queries over the given tables: one per operator, and the pipeline. Reference SQL is in :mod:`.reference_sql`."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import byte_cnn, decontamination, line_dedup, mixing, quality, secret_scan, simhash, tokens, url_filter, warc
from .common import load
from .reference_sql import SQL

TOKENIZER = "word_bpe_49k.json"


def tokenizer_path(name: str = TOKENIZER) -> str:
    """Where the public tokenizer files are installed."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    judged, counts, failed, kept = quality.judge(docs, keep=["doc_id"])
    named = dict(zip(quality.COUNTS, counts, strict=True))
    return judged.select("doc_id", *[F.col(named[c]).alias(c) for c in quality.COUNTS[:5]], F.col(failed).alias("base_failed"), F.col(kept).alias("kept"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    return tokens.token_counts(docs, tokenizer_path(), keep=["doc_id"])


def op3_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan_secrets(load(spark, sf_dir, "documents").select("doc_id", "text"), keep=["doc_id"])


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    bad = (F.col("quality") == 0) | (F.col("toxic") == 1)
    labels = load(spark, sf_dir, "labels").select(F.col("doc_id").alias("key"), bad.alias("bad"))
    judged, (host, path, rule, verdict) = url_filter.judge_urls(load(spark, sf_dir, "pages").select("page_id", "url"), labels=labels)
    return judged.select("page_id", F.col(host).alias("host"), F.col(path).alias("path"), F.col(rule).alias("rule"), F.col(verdict).alias("verdict"))


def op5_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    model = byte_cnn.fit(docs, load(spark, sf_dir, "labels").select("doc_id", "quality"))
    scored = byte_cnn.score_quality(docs, model, keep=["doc_id"])
    return scored.select("doc_id", byte_cnn.held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def op6_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    mixed, (domain, n_tokens, copies) = mixing.mix(docs, keep=["doc_id", "lang", "source"])
    return mixed.select("doc_id", F.col(domain).alias("domain"), "lang", "source", F.col(n_tokens).alias("n_tokens"), F.col(copies).alias("copies"))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    grouped, fp, comp = simhash.group_near_copies(docs, keep=["doc_id"])
    return grouped.select("doc_id", F.lower(F.lpad(F.hex(fp), 16, "0")).alias("fingerprint"), F.col(comp).alias("component_id"))


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(load(spark, sf_dir, "pages").select("page_id", "url", "html"))


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, bench = load(spark, sf_dir, "documents").select("doc_id", "text"), load(spark, sf_dir, "benchmark").select("item_id", "text")
    judged, (n_words, n_hit, n_items, items) = decontamination.judge_contamination(docs, bench, keep=["doc_id"], near="n_near")
    return judged.select(
        "doc_id", F.col(n_words).alias("n_words"), F.col(n_hit).alias("n_hit"), F.col(n_items).alias("n_items"), F.sha2(F.array_join(F.col(items), ",").cast("binary"), 256).alias("items_sha256"), (F.col(n_hit) > 0).alias("contaminated"), "n_near"
    )


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    marked, n_lines, n_dropped, kept = line_dedup.mark_lines(docs, keep=["doc_id"])
    return marked.select("doc_id", F.col(n_lines).alias("n_lines"), F.col(n_dropped).alias("n_dropped"), F.sha2(F.col(kept).cast("binary"), 256).alias("kept_sha256"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    import corpus_pipeline

    ops = (op1_quality_rules, op2_token_counts, op3_secret_scan, op4_url_filter, op5_quality_classifier, op6_source_mix, op7_simhash, op8_warc, op9_decontamination, op10_line_dedup)
    return {f.__name__: f for f in ops} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    import corpus_pipeline

    return SQL | ({"pipeline": corpus_pipeline.ORACLE_SQL} if corpus_pipeline.ORACLE_SQL else {})
