"""The registered queries of the operators, each over its whole table, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, fingerprint, htmltext, lmscore, neardup, packing, quality, sqltext, substring, tokencount, urlfilter


def _tokenizers():
    import public_tokenizers

    return public_tokenizers


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = packing.pack(_table(spark, sf_dir, "documents"), _tokenizers().path("word_bpe_49k.json"))
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def op2_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return htmltext.extract(_table(spark, sf_dir, "pages"))


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    files = _tokenizers()
    path, pattern = files.path("byte_bpe_multi_50k.tiktoken"), files.PATTERN
    done = bpe.decode(bpe.encode(_table(spark, sf_dir, "documents"), path, pattern), path)
    return done.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), F.sha2(F.array_join(F.col("ids").cast("array<string>"), ","), 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op4_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.link(_table(spark, sf_dir, "documents"))


def op5_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judge(_table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")


def op6_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = fingerprint.with_next(_table(spark, sf_dir, "documents"))
    digests = [F.lower(F.hex(c)).alias(c) for c in ("edited_sha256", "fingerprint", "edited_fingerprint")]
    return found.select("doc_id", "n_chars", *digests, "near_edited", "near_next")


def op7_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = substring.measure(_table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def op8_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    target = _table(spark, sf_dir, "labels").where("quality = 1").select("doc_id")
    found = lmscore.score(_table(spark, sf_dir, "documents"), target)
    return found.select("doc_id", "n_words", *((F.round(c, 6) + F.lit(0.0)).alias(c) for c in ("target_loss", "background_loss", "score")))


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    files = _tokenizers()
    return tokencount.count(_table(spark, sf_dir, "documents"), files.path("byte_bpe_multi_50k.tiktoken"), files.PATTERN)


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = quality.measure(_table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


QUERIES = {f.__name__: f for f in (op1_packing, op2_html_text, op3_byte_bpe, op4_near_dedup, op5_url_filter, op6_fingerprints, op7_substring_dedup, op8_lm_scoring, op9_token_counts, op10_quality_rules)}
ORACLES: dict[str, str] = {
    "op4_near_dedup": sqltext.near_dedup(),
    "op5_url_filter": sqltext.url_filter(),
    "op7_substring_dedup": sqltext.substring_dedup(),
    "op8_lm_scoring": sqltext.lm_scoring(),
    "op10_quality_rules": sqltext.quality_rules(),
}
