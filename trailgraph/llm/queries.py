"""One query per operator over its whole table, and DuckDB SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trailgraph.llm import decontamination, line_dedup, mixing, quality, sharding, simhash, substring, token_counts, token_output, url_filter

SHARD_BYTES = 64 << 20


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shard_report(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, shard, local_depth, shard_bytes of every row; the texts don't move."""
    sizes = docs.select("doc_id", sharding.text_bytes(F.col("text")).alias("n_bytes"))
    s = F.col("shard")
    return sharding.assign(sizes, SHARD_BYTES, size=F.col("n_bytes")).select("doc_id", "n_bytes", s["name"].alias("shard"), s["local_depth"].alias("local_depth"), s["bytes"].alias("shard_bytes"))


def op1_extendible_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_report(_table(spark, sf_dir, "documents"))


def op2_fixed_block_anchors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.deduplicate(_table(spark, sf_dir, "documents"))


def op3_whole_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.counts(_table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op4_context_mixing_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_output.roundtrip(_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op5_pigeonhole_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = simhash.components(_table(spark, sf_dir, "documents"))
    return x.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op6_redirect_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(_table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")


def op7_wu_manber_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = decontamination.judge(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))
    return x.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op8_divergence_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = quality.with_verdict(_table(spark, sf_dir, "documents").select("doc_id", "text", "lang"), name="q")
    return x.select("doc_id", "q.n_words", "q.word_chars", "q.n_symbols", "q.n_dup_lines", "q.n_repeat_words", "q.base_failed", "q.kept", "q.class_distance", "q.word_distance")


def op9_prefix_sum_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op10_deletion_neighbourhood_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.deduplicate(_table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for k, f in globals().items() if k.startswith("op") and callable(f)}


def oracle_sql() -> dict[str, str]:
    """Operators 3, 4, 5, 8 and 10 have none: tokenizers, XXH64, hash order of ties and the neighbourhood of all lines are beyond it, or too slow."""
    from trailgraph.llm import oracles

    return oracles.ALL
