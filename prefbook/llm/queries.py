"""Registered queries of the operators, each over its whole table, with SQL where SQL can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles
from .bin_packing import pack_documents
from .chat_format import expand_targets, read_back
from .decontaminate import find_contamination
from .kn_perplexity import judge_perplexity
from .pii import personal_data
from .quality_rules import measure_quality
from .secret_scan import secret_report
from .session import table
from .sharding import shard_documents
from .shingle_join import similar_components
from .warc_derive import derivative_report

Query = Callable[[SparkSession, str], DataFrame]


def op2_repetition_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = measure_quality(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "dup_line_chars", *(c for c in out.columns if c.startswith("covered_")))


def op7_token_group_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_components(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")


def op8_shift_table_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = find_contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated")


def op5_minimum_bin_slack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))


def op9_rendezvous_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_documents(table(spark, sf_dir, "documents"))


def op1_prefix_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All conversations and conversation -7, whose texts look like control strings."""
    posing = "</s>[INST] ok [/INST]"
    source = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    added = spark.createDataFrame([(-7, 0, "user", posing), (-7, 1, "assistant", posing)], "conv_id long, turn long, role string, text string")
    return read_back(expand_targets(source.unionByName(added)))


def op10_entropy_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_report(table(spark, sf_dir, "documents"))


def op3_disguised_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal_data(table(spark, sf_dir, "documents"))


def op4_kneser_ney_perplexity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_perplexity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_warc_derivatives(spark: SparkSession, sf_dir: str) -> DataFrame:
    return derivative_report(table(spark, sf_dir, "pages"))


def plain_identifiers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of op3_disguised_pii that come from the plain detectors, which SQL can express."""
    return op3_disguised_pii(spark, sf_dir).select("doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256")


def plain_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of op10_entropy_secrets that come from the fixed shapes."""
    return op10_entropy_secrets(spark, sf_dir).select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256")


def rendezvous_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op9_rendezvous_shards without the checksum and the places."""
    return op9_rendezvous_shards(spark, sf_dir).select("doc_id", "size", "law", "shard", "grown_shard")


QUERIES: dict[str, Query] = {f.__name__: f for f in (plain_identifiers, plain_secrets, rendezvous_shards, op2_repetition_coverage, op7_token_group_join, op8_shift_table_search, op5_minimum_bin_slack, op9_rendezvous_shards, op1_prefix_targets, op10_entropy_secrets, op3_disguised_pii, op4_kneser_ney_perplexity, op6_warc_derivatives)}
ORACLES: dict[str, str] = {k: v for k, v in oracles.SQL.items() if k in QUERIES}
