"""The queries ``opN_<name>`` of the training-data operators, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from polyprov.llm import oracles
from polyprov.llm.common import table

TOKENIZER = "piece_bpe_32k.model"


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from public_tokenizers import path

    from polyprov.llm.token_counts import token_counts

    return token_counts(table(spark, sf_dir, "documents"), path(TOKENIZER))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from polyprov.llm.quality import quality_scores

    return quality_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from polyprov.llm.url_filter import url_filter

    return url_filter(table(spark, sf_dir, "pages"))


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from public_tokenizers import path

    from polyprov.llm.packing import pack_documents

    return pack_documents(table(spark, sf_dir, "documents"), model_path=path(TOKENIZER))


def op5_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    from polyprov.llm.lm_score import lm_scores

    return lm_scores(table(spark, sf_dir, "documents"))


def op6_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    from polyprov.llm.topk import top_k

    return top_k(table(spark, sf_dir, "embeddings"))


def op7_near_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    from polyprov.llm.hnsw import near_vectors

    return near_vectors(table(spark, sf_dir, "embeddings"))


def op8_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from polyprov.llm.near_dup import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op9_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from polyprov.llm.source_mix import source_mix

    return source_mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op10_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from polyprov.llm.shards import compacted, placement

    docs = table(spark, sf_dir, "documents")
    return placement(compacted(docs), docs)


def url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the listed rules alone say, as far as SQL can express operator 3."""
    return op3_url_filter(spark, sf_dir).select("page_id", "host", "path", "rule")


def mix_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes and targets, as far as SQL can express operator 9."""
    return op9_source_mix(spark, sf_dir).select("doc_id", "size", "source_size", "target")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (op1_token_counts, op2_quality, op3_url_filter, op4_packing, op5_lm_score, op6_top_k, op7_near_vectors, op8_near_dup, op9_source_mix, op10_shards)
    return {f.__name__: f for f in (*own, url_rules, mix_targets)}


def oracle_sql() -> dict[str, str]:
    return {"op6_top_k": oracles.TOP_K, "op7_near_vectors": oracles.NEAR_VECTORS, "op8_near_dup": oracles.NEAR_DUP, "url_rules": oracles.URL_RULES, "mix_targets": oracles.MIX_TARGETS}
