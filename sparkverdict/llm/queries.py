"""The opN queries: each applies its operator, with production parameters, to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from sparkverdict.llm.common import table

Query = Callable[[SparkSession, str], DataFrame]


def op1_host_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sparkverdict.llm.host_quality import apply_host_rules

    return apply_host_rules(table(spark, sf_dir, "documents"))


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op2_token_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sparkverdict.llm.token_frames import token_frames

    return token_frames(table(spark, sf_dir, "documents"), vocabulary())


def op3_simhash_covering(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sparkverdict.llm.simhash import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op4_line_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sparkverdict.llm.line_spread import deduplicated_lines

    return deduplicated_lines(table(spark, sf_dir, "documents"))


def op5_hash_tree_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sparkverdict.llm.hash_tree import shard

    return shard(table(spark, sf_dir, "documents"))


def op6_fair_queue_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sparkverdict.llm.fair_queue import mix

    return mix(table(spark, sf_dir, "documents"))


def op7_bpe_forced_cuts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sparkverdict.llm.bpe import digests

    return digests(table(spark, sf_dir, "documents"), vocabulary())


def op8_mtree_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sparkverdict.llm.m_tree import top_k

    return top_k(table(spark, sf_dir, "embeddings"))


def op9_pu_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sparkverdict.llm.pu_quality import classify

    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_site_style_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sparkverdict.llm.site_tree import extract

    return extract(table(spark, sf_dir, "pages"))


def queries() -> dict[str, Query]:
    return {f.__name__: f for f in (op1_host_quality, op2_token_frames, op3_simhash_covering, op4_line_spread, op5_hash_tree_shards, op6_fair_queue_mix, op7_bpe_forced_cuts, op8_mtree_topk, op9_pu_quality, op10_site_style_tree)}
