"""Driver queries of this subpackage, one for each operator, and their SQL oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_minmax_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from certgraph.llm.near_duplicates import near_duplicate_classes

    return near_duplicate_classes(_table(spark, sf_dir, "documents"), width=2, percent=80)


def _vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op2_ranked_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from certgraph.llm.token_files import read_token_files, write_token_files
    from certgraph.plans.staging import Stages

    at = Stages(spark, "op2").path("files")
    write_token_files(_table(spark, sf_dir, "documents"), at, _vocabulary("byte_bpe_50k.json"), end_id=2)
    return read_token_files(spark, at)


def op5_viterbi_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    from certgraph.llm.chat import formatted_chats

    return formatted_chats(_table(spark, sf_dir, "conversations"))


def op6_two_tier_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from certgraph.llm.token_counts import token_counts

    return token_counts(_table(spark, sf_dir, "documents"), _vocabulary("byte_bpe_50k.json"), limit=1024)


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from certgraph.llm.packing import pack_documents

    return pack_documents(_table(spark, sf_dir, "documents"), _vocabulary("byte_bpe_50k.json"), capacity=1024, end_id=2)


def op3_compression_band_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from certgraph.llm.quality import fitted_bands, labels_beside, quality_verdicts

    docs = _table(spark, sf_dir, "documents")
    return quality_verdicts(docs, fitted_bands(docs, labels_beside(spark, sf_dir)))


def op10_splitting_tree_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from certgraph.llm.mixing import mixed_amounts

    return mixed_amounts(_table(spark, sf_dir, "documents"))


def op4_text_to_tag_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    from certgraph.llm.html_text import extract_pages

    return extract_pages(_table(spark, sf_dir, "pages"))


def op8_cross_polytope_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    from certgraph.llm.nearest import nearest_neighbours

    return nearest_neighbours(_table(spark, sf_dir, "embeddings"), queries="vec_id % 20 = 0", k=20)


def op9_hidden_markov_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    from certgraph.llm.language_model import language_model_scores

    return language_model_scores(_table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = (
        op1_minmax_near_duplicates,
        op2_ranked_token_files,
        op3_compression_band_quality,
        op4_text_to_tag_html_extraction,
        op5_viterbi_chat_formatting,
        op6_two_tier_token_counts,
        op7_best_fit_packing,
        op8_cross_polytope_neighbours,
        op9_hidden_markov_scores,
        op10_splitting_tree_mixing,
    )
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {}
