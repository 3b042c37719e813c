"""The queries ``opN_*`` and their SQL; ``__spark_entry__`` adds them when this subpackage is there."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_huffman_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    from evenbox.llm.huffman_ids import token_file_digest

    return token_file_digest(_table(spark, sf_dir, "documents"))


def op2_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    from evenbox.llm.ngram_jaccard import jaccard_components

    return jaccard_components(_table(spark, sf_dir, "documents"), k=4, num=85, den=100)


def op3_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    from evenbox.llm.best_fit import pack_documents

    return pack_documents(_table(spark, sf_dir, "documents"))


def op4_fuzzy_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    from evenbox.llm.fuzzy_lines import repeated_lines

    return repeated_lines(_table(spark, sf_dir, "documents"))


def op5_suffix_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    from evenbox.llm.suffix_repeats import judge_documents

    return judge_documents(_table(spark, sf_dir, "documents"))


def op6_warc_dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    from evenbox.llm.warc_archives import archive_digest

    return archive_digest(_table(spark, sf_dir, "pages"))


def op7_edit_matching(spark: SparkSession, sf_dir: str) -> DataFrame:
    from evenbox.llm.edit_matching import benchmark_matches

    return benchmark_matches(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op8_bloom_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    from evenbox.llm.bloom_lm import score_documents

    return score_documents(_table(spark, sf_dir, "documents"))


def op9_lookup_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from evenbox.llm.lookup_shards import place_rows

    return place_rows(_table(spark, sf_dir, "documents").select("doc_id"), "doc_id")


def op10_edit_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from evenbox.llm.edit_counts import edited_counts

    return edited_counts(_table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, f in globals().items() if callable(f) and (name.startswith("op") or name == "pipeline")}


def oracle_sql() -> dict[str, str]:
    from evenbox.llm.lookup_shards import placement_sql

    return {"op9_lookup_shards": placement_sql("documents", "doc_id")}
