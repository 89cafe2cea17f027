"""The queries of this subpackage, one for each operator, and the SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tabqa.llm import bpe, html_text, jaccard_join, language, line_dedup, ngram_model, packing, prefix_forest, quality, suffix_dedup
from tabqa.llm.common import held_out
from tabqa.session import ship_package, table

VOCABULARY = "word_bpe_49k.json"


def vocabulary(name: str = VOCABULARY) -> str:
    """Where the public tokenizer's file lies on this machine and the executors."""
    import public_tokenizers

    return public_tokenizers.path(name)


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return table(spark, sf_dir, "documents")


def op1_prefix_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    vectors = table(spark, sf_dir, "embeddings")
    return prefix_forest.nearest(vectors, vectors.where("vec_id % 20 = 0"))


def op2_language_families(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir).withColumn("held_out", held_out("doc_id", 3))
    return language.predict(docs, language.train(docs.where("NOT held_out")), ["doc_id", "held_out"])


def op3_tag_path_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return html_text.extract_pages(table(spark, sf_dir, "pages"))


def op4_quality_cascade(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, measures = _documents(spark, sf_dir), ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    order = quality.cascade_order(quality.RULES, quality.estimate(docs, known=measures))
    return quality.apply_cascade(docs, order, measures=measures)


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir).select("doc_id", "text")
    return line_dedup.dedup_lines(docs, digest=True).withColumnRenamed("text", "kept_sha256")


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir).select("doc_id", "text")
    return suffix_dedup.dedup_substrings(docs, digest=True).select("doc_id", "n_bytes", "n_removed", "n_spans", F.col("text").alias("kept_sha256"))


def op7_jaccard_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.join_documents(_documents(spark, sf_dir), words=4, percent=85)


def op8_bpe_merge_queue(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digests(_documents(spark, sf_dir), vocabulary())


def op9_trie_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir).withColumn("held_out", held_out("doc_id", 5))
    return ngram_model.train_and_score(docs, "NOT held_out", ["doc_id", "held_out"])[1]


def op10_pack_first_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(_documents(spark, sf_dir), vocabulary())


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [f for name, f in globals().items() if name.startswith("op") and name[2].isdigit()]
    return {f.__name__: f for f in sorted(found, key=lambda f: int(f.__name__[2:].split("_")[0]))}


def oracle_sql() -> dict[str, str]:
    return {"op4_quality_cascade": quality.ORACLE_SQL, "op5_line_dedup": line_dedup.ORACLE_SQL, "op7_jaccard_components": jaccard_join.ORACLE_SQL}
