"""A training corpus from `documents`: quality rules, line dedup, near duplicates, repeated passages, packing.

Each stage takes what its predecessor kept and returns the columns of `documents`; the last returns the packed pieces.
Rows that repeat a doc_id are one document and stay or go together; a null doc_id is one document as well. A null text is an empty one,
which the quality rules reject. Further columns come through all stages but the last, whatever their names. A stage on an empty table returns an empty one.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tabqa.llm import jaccard_join, line_dedup, packing, quality, suffix_dedup
from tabqa.llm.common import unused
from tabqa.llm.queries import vocabulary
from tabqa.session import scratch_folder, ship_package, written

#: No SQL expresses the packing and the tokens; tests hold the pipeline against a brute-force version.
ORACLE_SQL = None
COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _documents(df: DataFrame, like: DataFrame) -> DataFrame:
    """The columns that came in, with n_chars told anew."""
    return df.select(*(F.char_length("text").cast("bigint").alias("n_chars") if c == "n_chars" else F.col(f"`{c}`") for c in like.columns))


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no quality rule rejects."""
    ship_package(spark)
    return quality.filter_documents(docs)


def repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that a document of smaller id has; one of which no word is left goes."""
    ship_package(spark)
    counts = unused(docs, "n_lines", "n_dropped")
    left = line_dedup.dedup_lines(docs, counts=tuple(counts)).where((F.col(f"`{counts[1]}`") == 0) | F.col("text").rlike(r"[^\x20\x09-\x0D]"))
    return _documents(left, docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest id of each group of near duplicates (five words, 0.8)."""
    ship_package(spark)
    groups = jaccard_join.join_documents(docs, words=5, percent=80)
    kept = written(groups.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("__kept")).distinct(), "pipeline-kept")
    return docs.join(kept, docs["doc_id"].eqNullSafe(kept["__kept"]), "left_semi")


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the bytes of 200-byte strings that stand anywhere else, to whole characters."""
    ship_package(spark)
    return _documents(suffix_dedup.dedup_substrings(docs, counts=tuple(unused(docs, "n_bytes", "n_removed", "n_spans"))), docs)


def packed_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents' tokens in sequences of 4096."""
    ship_package(spark)
    return packing.pack_documents(docs, vocabulary())


STAGES = [
    ("quality_rules", quality_rules),
    ("repeated_lines", repeated_lines),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("packed_sequences", packed_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; each is written as Parquet in the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = f"{scratch_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
