"""Baselines and measures: keyword search, sequential look-up, joins without key completion, accuracy, effort, cost."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F


def word_tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(r"[\p{L}\p{N}]+"), F.lit(0))


def keyword_search(docs: DataFrame, terms: DataFrame, k: int = 10, every: bool = False) -> DataFrame:
    """(query_id, rank, doc_id, n): documents by how many distinct terms of (query_id, term) they hold; with `every`, all."""
    asked = terms.select("query_id", F.lower("term").alias("term")).distinct()
    words = docs.select("doc_id", F.explode(F.array_distinct(word_tokens(F.col("text")))).alias("term")).join(asked, "term")
    found = words.groupBy("query_id", "doc_id").agg(F.count(F.lit(1)).alias("n"))
    if every:
        found = found.join(asked.groupBy("query_id").agg(F.count(F.lit(1)).alias("n")), ["query_id", "n"])
    order = Window.partitionBy("query_id").orderBy(F.desc("n"), "doc_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "doc_id", "n")


def keyword_tfidf(docs: DataFrame, terms: DataFrame, k: int = 10) -> DataFrame:
    """(query_id, rank, doc_id, score): the sum of term frequency times ln(documents / documents with the term)."""
    asked = terms.select("query_id", F.lower("term").alias("term")).distinct()
    counts = docs.select("doc_id", F.explode(word_tokens(F.col("text"))).alias("term")).join(asked.select("term").distinct(), "term").groupBy("doc_id", "term").agg(F.count(F.lit(1)).alias("tf"))
    total = docs.agg(F.count(F.lit(1)).alias("total"))
    idf = counts.groupBy("term").agg(F.count(F.lit(1)).alias("df")).crossJoin(F.broadcast(total)).select("term", F.ln(F.col("total") / F.col("df")).alias("idf"))
    scored = counts.join(idf, "term").join(asked, "term").groupBy("query_id", "doc_id").agg(F.round(F.sum(F.col("tf") * F.col("idf")), 6).alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "doc_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "doc_id", "score")


def scan_cost(grids: DataFrame, wanted: DataFrame) -> DataFrame:
    """(query_id, cells_read): cells a reader of a document passes, table after table and row after row, until the wanted row (query_id,
    table_id, row) has been read."""
    sizes = grids.select("doc_id", "table_id", F.aggregate("grid", F.lit(0).cast("bigint"), lambda s, r: s + F.size(r)).alias("cells"), F.transform("grid", lambda r: F.size(r)).alias("widths"))
    before = Window.partitionBy("doc_id").orderBy("table_id").rowsBetween(Window.unboundedPreceding, -1)
    passed = sizes.withColumn("passed", F.coalesce(F.sum("cells").over(before), F.lit(0)))
    own = F.aggregate(F.slice("widths", 1, F.col("row") + 1), F.lit(0).cast("bigint"), lambda s, w: s + w)
    return wanted.join(passed, "table_id").select("query_id", (F.col("passed") + own).alias("cells_read"))


def semantic_header_start(grids: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """(table_id, header_rows): leading rows of which a word is in the vocabulary; the baseline that needs the words' meaning."""
    rows = grids.select("table_id", F.size("grid").alias("height"), F.posexplode("grid").alias("r", "row"))
    words = rows.select("table_id", "height", "r", F.explode(F.array_distinct(word_tokens(F.array_join("row", " ")))).alias("word"))
    known = words.join(vocabulary, "word").select("table_id", "r").distinct()
    heads = rows.select("table_id", "height", "r").join(known.withColumn("known", F.lit(True)), ["table_id", "r"], "left")
    first = heads.where("known IS NULL").groupBy("table_id").agg(F.min("r").alias("header_rows"))
    return grids.select("table_id", F.size("grid").alias("height")).join(first, "table_id", "left").select("table_id", F.coalesce("header_rows", "height").alias("header_rows"))


def row_set_pr(got: DataFrame, want: DataFrame) -> DataFrame:
    """One row: precision and recall of one set of rows against another."""
    columns = want.columns
    hit = got.select(*columns).distinct().intersect(want.select(*columns).distinct()).agg(F.count(F.lit(1)).alias("hit"))
    n_got, n_want = got.select(*columns).distinct().agg(F.count(F.lit(1)).alias("n_got")), want.distinct().agg(F.count(F.lit(1)).alias("n_want"))
    return hit.crossJoin(n_got).crossJoin(n_want).select((F.col("hit") / F.col("n_got")).alias("precision"), (F.col("hit") / F.col("n_want")).alias("recall"))


def deps_pr(got: DataFrame, want: DataFrame) -> DataFrame:
    """One row: precision and recall of found dependencies against the true ones, told by (table_id, lhs, rhs) with sorted attributes."""
    columns = ["table_id", "lhs", "rhs"]
    return row_set_pr(got.select(*columns), want.select(*columns))


def answer_quality(got: DataFrame, want: DataFrame, k: int = 10) -> DataFrame:
    """One row over (query_id, rank, row_id) and (query_id, row_id): hit rate at k and mean reciprocal rank."""
    first = got.join(want, ["query_id", "row_id"]).where(F.col("rank") <= k).groupBy("query_id").agg(F.min("rank").alias("first"))
    asked = want.select("query_id").distinct().join(first, "query_id", "left")
    return asked.agg(F.count(F.lit(1)).alias("queries"), F.avg(F.col("first").isNotNull().cast("double")).alias("hit_at_k"), F.avg(F.coalesce(1 / F.col("first"), F.lit(0.0))).alias("reciprocal_rank"))


def hours_per_year(lookups: Column, seconds: Column) -> Column:
    return lookups * seconds / 3600


def timed(make: Callable[[], DataFrame]) -> tuple[float, float, int]:
    """Seconds of a first and a second run, and the rows."""
    out = []
    for _ in range(2):
        began = time.perf_counter()
        rows = make().count()
        out.append(time.perf_counter() - began)
    return out[0], out[1], rows


def observed(df: DataFrame, name: str) -> tuple[DataFrame, Observation]:
    """The frame with a row count that can be read after it has run, without a job of its own."""
    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("rows")), seen
