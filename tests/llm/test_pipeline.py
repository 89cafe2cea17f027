"""The pipeline against its stages by brute force."""

import duckdb
import pytest

pytest.importorskip("public_tokenizers")
import corpus_pipeline  # noqa: E402
from tabqa.llm import bpe, quality  # noqa: E402
from tabqa.llm.queries import vocabulary  # noqa: E402
from tests.llm.test_operators import lines_without_repeats, near_components, without_repeats  # noqa: E402


def test_stages_keep_the_columns(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf)
        assert docs.columns == list(corpus_pipeline.COLUMNS), name


def test_pipeline(spark, sf):
    rows = duckdb.sql(f"SELECT doc_id, text FROM '{sf}/documents.parquet' ORDER BY doc_id").fetchall()
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    first = dict(corpus_pipeline.quality_rules(spark, docs, sf).select("doc_id", "text").collect())
    assert first == {i: t for i, t in rows if not any(r.rejects(quality.Measured((t or "").encode())) for r in quality.RULES)}
    second = corpus_pipeline.repeated_lines(spark, spark.createDataFrame([(i, t, "x", "y", 0) for i, t in first.items()], docs.schema), sf)
    got = second.collect()
    assert sorted((r["doc_id"], len(r["text"].split("\n"))) for r in got if r["text"]) == sorted((i, n - d) for i, n, d, _ in lines_without_repeats(first.items()) if n > d and dict((r["doc_id"], r["text"]) for r in got).get(i))
    assert all(r["n_chars"] == len(r["text"]) for r in got)
    lines = [(r["doc_id"], r["text"]) for r in got]
    third = corpus_pipeline.near_duplicates(spark, second, sf)
    kept = {r["doc_id"] for r in third.collect()}
    assert kept == {i for i, _, c in near_components(lines, 5, 80) if i == c}
    fourth = corpus_pipeline.repeated_passages(spark, third, sf).collect()
    removed = {i: gone for i, _, gone, _, _ in without_repeats([x for x in lines if x[0] in kept], 200)}
    for r in fourth:
        before = len(dict(lines)[r["doc_id"]].encode())
        assert 0 <= before - len(r["text"].encode()) <= removed[r["doc_id"]]
    own = bpe.MergeQueueEncoder.load(vocabulary())
    packed = corpus_pipeline.run(spark, sf).collect()
    assert sum(r["length"] for r in packed) == sum(len(own.encode(r["text"])) + 1 for r in fourth)


def test_stages_on_nulls_repeats_and_clashing_columns(spark):
    """Null ids and texts, repeated rows, and columns named like what the stages make."""
    words = " ".join(f"w{i}" for i in range(60))
    items = [(1, words + "\nthe same long line here"), (1, words + "\nthe same long line here"), (2, words + " x\nthe same long line here"), (3, None), (4, ""), (None, " ".join(f"v{i}" for i in range(50))), (5, "few")]
    docs = spark.createDataFrame([(i, t, "en", "s", 0, "a", "b", "c", 9) for i, t in items], "doc_id long, text string, lang string, source string, n_chars long, n_dropped string, n_removed string, id string, component_id int")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, "")
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars", "n_dropped", "n_removed", "id", "component_id"], name
        got = docs.collect()
        assert {(r["n_dropped"], r["n_removed"], r["id"], r["component_id"]) for r in got} == {("a", "b", "c", 9)}
        assert sorted(str(r["doc_id"]) for r in got) == (["1", "1", "2", "None"] if name in ("quality_rules", "repeated_lines") else ["1", "1", "None"]), name
    packed = corpus_pipeline.packed_sequences(spark, docs, "").collect()
    assert len(packed) == 3 and sum(r["length"] for r in packed) == sum(r["doc_tokens"] for r in packed)


def test_stages_on_an_empty_table(spark):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, "")
        assert docs.count() == 0
