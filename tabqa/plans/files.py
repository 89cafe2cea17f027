"""Sources and sinks of grids and postings, and functions callable from SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tabqa.operators import store
from tabqa.plans import answers, methods
from tabqa.plans.registry import plan
from tabqa.session import scratch_folder
from tabqa.sources import corpus
from tabqa.sources.grid_files import SCHEMA, read_grids

_SHAPES = methods.W + "SELECT 'zones' AS table_id, (SELECT count(*) + 1 FROM zones) AS height UNION ALL SELECT 'pair_codes', (SELECT count(DISTINCT brand) + 1 FROM pair_codes)"


def _grid_files(spark: SparkSession, sf: str) -> str:
    folder = f"{scratch_folder(spark)}/grids-{uuid.uuid4().hex}"
    corpus.handbook(spark, sf).where("table_id IN ('zones', 'pair_codes')").select("table_id", "family", "grid").write.json(folder)
    return folder


@plan(_SHAPES)
def scan_json_grids(spark: SparkSession, sf: str) -> DataFrame:
    """Grids in their interchange form, by Spark's own reader."""
    return spark.read.schema(SCHEMA).json(_grid_files(spark, sf)).select("table_id", F.size("grid").cast("bigint").alias("height"))


@plan(_SHAPES)
def scan_grid_source(spark: SparkSession, sf: str) -> DataFrame:
    """The same folder by the data source, a file to a partition."""
    return read_grids(spark, _grid_files(spark, sf)).select("table_id", F.size("grid").cast("bigint").alias("height"))


@plan(methods.W + "SELECT count(*) AS n FROM (SELECT code FROM pair_codes UNION ALL SELECT code FROM limits UNION ALL SELECT code FROM zone_counts) WHERE code = 'C3'")
def sink_bucketed(spark: SparkSession, sf: str) -> DataFrame:
    """Postings bucketed and sorted by value: a look-up reads one bucket."""
    name = f"tabqa_postings_{uuid.uuid4().hex}"
    path = f"{scratch_folder(spark)}/{name}"
    store.value_postings(answers.book(spark, sf)).write.bucketBy(8, "val_norm").sortBy("val_norm").option("path", path).saveAsTable(name)
    return spark.table(name).where("val_norm = 'c3'").agg(F.count(F.lit(1)).alias("n"))


@plan(methods.W + "SELECT 'zones' AS table_id, nation AS first_cell FROM zones UNION ALL SELECT 'zones', 'Nation'")
def udtf_grid_rows(spark: SparkSession, sf: str) -> DataFrame:
    """A grid's rows by a table function in Python."""

    @F.udtf(returnType="r int, cells array<string>")
    class GridRows:
        def eval(self, grid: list):
            yield from enumerate(grid or [])

    grids = corpus.handbook(spark, sf).where("table_id = 'zones'")
    return grids.lateralJoin(GridRows(F.col("grid").outer())).select("table_id", F.col("cells")[0].alias("first_cell"))


@plan("SELECT n_name, n_nationkey * 2 + 1 AS odd FROM nation")
def sql_function(spark: SparkSession, sf: str) -> DataFrame:
    """A function written in SQL, which Catalyst inlines."""
    from tabqa.session import table

    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tabqa_odd(x INT) RETURNS INT RETURN x * 2 + 1")
    table(spark, sf, "nation").createOrReplaceTempView("tabqa_nation")
    return spark.sql("SELECT n_name, tabqa_odd(n_nationkey) AS odd FROM tabqa_nation")
