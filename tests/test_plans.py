"""Every plan with SQL gives what DuckDB gives."""

import duckdb
import pytest

from tabqa.plans.catalog import PLANS, SQL, flagship

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Long ones, held against SQL by the driver's own comparison.
LONG = {"keys_lineitem", "w13_all_lookups", "batch_lookup", "w11_suggestion", "w12_incomplete", "w14_three_tables", "w03_join_discovered", "w01_pair_code", "w04_ranked"}


#: The stated values need the second size: the first has no rows for some of them.
SIZE = "/root/testdata/sf0.01"


def plain(value):
    return "null" if value is None else repr(round(float(value), 7) + 0.0) if isinstance(value, float) else str(value)


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SIZE}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(set(SQL) - LONG))
def test_plan_matches_sql(spark, duck, name):
    got = PLANS[name](spark, SIZE)
    want = duck.execute(SQL[name])
    columns = sorted(d[0] for d in want.description)
    assert sorted(got.columns) == columns
    order = [[d[0] for d in want.description].index(c) for c in columns]
    assert sorted(tuple(map(plain, r)) for r in got.select(*columns).collect()) == sorted(tuple(plain(r[i]) for i in order) for r in want.fetchall())


def test_flagship_has_an_answer(spark, sf):
    rows = flagship(spark, sf).collect()
    assert {r["label"] for r in rows} == {"min", "nom", "max"} and all(r["stage"] == "derived" and r["completeness"] == 1 for r in rows)


def test_filters_reach_the_scan(spark, sf):
    text = PLANS["scan_orders"](spark, sf)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(o_orderstatus)" in text and "ReadSchema: struct<o_orderkey:bigint,o_custkey:bigint,o_orderstatus:string>" in text


@pytest.mark.parametrize("name,of", [("class_closure", "customer"), ("corpus_stats", "lineitem"), ("cte_recursive", "lineitem"), ("dependency_catalog", "lineitem"), ("header_boundary", "lineitem"), ("header_boundary_majority", "lineitem"), ("header_boundary_reversed", "lineitem"), ("header_columns", "lineitem"), ("index_values", "lineitem")])
def test_plans_read_their_tables_in_every_call(spark, sf, name, of):
    """Also where the application has printed the handbook and filed its catalog before."""
    from tabqa.plans import answers
    from tests.test_units import last_stage, stage_totals

    answers.book(spark, sf)
    before = last_stage(spark)
    PLANS[name](spark, sf).collect()
    assert stage_totals(spark, "inputRecords", before) >= spark.read.parquet(f"{sf}/{of}.parquet").count()


def test_unfolding_does_not_shuffle(spark):
    from tabqa.operators.expand import unfold
    from tabqa.sources.corpus import registry

    grids = spark.createDataFrame([("t", "pair_matrix", [["", "a"], ["x", "1"]])], "table_id string, family string, grid array<array<string>>")
    assert "Exchange hashpartitioning" not in unfold(grids, registry(spark))._jdf.queryExecution().executedPlan().toString()
