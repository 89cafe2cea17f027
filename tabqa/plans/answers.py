"""Look-ups, answers over several tables, workloads, baselines and measures on the handbook."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tabqa.operators import deps, expand, family_model, ingest, layout, measures, query, store
from tabqa.plans import methods, oracles
from tabqa.plans.oracles import W
from tabqa.plans.registry import PLANS, SQL, plan
from tabqa.session import table as t
from tabqa.session import written
from tabqa.sources import corpus

_HELD: dict[tuple[str, str], store.Store] = {}
_GRIDS: dict[tuple[str, str], DataFrame] = {}
_TRAINED: dict[tuple[str, str], DataFrame] = {}
_INGESTED: dict[tuple[str, str], store.Store] = {}


def book(spark: SparkSession, sf: str) -> store.Store:
    """The handbook's store with its catalog, built once per application: the offline part."""
    key = (spark.sparkContext.applicationId, sf)
    if key not in _HELD:
        _HELD[key] = methods.cataloged(spark, sf)
    return _HELD[key]


def trained_parameters(spark: SparkSession, sf: str) -> DataFrame:
    """The adopted family model, trained on the training grids and written."""
    key = (spark.sparkContext.applicationId, sf)
    if key not in _TRAINED:
        _TRAINED[key] = written(family_model.gaussian_parameters(grid_features(spark, sf)), "family-parameters")
    return _TRAINED[key]


def ingested(spark: SparkSession, sf: str) -> store.Store:
    """The handbook read from its pages: tables found, families assigned by the trained model, names read or given by caption; built once."""
    key = (spark.sparkContext.applicationId, sf)
    if key not in _INGESTED:
        pages = written(corpus.as_html(corpus.handbook(spark, sf)), "pages")
        given = [(corpus.CAPTIONS[t], i, x) for t in ("pair_codes", "limits", "trade") for i, x in enumerate(corpus.LABELS[t]) if x and x not in ("Min", "Nom", "Max", "Quantity", "Value")]
        names = spark.createDataFrame(given, "caption string, ord int, label string")
        _INGESTED[key] = ingest.ingest(pages, corpus.registry(spark), trained_parameters(spark, sf), names, document="handbook")
    return _INGESTED[key]


def _batch(spark: SparkSession, **specs) -> query.Batch:
    return query.Batch.of(spark, specs)


def _values(held: store.Store, batch: query.Batch, rows: DataFrame) -> DataFrame:
    """query_id, label, value, a row for each value of each answer."""
    return query.wanted_values(held, batch, rows.select("query_id", "table_id", "row_id")).select("query_id", "label", "value")


_PAIR = {"given": [{"value": "Brand#14"}, {"value": "NATION_0"}]}
_LIMIT = {"wanted": ["Min", "Nom", "Max"], "given": [{"value": "8"}, {"value": "C3"}]}
_JOINED = {"targets": ["min", "nom", "max"], "conditions": [{"value": "8"}, {"value": "Brand#14"}, {"value": "NATION_0"}]}
_RANKED = {"table_caption": "quantity limits", "projection": ["Max"], "conditions": [{"attribute_name": "Size Code", "value": "08"}, {"value": "C2"}]}


# Specs and strict look-ups


@plan(W + "SELECT brand || '/' || nation AS query_id, CASE WHEN code = 'C3' THEN 'max|min' ELSE 'code' END AS wanted, 2 AS n_given, CASE WHEN code = 'C3' THEN 1 ELSE 0 END AS n_topics FROM pair_codes")
def query_specs(spark: SparkSession, sf: str) -> DataFrame:
    """A batch of specs as JSON, under any of their field names, one for each pair of codes."""
    given = '[{"attribute_name": "Brand", "value": "\', brand, \'"}, {"val": "\', nation, \'"}]'
    plain = f"""concat('{{"targets": "Code", "conditions": {given}}}')"""
    rich = f"""concat('{{"table_topics": ["Codes"], "wanted": ["Max", "Min"], "given": {given}}}')"""
    specs = corpus.pair_codes(spark, sf).select(F.concat_ws("/", "brand", "nation").alias("query_id"), F.expr(f"if(code = 'C3', {rich}, {plain})").alias("spec"))
    batch = query.Batch.of_frame(specs)
    per = batch.conditions.groupBy("query_id").agg(F.count(F.lit(1)).cast("int").alias("n_given"))
    wanted = batch.goals.groupBy("query_id").agg(F.array_join(F.array_sort(F.collect_list("label")), "|").alias("wanted"))
    topics = batch.topics.groupBy("query_id").agg(F.count(F.lit(1)).cast("int").alias("n_topics"))
    return per.join(wanted, "query_id", "left").join(topics, "query_id", "left").select("query_id", "wanted", "n_given", F.coalesce("n_topics", F.lit(0)).alias("n_topics"))


@plan(W + "SELECT 'pair_codes' AS table_id, count(*) AS n FROM pair_codes WHERE brand = 'Brand#14' AND nation = 'NATION_0' HAVING count(*) > 0")
def lookup_all_values(spark: SparkSession, sf: str) -> DataFrame:
    """Rows of any table that hold every value."""
    return query.rows_with_all(book(spark, sf), _batch(spark, q=_PAIR)).groupBy("table_id").agg(F.count(F.lit(1)).alias("n"))


@plan(W + "SELECT count(*) AS n FROM limits WHERE code = 'C3' AND list_contains([ltrim(size_code, '0'), CAST(min AS VARCHAR), CAST(nom AS VARCHAR), CAST(max AS VARCHAR)], '8')")
def lookup_in_table(spark: SparkSession, sf: str) -> DataFrame:
    return query.rows_with_all(book(spark, sf), _batch(spark, q=_LIMIT), table="limits").agg(F.count(F.lit(1)).alias("n"))


@plan(W + "SELECT count(*) AS n FROM trade WHERE qty = yr")
def lookup_distinct_cells(spark: SparkSession, sf: str) -> DataFrame:
    """Two conditions with one value need two cells."""
    spec = {"given": [{"value": "1995"}, {"value": "1995"}]}
    rows = query.rows_with_all(book(spark, sf), _batch(spark, q=spec), table="trade", distinct_cells=True)
    return rows.agg(F.count(F.lit(1)).alias("n"))


@plan(W + "SELECT table_id, count(*) AS n FROM (SELECT 'pair_codes' AS table_id, code FROM pair_codes UNION ALL SELECT 'limits', code FROM limits UNION ALL SELECT 'zone_counts', code FROM zone_counts) WHERE code = 'C3' GROUP BY ALL")
def lookup_value_only(spark: SparkSession, sf: str) -> DataFrame:
    """A bare value, wherever it stands."""
    found = query.hits(book(spark, sf), _batch(spark, q={"given": [{"value": "c3"}]}))
    return found.select("table_id", "row_id").distinct().groupBy("table_id").agg(F.count(F.lit(1)).alias("n"))


# Ranked look-ups


_BEST = W + "SELECT 'q' AS query_id, 'max' AS label, CAST(max AS VARCHAR) AS value FROM limits WHERE size_code = '08' AND code = 'C2'"


def _top(spark: SparkSession, sf: str, spec: dict, **options) -> tuple[store.Store, query.Batch, DataFrame]:
    held, batch = book(spark, sf), _batch(spark, q=spec)
    return held, batch, query.rank_rows(held, batch, **options)


@plan(_BEST)
def rank_rows(spark: SparkSession, sf: str) -> DataFrame:
    """The best row by caption, wanted label, attribute with value, and bare value."""
    held, batch, rows = _top(spark, sf, _RANKED)
    return _values(held, batch, rows.where("rank = 1"))


@plan(_BEST)
def rank_rows_strict_pair(spark: SparkSession, sf: str) -> DataFrame:
    held, batch, rows = _top(spark, sf, _RANKED, pairing="strict", mode="exact")
    return _values(held, batch, rows.where("rank = 1"))


@plan(_BEST)
def rank_rows_project(spark: SparkSession, sf: str) -> DataFrame:
    """A wanted label slightly misspelt is matched all the same, and the attribute it is taken for is returned."""
    held, batch, rows = _top(spark, sf, _RANKED | {"projection": ["Maxi"]})
    best = rows.where("rank = 1").select("query_id", "table_id", "row_id")
    return query.wanted_values(held, batch, best, fuzzy=True).select("query_id", "label", "value")


_EIGHT = "CASE WHEN ltrim(size_code, '0') = '8' THEN 1.5 WHEN list_contains([CAST(min AS VARCHAR), CAST(nom AS VARCHAR), CAST(max AS VARCHAR)], '8') THEN 1 ELSE 0 END"
_COUNTED = "CASE WHEN list_contains([{0}], '8') THEN 1 ELSE 0 END"


@plan(W + f""", s AS (SELECT 'limits' AS table_id, {_EIGHT} + CASE WHEN code = 'C3' THEN 1 ELSE 0 END AS v, 1.0 AS m FROM limits
UNION ALL SELECT 'pair_codes', CASE WHEN code = 'C3' THEN 1 ELSE 0 END, 0 FROM pair_codes
UNION ALL SELECT 'zone_counts', CASE WHEN code = 'C3' THEN 1 ELSE 0 END + {_COUNTED.format('CAST(pairs AS VARCHAR)')}, 0 FROM zone_counts
UNION ALL SELECT 'trade', {_COUNTED.format('CAST(yr AS VARCHAR), CAST(qty AS VARCHAR), CAST(cents AS VARCHAR)')}, 0 FROM trade)
SELECT table_id, CAST(round((v + m) * 1000) AS BIGINT) AS thousandths, count(*) AS n FROM s WHERE v > 0 GROUP BY ALL""")
def rank_rows_all(spark: SparkSession, sf: str) -> DataFrame:
    """Every row's score, not the best one's alone: a topic, a wanted label, a named value and a bare one."""
    spec = {"table_caption": "quantity limits", "projection": ["Max"], "conditions": [{"attribute_name": "Size Code", "value": "08"}, {"value": "C3"}]}
    rows = _top(spark, sf, spec, k=1_000_000, mode="exact")[2]
    return rows.groupBy("table_id", F.round(F.col("score") * 1000).cast("bigint").alias("thousandths")).agg(F.count(F.lit(1)).alias("n"))


@plan(W + "SELECT CAST(cond AS INTEGER) AS cond, label, val FROM (SELECT 0 AS cond, 'Size Code' AS label, '8' AS val UNION ALL SELECT 1, 'Code', 'c2') WHERE EXISTS (SELECT 1 FROM limits WHERE size_code = '08' AND code = 'C2')")
def rank_rows_matches(spark: SparkSession, sf: str) -> DataFrame:
    """Which attribute and value of the best row each condition was matched with."""
    held, _, rows = _top(spark, sf, _RANKED)
    return rows.where("rank = 1").select(F.inline("matches")).join(held.attrs.select("attr_id", "label"), "attr_id").select("cond", "label", F.col("val_norm").alias("val"))


@plan(W + "SELECT DISTINCT 'limits' AS table_id FROM limits WHERE code = 'C3'")
def rank_by_caption(spark: SparkSession, sf: str) -> DataFrame:
    """A value that many tables hold; the topic decides."""
    return _top(spark, sf, {"topics": ["quantity limits"], "given": [{"value": "C3"}]}, k=20)[2].select("table_id").distinct()


@plan(W + "SELECT least(count(*), 10) AS n FROM (SELECT code FROM pair_codes UNION ALL SELECT code FROM limits UNION ALL SELECT code FROM zone_counts) WHERE code = 'C3'")
def rank_rows_underspecified(spark: SparkSession, sf: str) -> DataFrame:
    """One bare value gives as many ranked rows as asked for."""
    return _top(spark, sf, {"given": [{"value": "C3"}]}, k=10, mode="exact")[2].agg(F.count(F.lit(1)).alias("n"))


# Steps of answering over several tables


@plan(f"WITH {oracles.LABELLED} SELECT 'q' AS query_id, table_id FROM labels WHERE lower(label) IN ('min', 'nom', 'max') GROUP BY table_id HAVING count(DISTINCT label) = 3")
def tables_by_goal(spark: SparkSession, sf: str) -> DataFrame:
    return query.tables_with_labels(book(spark, sf), _batch(spark, q=_JOINED), mode="all")


@plan(f"""{W}, {oracles.LONG}, {oracles.LABELLED}, k AS (SELECT l.table_id, CAST(count(DISTINCT val) FILTER (WHERE val IN ('brand#14', 'nation_0')) AS INTEGER) AS n_known FROM long l WHERE l.table_id IN (SELECT table_id FROM labels WHERE label = 'Nation') GROUP BY 1)
SELECT table_id, n_known, CAST(row_number() OVER (ORDER BY n_known DESC, table_id) AS INTEGER) AS place FROM k""")
def tables_ordered(spark: SparkSession, sf: str) -> DataFrame:
    """Tables with a nation, by how many of the values they hold."""
    held, batch = book(spark, sf), _batch(spark, q=_PAIR | {"wanted": ["Nation"]})
    ordered = query.order_tables(query.tables_with_labels(held, batch), query.hits(held, batch))
    return ordered.select("table_id", F.col("n_known").cast("int").alias("n_known"), "place")


@plan(f"""{W}, {oracles.LONG}, {oracles.counts('limits', oracles.COLUMNS['limits'])}, a AS (SELECT label, CAST(bit AS BIGINT) AS bit FROM (VALUES {', '.join(f"('{x}', {1 << (len(oracles.LABELS['limits']) - 1 - i)})" for i, x in enumerate(oracles.LABELS['limits']))}) v(label, bit))
SELECT label, EXISTS (SELECT 1 FROM long WHERE attr = 'limits.' || label AND val IN ('8', 'brand#14', 'nation_0')) AS bound FROM minimal JOIN a ON bits & bit <> 0""")
def key_split(spark: SparkSession, sf: str) -> DataFrame:
    """Which part of the key of the limits the values give, and which is missing."""
    held, batch = book(spark, sf), _batch(spark, q=_JOINED)
    candidates = query.tables_with_labels(held, batch).join(batch.conditions.select("query_id", "n_conds").distinct(), "query_id")
    return query.split_keys(candidates, held.keys, query.hits(held, batch)).where("table_id = 'limits'").join(held.attrs.select("attr_id", "label"), "attr_id").select("label", "bound")


def _recovered(spark: SparkSession, sf: str, spec: dict, **options) -> DataFrame:
    held, batch = book(spark, sf), _batch(spark, q=spec)
    found = query.hits(held, batch)
    candidates = query.tables_with_labels(held, batch).join(batch.conditions.select("query_id", "n_conds").distinct(), "query_id")
    parts = query.split_keys(candidates, held.keys, found)
    got = query.recover_values(held, query.row_masks(found), parts, **options)
    return got.join(held.attrs.select("attr_id", "label"), "attr_id").select("label", F.upper("value").alias("value")).distinct()


@plan(W + "SELECT 'Code' AS label, code AS value FROM pair_codes WHERE brand = 'Brand#14' AND nation = 'NATION_0'")
def recover_missing_part(spark: SparkSession, sf: str) -> DataFrame:
    return _recovered(spark, sf, _JOINED)


_ZONED = {"wanted": ["pairs"], "given": [{"value": "Brand#14"}, {"value": "NATION_0"}]}


@plan(W + "SELECT 'Code' AS label, code AS value FROM pair_codes WHERE brand = 'Brand#14' AND nation = 'NATION_0' UNION ALL SELECT 'Zone', zone FROM zones WHERE nation = 'NATION_0'")
def recover_cover_max(spark: SparkSession, sf: str) -> DataFrame:
    """Two missing parts, each read from another table that knows only some of the values."""
    got = _recovered(spark, sf, _ZONED, cover="max")
    return got.where("label IN ('Code', 'Zone')")


# Answers


def _answered(spark: SparkSession, sf: str, spec: dict, **options) -> tuple[store.Store, query.Batch, DataFrame]:
    held, batch = book(spark, sf), _batch(spark, q=spec)
    return held, batch, query.answer(held, batch, **options)


_W3 = W + ", r AS (SELECT min, nom, max FROM limits JOIN pair_codes USING (code) WHERE brand = 'Brand#14' AND nation = 'NATION_0' AND size_code = '08') SELECT 'derived' AS stage, label, value FROM (SELECT 'min' AS label, CAST(min AS VARCHAR) AS value FROM r UNION ALL SELECT 'nom', CAST(nom AS VARCHAR) FROM r UNION ALL SELECT 'max', CAST(max AS VARCHAR) FROM r)"


def _staged(held: store.Store, batch: query.Batch, rows: DataFrame) -> DataFrame:
    return query.wanted_values(held, batch, rows.select("query_id", "table_id", "row_id", "stage")).select("stage", "label", "value")


@plan(_W3)
def multi_table_answer(spark: SparkSession, sf: str) -> DataFrame:
    """Internal and external part and size; the code that joins their tables is found on the way."""
    return _staged(*_answered(spark, sf, _JOINED))


@plan(_W3)
def answer_first(spark: SparkSession, sf: str) -> DataFrame:
    return _staged(*_answered(spark, sf, _JOINED, stop="first"))


@plan(W + "SELECT 'direct' AS stage, 'code' AS label, code AS value FROM pair_codes WHERE brand = 'Brand#14' AND nation = 'NATION_0'")
def answer_direct(spark: SparkSession, sf: str) -> DataFrame:
    return _staged(*_answered(spark, sf, _PAIR | {"wanted": ["Code"]}))


@plan(W + "SELECT 'derived' AS stage, 'pairs' AS label, CAST(pairs AS VARCHAR) AS value FROM zone_counts JOIN pair_codes USING (code) JOIN zones USING (zone) WHERE brand = 'Brand#14' AND pair_codes.nation = 'NATION_0' AND zones.nation = 'NATION_0'")
def answer_three_tables(spark: SparkSession, sf: str) -> DataFrame:
    return _staged(*_answered(spark, sf, _ZONED, cover="max"))


@plan(W + "SELECT 'partial' AS stage, 'code' AS label, code AS value FROM pair_codes WHERE brand = 'Brand#14'")
def answer_incomplete(spark: SparkSession, sf: str) -> DataFrame:
    """An unknown nation: rows that hold what is known."""
    return _staged(*_answered(spark, sf, {"wanted": ["Code"], "given": [{"value": "Brand#14"}, {"value": "NATION_99"}]}))


_SUGGESTED = "SELECT 'limits' AS table_id, {names} AS attrs FROM open WHERE bit_count(bits) = (SELECT min(bit_count(bits)) FROM open)"
_CODE_BIT = 1 << (len(oracles.COLUMNS["limits"]) - 1 - oracles.COLUMNS["limits"].index("code"))


@plan(f"{W}, {oracles.counts('limits', oracles.COLUMNS['limits'])}, open AS (SELECT DISTINCT bits & ~{_CODE_BIT} AS bits FROM minimal WHERE bits & ~{_CODE_BIT} <> 0) " + _SUGGESTED.format(names=oracles.names_of("bits", oracles.LABELS["limits"])))
def suggest_parameters(spark: SparkSession, sf: str) -> DataFrame:
    """A code alone leaves fifty rows; what else to say comes from the key."""
    held, batch, rows = _answered(spark, sf, {"wanted": ["Max"], "given": [{"value": "C3"}]})
    return query.suggest_parameters(held, batch, rows).select("table_id", "attrs")


@plan(f"{W}, answered AS (SELECT size_code, min, nom, max FROM limits WHERE code = 'C3'), {oracles.counts('answered', ['size_code', 'min', 'nom', 'max'])}, open AS (SELECT bits FROM minimal) " + _SUGGESTED.format(names=oracles.names_of("bits", ["Size Code", "Min", "Nom", "Max"])))
def suggest_by_answers(spark: SparkSession, sf: str) -> DataFrame:
    """The same from the answer rows themselves."""
    held, batch, rows = _answered(spark, sf, {"wanted": ["Max"], "given": [{"value": "C3"}]})
    return query.suggest_parameters(held, batch, rows, by="answers").select("table_id", "attrs")


@plan(W + "SELECT 'derived' AS stage, 'pairs' AS label, CAST(pairs AS VARCHAR) AS value FROM zone_counts JOIN zones USING (zone) WHERE code = 'C3' AND nation = 'NATION_0'")
def recover_by_fd(spark: SparkSession, sf: str) -> DataFrame:
    """A key's missing zone, given by a dependency of another table (customers of a nation trade in its zone); no inclusion is used."""
    held = book(spark, sf)
    orders = _zone_orders(spark, sf)
    both = store.Store(held.tables.unionByName(orders.tables), held.attrs.unionByName(orders.attrs), held.cells.unionByName(orders.cells), held.keys, held.inds.where("false"), None, deps.find_fds_batch(orders.cells))
    batch = _batch(spark, q={"wanted": ["Pairs"], "given": [{"attr": "Code", "value": "C3"}, {"attr": "Nation", "value": "NATION_0"}]})
    return _staged(both, batch, query.answer(both, batch, use_fds=True))


def _zone_orders(spark: SparkSession, sf: str) -> store.Store:
    """A listing of the orders of each year by nation and zone, in which the nation determines the zone and is no key."""
    joined = corpus.trade(spark, sf).join(corpus.zones(spark, sf), "nation").select("nation", "yr", "zone")
    order = Window.partitionBy().orderBy("nation", "yr")  # a printed table of nations by years
    flat = joined.select(F.lit("zone_years").alias("table_id"), (F.row_number().over(order) - 1).alias("row_no"), F.array("nation", F.col("yr").cast("string"), "zone").alias("values"))
    tables = spark.createDataFrame([("zone_years", "handbook", "Years of trade by nation and zone", 3, 3, "plain_listing")], "table_id string, doc_id string, caption string, page_begin int, page_end int, family string")
    attrs = spark.createDataFrame([("zone_years", i, x) for i, x in enumerate(("Nation", "Year", "Zone"))], "table_id string, ord int, label string")
    return store.held(store.load_store(flat, tables, attrs))


_ONCE = "SELECT qty FROM trade GROUP BY qty HAVING count(DISTINCT nation) = 1 AND NOT bool_or(yr = 1995)"


@plan(W + f", q AS (SELECT min(qty) AS qty FROM ({_ONCE})) SELECT nation, CAST(qty AS VARCHAR) AS value FROM trade WHERE yr = 1995 AND nation IN (SELECT nation FROM trade WHERE qty = (SELECT qty FROM q))")
def recover_by_agreement(spark: SparkSession, sf: str) -> DataFrame:
    """A quantity that only one nation ever had gives the nation; the year then gives its row. The target's own rows agree, without a dependency."""
    held = book(spark, sf)
    qty = corpus.trade(spark, sf).groupBy("qty").agg(F.count_distinct("nation").alias("n"), F.bool_or(F.col("yr") == 1995).alias("b")).where("n = 1 AND NOT b").agg(F.min("qty")).first()[0]
    batch = _batch(spark, q={"wanted": ["Nation", "Quantity"], "given": [{"attr": "Year", "value": "1995"}, {"attr": "Quantity", "value": str(qty)}]})
    rows = query.answer(held, batch, use_fds="rows").where("table_id = 'trade' AND stage = 'derived'")
    got = _values(held, batch, rows).groupBy("query_id").pivot("label", ["nation", "quantity"]).agg(F.first("value"))
    return got.select("nation", F.col("quantity").alias("value"))


@plan(W + "SELECT CAST(max AS VARCHAR) AS value FROM limits WHERE size_code = '08' AND code IN (SELECT code FROM pair_codes JOIN zones USING (nation) WHERE zone = (SELECT min(zone) FROM zones))")
def recover_two_hops(spark: SparkSession, sf: str) -> DataFrame:
    """A zone leads to its nations, they to their codes, and these with a size to the limits."""
    held = book(spark, sf)
    zone = corpus.zones(spark, sf).agg(F.min("zone")).first()[0]
    part = held.part("table_id IN ('limits', 'pair_codes', 'zones')")
    batch = _batch(spark, q={"wanted": ["Max"], "given": [{"value": "08"}, {"value": zone}]})
    return _values(part, batch, query.answer(part, batch, max_hops=2).where("stage = 'derived'")).select("value")


def all_lookups(spark: SparkSession, sf: str) -> query.Batch:
    """Every (brand, nation) with every size: the look-ups of a whole organisation as one batch."""
    pairs = corpus.pair_codes(spark, sf).select("brand", "nation")
    sizes = corpus.limits(spark, sf).select("size_code").distinct()
    asked = pairs.crossJoin(F.broadcast(sizes)).withColumn("query_id", F.concat_ws("|", "brand", "nation", "size_code"))
    given = F.array("size_code", "brand", "nation")
    conditions = asked.select("query_id", F.posexplode(given).alias("cond", "val")).withColumn("attr", F.lit(None).cast("string")).withColumn("n_conds", F.lit(3))
    goals = asked.select("query_id", F.explode(F.array(*(F.lit(x) for x in ("min", "nom", "max")))).alias("label"))
    return query.Batch.normal(conditions, goals, spark.createDataFrame([], "query_id string, topic string"))


@plan(W + "SELECT brand || '|' || nation || '|' || size_code AS query_id, CAST(min AS VARCHAR) AS min, CAST(nom AS VARCHAR) AS nom, CAST(max AS VARCHAR) AS max FROM pair_codes JOIN limits USING (code)")
def batch_lookup(spark: SparkSession, sf: str) -> DataFrame:
    """All look-ups in one job, each joined over the code it has to find."""
    held, batch = book(spark, sf), all_lookups(spark, sf)
    rows = query.answer(held, batch).where("stage = 'derived'").select("query_id", "row_id")
    cells = held.cells.where("table_id = 'limits'").join(held.attrs.select("attr_id", F.lower("label").alias("label")), "attr_id")
    wide = cells.groupBy("row_id").pivot("label", ["min", "nom", "max"]).agg(F.first("val_raw"))
    return rows.join(wide, "row_id").select("query_id", "min", "nom", "max")


@plan(W + "SELECT brand, nation, size_code, min, nom, max FROM pair_codes JOIN limits USING (code)")
def multi_table_all(spark: SparkSession, sf: str) -> DataFrame:
    """The join itself, for a whole class of queries."""
    return corpus.pair_codes(spark, sf).join(corpus.limits(spark, sf), "code").select("brand", "nation", "size_code", "min", "nom", "max")


# Workloads: the ones above under their numbers, and the rest

for _name, _same in {"w01_pair_code": "answer_direct", "w03_join_discovered": "multi_table_answer", "w04_ranked": "rank_rows", "w06_unfold_missing": "unfold_missing_cells", "w08_masks": "mask_values", "w09_web_pages": "pages_without_tables", "w10_object_graph": "events_props_cells", "w11_suggestion": "suggest_parameters", "w12_incomplete": "answer_incomplete", "w13_all_lookups": "batch_lookup", "w14_three_tables": "answer_three_tables"}.items():
    plan(SQL.get(_same), _name)(PLANS[_same])


@plan(W + ", r AS (SELECT * FROM limits WHERE code = 'C3' AND list_contains([ltrim(size_code, '0'), CAST(min AS VARCHAR), CAST(nom AS VARCHAR), CAST(max AS VARCHAR)], '8')) SELECT label, value FROM (SELECT 'min' AS label, CAST(min AS VARCHAR) AS value FROM r UNION ALL SELECT 'nom', CAST(nom AS VARCHAR) FROM r UNION ALL SELECT 'max', CAST(max AS VARCHAR) FROM r)")
def w02_limits(spark: SparkSession, sf: str) -> DataFrame:
    """A size written without its zero, and a code."""
    held, batch, rows = _answered(spark, sf, _LIMIT)
    return _values(held, batch, rows.where("stage = 'direct'")).select("label", "value")


@plan(W + "SELECT label, value FROM (SELECT 'quantity' AS label, CAST(qty AS VARCHAR) AS value FROM trade WHERE nation = 'NATION_0' AND yr = 1995 UNION ALL SELECT 'value', CAST(cents AS VARCHAR) FROM trade WHERE nation = 'NATION_0' AND yr = 1995)")
def w05_year_and_nation(spark: SparkSession, sf: str) -> DataFrame:
    held, batch, rows = _answered(spark, sf, {"wanted": ["Quantity", "Value"], "given": [{"value": "NATION_0"}, {"value": "1995"}]})
    return _values(held, batch, rows).select("label", "value")


# Families


def grid_features(spark: SparkSession, sf: str) -> DataFrame:
    key = (spark.sparkContext.applicationId, sf)
    if key not in _GRIDS:
        _GRIDS[key] = written(layout.layout_features(corpus.training_grids(spark, sf)).select("table_id", "family", *family_model.FEATURES), "features")
    return _GRIDS[key]


def _slices(column: str, n: int) -> str:
    """Which of n overlapping slices a key's rows are in: told by the number in the key."""
    return f"unnest([(CAST(regexp_extract({column}, '(\\d+)', 1) AS INTEGER) % {n} + d) % {n} FOR d IN [0, 1, 2]])"


_TRAINING = f"""{W}, ids AS (SELECT 'pair_matrix' AS family, {_slices('brand', 25)} AS i FROM pair_codes UNION SELECT 'right_bottom', {_slices('nation', 15)} FROM pair_codes UNION SELECT 'limit_matrix', {_slices('size_code', 20)} FROM limits
UNION SELECT 'trade_matrix', {_slices('nation', 15)} FROM trade UNION SELECT 'plain_listing', {_slices('n_name', 20)} FROM nation UNION SELECT 'vertical_listing', c_nationkey % 20 FROM customer
UNION SELECT 'tall_pivot', unnest([3 * (epoch(ts::DATE) // 86400)::INTEGER % 15 + d FOR d IN [0, 1, 2]]) FROM events),
ranked AS (SELECT family, family || ':' || i AS table_id, row_number() OVER (PARTITION BY family ORDER BY md5(family || ':' || i)) - 1 AS r, count(*) OVER (PARTITION BY family) AS n FROM ids),
folded AS (SELECT family, table_id, CASE WHEN r < round(n * 0.15) THEN -1 ELSE (r - CAST(round(n * 0.15) AS INTEGER)) % 5 END AS fold FROM ranked)"""


@plan(_TRAINING + " SELECT family, CAST(count(*) AS INTEGER) AS n FROM ids GROUP BY 1")
def training_families(spark: SparkSession, sf: str) -> DataFrame:
    """The training grids by family: 130 in all."""
    return grid_features(spark, sf).groupBy("family").agg(F.count(F.lit(1)).cast("int").alias("n"))


_ALGORITHMS = ", ".join(f"'{a}'" for a in family_model.ALGORITHMS)


@plan(_TRAINING + f" SELECT algo, CAST(fold AS INTEGER) AS fold, count(*) AS n, true AS near_one FROM folded CROSS JOIN (SELECT unnest([{_ALGORITHMS}]) AS algo) WHERE fold >= 0 GROUP BY ALL")
def family_cv_scores(spark: SparkSession, sf: str) -> DataFrame:
    """The eight algorithms in five folds: grids tried, and whether nine in ten or more of them get their family."""
    scores = family_model.cv_scores(family_model.with_folds(grid_features(spark, sf)))
    return spark.createDataFrame([(s.algorithm, s.fold, s.n, s.accuracy >= 0.9) for s in scores], "algo string, fold int, n bigint, near_one boolean")


@plan(_TRAINING + " SELECT count(*) AS n, count(*) AS n_right, 1.0::DOUBLE AS accuracy FROM folded WHERE fold = -1")
def family_holdout(spark: SparkSession, sf: str) -> DataFrame:
    """The adopted model on the grids held out: all get their family."""
    return family_model.holdout_accuracy(family_model.with_folds(grid_features(spark, sf)))


plan(SQL["family_holdout"], "w07_families")(PLANS["family_holdout"])

_HELD_OUT = _TRAINING + " SELECT table_id, family AS predicted FROM folded WHERE fold = -1"


def _held_out(spark: SparkSession, sf: str, algorithm: str) -> DataFrame:
    """Predictions for the grids held out, which the SQL holds against their true families."""
    folded = written(family_model.with_folds(grid_features(spark, sf)), "folded")
    return family_model.predict(folded.where("fold = -1"), folded.where("fold >= 0"), algorithm).select("table_id", "predicted")


@plan(_HELD_OUT)
def knn_family(spark: SparkSession, sf: str) -> DataFrame:
    return _held_out(spark, sf, "knn")


@plan(_HELD_OUT)
def gnb_predict(spark: SparkSession, sf: str) -> DataFrame:
    """Gaussian naive Bayes in expressions; a test holds it against Spark ML's."""
    return _held_out(spark, sf, "gnb")


@plan(_HELD_OUT)
def lindisc_family(spark: SparkSession, sf: str) -> DataFrame:
    return _held_out(spark, sf, "lindisc")


_NUMBERS = ["p_size", "p_retailprice"]


@plan("""WITH w AS (SELECT 1e-9 * greatest(var_pop(p_size), var_pop(p_retailprice)) + 1e-12 AS eps, count(*) AS total FROM part),
c AS (SELECT p_type, count(*) / any_value(total) AS prior, avg(p_size) AS m1, avg(p_retailprice) AS m2, var_pop(p_size) + any_value(eps) AS v1, var_pop(p_retailprice) + any_value(eps) AS v2 FROM part, w GROUP BY 1),
s AS (SELECT p_partkey, c.p_type, ln(prior) - 0.5 * (ln(2 * pi() * v1) + (p_size - m1) ** 2 / v1) - 0.5 * (ln(2 * pi() * v2) + (p_retailprice - m2) ** 2 / v2) AS d FROM part CROSS JOIN c)
SELECT p_partkey, p_type AS predicted, CAST(round(d * 1000000) AS BIGINT) AS millionths FROM s QUALIFY row_number() OVER (PARTITION BY p_partkey ORDER BY d DESC) = 1""")
def gnb_parts(spark: SparkSession, sf: str) -> DataFrame:
    """The same model on the parts, formula by formula: the type by size and price, with the log density."""
    part = t(spark, sf, "part")
    found = family_model.gaussian_predict(part, family_model.gaussian_parameters(part, _NUMBERS, "p_type"), _NUMBERS, "p_partkey")
    return found.select("p_partkey", "predicted", F.round(F.col("log_density") * 1000000).cast("bigint").alias("millionths"))


@plan("""WITH z AS (SELECT n_nationkey AS id, n_name, (n_nationkey - avg(n_nationkey) OVER ()) / stddev_pop(n_nationkey) OVER () AS a, (n_regionkey - avg(n_regionkey) OVER ()) / stddev_pop(n_regionkey) OVER () AS b, n_regionkey % 2 AS side FROM nation),
d AS (SELECT x.id, y.id AS near, y.side, row_number() OVER (PARTITION BY x.id ORDER BY round((x.a - y.a) ** 2 + (x.b - y.b) ** 2, 9), y.id) AS r FROM z x JOIN z y ON x.id <> y.id),
v AS (SELECT id, side, count(*) AS n, min(r) AS first FROM d WHERE r <= 5 GROUP BY ALL)
SELECT id AS n_nationkey, CAST(side AS VARCHAR) AS predicted FROM v QUALIFY row_number() OVER (PARTITION BY id ORDER BY n DESC, first) = 1""")
def knn_nations(spark: SparkSession, sf: str) -> DataFrame:
    """Nearest neighbours, vote by vote, on the nations: each by the others."""
    nation = t(spark, sf, "nation").withColumn("side", (F.col("n_regionkey") % 2).cast("string"))
    return family_model.knn_predict(nation, nation, 5, ["n_nationkey", "n_regionkey"], "side", "n_nationkey")


@plan(W + "SELECT table_id, family FROM (VALUES ('limits', 'limit_matrix'), ('pair_codes', 'pair_matrix'), ('trade', 'trade_matrix'), ('zone_counts', 'plain_listing'), ('zones', 'plain_listing')) v(table_id, family) WHERE EXISTS (SELECT 1 FROM limits)")
def family_assignment(spark: SparkSession, sf: str) -> DataFrame:
    """Families of the handbook's own grids by the trained model, against those they were printed in."""
    grids = corpus.handbook(spark, sf).select("table_id", "grid")
    return ingest.recognised(grids, trained_parameters(spark, sf)).select("table_id", "family")


# Answers over tables whose families were predicted


_KEY_SIZES = " UNION ALL ".join(f"SELECT count(*) AS n FROM {name}_minimal" for name in oracles.COLUMNS)


@plan(W + "SELECT table_id, count(*) AS n FROM (SELECT 'pair_codes' AS table_id FROM pair_codes UNION ALL SELECT 'limits' FROM limits UNION ALL SELECT 'trade' FROM trade UNION ALL SELECT 'zones' FROM zones UNION ALL SELECT 'zone_counts' FROM zone_counts) GROUP BY 1")
def ingest_pages(spark: SparkSession, sf: str) -> DataFrame:
    """Rows of the store made from pages: grids, predicted families, unfolding; those without a missing cell are counted."""
    cells = ingested(spark, sf).cells
    whole = cells.groupBy("table_id", "row_id").agg(F.bool_or(F.col("val_norm").isNull()).alias("gap")).where("NOT gap")
    return whole.groupBy(F.regexp_extract("table_id", "([a-z_]+)#0$", 1).alias("table_id")).agg(F.count(F.lit(1)).alias("n"))


@plan(f"{methods._COUNTS}, {oracles.LONG}, {oracles.INCLUSIONS} SELECT 'keys' AS kind, sum(n)::BIGINT AS n FROM ({_KEY_SIZES}) UNION ALL SELECT 'inclusions', (SELECT count(*) FROM unary)")
def ingest_catalog(spark: SparkSession, sf: str) -> DataFrame:
    """The catalog of that store, counted; it is what the printed relations have."""
    held = ingested(spark, sf)
    keys = held.keys.agg(F.count_distinct("key_id").alias("n")).select(F.lit("keys").alias("kind"), "n")
    return keys.unionByName(held.inds.agg(F.count(F.lit(1)).alias("n")).select(F.lit("inclusions").alias("kind"), "n"))


@plan(SQL["answer_direct"])
def w01_ingested(spark: SparkSession, sf: str) -> DataFrame:
    """The first workload on the store made from pages."""
    held, batch = ingested(spark, sf), _batch(spark, q=_PAIR | {"wanted": ["Code"]})
    return _staged(held, batch, query.answer(held, batch))


@plan(SQL["multi_table_answer"])
def w03_ingested(spark: SparkSession, sf: str) -> DataFrame:
    """The third: the join is found in the catalog of the store made from pages."""
    held, batch = ingested(spark, sf), _batch(spark, q=_JOINED)
    return _staged(held, batch, query.answer(held, batch))


# Baselines and measures


@plan("WITH w AS (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+'))) AS term FROM documents), f AS (SELECT doc_id, count(*) AS n FROM w WHERE term IN ('license', 'version', 'the') GROUP BY 1) SELECT doc_id, n FROM f ORDER BY n DESC, doc_id LIMIT 10")
def keyword_search(spark: SparkSession, sf: str) -> DataFrame:
    """Plain keyword search: documents, not cells."""
    terms = spark.createDataFrame([("q", x) for x in ("license", "version", "the")], "query_id string, term string")
    return measures.keyword_search(t(spark, sf, "documents"), terms).select("doc_id", "n")


@plan("WITH w AS (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+'))) AS term FROM documents), f AS (SELECT doc_id, count(*) AS n FROM w WHERE term IN ('license', 'version') GROUP BY 1) SELECT doc_id FROM f WHERE n = 2 ORDER BY doc_id LIMIT 10")
def keyword_search_all(spark: SparkSession, sf: str) -> DataFrame:
    terms = spark.createDataFrame([("q", x) for x in ("license", "version")], "query_id string, term string")
    return measures.keyword_search(t(spark, sf, "documents"), terms, every=True).select("doc_id")


@plan("WITH w AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+')) AS term FROM documents), c AS (SELECT doc_id, term, count(*) AS tf FROM w WHERE term IN ('license', 'version') GROUP BY ALL), d AS (SELECT term, ln((SELECT count(*) FROM documents) / count(*)) AS idf FROM c GROUP BY 1), s AS (SELECT doc_id, round(sum(tf * idf), 6) AS score FROM c JOIN d USING (term) GROUP BY 1) SELECT doc_id, CAST(round(score * 1000) AS BIGINT) AS thousandths FROM s ORDER BY score DESC, doc_id LIMIT 10")
def keyword_tfidf(spark: SparkSession, sf: str) -> DataFrame:
    terms = spark.createDataFrame([("q", x) for x in ("license", "version")], "query_id string, term string")
    return measures.keyword_tfidf(t(spark, sf, "documents"), terms).select("doc_id", F.round(F.col("score") * 1000).cast("bigint").alias("thousandths"))


@plan(W + ", g AS (SELECT (count(DISTINCT size_code) + 4) * (3 * count(DISTINCT code) + 1) AS cells, 3 * count(DISTINCT code) + 1 AS width FROM limits) SELECT CAST(5 * (count(DISTINCT nation) + 1) + (SELECT cells FROM g) AS BIGINT) AS cells_read FROM pair_codes")
def manual_scan_cost(spark: SparkSession, sf: str) -> DataFrame:
    """Cells a reader passes to the fifth row of the second table."""
    wanted = spark.createDataFrame([("q", "pair_codes", 4)], "query_id string, table_id string, row int")
    return measures.scan_cost(corpus.handbook(spark, sf), wanted).select(F.col("cells_read").cast("bigint").alias("cells_read"))


@plan(W + "SELECT count(*) AS n FROM limits WHERE size_code = '08' AND code IN (SELECT code FROM pair_codes)")
def naive_join(spark: SparkSession, sf: str) -> DataFrame:
    """Joining on the shared column without completing the key: every code goes with the size, so the answer is ambiguous."""
    limits = corpus.limits(spark, sf).where("size_code = '08'")
    return limits.join(corpus.pair_codes(spark, sf).select("code").distinct(), "code", "left_semi").agg(F.count(F.lit(1)).alias("n"))


@plan("SELECT count(*) AS rows, count(*) AS seen, true AS timed FROM orders WHERE o_orderstatus = 'F'")
def measured_scan(spark: SparkSession, sf: str) -> DataFrame:
    """A plan's rows observed while it runs, and its time, cold and warm."""
    watched, seen = measures.observed(t(spark, sf, "orders").where("o_orderstatus = 'F'"), "finished-orders")
    rows = watched.count()
    cold, warm, again = measures.timed(lambda: t(spark, sf, "orders").where("o_orderstatus = 'F'"))
    return spark.createDataFrame([(rows, seen.get["rows"], cold > 0 and warm > 0 and again == rows)], "rows bigint, seen bigint, timed boolean")


_WORDS = ("limits", "quantity", "class", "min", "nom", "max", "zone", "code", "pairs", "value", "year")


@plan(f"""{oracles.CELLS}, known AS (SELECT DISTINCT table_id, r FROM (SELECT table_id, r, unnest(regexp_extract_all(lower(txt), '[\\p{{L}}\\p{{N}}]+')) AS word FROM cells) WHERE word IN ({', '.join(f"'{w}'" for w in _WORDS)}))
SELECT table_id, CAST(min(r) AS INTEGER) AS header_rows FROM (SELECT DISTINCT table_id, r FROM cells) WHERE (table_id, r) NOT IN (SELECT (table_id, r) FROM known) GROUP BY 1""")
def semantic_header(spark: SparkSession, sf: str) -> DataFrame:
    """Headers by a vocabulary of label words: codes and years in header rows are beyond it."""
    return measures.semantic_header_start(corpus.handbook(spark, sf), spark.createDataFrame([(x,) for x in _WORDS], "word string"))


@plan("SELECT count(*) * 120 / 3600 AS by_hand, count(*) * 2 / 3600 AS by_query FROM events")
def hours_saved(spark: SparkSession, sf: str) -> DataFrame:
    """Hours of look-ups by hand (two minutes each) and by query (two seconds), an event being a look-up."""
    lookups = t(spark, sf, "events").agg(F.count(F.lit(1)).alias("n"))
    return lookups.select(measures.hours_per_year(F.col("n"), F.lit(120)).alias("by_hand"), measures.hours_per_year(F.col("n"), F.lit(2)).alias("by_query"))


@plan(_TRAINING + " SELECT count(DISTINCT family) AS families, count(*) AS tables FROM ids")
def effort_ratio(spark: SparkSession, sf: str) -> DataFrame:
    """What is set by hand, families, against the tables they serve."""
    return corpus.registry(spark).agg(F.count(F.lit(1)).alias("families")).crossJoin(grid_features(spark, sf).agg(F.count(F.lit(1)).alias("tables")))


_FAMILY_OF = {"pair_codes": "pair_matrix", "limits": "limit_matrix", "trade": "trade_matrix", "zones": "plain_listing", "zone_counts": "plain_listing"}


@plan(oracles.CELLS + "SELECT family, count(DISTINCT table_id) AS tables, count(*) AS cells FROM cells JOIN (VALUES " + ", ".join(f"('{k}', '{v}')" for k, v in _FAMILY_OF.items()) + ") f(table_id, family) USING (table_id) GROUP BY 1")
def corpus_stats(spark: SparkSession, sf: str) -> DataFrame:
    """The handbook by families: tables and cells."""
    cells = F.aggregate("grid", F.lit(0).cast("bigint"), lambda s, r: s + F.size(r))
    return corpus.printed_anew(spark, sf).groupBy("family").agg(F.count(F.lit(1)).alias("tables"), F.sum(cells).alias("cells"))


@plan(W + ", a AS (SELECT brand, nation, size_code, l.code FROM pair_codes p JOIN limits l ON true), r AS (SELECT brand, nation, size_code, code FROM pair_codes JOIN limits USING (code)) SELECT (SELECT count(*) FROM r) / count(*) AS precision, CAST((SELECT count(*) FROM r) / (SELECT count(*) FROM r) AS DOUBLE) AS recall FROM a")
def naive_join_quality(spark: SparkSession, sf: str) -> DataFrame:
    """The baseline that joins on the size alone, measured on all look-ups: it has the right row, among those of all codes."""
    asked = all_lookups(spark, sf).conditions.where("cond = 0").select("query_id", F.lpad("val", 2, "0").alias("size_code"))
    naive = asked.join(corpus.limits(spark, sf).select("size_code", "code"), "size_code").select("query_id", "code")
    right = asked.join(corpus.pair_codes(spark, sf).select(F.concat_ws("|", "brand", "nation").alias("pair"), "code"), F.expr("startswith(query_id, concat(pair, '|'))"))
    right = right.join(corpus.limits(spark, sf).select("size_code", "code"), ["size_code", "code"]).select("query_id", "code")
    return measures.row_set_pr(naive, right)


@plan(W + ", g AS (SELECT count(DISTINCT size_code) * count(DISTINCT code) AS places FROM limits) SELECT (SELECT count(*) FROM limits WHERE min < max) / places AS precision, CAST(1.0 AS DOUBLE) AS recall FROM g")
def unfold_precision_recall(spark: SparkSession, sf: str) -> DataFrame:
    """Unfolded rows, missing places and all, against the tuples of the relation whose limits differ."""
    v = F.col("values")
    flat = expand.unfold(corpus.handbook(spark, sf).where("table_id = 'limits'"), corpus.registry(spark))
    got = flat.select(v[0].alias("size_code"), v[3].alias("code"), v[5].alias("lo"), v[7].alias("hi"))
    want = corpus.limits(spark, sf).where("min < max").select("size_code", "code", F.col("min").cast("string").alias("lo"), F.col("max").cast("string").alias("hi"))
    return measures.row_set_pr(got, want)


@plan(W + "SELECT count(*) AS queries, CAST(count(*) / count(*) AS DOUBLE) AS hit_at_k, CAST(count(*) / count(*) AS DOUBLE) AS reciprocal_rank FROM limits WHERE size_code = '08'")
def answer_quality(spark: SparkSession, sf: str) -> DataFrame:
    """Ranked look-ups of every code with one size, by where the right row stands."""
    held = book(spark, sf)
    codes = [r["code"] for r in corpus.limits(spark, sf).where("size_code = '08'").select("code").collect()]
    specs = {c: {"table_caption": "quantity limits", "projection": ["Max"], "conditions": [{"attribute_name": "Size Code", "value": "08"}, {"attribute_name": "Code", "value": c}]} for c in codes}
    rows = query.rank_rows(held, _batch(spark, **specs))
    cells = held.cells.where("table_id = 'limits'").groupBy("row_id").agg(F.max(F.when(F.col("attr_id").endswith("#a0"), F.col("val_raw"))).alias("s"), F.max(F.when(F.col("attr_id").endswith("#a3"), F.col("val_raw"))).alias("query_id")).where("s = '08'")
    return measures.answer_quality(rows, cells.select("query_id", "row_id"))


@plan(W + ", g AS (SELECT count(DISTINCT size_code) AS s, count(DISTINCT code) AS c FROM limits) SELECT (s + 4) * (3 * c + 1) AS grid_cells, s * c * 8 AS flat_cells FROM g")
def unfold_inflation(spark: SparkSession, sf: str) -> DataFrame:
    """Cells before and after unfolding."""
    grids = corpus.handbook(spark, sf).where("table_id = 'limits'")
    before = grids.agg(F.sum(F.aggregate("grid", F.lit(0), lambda s, r: s + F.size(r))).alias("grid_cells"))
    after = expand.unfold(grids, corpus.registry(spark)).agg(F.sum(F.size("values")).alias("flat_cells"))
    return before.crossJoin(F.broadcast(after))


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """The look-up over two tables with values drawn from the data, so that it has an answer at any size."""
    first = corpus.pair_codes(spark, sf).orderBy("brand", "nation").first()
    held = book(spark, sf)
    batch = _batch(spark, q={"wanted": ["Min", "Nom", "Max"], "given": [{"value": "01"}, {"value": first["brand"]}, {"value": first["nation"]}]})
    return query.wanted_values(held, batch, query.answer(held, batch)).select("query_id", "stage", "completeness", "label", "value")
