"""The methods on the derived corpus: ingestion, layout, unfolding, store, dependencies."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tabqa.functions.text import match_score, mask_text, normalize_value
from tabqa.operators import deps, expand, ingest, layout, store
from tabqa.plans import oracles
from tabqa.plans.oracles import MASK as _MASK
from tabqa.plans.oracles import W
from tabqa.plans.registry import plan
from tabqa.session import table as t
from tabqa.session import written
from tabqa.sources import corpus
from tabqa.sources.html_tables import extract_tables

def _flat(spark: SparkSession, sf: str, name: str) -> DataFrame:
    """A handbook table unfolded."""
    return expand.unfold(corpus.handbook(spark, sf).where(F.col("table_id") == name), corpus.registry(spark))


def _text(name: str):
    return F.col(name).cast("string")


# Ingestion


def _pages(spark: SparkSession, sf: str) -> DataFrame:
    return written(corpus.as_html(corpus.handbook(spark, sf)), "pages")


@plan(W + """, s AS (SELECT 'pair_codes' AS name, (SELECT count(DISTINCT brand) + 1 FROM pair_codes) AS h, (SELECT count(DISTINCT nation) + 1 FROM pair_codes) AS w
UNION ALL SELECT 'limits', (SELECT count(DISTINCT size_code) + 4 FROM limits), (SELECT 3 * count(DISTINCT code) + 1 FROM limits)
UNION ALL SELECT 'trade', (SELECT count(DISTINCT nation) + 2 FROM trade), (SELECT 2 * count(DISTINCT yr) + 1 FROM trade)
UNION ALL SELECT 'zones', (SELECT count(*) + 1 FROM zones), 2 UNION ALL SELECT 'zone_counts', (SELECT count(*) + 1 FROM zone_counts), 3)
SELECT 'https://handbook.example/' || name || '#0' AS table_id, CAST(h AS INTEGER) AS height, CAST(w AS INTEGER) AS width FROM s""")
def extract_html_tables(spark: SparkSession, sf: str) -> DataFrame:
    """Pages to grids: shapes after spans are undone."""
    grids = expand.unspan(extract_tables(_pages(spark, sf)))
    return grids.select("table_id", F.size("grid").alias("height"), F.array_max(F.transform("grid", lambda r: F.size(r))).alias("width"))


@plan("SELECT count(*) AS pages, CAST(sum(len(regexp_extract_all(html, '<table'))) AS BIGINT) AS tables, CAST(sum(len(regexp_extract_all(html, '<li>'))) AS BIGINT) AS items FROM pages")
def pages_without_tables(spark: SparkSession, sf: str) -> DataFrame:
    """The given pages hold no table; their lists are counted."""
    pages = t(spark, sf, "pages")
    tables = extract_tables(pages).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))
    counted = pages.join(tables, pages["url"] == tables["doc_id"], "left")
    return counted.agg(F.count(F.lit(1)).alias("pages"), F.sum(F.coalesce("n", F.lit(0))).cast("bigint").alias("tables"), F.sum(F.size(F.regexp_extract_all("html", F.lit("(<li>)")))).alias("items"))


@plan(W + "SELECT brand AS b, nation AS n, code AS c FROM pair_codes")
def unspan_grid(spark: SparkSession, sf: str) -> DataFrame:
    """A folded table as a page with spans, read back, unspanned and unfolded."""
    grids = expand.unspan(extract_tables(_pages(spark, sf).where("url LIKE '%/pair_codes'"))).withColumn("family", F.lit("pair_matrix"))
    flat = expand.unfold(grids, corpus.registry(spark))
    return flat.select(F.col("values")[0].alias("b"), F.col("values")[1].alias("n"), F.col("values")[2].alias("c")).where("c <> 'n/a'")


@plan("SELECT 'split' AS nested, 2 * count(*) AS tables, count(*) + (SELECT count(*) FROM nation) AS n_rows FROM region UNION ALL SELECT 'text', count(*), count(*) FROM region")
def nested_tables(spark: SparkSession, sf: str) -> DataFrame:
    """Each region's page has a table with a table of its nations in a cell: read as tables of their own, or into the cell's text."""
    rows = t(spark, sf, "nation").groupBy("n_regionkey").agg(F.concat_ws("", F.sort_array(F.collect_list(F.concat(F.lit("<tr><td>"), "n_name")))).alias("inner"))
    html = F.concat(F.lit("<table><tr><td>"), "r_name", F.lit("<td>its nations:<table>"), F.coalesce("inner", F.lit("")), F.lit("</table></table>"))
    pages = t(spark, sf, "region").join(rows, F.col("r_regionkey") == F.col("n_regionkey"), "left").select(F.col("r_name").alias("url"), html.alias("html"))
    counted = [expand.unspan(extract_tables(pages, nested)).agg(F.count(F.lit(1)).alias("tables"), F.sum(F.size("grid")).alias("n_rows")).withColumn("nested", F.lit(nested)) for nested in ("split", "text")]
    return reduce(DataFrame.unionByName, counted).select("nested", "tables", "n_rows")


_MASKED = "SELECT 'customer' AS what, c_name AS txt FROM customer UNION ALL SELECT 'priority', o_orderpriority FROM orders UNION ALL SELECT 'time', strftime(ts, '%Y-%m-%d %H:%M:%S') FROM events UNION ALL SELECT 'example', 'Eng FNU-52X'"


def _masked(spark: SparkSession, sf: str) -> DataFrame:
    parts = [t(spark, sf, "customer").select(F.lit("customer").alias("what"), F.col("c_name").alias("txt")), t(spark, sf, "orders").select(F.lit("priority").alias("what"), F.col("o_orderpriority").alias("txt")), t(spark, sf, "events").select(F.lit("time").alias("what"), F.date_format("ts", "yyyy-MM-dd HH:mm:ss").alias("txt")), spark.createDataFrame([("example", "Eng FNU-52X")], "what string, txt string")]
    return reduce(DataFrame.unionByName, parts)


@plan("SELECT what, " + _MASK.format("regexp_replace(txt, '\\s+', '', 'g')") + f" AS mask, count(*) AS n FROM ({_MASKED}) GROUP BY ALL")
def mask_values(spark: SparkSession, sf: str) -> DataFrame:
    return _masked(spark, sf).groupBy("what", mask_text(F.col("txt")).alias("mask")).agg(F.count(F.lit(1)).alias("n"))


@plan(f"SELECT what, {_MASK.format('txt')} AS mask, count(*) AS n FROM ({_MASKED}) GROUP BY ALL")
def mask_values_keep(spark: SparkSession, sf: str) -> DataFrame:
    return _masked(spark, sf).groupBy("what", mask_text(F.col("txt"), whitespace="keep").alias("mask")).agg(F.count(F.lit(1)).alias("n"))


@plan("SELECT c_mktsegment, 'A' || length(c_mktsegment) AS mask FROM customer GROUP BY ALL")
def mask_values_lengths(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "customer").select("c_mktsegment", mask_text(F.col("c_mktsegment"), lengths=True).alias("mask")).distinct()


# Layout


@plan(oracles.boundary_sql("top", "data_row"))
def header_boundary(spark: SparkSession, sf: str) -> DataFrame:
    """Where data start: in each column the mask changes and then repeats, and columns vote."""
    return layout.find_data_start(corpus.printed_anew(spark, sf)).select("table_id", "data_row")


@plan(oracles.boundary_sql("top", "data_row", "majority"))
def header_boundary_majority(spark: SparkSession, sf: str) -> DataFrame:
    """The rule by the share of the commonest mask."""
    return layout.find_data_start(corpus.printed_anew(spark, sf), rule="majority").select("table_id", "data_row")


@plan(oracles.boundary_sql("left", "data_col"))
def header_columns(spark: SparkSession, sf: str) -> DataFrame:
    """Key columns of digits before data of digits don't change the mask, so the limits show none."""
    return layout.find_data_start(corpus.printed_anew(spark, sf), transposed=True, name="data_col").select("table_id", "data_col")


@plan(oracles.boundary_sql("top", "foot_rows"))
def header_boundary_reversed(spark: SparkSession, sf: str) -> DataFrame:
    """Headers below, found on the grid upside down."""
    turned = corpus.printed_anew(spark, sf).withColumn("grid", F.reverse("grid"))
    return layout.find_data_start(turned, backwards=True, name="foot_rows").select("table_id", "foot_rows")


@plan(f"""{oracles.CELLS}, {", ".join(oracles.boundary(side, prefix=side[0] + "_") for side in ("top", "left", "bottom", "right"))},
h AS (SELECT table_id, t.v AS f1, l.v AS f2, b.v AS f6, r.v AS f7 FROM t_start t JOIN l_start l USING (table_id) JOIN b_start b USING (table_id) JOIN r_start r USING (table_id)),
head AS (SELECT table_id, list(txt ORDER BY c) AS x FROM cells JOIN h USING (table_id) WHERE r = f1 - 1 AND c >= f2 GROUP BY 1),
rep AS (SELECT table_id, len(x) / list_filter(range(1, len(x) + 1), lambda p: len(x) % p = 0 AND len(list_filter(range(len(x)), lambda i: x[i + 1] <> x[(i % p) + 1])) = 0)[1] AS f3 FROM head),
span AS (SELECT DISTINCT a.table_id FROM cells a JOIN cells b ON a.table_id = b.table_id AND a.r = b.r AND b.c = a.c + 1 AND a.txt = b.txt JOIN h ON h.table_id = a.table_id WHERE a.r < f1 - 1 AND trim(a.txt) <> ''),
corner AS (SELECT table_id, count(*) AS n FROM cells JOIN h USING (table_id) WHERE r < f1 AND c < f2 AND trim(txt) = '' GROUP BY 1),
num AS (SELECT table_id, avg(CAST(regexp_full_match(txt, '[+-]?[0-9]+([.,][0-9]+)?') AS INTEGER)) AS f8 FROM cells JOIN h USING (table_id) WHERE r >= f1 AND c >= f2 GROUP BY 1)
SELECT table_id, f1::DOUBLE AS f1, f2::DOUBLE AS f2, coalesce(f3, 0)::DOUBLE AS f3, CASE WHEN span.table_id IS NULL THEN 0 ELSE 1 END::DOUBLE AS f4, coalesce(corner.n, 0)::DOUBLE AS f5, f6::DOUBLE AS f6, f7::DOUBLE AS f7, f8::DOUBLE AS f8
FROM h LEFT JOIN rep USING (table_id) LEFT JOIN span USING (table_id) LEFT JOIN corner USING (table_id) LEFT JOIN num USING (table_id)""")
def layout_features(spark: SparkSession, sf: str) -> DataFrame:
    return layout.layout_features(corpus.handbook(spark, sf)).select("table_id", *(f"f{i}" for i in range(1, 9)))


# Unfolding


@plan(W + "SELECT brand, nation, code FROM pair_codes")
def unfold_pair_matrix(spark: SparkSession, sf: str) -> DataFrame:
    v = F.col("values")
    return _flat(spark, sf, "pair_codes").select(v[0].alias("brand"), v[1].alias("nation"), v[2].alias("code")).where("code <> 'n/a'")


@plan(W + "SELECT size_code, code, CAST(min AS VARCHAR) AS lo, CAST(nom AS VARCHAR) AS mid, CAST(max AS VARCHAR) AS hi, 'Min' AS noise FROM limits")
def unfold_limits(spark: SparkSession, sf: str) -> DataFrame:
    """Four band rows and a pivot of three cells: nine columns, one of them the sub-header of the pivot's first cell."""
    v = F.col("values")
    return _flat(spark, sf, "limits").where(F.size("values") == 8).select(v[0].alias("size_code"), v[3].alias("code"), v[5].alias("lo"), v[6].alias("mid"), v[7].alias("hi"), v[4].alias("noise")).where("lo <> 'n/a'")


@plan(W + "SELECT nation, CAST(yr AS VARCHAR) AS y, CAST(qty AS VARCHAR) AS q, CAST(cents AS VARCHAR) AS c FROM trade")
def unfold_trade(spark: SparkSession, sf: str) -> DataFrame:
    v = F.col("values")
    return _flat(spark, sf, "trade").select(v[0].alias("nation"), v[1].alias("y"), v[3].alias("q"), v[4].alias("c")).where("q <> 'n/a'")


@plan(W + "SELECT nation, zone FROM zones")
def unfold_listing(spark: SparkSession, sf: str) -> DataFrame:
    v = F.col("values")
    return _flat(spark, sf, "zones").select(v[0].alias("nation"), v[1].alias("zone"))


def _trained(spark: SparkSession, sf: str, family: str) -> DataFrame:
    return expand.unfold(corpus.training_grids(spark, sf).where(F.col("family") == family), corpus.registry(spark))


@plan("SELECT DISTINCT c_name AS name, CAST(c_nationkey AS VARCHAR) AS country, CAST(CAST(round(c_acctbal * 100) AS BIGINT) AS VARCHAR) AS balance FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey % 20 ORDER BY CAST(round(c_acctbal * 100) AS BIGINT) DESC, c_custkey) AS place FROM customer) WHERE place <= 6")
def unfold_vertical(spark: SparkSession, sf: str) -> DataFrame:
    """A record is a column: the pivot takes a whole column."""
    v = F.col("values")
    return _trained(spark, sf, "vertical_listing").select(v[0].alias("name"), v[1].alias("country"), v[2].alias("balance")).distinct()


@plan(W + "SELECT brand, nation, code FROM pair_codes")
def unfold_right_bottom(spark: SparkSession, sf: str) -> DataFrame:
    """Keys right of and below the data."""
    v = F.col("values")
    return _trained(spark, sf, "right_bottom").select(v[0].alias("brand"), v[1].alias("nation"), v[2].alias("code")).where("code <> 'n/a'").distinct()


@plan("SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, CAST(count(*) AS VARCHAR) AS n, 'max ' || CAST(max(CAST(round(value * 100) AS BIGINT)) AS VARCHAR) AS top FROM events GROUP BY 1, 2")
def unfold_tall(spark: SparkSession, sf: str) -> DataFrame:
    """A pivot two rows high."""
    v = F.col("values")
    return _trained(spark, sf, "tall_pivot").select(v[0].alias("day"), v[1].alias("event_type"), v[2].alias("n"), v[3].alias("top")).where("n <> 'n/a'").distinct()


@plan(W + "SELECT (SELECT count(DISTINCT size_code) * count(DISTINCT code) FROM limits) AS places, (SELECT count(DISTINCT size_code) * count(DISTINCT code) - count(*) FROM limits) AS missing")
def unfold_missing_cells(spark: SparkSession, sf: str) -> DataFrame:
    """Missing cells stay as rows; without them only the full ones are left."""
    grids = corpus.handbook(spark, sf).where("table_id = 'limits'")
    kept = expand.unfold(grids, corpus.registry(spark)).agg(F.count(F.lit(1)).alias("places"))
    full = expand.unfold(grids, corpus.registry(spark), keep_missing=False).agg(F.count(F.lit(1)).alias("n"))
    return kept.crossJoin(F.broadcast(full)).select("places", (F.col("places") - F.col("n")).alias("missing"))


@plan(W + "SELECT brand, nation, code FROM pair_codes")
def unfold_long_form(spark: SparkSession, sf: str) -> DataFrame:
    """The same unfolding by joins, for grids too large for one row."""
    cells = corpus.handbook(spark, sf).where("table_id = 'pair_codes'").select("table_id", F.posexplode("grid").alias("r", "row")).select("table_id", "r", F.posexplode("row").alias("c", "text"))
    v = F.col("values")
    return expand.unfold_cells(cells, corpus.FAMILIES[0]).select(v[0].alias("brand"), v[1].alias("nation"), v[2].alias("code")).where("code <> 'n/a'")


@plan(W + "SELECT size_code, code, CAST(min AS VARCHAR) AS first_min, CAST(max AS VARCHAR) AS last_max FROM limits")
def fold_unfold_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    relation = corpus.limits(spark, sf).withColumn("t", F.lit("again"))
    grid = expand.fold(relation, "t", ["size_code"], ["code"], ["min", "nom", "max"], ["Min", "Nom", "Max"], ["Limits of quantity", "Class"]).withColumn("family", F.lit("limit_matrix"))
    v = F.col("values")
    return expand.unfold(grid, corpus.registry(spark)).select(v[0].alias("size_code"), v[3].alias("code"), v[5].alias("first_min"), v[7].alias("last_max")).where("first_min <> 'n/a'")


@plan(W + """, u AS (SELECT 'pair_codes' AS t, [b.brand, n.nation, coalesce(p.code, 'n/a')] AS v FROM (SELECT DISTINCT brand FROM pair_codes) b CROSS JOIN (SELECT DISTINCT nation FROM pair_codes) n LEFT JOIN pair_codes p ON p.brand = b.brand AND p.nation = n.nation
UNION ALL SELECT 'limits', [s.size_code, 'Limits of quantity', 'Class', c.code, 'Min', coalesce(CAST(min AS VARCHAR), 'n/a'), coalesce(CAST(nom AS VARCHAR), 'n/a'), coalesce(CAST(max AS VARCHAR), 'n/a')] FROM (SELECT DISTINCT size_code FROM limits) s CROSS JOIN (SELECT DISTINCT code FROM limits) c LEFT JOIN limits l ON l.size_code = s.size_code AND l.code = c.code
UNION ALL SELECT 'trade', [n.nation, CAST(y.yr AS VARCHAR), 'Quantity', coalesce(CAST(qty AS VARCHAR), 'n/a'), coalesce(CAST(cents AS VARCHAR), 'n/a')] FROM (SELECT DISTINCT nation FROM trade) n CROSS JOIN (SELECT DISTINCT yr FROM trade) y LEFT JOIN trade t ON t.nation = n.nation AND t.yr = y.yr
UNION ALL SELECT 'zones', [nation, zone] FROM zones UNION ALL SELECT 'zone_counts', [code, zone, CAST(pairs AS VARCHAR)] FROM zone_counts)
SELECT t AS table_id, CAST(i AS INTEGER) AS ord FROM (SELECT t, i, v[i + 1] AS x FROM (SELECT t, v, unnest(range(len(v))) AS i FROM u)) GROUP BY ALL HAVING count(DISTINCT x) = 1 AND count(*) > 1""")
def noise_columns(spark: SparkSession, sf: str) -> DataFrame:
    """Constant columns: label rows and sub-headers."""
    flat = expand.unfold(corpus.handbook(spark, sf), corpus.registry(spark))
    return store.constant_columns(flat)


@plan(oracles.CELLS + """SELECT table_id, CAST(c AS INTEGER) AS ord, txt AS label FROM cells WHERE table_id IN ('zones', 'zone_counts') AND r = 0
UNION ALL SELECT 'limits', CAST(c + 4 AS INTEGER), txt FROM cells WHERE table_id = 'limits' AND r = 3 AND c BETWEEN 1 AND 3 UNION ALL SELECT 'trade', CAST(c + 2 AS INTEGER), txt FROM cells WHERE table_id = 'trade' AND r = 1 AND c BETWEEN 1 AND 2""")
def expanded_names(spark: SparkSession, sf: str) -> DataFrame:
    """Names that the printed tables have for their columns: listings' headers and sub-headers over a pivot's cells."""
    return ingest.names_of(corpus.handbook(spark, sf), corpus.registry(spark)).select("table_id", F.col("ord").cast("int").alias("ord"), "label")


# Store


def handbook_store(spark: SparkSession, sf: str, anew: bool = False) -> store.Store:
    """The handbook unfolded into the store, without its constant columns; with `anew` from the given tables on."""
    book = written(corpus.printed_anew(spark, sf), "handbook") if anew else corpus.handbook(spark, sf)
    flat = expand.unfold(book, corpus.registry(spark))
    attrs = spark.createDataFrame([(name, i, label, "Limits of quantity" if name == "limits" and i > 3 else None) for name, labels in corpus.LABELS.items() for i, label in enumerate(labels) if label], "table_id string, ord int, label string, parent_label string")
    return store.load_store(flat, book.drop("grid"), attrs)


@plan(W + """SELECT table_id, count(*) AS cells FROM (SELECT 'pair_codes' AS table_id FROM pair_codes, range(3) UNION ALL SELECT 'limits' FROM limits, range(5)
UNION ALL SELECT 'trade' FROM trade, range(4) UNION ALL SELECT 'zones' FROM zones, range(2) UNION ALL SELECT 'zone_counts' FROM zone_counts, range(3)) GROUP BY ALL""")
def store_cells(spark: SparkSession, sf: str) -> DataFrame:
    cells = handbook_store(spark, sf).cells
    full = cells.groupBy("row_id").agg(F.bool_or(F.col("val_norm").isNull()).alias("gap"), F.first("table_id").alias("table_id"), F.count(F.lit(1)).alias("n")).where("NOT gap")
    return full.groupBy("table_id").agg(F.sum("n").alias("cells"))


@plan(W + """SELECT p, count(*) AS n FROM (SELECT 'hasRow' AS p FROM pair_codes UNION ALL SELECT 'hasRow' FROM zones UNION ALL SELECT 'hasRow' FROM zone_counts
UNION ALL SELECT unnest(['hasTable', 'hasCaption', 'label', 'hasID', 'pageNumBegin', 'pageNumEnd']) FROM range(3) UNION ALL SELECT 'hasAttribute' FROM range(8) UNION ALL SELECT 'label' FROM range(8)) GROUP BY ALL""")
def store_triples(spark: SparkSession, sf: str) -> DataFrame:
    """The graph view of three of the tables, counted by predicate; attributes as predicates aside."""
    book = handbook_store(spark, sf)
    some = "table_id IN ('pair_codes', 'zones', 'zone_counts')"
    cells = book.cells.where(some)
    whole = cells.groupBy("row_id").agg(F.bool_or(F.col("val_norm").isNull()).alias("gap")).where("NOT gap").select("row_id")
    part = store.Store(book.tables.where(some), book.attrs.where(some), cells.join(whole, "row_id", "left_semi"))
    return part.triples().where(~F.col("p").contains("#")).groupBy("p").agg(F.count(F.lit(1)).alias("n"))


@plan("""WITH RECURSIVE direct AS MATERIALIZED (SELECT 'customer ' || c_custkey AS sub, n_name AS super FROM customer JOIN nation ON c_nationkey = n_nationkey UNION SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey),
up AS (SELECT sub, super FROM direct UNION SELECT up.sub, d.super FROM up JOIN direct d ON up.super = d.sub) SELECT sub, super FROM up UNION SELECT sub, sub FROM direct UNION SELECT super, super FROM direct""")
def class_closure(spark: SparkSession, sf: str) -> DataFrame:
    """Customers, nations and regions as classes, each with all that it is part of."""
    customer, nation, region = (t(spark, sf, x) for x in ("customer", "nation", "region"))
    customers = customer.join(nation, F.col("c_nationkey") == F.col("n_nationkey")).select(F.concat(F.lit("customer "), "c_custkey").alias("sub"), F.col("n_name").alias("super"))
    nations = nation.join(region, F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_name").alias("sub"), F.col("r_name").alias("super"))
    return store.class_closure(spark, customers.unionByName(nations))


def cataloged(spark: SparkSession, sf: str) -> store.Store:
    return ingest.cataloged(handbook_store(spark, sf))


_SIZES = " UNION ALL ".join(f"SELECT '{t}' AS table_id, (SELECT count(*) FROM {t}) AS n" for t in oracles.COLUMNS)


@plan(W + f"SELECT violation, table_id AS subject FROM ({_SIZES}) CROSS JOIN (SELECT unnest(['table without row', 'table without dependency']) AS violation) WHERE n <= 100")
def schema_violations(spark: SparkSession, sf: str) -> DataFrame:
    """A store that lost the rows and keys of its small tables says so; the whole one has no violation."""
    book = answers_book(spark, sf)
    whole = book.cells.groupBy("table_id", "row_id").agg(F.bool_or(F.col("val_norm").isNull()).alias("gap")).where("NOT gap")
    large = whole.groupBy("table_id").agg(F.count(F.lit(1)).alias("n")).where("n > 100").select("table_id")
    lost = store.Store(book.tables, book.attrs, book.cells.join(large, "table_id", "left_semi"), book.keys.join(large, "table_id", "left_semi"), book.inds)
    return lost.validate().unionByName(book.validate())


def answers_book(spark: SparkSession, sf: str) -> store.Store:
    from tabqa.plans import answers

    return answers.book(spark, sf)


@plan(f"{W}, {oracles.LONG} SELECT val AS val_norm, count(*) AS n_postings FROM long GROUP BY 1")
def index_values(spark: SparkSession, sf: str) -> DataFrame:
    """The index's dictionary: every value with the length of its list."""
    return store.indexed(store.held(handbook_store(spark, sf, anew=True))).index.values.select("val_norm", "n_postings")


@plan(f"""{W}, {oracles.LONG}, v AS (SELECT DISTINCT val FROM long), q AS (SELECT lower(nation) AS asked FROM zones UNION SELECT lower(zone) || 'n' FROM zones)
SELECT asked, val AS val_norm, CAST(round((1 - levenshtein(asked, val) / greatest(length(asked), length(val))) * 1000000) AS BIGINT) AS millionths FROM q JOIN v ON 1 - levenshtein(asked, val) / greatest(length(asked), length(val)) >= 0.6""")
def index_similar_values(spark: SparkSession, sf: str) -> DataFrame:
    """All values of the store that are near to a nation's or a misspelt zone's name; found by shared grams, held against all pairs."""
    book = answers_book(spark, sf)
    zones = corpus.zones(spark, sf)
    asked = zones.select(F.lower("nation").alias("val")).union(zones.select(F.concat(F.lower("zone"), F.lit("n")))).distinct()
    conditions = asked.select(F.col("val").alias("query_id"), F.lit(0).alias("cond"), F.lit(None).cast("string").alias("attr"), "val", F.lit(1).alias("n_conds"))
    from tabqa.operators import query

    none = spark.createDataFrame([], "query_id string, label string")
    found = query.match_values(book, query.Batch.normal(conditions, none, none.withColumnRenamed("label", "topic")))
    return found.select(F.col("query_id").alias("asked"), "val_norm", F.round(F.col("s_val") * 1000000).cast("bigint").alias("millionths"))


@plan(f"{W}, {oracles.LONG} SELECT token, count(DISTINCT val) AS n FROM (SELECT val, unnest(regexp_extract_all(val, '[\\p{{L}}\\p{{N}}]+')) AS token FROM long) GROUP BY 1")
def token_postings(spark: SparkSession, sf: str) -> DataFrame:
    """How many values of the store hold each token."""
    return answers_book(spark, sf).index.tokens.groupBy("token").agg(F.count(F.lit(1)).alias("n"))


@plan(W + "SELECT lower(nation) AS nation, lower(zone) AS zone FROM zones")
def row_assembly(spark: SparkSession, sf: str) -> DataFrame:
    rows = handbook_store(spark, sf).rows().where("table_id = 'zones'")
    return rows.select(F.lower(F.element_at("row_map", F.lit("zones#a0"))).alias("nation"), F.lower(F.element_at("row_map", F.lit("zones#a1"))).alias("zone"))


@plan("SELECT CAST(event_id AS VARCHAR) AS row_id, 'k' AS attr_id, json_extract_string(props, '$.k') AS val_raw FROM events")
def events_props_cells(spark: SparkSession, sf: str) -> DataFrame:
    return store.objects_to_cells(t(spark, sf, "events"), "event_id", "props", "events").select("row_id", "attr_id", "val_raw")


@plan("SELECT v AS txt, CASE WHEN v IN ('n/a', '–', '') THEN '(missing)' WHEN v = '3,5' THEN '3.5' WHEN v = '008' THEN '8' WHEN v = '0' THEN '0' ELSE lower(v) END AS norm FROM (VALUES ('n/a'), ('–'), (''), ('3,5'), ('008'), ('0'), ('Brand#14'), ('C3')) t(v)")
def normalize_values(spark: SparkSession, sf: str) -> DataFrame:
    texts = spark.createDataFrame([(x,) for x in ("n/a", "–", "", "3,5", "008", "0", "Brand#14", "C3")], "txt string")
    return texts.select("txt", F.coalesce(normalize_value(F.col("txt")), F.lit("(missing)")).alias("norm"))


# Dependencies


@plan("SELECT DISTINCT c_nationkey FROM customer")
def projection_set(spark: SparkSession, sf: str) -> DataFrame:
    return deps.project(t(spark, sf, "customer"), ["c_nationkey"])


def _answers(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, "what string, holds boolean")


@plan("""SELECT * FROM (SELECT 'nation' AS what, (SELECT count(*) FROM (SELECT n_nationkey FROM nation GROUP BY 1 HAVING count(DISTINCT n_regionkey) > 1)) = 0 AS holds
UNION ALL SELECT 'customer', (SELECT count(*) FROM (SELECT c_nationkey FROM customer GROUP BY 1 HAVING count(DISTINCT c_mktsegment) > 1)) = 0)""")
def fd_check(spark: SparkSession, sf: str) -> DataFrame:
    return _answers(spark, [("nation", deps.fd_holds(t(spark, sf, "nation"), ["n_nationkey"], ["n_regionkey"])), ("customer", deps.fd_holds(t(spark, sf, "customer"), ["c_nationkey"], ["c_mktsegment"]))])


@plan("SELECT c_nationkey, count(DISTINCT c_mktsegment) AS n_rhs FROM customer GROUP BY 1 HAVING count(DISTINCT c_mktsegment) > 1")
def fd_violations(spark: SparkSession, sf: str) -> DataFrame:
    return deps.fd_violations(t(spark, sf, "customer"), ["c_nationkey"], ["c_mktsegment"])


def _fds_sql(columns: list[str]) -> str:
    """Every single column against every other, by counting groups; nation has no minimal dependency of two columns beside these."""
    parts = [f"SELECT '{x}' AS lhs, '{a}' AS rhs WHERE NOT EXISTS (SELECT 1 FROM nation GROUP BY {x} HAVING count(DISTINCT {a}) > 1)" for x in columns for a in columns if a != x]
    pairs = [(x, y, a) for i, x in enumerate(columns) for y in columns[i + 1 :] for a in columns if a not in (x, y)]
    parts += [
        f"SELECT '{x},{y}', '{a}' WHERE NOT EXISTS (SELECT 1 FROM nation GROUP BY {x}, {y} HAVING count(DISTINCT {a}) > 1) AND EXISTS (SELECT 1 FROM nation GROUP BY {x} HAVING count(DISTINCT {a}) > 1) AND EXISTS (SELECT 1 FROM nation GROUP BY {y} HAVING count(DISTINCT {a}) > 1)"
        for x, y, a in pairs
    ]
    return " UNION ALL ".join(parts)


@plan(_fds_sql(["n_nationkey", "n_name", "n_regionkey"]))
def fds_nation(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame([(",".join(x), a) for x, a in deps.find_fds(t(spark, sf, "nation"), 2)], "lhs string, rhs string")


@plan("SELECT 'lineitem' AS what, (SELECT count(*) FROM lineitem) = (SELECT count(*) FROM (SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem)) AS holds UNION ALL SELECT 'events', (SELECT count(*) = count(DISTINCT event_id) FROM events)")
def key_check(spark: SparkSession, sf: str) -> DataFrame:
    return _answers(spark, [("lineitem", deps.is_key(t(spark, sf, "lineitem"), ["l_orderkey", "l_linenumber"])), ("events", deps.is_key(t(spark, sf, "events"), ["event_id"]))])


_CUSTOMER = ["c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"]


@plan(oracles.keys_sql("customer", _CUSTOMER))
def keys_customer(spark: SparkSession, sf: str) -> DataFrame:
    return deps.keys_frame(spark, "customer", deps.minimal_keys(t(spark, sf, "customer"), approx=False))


@plan(oracles.keys_sql("supplier", ["s_suppkey", "s_name", "s_nationkey", "s_acctbal"]))
def keys_supplier_approx(spark: SparkSession, sf: str) -> DataFrame:
    """With the estimating screen before exact counts."""
    return deps.keys_frame(spark, "supplier", deps.minimal_keys(t(spark, sf, "supplier")))


_LINE = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]


@plan(oracles.keys_sql("lineitem", _LINE))
def keys_lineitem(spark: SparkSession, sf: str) -> DataFrame:
    """All minimal keys over all columns, of any size."""
    return deps.keys_frame(spark, "lineitem", deps.minimal_keys_large(t(spark, sf, "lineitem")))


_COUNTS = W + ", " + ", ".join(oracles.counts(name, columns, f"{name}_") for name, columns in oracles.COLUMNS.items())


@plan(_COUNTS + " " + " UNION ALL ".join(f"SELECT '{name}' AS table_id, {oracles.names_of('bits', oracles.LABELS[name])} AS attrs FROM {name}_minimal" for name in oracles.COLUMNS))
def keys_all_flat_tables(spark: SparkSession, sf: str) -> DataFrame:
    """All minimal keys of all printed tables at once, rows with missing cells left out."""
    book = handbook_store(spark, sf)
    gaps = book.cells.where("val_norm IS NULL").select("row_id").distinct()
    keys = deps.minimal_keys_batch(book.cells.join(gaps, "row_id", "left_anti")).join(book.attrs.select("attr_id", "label"), "attr_id")
    return keys.groupBy("table_id", "key_id").agg(F.array_join(F.array_sort(F.collect_list("label")), ",").alias("attrs")).select("table_id", "attrs")


@plan(f"""WITH {oracles.counts("customer", _CUSTOMER)}, near AS (SELECT bits, d = n AS exact FROM d, n WHERE bits <> 0 AND d >= 0.9 * n)
SELECT avg(CAST(exact AS INTEGER)) AS precision, CAST(1.0 AS DOUBLE) AS recall FROM near a WHERE exact OR NOT EXISTS (SELECT 1 FROM near b WHERE b.bits <> a.bits AND b.bits & a.bits = b.bits) AND NOT exact""")
def deps_precision(spark: SparkSession, sf: str) -> DataFrame:
    """Keys that tolerate noise (up to a tenth of the rows deleted) against true ones: every set of attributes that is a key, and minimal ones that nearly are."""
    from itertools import combinations

    from tabqa.operators import measures

    customer = t(spark, sf, "customer")
    sets = [c for size in range(1, len(_CUSTOMER) + 1) for c in combinations(_CUSTOMER, size)]
    counted = customer.agg(F.count(F.lit(1)).alias("n"), *(F.count_distinct(*c).alias(f"c{i}") for i, c in enumerate(sets))).first()
    near = [c for i, c in enumerate(sets) if counted[f"c{i}"] >= 0.9 * counted["n"]]
    exact = [c for i, c in enumerate(sets) if counted[f"c{i}"] == counted["n"]]
    got = [c for c in near if c in exact or not any(set(x) < set(c) for x in near)]
    frame = lambda rows: spark.createDataFrame([("customer", ",".join(c), "*") for c in rows], "table_id string, lhs string, rhs string")
    return measures.deps_pr(frame(got), frame(exact))


@plan(f"{W}, {oracles.LONG}, {oracles.INCLUSIONS} SELECT lhs, rhs FROM unary")
def inclusions_core(spark: SparkSession, sf: str) -> DataFrame:
    """Inclusions within the handbook."""
    book = handbook_store(spark, sf)
    return _named(book, deps.unary_inclusions(book.cells))


@plan(f"{W}, {oracles.LONG}, {oracles.INCLUSIONS} SELECT lhs_table, rhs_table, count(*) AS n FROM pairs GROUP BY ALL")
def inclusions_composite(spark: SparkSession, sf: str) -> DataFrame:
    """Inclusions of two attribute pairs in the catalog, counted by tables."""
    sets = answers_book(spark, sf).composites.where("arity = 2").select("lhs_table", "rhs_table", "ind_id").distinct()
    return sets.groupBy("lhs_table", "rhs_table").agg(F.count(F.lit(1)).alias("n"))


def _named(book: store.Store, pairs: DataFrame) -> DataFrame:
    labels = book.attrs.select("attr_id", F.concat_ws(".", "table_id", "label").alias("name"))
    return pairs.join(labels.withColumnsRenamed({"attr_id": "lhs_attr", "name": "lhs"}), "lhs_attr").join(labels.withColumnsRenamed({"attr_id": "rhs_attr", "name": "rhs"}), "rhs_attr").select("lhs", "rhs")


#: All columns of the given tables but vectors, as expressions that Spark and DuckDB write alike; money in cents, times in seconds.
_GIVEN = {
    "region": ["r_regionkey", "r_name"], "nation": ["n_nationkey", "n_name", "n_regionkey"], "customer": ["c_custkey", "c_name", "c_nationkey", "c_acctbal*", "c_mktsegment"],
    "supplier": ["s_suppkey", "s_name", "s_nationkey", "s_acctbal*"], "part": ["p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice*"],
    "orders": ["o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice*", "o_orderdate@", "o_orderpriority"],
    "lineitem": ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity*", "l_extendedprice*", "l_discount*", "l_tax*", "l_returnflag", "l_linestatus", "l_shipdate@"],
    "events": ["event_id", "ts@", "user_id", "event_type", "value*", "props"], "documents": ["doc_id", "text", "lang", "source", "n_chars"], "embeddings": ["vec_id", "label"],
    "pages": ["page_id", "url", "html"], "benchmark": ["item_id", "text"], "labels": ["doc_id", "quality", "toxic"], "conversations": ["conv_id", "turn", "role", "text"],
}


def _plain_value(column: str, time: str, text: str) -> str:
    if column.endswith("*"):
        return f"concat('cents ', cast(cast(round({column[:-1]} * 100) as bigint) as {text}))"
    return f"concat('time ', cast(cast({time.format(column[:-1])} as bigint) as {text}))" if column.endswith("@") else f"cast({column} as {text})"


def _given_sql() -> str:
    rows = " UNION ALL ".join(f"SELECT DISTINCT '{t}' AS tab, '{t}.{c.rstrip('*@')}' AS attr, md5({_plain_value(c, 'epoch({})', 'varchar')}) AS val FROM {t} WHERE {c.rstrip('*@')} IS NOT NULL" for t, cs in _GIVEN.items() for c in cs)
    return f"WITH one AS MATERIALIZED ({rows}), n AS (SELECT attr, count(*) AS n FROM one GROUP BY 1) SELECT a.attr AS lhs, b.attr AS rhs FROM one a JOIN one b ON a.val = b.val AND a.tab <> b.tab JOIN n ON n.attr = a.attr GROUP BY ALL HAVING count(*) = any_value(n)"


@plan(_given_sql())
def inclusions_global(spark: SparkSession, sf: str) -> DataFrame:
    """Over all columns of all given tables, not within a document: accidental ones appear among dense integers. Values travel as digests."""
    parts = []
    for name, columns in _GIVEN.items():
        values = [F.md5(F.expr(_plain_value(c, "unix_timestamp(cast({} as timestamp))", "string")).cast("binary")).alias(f"{name}.{c.rstrip('*@')}") for c in columns]
        frame = t(spark, sf, name).select(*values)
        long = frame.unpivot([], [F.col(f"`{c}`") for c in frame.columns], "attr_id", "val_norm")
        parts.append(long.where("val_norm IS NOT NULL").distinct().select("attr_id", "val_norm", F.lit(name).alias("table_id"), F.lit(name).alias("doc_id")))
    return deps.unary_inclusions(reduce(DataFrame.unionByName, parts), scope="corpus").select(F.col("lhs_attr").alias("lhs"), F.col("rhs_attr").alias("rhs"))


@plan("SELECT 'orders' AS what, NOT EXISTS (SELECT o_custkey FROM orders EXCEPT SELECT c_custkey FROM customer) AS holds UNION ALL SELECT 'documents', NOT EXISTS (SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels)")
def inclusion_check(spark: SparkSession, sf: str) -> DataFrame:
    return _answers(spark, [("orders", deps.inclusion_holds(t(spark, sf, "orders"), ["o_custkey"], t(spark, sf, "customer"), ["c_custkey"])), ("documents", deps.inclusion_holds(t(spark, sf, "documents"), ["doc_id"], t(spark, sf, "labels"), ["doc_id"]))])


_PAIRS = "SELECT DISTINCT 'customer' AS tab, c_custkey AS k, c_nationkey AS n FROM customer UNION SELECT 'orders', o_custkey, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey UNION SELECT 'events', user_id, c_nationkey FROM events JOIN customer ON user_id = c_custkey"


@plan(f"WITH p AS MATERIALIZED (SELECT tab, CAST(k AS VARCHAR) AS k, CAST(n AS VARCHAR) AS n FROM ({_PAIRS})) SELECT DISTINCT a.tab || '.k,' || a.tab || '.n' AS lhs, b.tab || '.k,' || b.tab || '.n' AS rhs FROM p a JOIN p b ON a.tab <> b.tab WHERE (a.tab, b.tab) NOT IN (SELECT (x.tab, y.tab) FROM p x CROSS JOIN (SELECT DISTINCT tab FROM p) y WHERE x.tab <> y.tab AND NOT EXISTS (SELECT 1 FROM p z WHERE z.tab = y.tab AND z.k = x.k AND z.n = x.n))")
def inclusion_nary(spark: SparkSession, sf: str) -> DataFrame:
    """Inclusions of pairs, customer and nation, between three tables, grown from unary ones: all candidates of a level in one job."""
    customer = t(spark, sf, "customer").select(F.col("c_custkey").alias("k"), F.col("c_nationkey").alias("n"))
    rows = {"customer": customer, "orders": t(spark, sf, "orders").select(F.col("o_custkey").alias("k")).join(customer, "k"), "events": t(spark, sf, "events").select(F.col("user_id").alias("k")).join(customer, "k")}
    cells = []
    for name, df in rows.items():
        held = df.distinct().select(F.col("k").cast("string").alias(f"{name}.k"), F.col("n").cast("string").alias(f"{name}.n")).withColumn("row_id", F.concat_ws("|", F.lit(name), F.col(f"`{name}.k`")))
        cells.append(held.unpivot(["row_id"], [F.col(f"`{name}.{c}`") for c in "kn"], "attr_id", "val_norm").withColumn("table_id", F.lit(name)).withColumn("doc_id", F.lit("given")))
    held = written(reduce(DataFrame.unionByName, cells), "nary-cells")
    listed = lambda side: F.array_join(F.expr(f"transform(array_sort(collect_list(struct(pos, {side}_attr))), x -> x.{side}_attr)"), ",").alias(side)
    return deps.composite_inclusions(held, deps.unary_inclusions(held)).groupBy("ind_id").agg(listed("lhs"), listed("rhs")).select("lhs", "rhs")


@plan(f"{W}, {oracles.LONG}, {oracles.INCLUSIONS}, rows_of AS (SELECT table_id, count(DISTINCT row_id) AS n FROM long GROUP BY 1), whole AS (SELECT attr FROM long JOIN rows_of USING (table_id) GROUP BY attr HAVING count(DISTINCT val) = any_value(n)) SELECT lhs, rhs FROM unary WHERE rhs IN (SELECT attr FROM whole)")
def foreign_keys_core(spark: SparkSession, sf: str) -> DataFrame:
    book = answers_book(spark, sf)
    return _named(book, deps.foreign_keys(book.inds.select("lhs_table", "lhs_attr", "rhs_table", "rhs_attr"), book.keys))


@plan("SELECT n_left, n_right, n_both, n_both / n_left AS left_held, n_both / n_right AS right_held FROM (SELECT (SELECT count(DISTINCT user_id) FROM events) AS n_left, (SELECT count(*) FROM customer) AS n_right, (SELECT count(DISTINCT user_id) FROM events WHERE user_id IN (SELECT c_custkey FROM customer)) AS n_both)")
def joinability(spark: SparkSession, sf: str) -> DataFrame:
    return deps.joinable(t(spark, sf, "events"), "user_id", t(spark, sf, "customer"), "c_custkey")


@plan("""SELECT 'customer: c_nationkey -> c_mktsegment' AS dependency, (SELECT count(*) FROM (SELECT c_nationkey FROM customer GROUP BY 1 HAVING count(DISTINCT c_mktsegment) > 1)) AS violations
UNION ALL SELECT 'customer: key c_custkey', (SELECT count(*) FROM (SELECT c_custkey FROM customer GROUP BY 1 HAVING count(*) > 1)) UNION ALL SELECT 'orders.o_custkey in customer.c_custkey', (SELECT count(*) FROM (SELECT o_custkey FROM orders EXCEPT SELECT c_custkey FROM customer))""")
def consistency_report(spark: SparkSession, sf: str) -> DataFrame:
    tables = {n: t(spark, sf, n) for n in ("customer", "orders")}
    return deps.check_consistency(tables, [("customer", ["c_nationkey"], ["c_mktsegment"])], [("customer", ["c_custkey"])], [("orders", ["o_custkey"], "customer", ["c_custkey"])])


@plan("SELECT count(*) = 0 AS holds, count(*) AS violations FROM (SELECT o_orderkey FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1 HAVING count(DISTINCT c_nationkey) > 1)")
def fd_across(spark: SparkSession, sf: str) -> DataFrame:
    """An order's customer determines the nation in the customer table, aligned by their inclusion."""
    return deps.fd_holds_across(t(spark, sf, "orders").select("o_orderkey", "o_custkey"), ["o_orderkey"], t(spark, sf, "customer"), ["c_nationkey"], (["o_custkey"], ["c_custkey"]))


_FDS = " UNION ALL ".join(f"SELECT 'dependencies' AS kind, '{name}' AS table_id FROM ({oracles.fds(columns, deps.MOST_LEFT, f'{name}_')})" for name, columns in oracles.COLUMNS.items())
_KEYS = " UNION ALL ".join(f"SELECT 'keys' AS kind, '{name}' AS table_id FROM {name}_minimal" for name in oracles.COLUMNS)


@plan(f"{_COUNTS}, {oracles.LONG}, {oracles.INCLUSIONS} SELECT kind, table_id, count(*) AS n FROM ({_KEYS} UNION ALL {_FDS} UNION ALL SELECT 'inclusions', lhs_table FROM unary UNION ALL SELECT 'composite inclusions', lhs_table FROM pairs) GROUP BY ALL")
def dependency_catalog(spark: SparkSession, sf: str) -> DataFrame:
    """The offline catalog of all printed tables: keys, functional dependencies, inclusions of one attribute and of two, counted."""
    book = deps.build_catalog(store.held(handbook_store(spark, sf, anew=True)))
    parts = [("keys", book.keys, "table_id", "key_id"), ("dependencies", book.fds, "table_id", "fd_id"), ("inclusions", book.inds, "lhs_table", "ind_id"), ("composite inclusions", book.composites, "lhs_table", "ind_id")]
    counted = [df.groupBy(F.col(table).alias("table_id")).agg(F.count_distinct(number).alias("n")).withColumn("kind", F.lit(kind)) for kind, df, table, number in parts]
    return reduce(DataFrame.unionByName, counted).select("kind", "table_id", "n")


@plan("""SELECT 'fd' AS kind, round(1 - (SELECT sum(m) FROM (SELECT l_orderkey, max(c) AS m FROM (SELECT l_orderkey, l_linestatus, count(*) AS c FROM lineitem GROUP BY ALL) GROUP BY 1)) / (SELECT count(*) FROM lineitem), 9) AS error
UNION ALL SELECT 'key', round(1 - (SELECT count(*) FROM (SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem)) / (SELECT count(*) FROM lineitem), 9)
UNION ALL SELECT 'inclusion', round((SELECT count(*) FROM (SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels)) / (SELECT count(DISTINCT doc_id) FROM documents), 9)""")
def fd_error_lineitem(spark: SparkSession, sf: str) -> DataFrame:
    """How far three dependencies miss."""
    line = t(spark, sf, "lineitem")
    parts = {"fd": deps.fd_error(line, ["l_orderkey"], ["l_linestatus"]), "key": deps.key_error(line, ["l_orderkey", "l_linenumber"]), "inclusion": deps.inclusion_error(t(spark, sf, "documents"), ["doc_id"], t(spark, sf, "labels"), ["doc_id"])}
    return reduce(DataFrame.unionByName, [df.select(F.lit(k).alias("kind"), F.round("error", 9).alias("error")) for k, df in parts.items()])


# Matching


@plan("""WITH q AS (SELECT lower(r_name) AS asked FROM region UNION SELECT substr(lower(r_name), 1, 4) FROM region UNION SELECT split_part(lower(r_name), ' ', 1) FROM region UNION SELECT substr(lower(r_name), 2) FROM region),
p AS (SELECT asked, lower(r_name) AS held, list_distinct(regexp_extract_all(asked, '[\\p{L}\\p{N}]+')) AS words, regexp_extract_all(lower(r_name), '[\\p{L}\\p{N}]+') AS others FROM q CROSS JOIN region),
s AS (SELECT asked, held, 'exact' AS mode, CASE WHEN asked = held THEN 1.0 ELSE 0.0 END AS s FROM p
UNION ALL SELECT asked, held, 'edit', CASE WHEN 1 - levenshtein(asked, held) / greatest(length(asked), length(held)) >= 0.6 THEN 1 - levenshtein(asked, held) / greatest(length(asked), length(held)) ELSE 0 END FROM p
UNION ALL SELECT asked, held, 'token', CASE WHEN asked = held THEN 1 WHEN len(list_intersect(words, others)) / len(words) >= 0.6 THEN least(len(list_intersect(words, others)) / len(words), 0.99) ELSE 0 END FROM p
UNION ALL SELECT asked, held, 'prefix', CASE WHEN asked = held THEN 1 WHEN starts_with(held, asked) THEN 0.6 + 0.4 * length(asked) / length(held) * 0.99 ELSE 0 END FROM p)
SELECT asked, held, mode, CAST(round(s * 1000000) AS BIGINT) AS millionths FROM s WHERE s > 0""")
def match_modes(spark: SparkSession, sf: str) -> DataFrame:
    """Region names, and parts of them, against region names, in each way of matching."""
    held = t(spark, sf, "region").select(F.lower("r_name").alias("held"))
    parts = [F.col("held"), F.substring("held", 1, 4), F.split_part("held", F.lit(" "), F.lit(1)), F.expr("substr(held, 2)")]
    asked = reduce(DataFrame.union, [held.select(c.alias("asked")) for c in parts]).distinct()
    pairs = asked.crossJoin(held)  # twenty by five
    each = [pairs.select("asked", "held", F.lit(m).alias("mode"), match_score(F.col("asked"), F.col("held"), m).alias("s")) for m in ("exact", "edit", "token", "prefix")]
    return reduce(DataFrame.unionByName, each).where("s > 0").select("asked", "held", "mode", F.round(F.col("s") * 1000000).cast("bigint").alias("millionths"))


@plan("SELECT a.n_name AS asked, b.n_name AS held, CAST(round((1 - levenshtein(lower(a.n_name), lower(b.n_name)) / greatest(length(a.n_name), length(b.n_name))) * 1000000) AS BIGINT) AS millionths FROM nation a JOIN nation b ON 1 - levenshtein(lower(a.n_name), lower(b.n_name)) / greatest(length(a.n_name), length(b.n_name)) >= 0.6")
def fuzzy_match(spark: SparkSession, sf: str) -> DataFrame:
    a = t(spark, sf, "nation").select(F.col("n_name").alias("asked"))
    b = t(spark, sf, "nation").select(F.col("n_name").alias("held"))
    s = match_score(F.lower("asked"), F.lower("held"), "edit", 0.6)
    return a.crossJoin(F.broadcast(b)).withColumn("s", s).where("s > 0").select("asked", "held", F.round(F.col("s") * 1000000).cast("bigint").alias("millionths"))


# Windows of the paper's SQL form


@plan("SELECT c_custkey, changed FROM (SELECT c_custkey, " + _MASK.format("c_name") + " <> lag(" + _MASK.format("c_name") + ") OVER (ORDER BY c_custkey) AS changed FROM customer) WHERE changed")
def mask_changes(spark: SparkSession, sf: str) -> DataFrame:
    """Where a column's mask changes from one row to the next; names of customers all look alike. Keys are dense, so the
    row before is found by its key."""
    c = t(spark, sf, "customer").select("c_custkey", mask_text(F.col("c_name"), "keep").alias("m"))
    before = c.select((F.col("c_custkey") + 1).alias("c_custkey"), F.col("m").alias("b"))
    return c.join(before, "c_custkey").withColumn("changed", F.col("m") != F.col("b")).where("changed").select("c_custkey", "changed")
