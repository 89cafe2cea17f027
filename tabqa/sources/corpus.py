"""Compact tables folded from the given relations: the handbook that queries are asked of, and the training grids.

The base relations are plain SQL over the given tables; folding compacts them, and everything downstream sees only grids.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tabqa.operators.expand import FamilySpec, family_registry, fold
from tabqa.session import table, written


def pair_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """brand, nation of the supplier, code."""
    line, part, supplier, nation = (table(spark, sf_dir, t) for t in ("lineitem", "part", "supplier", "nation"))
    joined = line.select("l_partkey", "l_suppkey").join(part.select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")).join(supplier.select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    joined = joined.groupBy("p_brand", "s_nationkey").agg(F.count(F.lit(1)).alias("n")).join(nation, F.col("s_nationkey") == F.col("n_nationkey"))
    return joined.select(F.col("p_brand").alias("brand"), F.col("n_name").alias("nation"), F.concat(F.lit("C"), (F.col("n") % 7 + 1).cast("string")).alias("code"))


def limits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """size_code, code, min, nom, max of the quantity."""
    line, part, supplier, nation = (table(spark, sf_dir, t) for t in ("lineitem", "part", "supplier", "nation"))
    codes = pair_codes(spark, sf_dir).join(nation, F.col("nation") == F.col("n_name")).select("brand", F.col("n_nationkey").alias("key"), "code")
    joined = line.select("l_partkey", "l_suppkey", "l_quantity").join(part.select("p_partkey", "p_brand", "p_size"), F.col("l_partkey") == F.col("p_partkey")).join(supplier.select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    joined = joined.join(codes, (F.col("p_brand") == F.col("brand")) & (F.col("s_nationkey") == F.col("key")))
    grouped = joined.groupBy(F.lpad(F.col("p_size").cast("string"), 2, "0").alias("size_code"), "code")
    return grouped.agg(F.min("l_quantity").cast("bigint").alias("min"), F.floor(F.median("l_quantity")).cast("bigint").alias("nom"), F.max("l_quantity").cast("bigint").alias("max"))


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """nation, yr, qty, cents of orders."""
    orders, customer, nation = (table(spark, sf_dir, t) for t in ("orders", "customer", "nation"))
    joined = orders.join(customer, F.col("o_custkey") == F.col("c_custkey")).join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.groupBy(F.col("n_name").alias("nation"), F.year("o_orderdate").alias("yr")).agg(F.count(F.lit(1)).alias("qty"), F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents"))


def zones(spark: SparkSession, sf_dir: str) -> DataFrame:
    """nation, zone."""
    nation, region = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    return nation.join(region, F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_name").alias("nation"), F.col("r_name").alias("zone"))


def zone_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """code, zone, pairs."""
    return pair_codes(spark, sf_dir).join(zones(spark, sf_dir), "nation").groupBy("code", "zone").agg(F.count(F.lit(1)).alias("pairs"))


RELATIONS = {"pair_codes": pair_codes, "limits": limits, "trade": trade, "zones": zones, "zone_counts": zone_counts}

#: DuckDB SQL of the same relations, as the head of a WITH clause.
BASE_SQL = """
j AS (SELECT p_brand, p_size, s_nationkey, l_quantity FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey),
pair_codes AS (SELECT p_brand AS brand, n_name AS nation, 'C' || (1 + count(*) % 7) AS code FROM j JOIN nation ON s_nationkey = n_nationkey GROUP BY ALL),
limits AS (SELECT lpad(CAST(p_size AS VARCHAR), 2, '0') AS size_code, code, CAST(min(l_quantity) AS BIGINT) AS min, CAST(floor(median(l_quantity)) AS BIGINT) AS nom, CAST(max(l_quantity) AS BIGINT) AS max
           FROM j JOIN nation ON s_nationkey = n_nationkey JOIN pair_codes ON brand = p_brand AND nation = n_name GROUP BY ALL),
trade AS (SELECT n_name AS nation, CAST(year(o_orderdate) AS INTEGER) AS yr, count(*) AS qty, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS cents
          FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL),
zones AS (SELECT n_name AS nation, r_name AS zone FROM nation JOIN region ON n_regionkey = r_regionkey),
zone_counts AS (SELECT code, zone, count(*) AS pairs FROM pair_codes JOIN zones USING (nation) GROUP BY ALL)"""

#: Captions and attribute labels of the handbook.
CAPTIONS = {"pair_codes": "Combination codes", "limits": "Quantity limits", "trade": "Orders by nation and year", "zones": "Nation zones", "zone_counts": "Code counts per zone"}
LABELS = {
    "pair_codes": ["Brand", "Nation", "Code"], "limits": ["Size Code", None, None, "Code", None, "Min", "Nom", "Max"], "trade": ["Nation", "Year", None, "Quantity", "Value"],
    "zones": ["Nation", "Zone"], "zone_counts": ["Code", "Zone", "Pairs"],
}
#: The grids of the handbook, cell by cell, as SQL over the relations above; the last CTEs of a WITH clause.
CELLS_SQL = """
zone_order AS (SELECT *, row_number() OVER (ORDER BY nation, zone) AS r FROM zones),
count_order AS (SELECT *, row_number() OVER (ORDER BY code, zone, CAST(pairs AS VARCHAR)) AS r FROM zone_counts),
brands AS (SELECT brand, row_number() OVER (ORDER BY brand) AS r FROM (SELECT DISTINCT brand FROM pair_codes)),
pair_nations AS (SELECT nation, row_number() OVER (ORDER BY nation) AS c FROM (SELECT DISTINCT nation FROM pair_codes)),
sizes AS (SELECT size_code, 3 + row_number() OVER (ORDER BY size_code) AS r FROM (SELECT DISTINCT size_code FROM limits)),
codes AS (SELECT code, 3 * row_number() OVER (ORDER BY code) - 2 AS c FROM (SELECT DISTINCT code FROM limits)),
traders AS (SELECT nation, 1 + row_number() OVER (ORDER BY nation) AS r FROM (SELECT DISTINCT nation FROM trade)),
years AS (SELECT yr, 2 * row_number() OVER (ORDER BY CAST(yr AS VARCHAR)) - 1 AS c FROM (SELECT DISTINCT yr FROM trade)),
limit_cells AS (SELECT s.r, c.c + k AS c, coalesce(CAST(CASE k WHEN 0 THEN l.min WHEN 1 THEN l.nom ELSE l.max END AS VARCHAR), 'n/a') AS txt FROM sizes s CROSS JOIN codes c CROSS JOIN (SELECT unnest(range(3)) AS k) LEFT JOIN limits l ON l.size_code = s.size_code AND l.code = c.code),
trade_cells AS (SELECT s.r, y.c + k AS c, coalesce(CAST(CASE k WHEN 0 THEN t.qty ELSE t.cents END AS VARCHAR), 'n/a') AS txt FROM traders s CROSS JOIN years y CROSS JOIN (SELECT unnest(range(2)) AS k) LEFT JOIN trade t ON t.nation = s.nation AND t.yr = y.yr),
pair_cells AS (SELECT b.r, n.c, coalesce(p.code, 'n/a') AS txt FROM brands b CROSS JOIN pair_nations n LEFT JOIN pair_codes p ON p.brand = b.brand AND p.nation = n.nation),
cells AS (
SELECT 'zones' AS table_id, CAST(0 AS BIGINT) AS r, CAST(0 AS BIGINT) AS c, 'Nation' AS txt UNION ALL SELECT 'zones', 0, 1, 'Zone' UNION ALL SELECT 'zones', r, 0, nation FROM zone_order UNION ALL SELECT 'zones', r, 1, zone FROM zone_order
UNION ALL SELECT 'zone_counts', 0, 0, 'Code' UNION ALL SELECT 'zone_counts', 0, 1, 'Zone' UNION ALL SELECT 'zone_counts', 0, 2, 'Pairs' UNION ALL SELECT 'zone_counts', r, 0, code FROM count_order UNION ALL SELECT 'zone_counts', r, 1, zone FROM count_order UNION ALL SELECT 'zone_counts', r, 2, CAST(pairs AS VARCHAR) FROM count_order
UNION ALL SELECT 'pair_codes', 0, 0, '' UNION ALL SELECT 'pair_codes', 0, c, nation FROM pair_nations UNION ALL SELECT 'pair_codes', r, 0, brand FROM brands UNION ALL SELECT 'pair_codes', r, c, txt FROM pair_cells
UNION ALL SELECT 'limits', unnest(range(4)), 0, '' UNION ALL SELECT 'limits', 0, c + k, 'Limits of quantity' FROM codes, (SELECT unnest(range(3)) AS k) UNION ALL SELECT 'limits', 1, c + k, 'Class' FROM codes, (SELECT unnest(range(3)) AS k)
UNION ALL SELECT 'limits', 2, c + k, code FROM codes, (SELECT unnest(range(3)) AS k) UNION ALL SELECT 'limits', 3, c + k, ['Min', 'Nom', 'Max'][k + 1] FROM codes, (SELECT unnest(range(3)) AS k) UNION ALL SELECT 'limits', r, 0, size_code FROM sizes UNION ALL SELECT 'limits', r, c, txt FROM limit_cells
UNION ALL SELECT 'trade', unnest(range(2)), 0, '' UNION ALL SELECT 'trade', 0, c + k, CAST(yr AS VARCHAR) FROM years, (SELECT unnest(range(2)) AS k) UNION ALL SELECT 'trade', 1, c + k, ['Quantity', 'Value'][k + 1] FROM years, (SELECT unnest(range(2)) AS k)
UNION ALL SELECT 'trade', r, 0, nation FROM traders UNION ALL SELECT 'trade', r, c, txt FROM trade_cells)"""

#: Layout families of the handbook and the training grids.
FAMILIES = (
    FamilySpec("pair_matrix", data_row=1, data_col=1, side_cols=(0,), band_rows=(0,), pivot_w=1),
    FamilySpec("limit_matrix", data_row=4, data_col=1, side_cols=(0,), band_rows=(0, 1, 2, 3), pivot_w=3),
    FamilySpec("trade_matrix", data_row=2, data_col=1, side_cols=(0,), band_rows=(0, 1), pivot_w=2),
    FamilySpec("plain_listing", data_row=1),
    FamilySpec("vertical_listing", data_row=0, data_col=1, pivot_w=1, pivot_h=0),
    FamilySpec("right_bottom", data_row=0, data_col=0, foot_rows=1, foot_cols=1, side_cols=(-1,), band_rows=(-1,), pivot_w=1),
    FamilySpec("tall_pivot", data_row=1, data_col=1, side_cols=(0,), band_rows=(0,), pivot_w=1, pivot_h=2),
)


def registry(spark: SparkSession) -> DataFrame:
    return family_registry(spark, FAMILIES)


def listing(relation: DataFrame, table_id: str, columns: list[str], labels: list[str]) -> DataFrame:
    """(table_id, grid): a header row and a row for each tuple, sorted."""
    cells = F.array(*(F.col(c).cast("string") for c in columns))
    head = F.array(F.array(*(F.lit(x) for x in labels)))
    return relation.groupBy(F.col(table_id).alias("table_id")).agg(F.concat(head, F.array_sort(F.collect_list(cells))).alias("grid"))


def mirrored(grids: DataFrame) -> DataFrame:
    """Keys left and above become keys right and below."""
    return grids.withColumn("grid", F.reverse(F.transform("grid", lambda row: F.reverse(row))))


def _as(df: DataFrame, name: str) -> DataFrame:
    return df.withColumn("t", F.lit(name))


_PRINTED: dict[tuple[str, str, str], DataFrame] = {}


def _printed(spark: SparkSession, sf_dir: str, name: str, make: Callable[[SparkSession, str], DataFrame]) -> DataFrame:
    """Grids are documents, so they are made once in an application and read from then on."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _PRINTED:
        _PRINTED[key] = written(make(spark, sf_dir), name)
    return _PRINTED[key]


def handbook(spark: SparkSession, sf_dir: str) -> DataFrame:
    """table_id, doc_id, caption, page_begin, page_end, family, grid of the document the queries are about."""
    return _printed(spark, sf_dir, "handbook", _handbook)


def printed_anew(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The handbook as a plan over the given tables, for queries whose work starts there, not at what the application has printed before."""
    return _handbook(spark, sf_dir)


def training_grids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(table_id, family, grid): the 130 grids of seven families, sliced from the given tables by fixed rules."""
    return _printed(spark, sf_dir, "training-grids", _training_grids)


def _handbook(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = {name: _as(make(spark, sf_dir), name) for name, make in RELATIONS.items()}
    grids = [
        ("pair_matrix", fold(r["pair_codes"], "t", ["brand"], ["nation"], ["code"])),
        ("limit_matrix", fold(r["limits"], "t", ["size_code"], ["code"], ["min", "nom", "max"], ["Min", "Nom", "Max"], ["Limits of quantity", "Class"])),
        ("trade_matrix", fold(r["trade"], "t", ["nation"], ["yr"], ["qty", "cents"], ["Quantity", "Value"])),
        ("plain_listing", listing(r["zones"], "t", ["nation", "zone"], ["Nation", "Zone"])),
        ("plain_listing", listing(r["zone_counts"], "t", ["code", "zone", "pairs"], ["Code", "Zone", "Pairs"])),
    ]
    whole = reduce(DataFrame.unionByName, [g.withColumn("family", F.lit(f)) for f, g in grids])
    caption = F.create_map(*(F.lit(x) for kv in CAPTIONS.items() for x in kv))
    return whole.select("table_id", F.lit("handbook").alias("doc_id"), caption[F.col("table_id")].alias("caption"), F.lit(1).alias("page_begin"), F.lit(2).alias("page_end"), "family", "grid")


def _training_grids(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = []

    def add(family: str, grids: DataFrame) -> None:
        out.append(grids.select(F.concat(F.lit(family + ":"), F.col("table_id").cast("string")).alias("table_id"), F.lit(family).alias("family"), "grid"))

    def spread(df: DataFrame, n: int, key: str) -> DataFrame:
        """n overlapping slices: a row is in slice i when its key's number leaves i or one of two neighbours."""
        place = F.pmod(F.regexp_extract(F.col(key), r"(\d+)", 1).cast("int"), F.lit(n))
        return df.withColumn("i", F.explode(F.array(*(F.pmod(place + d, F.lit(n)) for d in range(3)))))

    codes = pair_codes(spark, sf_dir)
    add("pair_matrix", fold(spread(codes, 25, "brand"), "i", ["brand"], ["nation"], ["code"]))
    add("right_bottom", mirrored(fold(spread(codes, 15, "nation"), "i", ["brand"], ["nation"], ["code"])))
    add("limit_matrix", fold(spread(limits(spark, sf_dir), 20, "size_code"), "i", ["size_code"], ["code"], ["min", "nom", "max"], ["Min", "Nom", "Max"], ["Limits of quantity", "Class"]))
    add("trade_matrix", fold(spread(trade(spark, sf_dir), 15, "nation"), "i", ["nation"], ["yr"], ["qty", "cents"], ["Quantity", "Value"]))
    nation = table(spark, sf_dir, "nation").withColumn("code", F.concat(F.lit("N"), F.lpad(F.col("n_nationkey").cast("string"), 3, "0")))
    add("plain_listing", listing(spread(nation, 20, "n_name"), "i", ["n_name", "code", "n_nationkey"], ["Nation", "Code", "Key"]))
    # a printed list: the six greatest balances of some nations
    customer = table(spark, sf_dir, "customer").withColumn("cents", F.round(F.col("c_acctbal") * 100).cast("bigint")).withColumn("i", F.col("c_nationkey") % 20)
    greatest = Window.partitionBy("i").orderBy(F.desc("cents"), "c_custkey")
    customer = customer.withColumn("place", F.row_number().over(greatest)).where("place <= 6")
    columns = F.sort_array(F.collect_list(F.array("c_name", F.col("c_nationkey").cast("string"), F.col("cents").cast("string"))))
    named = customer.groupBy("i").agg(columns.alias("people"))
    grid = F.expr("transform(sequence(0, 2), r -> concat(array(array('Name', 'Country', 'Balance')[r]), transform(people, p -> p[r])))")
    add("vertical_listing", named.select(F.col("i").alias("table_id"), grid.alias("grid")))
    events = table(spark, sf_dir, "events").groupBy(F.to_date("ts").alias("day"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.max(F.round(F.col("value") * 100).cast("bigint")).alias("top"))
    tall = events.withColumn("i", F.pmod(F.unix_date("day"), F.lit(5)).cast("int") * 3).withColumn("i", F.explode(F.sequence("i", F.col("i") + 2)))
    flat = fold(tall, "i", ["day"], ["event_type"], ["n", "top"])  # two cells side by side, to be set one above the other
    high = F.expr("flatten(transform(grid, (row, k) -> if(k = 0, array(concat(array(row[0]), transform(sequence(0, cast((size(row) - 1) / 2 as int) - 1), j -> row[1 + 2 * j]))), transform(sequence(0, 1), h -> concat(array(row[0]), transform(sequence(0, cast((size(row) - 1) / 2 as int) - 1), j -> if(h = 0, row[1 + 2 * j], concat('max ', row[2 + 2 * j]))))))))")
    add("tall_pivot", flat.withColumn("grid", high))
    return reduce(DataFrame.unionByName, out)


def as_html(grids: DataFrame) -> DataFrame:
    """(page_id, url, html): each grid as a page with a caption, a malformed preamble, and equal neighbours of a row joined by colspan."""
    escaped = F.expr("transform(grid, row -> transform(row, c -> replace(replace(coalesce(c, ''), '&', '&amp;'), '<', '&lt;')))")
    heads = F.expr("transform(g, row -> transform(filter(sequence(0, size(row) - 1), j -> j = 0 or row[j] <> row[j - 1] or row[j] = ''), j -> struct(row[j] as t, j as a, coalesce(get(filter(sequence(j, size(row) - 1), e -> e > j and (row[e] <> row[j] or row[e] = '')), 0), size(row)) as b)))")
    rows = F.expr("array_join(transform(h, cells -> concat('<tr>', array_join(transform(cells, x -> concat('<td', if(x.b - x.a > 1, concat(' colspan=', x.b - x.a), ''), '>', x.t, '</td>')), ''))), '')")
    pages = grids.withColumn("g", escaped).withColumn("h", heads).withColumn("rows", rows)
    caption = F.coalesce(F.col("caption"), F.lit("")) if "caption" in grids.columns else F.lit("")
    html = F.concat(F.lit('<html><script>var t="</table>";</script><body><p>See &amp; compare<p>table: <table><caption>'), caption, F.lit("</caption>"), F.col("rows"), F.lit("</table></body>"))
    return pages.select(F.xxhash64("table_id").alias("page_id"), F.concat(F.lit("https://handbook.example/"), F.col("table_id")).alias("url"), html.alias("html"))
