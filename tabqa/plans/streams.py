"""Streaming plans; what a run over everything gives is held against batch SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tabqa.plans import answers, methods
from tabqa.plans.registry import plan
from tabqa.session import table as t
from tabqa.sources import corpus
from tabqa.streaming import streams


def _day(c: str):
    return F.date_format(c, "yyyy-MM-dd").alias("day")


@plan("SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    return streams.settled(streams.tumbling_counts(streams.events_of(spark, sf)), "tumbling", "complete").select(_day("window.start"), "event_type", "n")


@plan("SELECT strftime(d, '%Y-%m-%d') AS day, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS d FROM events) GROUP BY ALL")
def stream_sliding(spark: SparkSession, sf: str) -> DataFrame:
    return streams.settled(streams.sliding_counts(streams.events_of(spark, sf)), "sliding", "complete").select(_day("window.start"), "n")


@plan("""WITH m AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOURS THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM m)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS began, count(*) AS n FROM s GROUP BY user_id, k HAVING max(ts) + INTERVAL 6 HOURS <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR""")
def stream_session(spark: SparkSession, sf: str) -> DataFrame:
    """Sessions that the watermark has closed."""
    return streams.settled(streams.sessions(streams.events_of(spark, sf)), "sessions").select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("began"), "n")


@plan("SELECT DISTINCT event_id FROM events")
def stream_dedup(spark: SparkSession, sf: str) -> DataFrame:
    events = streams.events_of(spark, sf)
    return streams.settled(streams.deduplicated(events.unionByName(events)).select("event_id"), "dedup")


@plan("SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark: SparkSession, sf: str) -> DataFrame:
    return streams.settled(streams.with_customers(streams.events_of(spark, sf), t(spark, sf, "customer")).select("event_id", "c_mktsegment"), "static")


@plan("SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR WHERE v.event_type = 'view' AND p.event_type = 'purchase'")
def stream_stream_join(spark: SparkSession, sf: str) -> DataFrame:
    return streams.settled(streams.views_then_purchases(streams.events_of(spark, sf)), "pairs")


@plan("SELECT user_id, count(*) AS hits FROM events GROUP BY ALL")
def stream_stateful(spark: SparkSession, sf: str) -> DataFrame:
    return streams.settled(streams.running_hits(streams.events_of(spark, sf)), "hits", "update")


@plan(methods.W + "SELECT 'https://handbook.example/pair_codes#0' AS table_id, count(*) * 3 AS cells FROM pair_codes")
def stream_ingest(spark: SparkSession, sf: str) -> DataFrame:
    """The page of the code matrix arrives; its full rows' cells are counted."""
    place = streams.place(spark, "pages")
    corpus.as_html(corpus.handbook(spark, sf).where("table_id = 'pair_codes'")).write.parquet(place)
    pages = spark.readStream.schema("page_id bigint, url string, html string").parquet(place)
    cells = streams.ingest_pages(pages, lambda grids: grids.withColumn("family", F.lit("pair_matrix")), corpus.registry(spark))
    full = cells.groupBy("table_id", "row_no").agg(F.bool_or(F.col("val_raw") == "n/a").alias("gap"), F.count(F.lit(1)).alias("n")).where("NOT gap")
    return full.groupBy("table_id").agg(F.sum("n").alias("cells"))


@plan(methods.W + "SELECT 'a' AS query_id, 'derived' AS stage, count(*) AS n FROM limits JOIN pair_codes USING (code) WHERE brand = 'Brand#14' AND nation = 'NATION_0' AND size_code = '08' UNION ALL SELECT 'b', 'direct', count(*) FROM limits WHERE code = 'C3'")
def stream_query_lookup(spark: SparkSession, sf: str) -> DataFrame:
    """Two queries arrive as JSON."""
    specs = [("a", '{"wanted": ["min"], "given": [{"val": "8"}, {"val": "Brand#14"}, {"val": "NATION_0"}]}'), ("b", '{"wanted": ["max"], "given": [{"val": "C3"}]}')]
    place = streams.place(spark, "specs")
    spark.createDataFrame(specs, "query_id string, spec string").write.parquet(place)
    asked = spark.readStream.schema("query_id string, spec string").parquet(place)
    return streams.answer_stream(asked, answers.book(spark, sf)).groupBy("query_id", "stage").agg(F.count(F.lit(1)).alias("n"))


@plan("SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_memory(spark: SparkSession, sf: str) -> DataFrame:
    """Results of a few rows in a table in the driver's memory."""
    name = f"tabqa_counts_{abs(hash(streams.place(spark, 'memory')))}"
    counts = streams.events_of(spark, sf).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    counts.writeStream.outputMode("complete").format("memory").queryName(name).option("checkpointLocation", streams.place(spark, "memory")).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


@plan("SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n FROM events WHERE ts::DATE = (SELECT max(ts)::DATE FROM events) GROUP BY 1")
def stream_late(spark: SparkSession, sf: str) -> DataFrame:
    """Rows that come after their window has closed are dropped: the last day arrives first, then the first one, of which nothing is seen."""
    place = streams.place(spark, "late")
    events = t(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")).select("event_id", "ts")
    first, last = events.agg(F.min("ts"), F.max("ts")).first()
    write = lambda batch, number: batch.write.mode("overwrite").parquet(f"{place}/out/batch={number}")
    for day in (last, first):  # a run for each day; the second goes on from the first one's state
        events.where(F.to_date("ts") == F.lit(day).cast("date")).coalesce(1).write.mode("append").parquet(f"{place}/in")
        stream = spark.readStream.schema("event_id bigint, ts timestamp").parquet(f"{place}/in")
        counts = stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n")).select(_day("window.start"), "n")
        counts.writeStream.outputMode("update").option("checkpointLocation", f"{place}/checkpoint").trigger(availableNow=True).foreachBatch(write).start().awaitTermination()
    return spark.read.schema("day string, n bigint").parquet(f"{place}/out").select("day", "n")


@plan(methods.W + ", " + ", ".join(f"{name}_n AS (SELECT count(*) AS n FROM {name})" for name in ("pair_codes", "limits", "trade", "zones", "zone_counts")) + """
SELECT 'pair_matrix' AS family, 1::BIGINT AS tables, (SELECT n FROM pair_codes_n) AS n_rows UNION ALL SELECT 'limit_matrix', 1, (SELECT n FROM limits_n) UNION ALL SELECT 'trade_matrix', 1, (SELECT n FROM trade_n) UNION ALL SELECT 'plain_listing', 2, (SELECT n FROM zones_n) + (SELECT n FROM zone_counts_n)""")
def stream_recognise(spark: SparkSession, sf: str) -> DataFrame:
    """Pages arrive, and the trained model assigns their tables' families: no family is named beforehand."""
    place = streams.place(spark, "unnamed")
    corpus.as_html(corpus.handbook(spark, sf)).write.parquet(place)
    pages = spark.readStream.schema("page_id bigint, url string, html string").parquet(place)
    parameters = answers.trained_parameters(spark, sf)
    from tabqa.operators import ingest

    cells = streams.ingest_pages(pages, lambda grids: ingest.recognised(grids, parameters), corpus.registry(spark), keep=("family",))
    rows = cells.groupBy("family", "table_id", "row_no").agg(F.bool_or(F.col("val_raw") == "n/a").alias("gap")).where("NOT gap")
    return rows.groupBy("family").agg(F.count_distinct("table_id").alias("tables"), F.count(F.lit(1)).alias("n_rows"))
