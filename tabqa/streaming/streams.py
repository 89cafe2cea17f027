"""Streams over the given tables and over pages and queries.

A table is read as a file stream; a run takes what is there and ends. Results land in the shared folder, a batch under its
own number, so a batch that is repeated replaces itself.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tabqa.operators import expand, query, store
from tabqa.session import scratch_folder, table, written
from tabqa.sources.html_tables import extract_tables


def stream_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table as a file stream of its own schema."""
    schema = table(spark, sf_dir, name).schema
    return spark.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)


def events_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stream_of(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def place(spark: SparkSession, name: str) -> str:
    return f"{scratch_folder(spark)}/stream-{name}-{uuid.uuid4().hex}"


def settled(frame: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there. Appended rows are files; complete results replace one another batch by batch."""
    spark = frame.sparkSession
    folder = place(spark, name)
    writer = frame.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True)
    if mode == "append":
        run = writer.format("parquet").option("path", f"{folder}/rows").start()
    else:
        run = writer.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(f"{folder}/rows")).start()
    run.awaitTermination()
    return spark.read.schema(frame.schema).parquet(f"{folder}/rows")


def tumbling_counts(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"))


def sliding_counts(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "1 hour").groupBy(F.window("ts", "2 days", "1 day")).agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "1 hour").groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n"))


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    return events.join(customers, events["user_id"] == customers["c_custkey"])


def views_then_purchases(events: DataFrame) -> DataFrame:
    """Both sides are kept for the hour they can match in, and no longer."""
    view = events.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("viewer"), F.col("ts").alias("seen")).withWatermark("seen", "1 hour")
    purchase = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "ts").withWatermark("ts", "1 hour")
    return view.join(purchase, F.expr("viewer = user_id AND ts >= seen AND ts <= seen + INTERVAL 1 HOUR")).select("view_id", "purchase_id")


def running_hits(events: DataFrame) -> DataFrame:
    """(user_id, hits) with the count kept as state."""

    def count(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        hits = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((hits,))
        yield pd.DataFrame({"user_id": [key[0]], "hits": [hits]})

    return events.groupBy("user_id").applyInPandasWithState(count, "user_id bigint, hits bigint", "hits bigint", "update", GroupStateTimeout.NoTimeout)


def ingest_pages(pages: DataFrame, family_of: Callable[[DataFrame], DataFrame], registry: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """Pages as they come: tables, grids, families, flat cells. A batch's cells replace those of an earlier try of it."""
    spark = pages.sparkSession
    folder = place(spark, "ingest")

    def take(batch: DataFrame, number: int) -> None:
        grids = written(family_of(expand.unspan(extract_tables(batch))), "stream-grids")
        flat = expand.unfold(grids, registry).join(grids.select("table_id", *keep), "table_id")
        cells = flat.select("table_id", *keep, "row_no", F.posexplode("values").alias("ord", "val_raw"))
        cells.write.mode("overwrite").parquet(f"{folder}/cells/batch={number}")

    pages.writeStream.foreachBatch(take).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{folder}/cells")


def answer_stream(specs: DataFrame, held: store.Store) -> DataFrame:
    """Queries (query_id, spec as JSON) as they come, answered against the store that is there."""
    spark = specs.sparkSession
    folder = place(spark, "answers")

    def take(batch: DataFrame, number: int) -> None:
        spec = F.from_json("spec", query.SPEC_SCHEMA)
        asked = batch.select("query_id", spec.alias("s")).persist()
        conditions = asked.select("query_id", F.size("s.given").alias("n_conds"), F.posexplode("s.given").alias("cond", "g")).select("query_id", "cond", "g.attr", "g.val", "n_conds")
        goals = asked.select("query_id", F.explode("s.wanted").alias("label"))
        topics = asked.select("query_id", F.explode("s.topics").alias("topic"))
        rows = query.answer(held, query.Batch.normal(conditions, goals, topics))
        rows.write.mode("overwrite").parquet(f"{folder}/answers/batch={number}")
        asked.unpersist()

    specs.writeStream.foreachBatch(take).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{folder}/answers")
