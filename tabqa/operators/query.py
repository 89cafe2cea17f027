"""Answering queries that name values, and perhaps attributes and topics, but no schema.

All functions take a batch: conditions (query_id, cond, attr, val, n_conds), goals (query_id, label) and topics (query_id,
topic) are frames. One index join gives every hit of every condition; the stages that follow aggregate it. Which conditions a row
meets is a bit mask, so a query has at most MOST_CONDITIONS; more are refused.

Nothing here is broadcast by a hint: which side is small depends on tables and queries, and is left to the engine's measured sizes.
"""

from __future__ import annotations

import json
from dataclasses import dataclass
from itertools import combinations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tabqa.functions.text import TAU, match_score, normalize_value, tokens_of
from tabqa.operators.store import Store, gram_postings, similar, sized, token_postings, value_dictionary

# Specs ---------------------------------------------------------------------------------------------------------------

_ALIASES = {"topics": ("topics", "table_caption", "table_topics"), "wanted": ("wanted", "projection", "targets"), "given": ("given", "conditions")}
SPEC_SCHEMA = "struct<topics:array<string>,wanted:array<string>,given:array<struct<attr:string,val:string>>>"


#: Bits of a mask.
MOST_CONDITIONS = 62
#: Conditions of a batch whose values go to the scan as a filter.
FEW = 256


@dataclass(frozen=True)
class QuerySpec:
    given: tuple[tuple[str | None, str], ...]
    wanted: tuple[str, ...] = ()
    topics: tuple[str, ...] = ()


def parse_query(spec: str | dict) -> QuerySpec:
    """A query as JSON or a dict. Only the values of conditions are mandatory; field names may be any of the known ones."""
    held = json.loads(spec) if isinstance(spec, str) else dict(spec)
    unknown = set(held) - {a for names in _ALIASES.values() for a in names}
    if unknown:
        raise ValueError(f"unknown fields: {sorted(unknown)}")
    pick = lambda name: next((held[a] for a in _ALIASES[name] if a in held), None) or ()
    listed = lambda x: (x,) if isinstance(x, str) else tuple(x)
    given = []
    for c in pick("given"):
        value = c.get("value", c.get("val"))
        if value is None or not str(value).strip():
            raise ValueError("a condition needs a value")
        given.append((c.get("attribute_name") or c.get("attr") or None, str(value)))
    if not given:
        raise ValueError("a query needs at least one condition")
    if len(given) > MOST_CONDITIONS:
        raise ValueError(f"a query has at most {MOST_CONDITIONS} conditions")
    return QuerySpec(tuple(given), listed(pick("wanted")), listed(pick("topics")))


@dataclass
class Batch:
    """A batch of queries as frames. Of a batch of few conditions the values are known to the driver."""

    conditions: DataFrame
    goals: DataFrame
    topics: DataFrame
    few: bool = False

    @classmethod
    def of(cls, spark: SparkSession, specs: dict[str, QuerySpec | dict | str]) -> Batch:
        parsed = {q: s if isinstance(s, QuerySpec) else parse_query(s) for q, s in specs.items()}
        rows = [(q, i, a, v, len(s.given)) for q, s in parsed.items() for i, (a, v) in enumerate(s.given)]
        conditions = spark.createDataFrame(rows, "query_id string, cond int, attr string, val string, n_conds int")
        goals = spark.createDataFrame([(q, w) for q, s in parsed.items() for w in s.wanted], "query_id string, label string")
        out = cls.normal(conditions, goals, spark.createDataFrame([(q, t) for q, s in parsed.items() for t in s.topics], "query_id string, topic string"))
        out.few = len(rows) <= FEW
        return out

    @classmethod
    def of_frame(cls, specs: DataFrame) -> Batch:
        """From (query_id, spec), specs being JSON with any of the known field names; as many queries as there are rows."""
        condition = "array<struct<attr:string,attribute_name:string,val:string,value:string>>"
        fields = ", ".join(f"{name} {condition if field == 'given' else 'string'}" for field, names in _ALIASES.items() for name in names)
        held = specs.select("query_id", F.from_json("spec", fields).alias("s"))
        either = lambda field: F.coalesce(*(F.col(f"s.{name}") for name in _ALIASES[field]))
        # a list, or one text alone
        texts = lambda field: F.coalesce(F.from_json(either(field), "array<string>"), F.array(either(field)))
        given = held.select("query_id", either("given").alias("given"))
        given = given.withColumn("given", F.when(F.size("given") > 0, F.col("given")).otherwise(F.raise_error(F.concat(F.lit("a query needs at least one condition: "), F.col("query_id")))))
        rows = given.select("query_id", F.size("given").alias("n_conds"), F.posexplode("given").alias("cond", "c"))
        value = F.coalesce("c.value", "c.val")
        value = F.when(F.trim(value) != "", value).otherwise(F.raise_error(F.concat(F.lit("a condition needs a value: "), F.col("query_id"))))
        conditions = rows.select("query_id", "cond", F.coalesce("c.attribute_name", "c.attr").alias("attr"), value.alias("val"), "n_conds")
        labels = held.where(either("wanted").isNotNull()).select("query_id", F.explode(texts("wanted")).alias("label"))
        return cls.normal(conditions, labels, held.where(either("topics").isNotNull()).select("query_id", F.explode(texts("topics")).alias("topic")))

    @classmethod
    def normal(cls, conditions: DataFrame, goals: DataFrame, topics: DataFrame) -> Batch:
        """Values, attribute names and labels in their canonical forms."""
        bounded = F.when(F.col("n_conds") <= MOST_CONDITIONS, F.col("n_conds")).otherwise(F.raise_error(F.lit(f"a query has at most {MOST_CONDITIONS} conditions")))
        conditions = conditions.withColumns({"attr": F.lower(F.trim("attr")), "val": normalize_value(F.col("val")), "n_conds": bounded})
        return cls(conditions, goals.withColumn("label", F.lower(F.trim("label"))), topics)

    def values(self) -> list[str] | None:
        """The distinct values of a batch of few conditions."""
        return sorted({r["val"] for r in self.conditions.select("val").collect() if r["val"] is not None}) if self.few else None


@dataclass(frozen=True)
class Weights:
    """Weights of a row's score. All above 0, so that a match of any field, however fuzzy, beats none."""

    topic: float = 0.5
    wanted: float = 0.5
    attr: float = 0.5
    val: float = 1.0

    def __post_init__(self):
        if min(self.topic, self.wanted, self.attr, self.val) <= 0:
            raise ValueError("weights lie above 0")


# Hits ----------------------------------------------------------------------------------------------------------------


def _postings(store: Store, batch: Batch | None = None) -> DataFrame:
    """The inverted lists: the index's, or made from the cells; of a batch of few conditions only what their values select,
    which the scan of the sorted lists skips to."""
    lists = store.index.postings if store.index else store.cells.where("val_norm IS NOT NULL")
    values = batch.values() if batch else None
    lists = lists.where(F.col("val_norm").isin(values)) if values is not None else lists
    return lists.select("val_norm", "table_id", "row_id", "attr_id")


def _dictionary(store: Store, tau: float) -> DataFrame:
    return store.index.values if store.index else sized(value_dictionary(store), F.col("val_norm"), tau)


def match_values(store: Store, batch: Batch, mode: str = "edit", tau: float = TAU) -> DataFrame:
    """(query_id, cond, val_norm, s_val): dictionary values that conditions match; distinct values are far fewer than cells.

    Candidates come from the index: values that share enough grams with the asked one (edit) or a token (token), or lie behind it in
    order (prefix). The likeness is computed for candidates only.
    """
    asked = batch.conditions.select("query_id", "cond", "val").where("val IS NOT NULL")
    if mode == "exact":
        return asked.join(_dictionary(store, tau).select("val_norm"), F.col("val") == F.col("val_norm")).select("query_id", "cond", "val_norm", F.lit(1.0).alias("s_val"))
    distinct = asked.select(F.col("val").alias("asked")).distinct()
    values = _dictionary(store, tau)
    if mode == "edit":
        if store.index and tau != TAU:  # what is weak depends on tau
            values = sized(values.select("val_norm"), F.col("val_norm"), tau)
        grams = store.index.grams if store.index and tau == TAU else gram_postings(values)
        pairs = similar(distinct, values, grams, tau)
    elif mode == "token":
        tokens = store.index.tokens if store.index else token_postings(values)
        pairs = distinct.withColumn("token", F.explode(tokens_of(F.col("asked")))).join(tokens, "token").select("asked", "val_norm").distinct()
    elif mode == "prefix":
        begins = F.sequence(F.lit(1), F.greatest(F.col("length"), F.lit(1)))
        heads = values.select("val_norm", F.explode(F.transform(begins, lambda n: F.substring("val_norm", F.lit(1), n))).alias("asked"))
        pairs = distinct.join(heads, "asked")
    else:
        raise ValueError(f"no such mode: {mode}")
    scored = pairs.withColumn("s_val", match_score(F.col("asked"), F.col("val_norm"), mode, tau)).where("s_val > 0")
    return asked.join(scored.withColumnRenamed("asked", "val"), "val").select("query_id", "cond", "val_norm", "s_val")


def hits(store: Store, batch: Batch, mode: str = "exact", tau: float = TAU) -> DataFrame:
    """(query_id, cond, n_conds, table_id, row_id, attr_id, val_norm, s_val): every cell that a condition's value matches.

    Where a condition names an attribute, `attr_ok` tells whether the cell's attribute has that label.
    """
    if mode == "exact":
        found = batch.conditions.join(_postings(store, batch), F.col("val") == F.col("val_norm")).withColumn("s_val", F.lit(1.0))
    else:
        found = match_values(store, batch, mode, tau).join(batch.conditions, ["query_id", "cond"]).join(_postings(store), "val_norm")
    labels = store.attrs.select("attr_id", F.lower(F.trim("label")).alias("held_label"))
    found = found.join(labels, "attr_id", "left").withColumn("attr_ok", F.col("attr").isNull() | F.coalesce(F.col("attr") == F.col("held_label"), F.lit(False)))
    return found.select("query_id", "cond", "n_conds", "attr", "table_id", "row_id", "attr_id", "val_norm", "s_val", "attr_ok", "held_label")


def row_masks(found: DataFrame) -> DataFrame:
    """(query_id, n_conds, table_id, row_id, mask): which conditions each row meets, a bit for each."""
    return found.where("attr_ok").groupBy("query_id", "n_conds", "table_id", "row_id").agg(F.bit_or(F.expr("shiftleft(1L, cond)")).alias("mask"))


_FULL = "shiftleft(1L, n_conds) - 1"


def rows_with_all(store: Store, batch: Batch, table: str | None = None, distinct_cells: bool = False) -> DataFrame:
    """(query_id, table_id, row_id): rows that hold every given value, in any table or a named one.

    The list of each query's rarest value is read; of the rows in it the other values are looked for in the rows' own cells, so
    that no long list is read. With `distinct_cells` two conditions need two cells.
    """
    sizes = _dictionary(store, TAU).select("val_norm", "n_postings")
    values = batch.values()
    sizes = sizes.where(F.col("val_norm").isin(values)) if values is not None else sizes
    known = batch.conditions.join(sizes, F.col("val") == F.col("val_norm"))
    rarest = known.groupBy("query_id", "n_conds").agg(F.count(F.lit(1)).alias("known"), F.min_by("val", F.struct("n_postings", "cond")).alias("val")).where("known = n_conds")
    lists = _postings(store, batch).where(F.col("table_id") == table) if table else _postings(store, batch)
    rows = rarest.join(lists, F.col("val") == F.col("val_norm")).select("query_id", "n_conds", "table_id", "row_id").distinct()
    labels = store.attrs.select("attr_id", F.lower(F.trim("label")).alias("held_label"))
    cells = store.cells.where(F.col("table_id") == table) if table else store.cells
    own = rows.join(cells.where("val_norm IS NOT NULL").select("table_id", "row_id", "attr_id", "val_norm"), ["table_id", "row_id"]).join(labels, "attr_id", "left")
    met = own.join(batch.conditions.select("query_id", "cond", "attr", F.col("val").alias("val_norm")), ["query_id", "val_norm"]).where("attr IS NULL OR attr = held_label")
    out = met.groupBy("query_id", "n_conds", "table_id", "row_id").agg(F.bit_or(F.expr("shiftleft(1L, cond)")).alias("mask"), F.count_distinct("attr_id").alias("n_cells"))
    out = out.where(f"mask = {_FULL}" + (" AND n_cells >= n_conds" if distinct_cells else ""))
    return out.select("query_id", "table_id", "row_id")


# Ranked look-up --------------------------------------------------------------------------------------------------------


def rank_rows(store: Store, batch: Batch, k: int = 10, pairing: str = "lenient", mode: str = "edit", tau: float = TAU, weights: Weights = Weights()) -> DataFrame:  # noqa: B008
    """(query_id, rank, table_id, row_id, score, matches): rows by the weighted sum over the query's fields.

    Every clause is optional; a row needs one matched value. With strict pairing a named attribute must match too for its
    value to count. Fields of the table (topics, wanted labels) are scored on metadata and joined to the rows. `matches` has, for each
    condition that the row meets, the cell that counts: its attribute, its value, and what it adds to the score.
    """
    if pairing not in ("lenient", "strict"):
        raise ValueError(f"no such pairing: {pairing}")
    found = hits(store, batch, mode, tau)
    s_attr = F.when(F.col("attr").isNull(), 0.0).otherwise(match_score(F.col("attr"), F.col("held_label"), "edit", tau))
    found = found.withColumn("s_attr", s_attr)
    if pairing == "strict":
        found = found.where("attr IS NULL OR s_attr > 0")
    found = found.withColumn("f", weights.val * F.col("s_val") + weights.attr * F.col("s_attr"))
    best = F.max(F.struct("f", "attr_id", "val_norm"))
    value = found.groupBy("query_id", "table_id", "row_id", "cond").agg(best.alias("m"))
    match = F.struct("cond", "m.attr_id", "m.val_norm", F.round("m.f", 9).alias("score"))
    rows = value.groupBy("query_id", "table_id", "row_id").agg(F.sum("m.f").alias("v"), F.array_sort(F.collect_list(match)).alias("matches"))
    meta = _table_scores(store, batch, tau, weights)
    scored = rows.join(meta, ["query_id", "table_id"], "left").withColumn("score", F.round(F.col("v") + F.coalesce("s", F.lit(0.0)), 9))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "table_id", "row_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "table_id", "row_id", "score", "matches")


def match_labels(store: Store, batch: Batch, tau: float = TAU) -> DataFrame:
    """(query_id, label, table_id, attr_id, held, s): the likest attribute of each table for every wanted label; ties go to the first attribute."""
    held = store.attrs.select("table_id", "attr_id", "ord", F.lower(F.trim("label")).alias("held")).where("held IS NOT NULL")
    texts = sized(held.select(F.col("held").alias("val_norm")).distinct(), F.col("val_norm"), tau)
    pairs = similar(batch.goals.select(F.col("label").alias("asked")), texts, gram_postings(texts), tau)
    scored = pairs.withColumn("s", match_score(F.col("asked"), F.col("val_norm"), "edit", tau)).where("s > 0").select(F.col("asked").alias("label"), F.col("val_norm").alias("held"), "s")
    met = batch.goals.distinct().join(scored, "label").join(held, "held")
    return met.groupBy("query_id", "label", "table_id").agg(F.max(F.struct("s", -F.col("ord"), "attr_id", "held")).alias("m")).select("query_id", "label", "table_id", "m.attr_id", "m.held", "m.s")


def match_topics(store: Store, batch: Batch, tau: float = TAU) -> DataFrame:
    """(query_id, topic, table_id, s): tables whose caption holds enough of a topic's words; found by the words they share."""
    words = lambda df, c: df.withColumn("token", F.explode(tokens_of(F.col(c))))
    met = words(batch.topics, "topic").join(words(store.tables.select("table_id", "caption"), "caption"), "token").select("query_id", "topic", "table_id", "caption").distinct()
    return met.select("query_id", "topic", "table_id", match_score(F.lower("topic"), F.lower("caption"), "token", tau).alias("s")).where("s > 0")


def _table_scores(store: Store, batch: Batch, tau: float, weights: Weights) -> DataFrame:
    """(query_id, table_id, s): what topics and wanted labels add to a table's rows; metadata only."""
    topic = match_topics(store, batch, tau).select("query_id", "table_id", (weights.topic * F.col("s")).alias("s"))
    label = match_labels(store, batch, tau).select("query_id", "table_id", (weights.wanted * F.col("s")).alias("s"))
    return topic.unionByName(label).groupBy("query_id", "table_id").agg(F.sum("s").alias("s"))


def wanted_values(store: Store, batch: Batch, rows: DataFrame, fuzzy: bool = False, tau: float = TAU) -> DataFrame:
    """The rows (with query_id, table_id, row_id) and (label, value) of each wanted attribute; of every attribute where the query wants none.

    With `fuzzy` a wanted label stands for the likest attribute of the row's table; `label` is that attribute's own.
    """
    labels = store.attrs.select("attr_id", F.lower(F.trim("label")).alias("label"))
    cells = store.cells.select("row_id", "attr_id", F.col("val_raw").alias("value")).join(labels, "attr_id")
    asking = batch.goals.select("query_id").distinct()
    some = rows.join(asking, "query_id", "left_semi")
    if fuzzy:
        wanted = match_labels(store, batch, tau).select("query_id", "table_id", "attr_id").distinct()
        some = some.join(wanted, ["query_id", "table_id"]).join(cells, ["row_id", "attr_id"])
    else:
        some = some.join(cells, "row_id").join(batch.goals, ["query_id", "label"], "left_semi")
    columns = [*rows.columns, "attr_id", "value", "label"]
    return some.select(*columns).unionByName(rows.join(asking, "query_id", "left_anti").join(cells, "row_id").select(*columns))


# Several tables --------------------------------------------------------------------------------------------------------


def tables_with_labels(store: Store, batch: Batch, mode: str = "any", found: DataFrame | None = None, hops: int = 1) -> DataFrame:
    """(query_id, table_id): tables with an attribute (with `all`: every one) that the query wants; any table where it wants none.

    Of the latter, given what the conditions hit, only tables are named that can have an answer: those with a hit, and those linked
    with them by inclusions over up to `hops` links.
    """
    held = store.attrs.select("table_id", F.lower(F.trim("label")).alias("label"))
    goals = batch.goals.distinct()
    wanted = goals.join(held, "label").groupBy("query_id", "table_id").agg(F.count_distinct("label").alias("n"))
    if mode == "all":
        wanted = wanted.join(goals.groupBy("query_id").agg(F.count(F.lit(1)).alias("n")), ["query_id", "n"])
    free = batch.conditions.select("query_id").distinct().join(goals, "query_id", "left_anti")
    if found is None:
        reached = free.crossJoin(store.tables.select("table_id"))
    else:
        reached = found.join(free, "query_id", "left_semi").select("query_id", "table_id").distinct()
        links = links_of(store.inds).join(store.attrs.select("attr_id", "table_id"), "attr_id").select("table_id", "link_table").distinct()
        for _ in range(hops):
            reached = reached.unionByName(reached.join(links.select(F.col("link_table").alias("table_id"), F.col("table_id").alias("to")), "table_id").select("query_id", F.col("to").alias("table_id"))).distinct()
    return wanted.select("query_id", "table_id").unionByName(reached)


def order_tables(candidates: DataFrame, found: DataFrame) -> DataFrame:
    """(query_id, table_id, n_known, place): tables by how many conditions occur in them, most first, ties by id."""
    known = found.groupBy("query_id", "table_id").agg(F.count_distinct("cond").alias("n_known"))
    order = Window.partitionBy("query_id").orderBy(F.desc("n_known"), "table_id")
    return candidates.join(known, ["query_id", "table_id"], "left").withColumn("n_known", F.coalesce("n_known", F.lit(0))).withColumn("place", F.row_number().over(order))


def split_keys(candidates: DataFrame, keys: DataFrame, found: DataFrame) -> DataFrame:
    """(query_id, n_conds, table_id, key_id, attr_id, bound, used): each key attribute, whether a condition's value
    occurs in it, and the key's conditions as bits."""
    held = found.where("attr_ok").groupBy("query_id", "n_conds", "table_id", "attr_id").agg(F.bit_or(F.expr("shiftleft(1L, cond)")).alias("bits"))
    whole = candidates.select("query_id", "n_conds", "table_id").join(keys.select("table_id", "key_id", "attr_id"), "table_id")
    joined = whole.join(held, ["query_id", "n_conds", "table_id", "attr_id"], "left")
    of_key = Window.partitionBy("query_id", "table_id", "key_id")
    return joined.withColumns({"bound": F.col("bits").isNotNull(), "used": F.coalesce(F.bit_or("bits").over(of_key), F.lit(0).cast("bigint"))}).drop("bits")


def links_of(inds: DataFrame, direction: str = "both") -> DataFrame:
    """(attr_id, link_table, link_attr, ind_id): where an attribute's values can be read, by inclusions either way."""
    out = inds.select(F.col("lhs_attr").alias("attr_id"), F.col("rhs_table").alias("link_table"), F.col("rhs_attr").alias("link_attr"), "ind_id")
    into = inds.select(F.col("rhs_attr").alias("attr_id"), F.col("lhs_table").alias("link_table"), F.col("lhs_attr").alias("link_attr"), "ind_id")
    both = {"out": out, "in": into, "both": out.unionByName(into)}[direction]
    return both.groupBy("attr_id", "link_table", "link_attr").agg(F.min("ind_id").alias("ind_id"))


def recover_values(store: Store, masks: DataFrame, missing: DataFrame, direction: str = "both", cover: str = "all", links: DataFrame | None = None) -> DataFrame:
    """(query_id, table_id, key_id, attr_id, value, link_attr, ind_id, met): values for the missing key attributes.

    They are read from linked rows that meet all conditions the key leaves unused, or, with cover="max", the
    greatest number of them; `met` has the conditions as bits. A key that leaves none unused recovers nothing.
    """
    if cover not in ("all", "max"):
        raise ValueError(f"no such cover: {cover}")
    open_ = missing.where(f"NOT bound AND used <> {_FULL}").withColumn("unused", F.expr(f"({_FULL}) & ~used"))
    linked = open_.join(links if links is not None else links_of(store.inds, direction), "attr_id")
    rows = masks.select("query_id", F.col("table_id").alias("link_table"), "row_id", "mask")
    read = linked.join(rows, ["query_id", "link_table"]).withColumn("met", F.expr("mask & unused"))
    if cover == "all":
        read = read.where("met = unused")
    else:
        best = Window.partitionBy("query_id", "key_id", "attr_id", "link_attr")
        read = read.where("met <> 0").withColumn("most", F.max(F.bit_count("met")).over(best)).where(F.bit_count("met") == F.col("most")).drop("most")
    cells = store.cells.select("row_id", F.col("attr_id").alias("link_attr"), F.col("val_norm").alias("value")).where("value IS NOT NULL")
    got = read.join(cells, ["row_id", "link_attr"])
    return got.groupBy("query_id", "table_id", "key_id", "attr_id", "value", "link_attr", "ind_id").agg(F.bit_or("met").alias("met"))


def answer(store: Store, batch: Batch, stop: str = "all", direction: str = "both", cover: str = "all", goal_filter: bool = True, use_fds: bool | str = False, max_hops: int = 1) -> DataFrame:
    """(query_id, table_id, row_id, stage, via, completeness): rows that answer each query.

    direct: one row holds all values. derived: a key of a goal table is completed by values read from linked tables. partial: no
    such row; the rows that hold most of the values. Queries pass on to a stage by an anti join with the one before.

    With `use_fds` a missing part is also read where a functional dependency of the catalog, of any table, gives it from what the
    query leaves unused; with `use_fds="rows"` where the target's own rows that meet the unused conditions agree on it.
    Parts that an inclusion of several attributes links are kept only where the linked table has them in one row.
    """
    from tabqa.session import written

    found = written(hits(store, batch).select("query_id", "cond", "n_conds", "table_id", "row_id", "attr_id", "attr_ok"), "query-hits")
    masks = written(row_masks(found), "query-masks")
    goal_tables = written(tables_with_labels(store, batch, found=found, hops=max_hops), "query-goals")
    direct = masks.where(f"mask = {_FULL}")
    if goal_filter:
        direct = direct.join(goal_tables, ["query_id", "table_id"], "left_semi")
    none = F.array().cast("array<string>")
    direct = direct.select("query_id", "table_id", "row_id", F.lit("direct").alias("stage"), none.alias("via"), F.lit(1.0).alias("completeness"))
    direct = written(direct, "query-direct")
    queries = batch.conditions.select("query_id", "n_conds").distinct()
    left = queries.join(direct.select("query_id").distinct(), "query_id", "left_anti")
    candidates = left.join(goal_tables, "query_id")
    parts = written(split_keys(candidates, store.keys, found), "query-keys")
    links = links_of(store.inds, direction)
    values = recover_values(store, masks, parts, direction, cover, links)
    if use_fds == "rows":
        values = values.unionByName(_recover_by_agreement(store, masks, parts))
    elif use_fds:
        values = values.unionByName(_recover_by_fds(store, found, parts))
    for _ in range(max_hops - 1):
        values = values.unionByName(_hop(store, masks, parts, values, links))
    values = written(values, "query-values")
    derived = _probe(store, found, parts, values)
    if store.composites is not None:
        derived = _together(store, parts, values, derived)
    if stop == "first":
        derived = _first_only(derived, order_tables(candidates, found))
    derived = written(derived, "query-derived")
    rest = left.join(derived.select("query_id").distinct(), "query_id", "left_anti")
    most = Window.partitionBy("query_id")
    some = masks.join(rest.select("query_id"), "query_id", "left_semi").withColumn("n", F.bit_count("mask"))
    partial = some.withColumn("most", F.max("n").over(most)).where("n = most").select("query_id", "table_id", "row_id", F.lit("partial").alias("stage"), none.alias("via"), (F.col("n") / F.col("n_conds")).alias("completeness"))
    return direct.unionByName(derived.select(*direct.columns)).unionByName(partial)


def _probe(store: Store, found: DataFrame, parts: DataFrame, values: DataFrame) -> DataFrame:
    """Rows of the target tables whose key attributes all hold a bound or a recovered value."""
    size = parts.groupBy("query_id", "n_conds", "table_id", "key_id").agg(F.count(F.lit(1)).alias("size"), F.max("used").alias("used"), F.bool_and("bound").alias("whole"))
    bound = parts.where("bound").join(found.where("attr_ok").select("query_id", "table_id", "row_id", "attr_id").distinct(), ["query_id", "table_id", "attr_id"])
    bound = bound.select("query_id", "table_id", "key_id", "row_id", "attr_id", F.lit(None).cast("string").alias("via"), F.lit(0).cast("bigint").alias("met"))
    cells = store.cells.where("val_norm IS NOT NULL").select("table_id", "row_id", "attr_id", F.col("val_norm").alias("value"))
    read = values.join(cells, ["table_id", "attr_id", "value"])
    read = read.select("query_id", "table_id", "key_id", "row_id", "attr_id", F.concat_ws("=", "link_attr", "value").alias("via"), "met")
    met = bound.unionByName(read).groupBy("query_id", "table_id", "key_id", "row_id").agg(F.count_distinct("attr_id").alias("n"), F.array_sort(F.collect_set("via")).alias("via"), F.bit_or("met").alias("met"))
    done = met.join(size.where("NOT whole"), ["query_id", "table_id", "key_id"]).where("n = size").withColumn("consumed", F.expr("bit_count(met | used)"))
    done = done.where("size(via) > 0").withColumn("completeness", F.col("consumed") / F.col("n_conds")).withColumn("stage", F.when(F.col("consumed") == F.col("n_conds"), "derived").otherwise("partial"))
    best = Window.partitionBy("query_id", "table_id", "row_id").orderBy(F.desc("completeness"), "key_id")
    one = done.withColumn("r", F.row_number().over(best)).where("r = 1")
    full = Window.partitionBy("query_id")
    return one.withColumn("whole", F.max(F.col("stage") == "derived").over(full)).where("NOT whole OR stage = 'derived'").select("query_id", "table_id", "row_id", "stage", "via", "completeness", "key_id")


def _first_only(derived: DataFrame, order: DataFrame) -> DataFrame:
    """The rows of each query's best-ordered table and key that answer."""
    placed = derived.join(order.select("query_id", "table_id", "place"), ["query_id", "table_id"])
    first = Window.partitionBy("query_id").orderBy("place", "key_id")
    return placed.withColumn("d", F.dense_rank().over(first)).where("d = 1").drop("d", "place")


def _hop(store: Store, masks: DataFrame, parts: DataFrame, values: DataFrame, links: DataFrame) -> DataFrame:
    """Values read over one link more: a linked row that meets conditions leads, by a link of another of its attributes,
    to rows of a third table, where the missing attribute's link is read."""
    known = values.select("query_id", "key_id", "attr_id").distinct()
    open_ = parts.where(f"NOT bound AND used <> {_FULL}").withColumn("unused", F.expr(f"({_FULL}) & ~used")).join(known, ["query_id", "key_id", "attr_id"], "left_anti")
    last = open_.join(links.withColumnRenamed("link_table", "mid_table"), "attr_id")  # where the value will be read
    attrs = store.attrs.select(F.col("table_id").alias("mid_table"), F.col("attr_id").alias("mid_attr"))
    through = last.join(attrs, "mid_table").where("mid_attr <> link_attr")
    onward = links.select(F.col("attr_id").alias("mid_attr"), F.col("link_table").alias("far_table"), F.col("link_attr").alias("far_attr"))
    rows = masks.select("query_id", F.col("table_id").alias("far_table"), F.col("row_id").alias("far_row"), "mask")
    far = through.join(onward, "mid_attr").join(rows, ["query_id", "far_table"]).withColumn("met", F.expr("mask & unused")).where("met = unused")
    cells = store.cells.where("val_norm IS NOT NULL")
    far = far.join(cells.select(F.col("row_id").alias("far_row"), F.col("attr_id").alias("far_attr"), F.col("val_norm").alias("bridge")), ["far_row", "far_attr"])
    mid = far.join(cells.select(F.col("attr_id").alias("mid_attr"), F.col("val_norm").alias("bridge"), F.col("row_id").alias("mid_row")), ["mid_attr", "bridge"])
    got = mid.join(cells.select(F.col("row_id").alias("mid_row"), F.col("attr_id").alias("link_attr"), F.col("val_norm").alias("value")), ["mid_row", "link_attr"])
    return got.groupBy("query_id", "table_id", "key_id", "attr_id", "value", "link_attr", "ind_id").agg(F.bit_or("met").alias("met"))


def _recover_by_fds(store: Store, found: DataFrame, parts: DataFrame) -> DataFrame:
    """Values of a missing attribute that a functional dependency of the catalog gives.

    The dependency may be any table's whose right side has the missing attribute's label: a row of that table in which unused
    conditions meet all of the left side holds the value, and every row with that left side holds the same one.
    """
    labels = store.attrs.select("attr_id", F.lower(F.trim("label")).alias("label"))
    open_ = parts.where(f"NOT bound AND used <> {_FULL}").withColumn("unused", F.expr(f"({_FULL}) & ~used")).join(labels, "attr_id")
    right = store.fds.select("fd_id", "rhs_attr", "n_lhs").distinct().join(labels.withColumnRenamed("attr_id", "rhs_attr"), "rhs_attr")
    left = store.fds.select("fd_id", F.col("lhs_attr").alias("met_attr"))
    asked = open_.join(right, "label").join(left, "fd_id")
    met = found.where("attr_ok").select("query_id", "cond", "row_id", F.col("attr_id").alias("met_attr"))
    rows = asked.join(met, ["query_id", "met_attr"]).where("shiftright(unused, cond) & 1 = 1")
    rows = rows.groupBy("query_id", "table_id", "key_id", "attr_id", "fd_id", "rhs_attr", "n_lhs", "unused", "row_id").agg(F.count_distinct("met_attr").alias("n"), F.bit_or(F.expr("shiftleft(1L, cond)")).alias("met"))
    cells = store.cells.where("val_norm IS NOT NULL").select("row_id", F.col("attr_id").alias("rhs_attr"), F.col("val_norm").alias("value"))
    got = rows.where("n = n_lhs AND met = unused").join(cells, ["row_id", "rhs_attr"])
    return got.groupBy("query_id", "table_id", "key_id", "attr_id", "value", F.col("rhs_attr").alias("link_attr"), F.concat(F.lit("fd:"), "fd_id").alias("ind_id")).agg(F.bit_or("met").alias("met"))


def _recover_by_agreement(store: Store, masks: DataFrame, parts: DataFrame) -> DataFrame:
    """Values of a missing attribute on which the target's own rows agree: those that meet all unused conditions."""
    open_ = parts.where(f"NOT bound AND used <> {_FULL}").withColumn("unused", F.expr(f"({_FULL}) & ~used"))
    rows = open_.join(masks.select("query_id", "table_id", "row_id", "mask"), ["query_id", "table_id"]).where("(mask & unused) = unused")
    cells = store.cells.where("val_norm IS NOT NULL").select("row_id", "attr_id", F.col("val_norm").alias("value"))
    got = rows.join(cells, ["row_id", "attr_id"]).groupBy("query_id", "table_id", "key_id", "attr_id").agg(F.count_distinct("value").alias("n"), F.min("value").alias("value"), F.max("unused").alias("met")).where("n = 1")
    return got.select("query_id", "table_id", "key_id", "attr_id", "value", F.col("attr_id").alias("link_attr"), F.concat(F.lit("rows:"), "attr_id").alias("ind_id"), "met")


def _together(store: Store, parts: DataFrame, values: DataFrame, derived: DataFrame) -> DataFrame:
    """The derived rows without those whose missing parts, though each is read from a table, stand in no one row of it.

    Only parts count whose attributes an inclusion of several pairs links with one table, as one set.
    """
    c = store.composites
    sides = c.select("ind_id", "pos", F.col("lhs_attr").alias("attr_id"), F.col("rhs_table").alias("far_table"), F.col("rhs_attr").alias("far_attr"), "arity")
    sides = sides.unionByName(c.select("ind_id", "pos", F.col("rhs_attr").alias("attr_id"), F.col("lhs_table").alias("far_table"), F.col("lhs_attr").alias("far_attr"), "arity"))
    missing = parts.where("NOT bound").select("query_id", "table_id", "key_id", "attr_id")
    read = values.select("query_id", "key_id", "attr_id", F.col("link_attr").alias("far_attr")).distinct()
    asked = derived.select("query_id", "table_id", "row_id", "key_id").join(missing, ["query_id", "table_id", "key_id"]).join(sides, "attr_id").join(read, ["query_id", "key_id", "attr_id", "far_attr"])
    cells = store.cells.where("val_norm IS NOT NULL")
    own = asked.join(cells.select("row_id", "attr_id", "val_norm"), ["row_id", "attr_id"])
    tuple_of = F.transform(F.array_sort(F.collect_list(F.struct("pos", "val_norm"))), lambda x: x["val_norm"]).alias("held")
    whole = own.groupBy("query_id", "row_id", "key_id", "ind_id", "far_table", "arity").agg(tuple_of).where("size(held) = arity")
    far = sides.select("ind_id", "pos", "far_table", "far_attr").join(cells.select(F.col("row_id").alias("far_row"), F.col("attr_id").alias("far_attr"), "val_norm"), "far_attr")
    far = far.join(whole.select("ind_id", "far_table").distinct(), ["ind_id", "far_table"], "left_semi").groupBy("ind_id", "far_table", "far_row").agg(tuple_of)
    apart = whole.join(far, ["ind_id", "far_table", "held"], "left_anti").select("query_id", "row_id", "key_id").distinct()
    return derived.join(apart, ["query_id", "row_id", "key_id"], "left_anti").select(*derived.columns)


# What else to specify ----------------------------------------------------------------------------------------------------


def suggest_parameters(store: Store, batch: Batch, answers: DataFrame, by: str = "catalog") -> DataFrame:
    """(query_id, table_id, attrs): the smallest sets of attributes whose values would make an ambiguous answer unique.

    From the catalog: a minimal key without what is bound. From the answers: minimal keys of the answer rows themselves.
    """
    many = answers.groupBy("query_id", "table_id").agg(F.count_distinct("row_id").alias("n")).where("n > 1").select("query_id", "table_id")
    held = hits(store, batch).where("attr_ok").join(answers.select("query_id", "table_id", "row_id"), ["query_id", "table_id", "row_id"], "left_semi")
    bound = held.select("query_id", "table_id", "attr_id").distinct()
    labels = store.attrs.select("attr_id", "label")
    if by == "catalog":
        keys = many.join(store.keys, "table_id").join(bound, ["query_id", "table_id", "attr_id"], "left_anti").join(labels, "attr_id")
        sets = keys.groupBy("query_id", "table_id", "key_id").agg(F.array_sort(F.collect_set("label")).alias("a"))
    elif by == "answers":
        free = answers.join(many, ["query_id", "table_id"], "left_semi").join(store.cells.select("row_id", "attr_id", "val_norm"), "row_id").join(bound, ["query_id", "table_id", "attr_id"], "left_anti").join(labels, "attr_id")

        def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
            wide = group.pivot_table(index="row_id", columns="label", values="val_norm", aggfunc="first", dropna=False).fillna("\x00")
            out: list[tuple[str, ...]] = []
            for size in range(1, len(wide.columns) + 1):
                out = [c for c in combinations(sorted(wide.columns), size) if len(wide.drop_duplicates(list(c))) == len(wide)]
                if out:
                    break
            return pd.DataFrame([(*key, ",".join(c), list(c)) for c in out], columns=["query_id", "table_id", "key_id", "a"])

        sets = free.select("query_id", "table_id", "row_id", "label", "val_norm").groupBy("query_id", "table_id").applyInPandas(run, "query_id string, table_id string, key_id string, a array<string>")
    else:
        raise ValueError(f"no such way: {by}")
    least = Window.partitionBy("query_id")
    return sets.withColumn("least", F.min(F.size("a")).over(least)).where("size(a) = least").select("query_id", "table_id", F.array_join("a", ",").alias("attrs")).distinct()
