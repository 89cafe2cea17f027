"""From pages to a store that can be asked: tables, grids, layout, family, flat rows, names, dependencies, index.

What is given beforehand are the families (registry), the parameters of a trained family model, and, where the printed table itself
doesn't name its columns, names by caption. Nothing is marked in single tables.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tabqa.functions.text import MISSING
from tabqa.operators import deps, expand, family_model, layout
from tabqa.operators import store as stores
from tabqa.session import written
from tabqa.sources.html_tables import extract_tables


def grids_of(pages: DataFrame, nested: str = "text") -> DataFrame:
    """(table_id, doc_id, caption, grid) of all tables of the pages (url, html). A document is a page."""
    return expand.unspan(extract_tables(pages, nested)).select("table_id", "doc_id", "caption", "grid")


def recognised(grids: DataFrame, parameters: DataFrame, min_log_density: float = -1e4, fallback: str = "plain_listing") -> DataFrame:
    """The grids with the family that the model assigns to each by its features."""
    features = layout.layout_features(grids.select("table_id", "grid")).select("table_id", *family_model.FEATURES)
    return grids.join(family_model.assign_family(features, parameters, min_log_density, fallback), "table_id")


def names_of(grids: DataFrame, registry: DataFrame) -> DataFrame:
    """(table_id, ord, label): what the printed tables call the columns of their flat rows.

    Key columns on the left are named by the corner cell in the last header row above them, pivot columns by the header row next to the
    data, if it isn't a key row of its own: a plain listing's header, or the sub-headers under a band key. What has no name gets none here.
    """
    sized = grids.select("table_id", "family", "grid").join(F.broadcast(registry), "family")
    # the vector's places: side keys, band keys, then the pivot's cells
    named = sized.where("data_row > 0").select("table_id", "side_cols", "data_col", "pivot_w", F.size("side_cols").alias("n_side"), F.size("band_rows").alias("n_band"), F.expr("get(grid, data_row - 1)").alias("head"))
    side = named.select("table_id", F.posexplode("side_cols").alias("ord", "c"), "head").select("table_id", "ord", F.expr("get(head, c)").alias("label"))
    width = F.when(F.col("pivot_w") > 0, F.col("pivot_w")).otherwise(F.size("head") - F.col("data_col"))
    # a pivot of one cell under a single key row has that row's key above it, which is no name
    own = named.where("pivot_w <> 1 OR n_band = 0").select("table_id", "head", "data_col", (F.col("n_side") + F.col("n_band")).alias("first"), F.posexplode(F.sequence(F.lit(0), F.greatest(width, F.lit(1)) - 1)).alias("p", "v"))
    pivot = own.select("table_id", (F.col("first") + F.col("p")).alias("ord"), F.expr("get(head, data_col + v)").alias("label"))
    return side.unionByName(pivot).where(F.col("label").isNotNull() & ~F.lower(F.trim("label")).isin(*MISSING))


def attributes_of(grids: DataFrame, flat: DataFrame, registry: DataFrame, names: DataFrame | None = None) -> DataFrame:
    """(table_id, ord, label, parent_label): a row for each column of the flat rows that isn't a label's.

    Key places that hold one value throughout are label rows and sub-headers, unless a name is given for them; what stands in a pivot's cells is data, though
    all of it may be equal. A column's label is the given name for tables of that caption (caption, ord, label[, parent_label]), else what the table itself calls it, else column_k.
    """
    places = flat.groupBy("table_id").agg(F.max(F.size("values")).alias("n")).select("table_id", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("ord"))
    width = F.expr("if(pivot_w = 0, greatest(aggregate(grid, 0, (w, r) -> greatest(w, size(r))) - data_col - foot_cols, 1), pivot_w)")
    n_keys = F.size("side_cols") + F.size("band_rows") * F.when(F.col("band_width") == "all", width).otherwise(1)
    keys = grids.select("table_id", "family", "grid").join(F.broadcast(registry), "family").where(n_keys > 0).select("table_id", F.explode(F.sequence(F.lit(0), n_keys - 1)).alias("ord"))
    labels = stores.constant_columns(flat).join(keys, ["table_id", "ord"], "left_semi")
    if names is not None:
        labels = labels.join(grids.select("table_id", "caption").join(names.select("caption", "ord"), "caption").select("table_id", "ord"), ["table_id", "ord"], "left_anti")
    places = places.join(labels, ["table_id", "ord"], "left_anti")
    out = places.join(names_of(grids, registry).withColumnRenamed("label", "own"), ["table_id", "ord"], "left")
    plain = F.concat(F.lit("column_"), (F.col("ord") + 1).cast("string"))
    if names is None:
        return out.select("table_id", "ord", F.coalesce(F.trim("own"), plain).alias("label"), F.lit(None).cast("string").alias("parent_label"))
    parent = F.col("parent_label") if "parent_label" in names.columns else F.lit(None).cast("string").alias("parent_label")
    given = grids.select("table_id", "caption").join(names.select("caption", "ord", F.col("label").alias("given"), parent), "caption").drop("caption")
    return out.join(given, ["table_id", "ord"], "left").select("table_id", "ord", F.coalesce("given", F.trim("own"), plain).alias("label"), "parent_label")


def ingest(pages: DataFrame, registry: DataFrame, parameters: DataFrame, names: DataFrame | None = None, document: str | None = None, nested: str = "text") -> stores.Store:
    """The store of all tables of the pages, with catalog and index. Families are assigned by the model.

    Inclusions are looked for within a document; `document` names the one that all pages belong to, where they are its parts.
    """
    found = grids_of(pages, nested)
    found = found.withColumn("doc_id", F.lit(document)) if document else found
    grids = written(recognised(found, parameters), "ingest-grids")
    flat = written(expand.unfold(grids, registry), "ingest-flat")
    tables = grids.select("table_id", "doc_id", "caption", F.lit(None).cast("int").alias("page_begin"), F.lit(None).cast("int").alias("page_end"), "family")
    attrs = attributes_of(grids, flat, registry, names)
    return cataloged(stores.load_store(flat, tables, attrs))


def cataloged(store: stores.Store, **options) -> stores.Store:
    """The store written, with its catalog of dependencies and its index: the offline part."""
    whole = deps.build_catalog(stores.held(store), **options)
    return replace(whole, index=stores.indexed(whole).index)
