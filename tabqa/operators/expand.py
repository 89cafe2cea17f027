"""Unfolding compact tables into flat rows, and folding relations into compact tables.

A layout family says where the plain area lies, which columns and rows beside it carry keys, and the pivot that slides
over the plain area. Each pivot position is one element of a sequence: its side and band cells are array look-ups, so
unfolding is one narrow stage.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, StringType, StructField, StructType


@dataclass(frozen=True)
class FamilySpec:
    """A layout family. Rows and columns count from 0; negative ones from the far end. A pivot size of 0 takes the whole area."""

    family: str
    data_row: int = 1
    data_col: int = 0
    foot_rows: int = 0
    foot_cols: int = 0
    side_cols: tuple[int, ...] = ()
    band_rows: tuple[int, ...] = ()
    pivot_w: int = 0
    pivot_h: int = 1
    band_width: str = "first"
    ragged: str = "pad"
    name_cells: tuple[tuple[int, int], ...] = field(default=())

    def __post_init__(self):
        if self.ragged not in ("pad", "drop", "error") or self.band_width not in ("first", "all"):
            raise ValueError(f"{self.family}: unknown option")


REGISTRY_SCHEMA = "family string, data_row int, data_col int, foot_rows int, foot_cols int, side_cols array<int>, band_rows array<int>, pivot_w int, pivot_h int, band_width string, ragged string, name_cells array<struct<r:int,c:int>>"


def family_registry(spark: SparkSession, specs: Sequence[FamilySpec]) -> DataFrame:
    """The families as a small frame; its size is the number of families."""
    return spark.createDataFrame([tuple(list(v) if isinstance(v, tuple) else v for v in vars(s).values()) for s in specs], REGISTRY_SCHEMA)


#: Vector of the pivot position p: side cells, band cells, pivot cells. Written in SQL for its nested lambdas.
_VECTOR = """concat(
  transform(side_cols, s -> get(get(grid, data_row + cast(p div across as int) * ph), if(s < 0, width + s, s))),
  flatten(transform(band_rows, b -> transform(sequence(0, if(band_width = 'all', pw - 1, 0)), v -> get(get(grid, if(b < 0, height + b, b)), data_col + cast(p % across as int) * pw + v)))),
  flatten(transform(sequence(0, ph - 1), u -> transform(sequence(0, pw - 1), v ->
    if(cast(p div across as int) * ph + u < rows and cast(p % across as int) * pw + v < cols, get(get(grid, data_row + cast(p div across as int) * ph + u), data_col + cast(p % across as int) * pw + v), null)))))"""


def unfold(grids: DataFrame, registry: DataFrame, keep_missing: bool = True) -> DataFrame:
    """table_id, row_no and values of every pivot position of (table_id, family, grid).

    An area that the pivot doesn't divide is padded with nulls, cut, or refused, as the family says. Without `keep_missing`
    positions whose pivot cells are all missing go.
    """
    sized = grids.join(F.broadcast(registry), "family").withColumns({"height": F.size("grid"), "width": F.coalesce(F.aggregate("grid", F.lit(0), lambda w, r: F.greatest(w, F.size(r))), F.lit(0))})
    sized = sized.withColumns({"rows": F.greatest(F.expr("height - data_row - foot_rows"), F.lit(0)), "cols": F.greatest(F.expr("width - data_col - foot_cols"), F.lit(0))})
    sized = sized.withColumns({"pw": F.expr("if(pivot_w = 0, greatest(cols, 1), pivot_w)"), "ph": F.expr("if(pivot_h = 0, greatest(rows, 1), pivot_h)")})
    sized = sized.withColumns({"across": F.expr("if(ragged = 'drop', cast(floor(cols / pw) as int), cast(ceil(cols / pw) as int))"), "down": F.expr("if(ragged = 'drop', cast(floor(rows / ph) as int), cast(ceil(rows / ph) as int))")})
    sized = sized.withColumn("grid", F.expr("if(ragged = 'error' and (cols % pw <> 0 or rows % ph <> 0), raise_error(concat('pivot does not divide table ', table_id)), grid)"))
    vectors = F.expr(f"if(across * down > 0, transform(sequence(0, across * down - 1), p -> {_VECTOR}), cast(array() as array<array<string>>))")
    flat = sized.select("table_id", F.expr("size(side_cols) + size(band_rows) * if(band_width = 'all', pw, 1)").alias("key_width"), F.posexplode(vectors).alias("row_no", "values"))
    if not keep_missing:
        flat = flat.where(F.exists(F.slice("values", F.col("key_width") + 1, F.size("values")), lambda v: v.isNotNull() & ~F.lower(F.trim(v)).isin("", "n/a", "na", "-", "–")))
    return flat.select("table_id", "row_no", "values")


def unfold_cells(cells: DataFrame, spec: FamilySpec) -> DataFrame:
    """The same from (table_id, r, c, text), for tables too large for one row: two joins on row and column."""
    if spec.foot_rows or spec.foot_cols or any(x < 0 for x in (*spec.side_cols, *spec.band_rows)) or spec.pivot_h != 1 or spec.pivot_w < 1:
        raise ValueError("long-form unfolding takes pivots of height one with keys left and above")
    data = cells.where((F.col("r") >= spec.data_row) & (F.col("c") >= spec.data_col)).withColumn("j", F.floor((F.col("c") - spec.data_col) / spec.pivot_w).cast("int"))
    pivots = data.groupBy("table_id", "r", "j").agg(F.transform(F.array_sort(F.collect_list(F.struct("c", "text"))), lambda x: x["text"]).alias("pivot"))
    side = cells.where(F.col("c").isin(*spec.side_cols) & (F.col("r") >= spec.data_row)).groupBy("table_id", "r").agg(F.transform(F.array_sort(F.collect_list(F.struct("c", "text"))), lambda x: x["text"]).alias("side"))
    band = cells.where(F.col("r").isin(*spec.band_rows) & (F.col("c") >= spec.data_col) & ((F.col("c") - spec.data_col) % spec.pivot_w == 0))
    band = band.withColumn("j", F.floor((F.col("c") - spec.data_col) / spec.pivot_w).cast("int")).groupBy("table_id", "j").agg(F.transform(F.array_sort(F.collect_list(F.struct("r", "text"))), lambda x: x["text"]).alias("band"))
    last = cells.groupBy("table_id").agg(F.ceil((F.max("c") + 1 - spec.data_col) / spec.pivot_w).cast("int").alias("across"))
    joined = pivots.join(side, ["table_id", "r"], "left").join(band, ["table_id", "j"], "left").join(last, "table_id")
    empty = F.array().cast("array<string>")
    return joined.select("table_id", ((F.col("r") - spec.data_row) * F.col("across") + F.col("j")).cast("int").alias("row_no"), F.concat(F.coalesce("side", empty), F.coalesce("band", empty), "pivot").alias("values"))


def fold(relation: DataFrame, table_id: str, side: Sequence[str], band: Sequence[str], pivot: Sequence[str], sub_header: Sequence[str] = (), labels: Sequence[str] = (), missing: str = "n/a") -> DataFrame:
    """(table_id, grid): a matrix with side keys left, band keys above (after constant `labels` rows), and pivot cells.

    One aggregation gathers a table's rows, since a printed table is one row of a frame; `table_id` names a column of the relation.
    """
    text = lambda c: F.col(c).cast("string")
    key = lambda cs: F.array(*(text(c) for c in cs))
    gathered = relation.groupBy(table_id).agg(
        F.array_sort(F.collect_set(key(side))).alias("sides"), F.array_sort(F.collect_set(key(band))).alias("bands"),
        F.map_from_entries(F.collect_list(F.struct(F.array_join(F.concat(key(side), key(band)), "\x1f"), key(pivot)))).alias("cells"),
    )
    w, s = len(pivot), len(side)
    blank = f"array_repeat('', {s})"
    tops = [f"concat({blank}, array_repeat('{label}', size(bands) * {w}))" for label in labels]
    tops += [f"concat({blank}, flatten(transform(bands, b -> array_repeat(b[{i}], {w}))))" for i in range(len(band))]
    if sub_header:
        tops.append(f"concat({blank}, flatten(transform(bands, b -> array({', '.join(repr(h) for h in sub_header)}))))")
    body = f"transform(sides, s -> concat(s, flatten(transform(bands, b -> coalesce(cells[array_join(concat(s, b), '\x1f')], array_repeat('{missing}', {w}))))))"
    return gathered.select(F.col(table_id).alias("table_id"), F.expr(f"concat(array({', '.join(tops)}), {body})").alias("grid"))


def unspan(raw: DataFrame) -> DataFrame:
    """(…, grid) from (…, cells: array of r, c, rs, cs, text): a spanning cell's text at each place it covers.

    Each cell writes its own places, so the work is the size of the grid. Where cells overlap the first one stands.
    """
    keys = [f for f in raw.schema.fields if f.name != "cells"]
    schema = StructType([*keys, StructField("grid", ArrayType(ArrayType(StringType())))])
    names = schema.names

    def grid_of(cells: list[dict] | None) -> list[list[str | None]]:
        height = max((x["r"] + x["rs"] for x in cells or ()), default=0)
        width = max((x["c"] + x["cs"] for x in cells or ()), default=0)
        grid = [[None] * width for _ in range(height)]
        for x in reversed(cells or ()):
            for row in grid[x["r"] : x["r"] + x["rs"]]:
                row[x["c"] : x["c"] + x["cs"]] = [x["text"]] * x["cs"]
        return grid

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            grids = pa.array([grid_of(cells.as_py()) for cells in batch.column(len(keys))], pa.list_(pa.list_(pa.string())))
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keys)], grids], names)

    return raw.select(*(f.name for f in keys), "cells").mapInArrow(run, schema)


def expanded_names(grid_row, spec: FamilySpec, labels: Sequence[str] | None = None) -> list[str]:
    """Names of an unfolded table's columns: what the family's name cells hold, else column_k."""
    width = len(spec.side_cols) + len(spec.band_rows) + max(1, spec.pivot_w) * max(1, spec.pivot_h)
    names = [grid_row[r][c] if r < len(grid_row) and c < len(grid_row[r]) else "" for r, c in spec.name_cells] + [""] * width
    return [n.strip() if n and n.strip() else (labels[i] if labels and i < len(labels) else f"column_{i + 1}") for i, n in enumerate(names[:width])]
