"""From a grid to its layout: header boundaries by masks, and features that don't depend on content.

A grid is ARRAY<ARRAY<STRING>>, one row of a frame per table. Masks and features are higher-order functions; the boundaries, which
need counts from the end of a line on, are an Arrow pass over the masks. Nothing here shuffles.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from tabqa.functions.text import MISSING, mask_text


def transpose(grid: Column) -> Column:
    width = F.aggregate(grid, F.lit(0), lambda w, row: F.greatest(w, F.size(row)))
    columns = F.when(width > 0, F.sequence(F.lit(0), width - 1)).otherwise(F.array().cast("array<int>"))
    return F.transform(columns, lambda j: F.transform(grid, lambda row: F.get(row, j)))


def reversed_grid(grid: Column, rows: bool = True) -> Column:
    return F.reverse(grid) if rows else F.transform(grid, lambda row: F.reverse(row))


def _mask_or_null(cell: Column) -> Column:
    return F.when(F.lower(F.trim(cell)).isin(*MISSING) | cell.isNull(), F.lit(None)).otherwise(mask_text(cell))


def first_change(masks: list[str], max_period: int, share: float) -> int | None:
    """First place where the mask changes and then repeats with the smallest period that fits; None where there is none.

    One pass from the end counts, for each period, how many of the later places repeat.
    """
    n, found = len(masks), None
    same = [0] * (max_period + 1)
    for i in range(n - 1, 0, -1):
        fits = False
        for p in range(1, max_period + 1):
            if i + p < n:
                again = masks[i] == masks[i + p]
                same[p] += again
                fits |= again and same[p] >= share * (n - p - i)
        if fits and masks[i - 1] != masks[i]:
            found = i
    return found


def majority_start(masks: list[str], theta: float) -> int | None:
    """First place where the mask changes and from which on it has at least the share theta."""
    n, found = len(masks), None
    later: Counter[str] = Counter()
    for i in range(n - 1, 0, -1):
        later[masks[i]] += 1
        if masks[i - 1] != masks[i] and later[masks[i]] >= theta * (n - i):
            found = i
    return found


def vote(lines: Iterable[list[str | None]], place: Callable[[list[str]], int | None]) -> int:
    """What most lines of cells say, ties to the smallest; lines without a place abstain, and 0 where all do. Missing cells don't count."""
    votes: Counter[int] = Counter()
    for line in lines:
        held = [(i, m) for i, m in enumerate(line) if m is not None]
        at = place([m for _, m in held])
        if at is not None:
            votes[held[at][0]] += 1
    return min(votes, key=lambda v: (-votes[v], v), default=0)


SIDES = ("top", "left", "bottom", "right")


def masks_of(grid: Column) -> Column:
    """The grid of the cells' masks, null for missing ones."""
    return F.transform(grid, lambda row: F.transform(row, _mask_or_null))


def with_starts(grids: DataFrame, names: dict[str, str], rule: str = "repeat", theta: float = 0.8, max_period: int = 3, share: float = 0.5) -> DataFrame:
    """Adds, under the names given for some sides, how many header rows or columns each grid has there. Linear in the grid.

    On a side each line of cells votes for where its masks change and then repeat; ties go to the smallest, none gives 0.
    """
    if rule not in ("repeat", "majority"):
        raise ValueError(f"no such rule: {rule}")

    def place(line: list[str]) -> int | None:
        return majority_start(line, theta) if rule == "majority" else first_change(line, max_period, share)

    def found(grid: list[list[str | None]] | None, side: str) -> int:
        rows = grid or []
        width = max(map(len, rows), default=0)
        lines = [[*row, *[None] * (width - len(row))] for row in rows]
        lines = lines if side in ("left", "right") else [list(column) for column in zip(*lines, strict=True)]
        return vote((line[::-1] for line in lines) if side in ("bottom", "right") else lines, place)

    out = StructType([*grids.schema.fields, *(StructField(name, IntegerType()) for name in names.values())])
    columns = out.names

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            masks = batch.column(batch.num_columns - 1).to_pylist()
            counts = [pa.array([found(grid, side) for grid in masks], pa.int32()) for side in names]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *counts], columns)

    return grids.withColumn("__masks", masks_of(F.col("grid"))).mapInArrow(run, out)


def find_data_start(grids: DataFrame, rule: str = "repeat", transposed: bool = False, backwards: bool = False, name: str = "data_row", **options) -> DataFrame:
    """Adds the number of header rows (columns with `transposed`) at the top (bottom with `backwards`)."""
    side = {(False, False): "top", (True, False): "left", (False, True): "bottom", (True, True): "right"}[transposed, backwards]
    return with_starts(grids, {side: name}, rule, **options)


def layout_features(grids: DataFrame, spans: str | None = None) -> DataFrame:
    """f1..f9 as doubles: header rows and columns, repeats of the last header row's group, spanning headers, empty corner cells,
    header rows below and columns right, numeric share of the plain area, and the mask period down the plain columns."""
    out = with_starts(grids, {"top": "f1", "left": "f2", "bottom": "f6", "right": "f7"})
    grid = F.col("grid")
    header = F.when(F.col("f1") > 0, F.filter(F.slice(F.get(grid, F.col("f1") - 1), F.col("f2") + 1, F.size(F.get(grid, F.col("f1") - 1))), lambda c: c.isNotNull())).otherwise(F.array().cast("array<string>"))
    n = F.size(header)
    periods = F.when(n > 0, F.sequence(F.lit(1), n)).otherwise(F.array().cast("array<int>"))
    period = F.get(F.filter(periods, lambda p: (n % p == 0) & F.forall(F.sequence(F.lit(0), n - 1), lambda i: F.get(header, i) == F.get(header, i % p))), F.lit(0))
    corner = F.flatten(F.transform(F.slice(grid, 1, F.greatest(F.col("f1"), F.lit(0))), lambda row: F.slice(row, 1, F.col("f2"))))
    top = F.slice(grid, 1, F.greatest(F.col("f1") - 1, F.lit(0)))
    spanning = F.exists(top, lambda row: F.exists(F.sequence(F.lit(1), F.greatest(F.size(row) - 1, F.lit(1))), lambda j: F.coalesce((F.get(row, j) == F.get(row, j - 1)) & (F.trim(F.get(row, j)) != ""), F.lit(False))))
    plain = F.transform(F.slice(grid, F.col("f1") + 1, F.size(grid)), lambda row: F.slice(row, F.col("f2") + 1, F.size(row)))
    cells = F.filter(F.flatten(plain), lambda c: c.isNotNull())
    numeric = F.size(F.filter(cells, lambda c: c.rlike(r"^[+-]?\d+([.,]\d+)?$"))) / F.greatest(F.size(cells), F.lit(1))
    masks = F.transform(transpose(plain), lambda column: F.transform(column, lambda c: mask_text(F.coalesce(c, F.lit("")))))
    steps = lambda p: F.aggregate(masks, F.lit(0.0), lambda s, column: s + F.size(F.filter(F.sequence(F.lit(0), F.greatest(F.size(column) - 1 - p, F.lit(0))), lambda i: F.coalesce(F.get(column, i) == F.get(column, i + p), F.lit(False)))) / F.greatest(F.size(column) - p, F.lit(1)))
    best = F.array_min(F.transform(F.array(*(F.struct((-steps(p)).alias("s"), F.lit(p).alias("p")) for p in (1, 2, 3))), lambda x: F.struct(x["s"].alias("s"), x["p"].alias("p"))))["p"]
    out = out.withColumns({"f3": F.coalesce(n / period, F.lit(0)), "f4": spanning, "f5": F.size(F.filter(corner, lambda c: c.isNull() | (F.trim(c) == ""))), "f8": numeric, "f9": best})
    return out.withColumns({f"f{i}": F.col(f"f{i}").cast("double") for i in range(1, 10)})
