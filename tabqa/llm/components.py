"""Connected components of links, distributed: alternating large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tabqa.session import discard, scratch, written


#: Edges to a file of a round, about.
FILE_EDGES = 50_000


def _stars(edges: DataFrame, large: bool, files: int) -> DataFrame:
    """One pass. Large: a node's greater neighbours are tied to the least of its neighbourhood; small: the others."""
    if large:
        sides = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
    else:
        sides = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    sides = written(sides.distinct().coalesce(2 * files), "star-sides")
    least = written(sides.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")).coalesce(files), "star-least")
    tied = sides.join(least, "u")
    if large:
        out = tied.where("v > u").select(F.col("v").alias("a"), F.col("m").alias("b"))
    else:
        out = tied.select(F.col("v").alias("a"), F.col("m").alias("b")).unionByName(least.select(F.col("u").alias("a"), F.col("m").alias("b")))
    return out.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def connected(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, component) for every node of an edge (a, b); the component is its smallest node.

    Each round is written to the shared folder. The edges form stars around the smallest nodes when a round
    changes nothing.
    """
    edges = written(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "star-edges")
    print_of = [F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))]
    seen = tuple(edges.agg(*print_of).first())
    files = max(1, seen[0] // FILE_EDGES)
    for _ in range(rounds):
        if not seen[0]:
            break
        with scratch():
            new = written(_stars(_stars(edges, True, files), False, files).coalesce(files), "star-edges", keep=True)
        discard(edges)
        edges, now = new, tuple(new.agg(*print_of).first())
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return edges.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("component")).unionByName(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
