"""Approximate nearest neighbours by a hash-prefix forest.

A tree gives every vector a long hash string: first the axis of a random rotation, and its sign, that the vector lies nearest to, then
one sign after another of its projections on random directions, 62 bits in all. A tree is its vectors' strings in sorted order. A query
descends each tree to its longest prefix match; then all trees ascend together, a digit at a time, until the subtrees they stand at hold
enough candidates. At the root of a tree stand all vectors, so a small table is searched whole, and so is any table with `exact`.

How deep a query may stop is measured: for a sample of the queries the true nearest are found by one pass over all vectors, with the
depth down to which each shares a subtree with its query. No query stops deeper than where the sample's recall, less two standard
errors, is what was asked for; where no depth has that recall, all vectors are searched. Strings with a digit for each bit make the depths
fine enough that little more than the recall asked for is paid for.

The distributed plan: the strings of all trees are one frame. Subtree sizes are one aggregation of it, and a query's depth follows from
the sizes at its own prefixes. Queries stop at a few depths, so that a few passes serve all: the deepest allowed one, and some above
it for queries in thinly held subtrees. For each, the vectors are sorted by tree and string into arrays, packed as blocks of bounded
size, and joined to blocks of the queries under the same prefix; a block pair scores its queries against its vectors by one matrix product
and passes on the best few of each. A subtree that holds very many vectors is many blocks. At the root vectors are dealt into
groups of bounded size instead, and each group meets all queries that end there.

Nearness is the inner product. Vectors are searched by direction of their augmented form (a further component makes all
lengths equal), so the longest inner products are the nearest angles. Scores are in double precision on the original vectors.

Vectors that are null, zero, or hold a null or non-finite component, or that have no id, take no part; nor do those of another width than
most have (of widths equally frequent the greater counts). Repeated (id, vector) rows count once; other columns take no part.
Ties go to the smaller id. An empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tabqa.llm.common import map_arrow
from tabqa.session import written

TREES = 28
#: Axes that the first digit chooses from; it has twice as many values. Every later digit is one bit.
AXES = 32
#: Bits of a hash string.
BITS = 62
#: Candidates, over all trees, at which the ascent stops, if the measured recall lets it go as deep: at least so many, and so many times the
#: square root of the number of vectors.
CANDIDATES = 6_000
PER_ROOT = 12
#: Depths that queries stop at, besides the root.
PASSES = 3
#: Vectors of a group at the root.
GROUP = 1 << 16
RECALL = 0.9
#: Queries on which recall is measured.
SAMPLE = 512
BLOCK = 256
QUERY_BLOCK = 256


def usable(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(vec_id, vector): the rows that take part, vectors as doubles."""
    chosen = vectors.select(F.col(id_col).cast("bigint").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("vector"))
    finite = F.forall("vector", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != F.lit(float("inf"))))
    return chosen.where(F.col("vec_id").isNotNull() & F.col("vector").isNotNull()).where(finite & F.exists("vector", lambda x: x != 0))


def of_one_width(vectors: DataFrame) -> tuple[DataFrame, int | None]:
    """The vectors of the commonest width, and that width."""
    widths = vectors.groupBy(F.size("vector").alias("width")).agg(F.count(F.lit(1)).alias("n"))
    found = widths.orderBy(F.desc("n"), F.desc("width")).first()
    return (vectors.where(F.size("vector") == found["width"]), found["width"]) if found else (vectors, None)


class Forest:
    """The rotations and directions of all trees, from a seed; `longest` is the greatest vector length.

    Level 0 is the root, level 1 the first digit, and each level more has a bit more.
    """

    def __init__(self, width: int, longest: float, trees: int = TREES, axes: int = AXES, seed: int = 17):
        self.width, self.longest, self.trees, self.axes, self.seed = width, longest, trees, min(axes, width + 1), seed
        self.first_bits = (2 * self.axes - 1).bit_length()
        self.levels = 1 + BITS - self.first_bits
        self._turns: tuple[np.ndarray, np.ndarray] | None = None

    def turns(self) -> tuple[np.ndarray, np.ndarray]:
        """The axes of all trees' first digits, and the directions of their bits, side by side."""
        if self._turns is None:
            rng, n = np.random.default_rng(self.seed), self.width + 1
            axes = np.hstack([np.linalg.qr(rng.normal(size=(n, n)))[0][:, : self.axes] for _ in range(self.trees)])
            self._turns = axes.astype(np.float32), rng.normal(size=(n, self.trees * (self.levels - 1))).astype(np.float32)
        return self._turns

    def augmented(self, x: np.ndarray, query: bool) -> np.ndarray:
        """Vectors with the component that makes their lengths equal; queries get none and length one."""
        square = (x * x).sum(axis=1)
        if query:
            return np.hstack([x / np.sqrt(square)[:, None], np.zeros((len(x), 1))]).astype(np.float32)
        return (np.hstack([x, np.sqrt(np.maximum(self.longest**2 - square, 0))[:, None]]) / self.longest).astype(np.float32)

    def strings(self, x: np.ndarray, query: bool) -> np.ndarray:
        """The hash string of each vector in each tree as an integer, its first digit highest."""
        full = self.augmented(x, query)
        axes, directions = self.turns()
        turned = (full @ axes).reshape(len(x), self.trees, self.axes)
        axis = np.abs(turned).argmax(axis=2)
        first = 2 * axis + (np.take_along_axis(turned, axis[:, :, None], 2)[:, :, 0] > 0)
        bits = (full @ directions > 0).reshape(len(x), self.trees, self.levels - 1)
        return (first << (self.levels - 1)) + bits @ (1 << np.arange(self.levels - 2, -1, -1, dtype=np.int64))

    def __getstate__(self):
        return self.__dict__ | {"_turns": None}

    def scale(self, level: int) -> int:
        """What a string is divided by for its prefix at a level below the root."""
        return 1 << (self.levels - level)

    def shared(self, one: np.ndarray, other: np.ndarray) -> np.ndarray:
        """The deepest level at which strings share a subtree in any tree; trees are the last axis."""
        unlike = (one ^ other).min(axis=-1)  # of all trees' the least has the longest common prefix
        for step in (1, 2, 4, 8, 16, 32):  # all bits below the highest, so that they can be counted
            unlike |= unlike >> step
        return np.maximum(self.levels - np.bitwise_count(unlike).astype(np.int64), 0)


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def hash_strings(vectors: DataFrame, forest: Forest, query: bool, single: bool) -> DataFrame:
    """(vec_id, vector as bytes, strings): each vector with its hash string in every tree.

    The bytes are single precision where that is what the vectors came in.
    """

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        x = _matrix(batch.column(1))
        strings = forest.strings(x, query)
        raw = [v.tobytes() for v in (x.astype(np.float32) if single else x)]
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(raw, pa.binary()), pa.array(list(strings), pa.list_(pa.int64()))], ["vec_id", "vector", "strings"])

    return map_arrow(vectors, run, "vec_id bigint, vector binary, strings array<bigint>", rows=2048)


def deepest_level(points: DataFrame, queries: DataFrame, forest: Forest, k: int, single: bool, recall: float = RECALL, sample: int = SAMPLE) -> int:
    """The deepest level at which a sample of the queries finds enough of its true k nearest; 0 where none does.

    One pass over the points; a task passes on one row, the sample's best of all its points.
    """
    kind = np.float32 if single else np.float64
    chosen = queries.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).collect()
    q_ids = np.array([r["vec_id"] for r in chosen], np.int64)
    q = np.array([np.frombuffer(r["vector"], kind) for r in chosen]).astype(np.float64)
    q_strings = np.array([r["strings"] for r in chosen], np.int64)
    n = len(chosen)

    def best(held: tuple[np.ndarray, ...] | None, more: tuple[np.ndarray, ...]) -> tuple[np.ndarray, ...]:
        """Scores, ids and depths of each query's k best; equal scores go to the smaller id."""
        joined = more if held is None else tuple(np.hstack(pair) for pair in zip(held, more, strict=True))
        order = np.lexsort((joined[1], -joined[0]), axis=1)[:, :k]
        return tuple(np.take_along_axis(x, order, axis=1) for x in joined)

    def packed(held: tuple[np.ndarray, ...] | None) -> Iterator[pa.RecordBatch]:
        if held is not None:
            yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in held], ["scores", "ids", "depths"])

    def opened(row: tuple[bytes, ...]) -> tuple[np.ndarray, ...]:
        return tuple(np.frombuffer(raw, t).reshape(n, -1) for raw, t in zip(row, (np.float64, np.int64, np.int64), strict=True))

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                part = batch.slice(at, 4096)
                ids, p = part.column(0).to_numpy(), np.frombuffer(b"".join(part.column(1).to_pylist()), kind).reshape(part.num_rows, -1).astype(np.float64)
                near = q @ p.T
                near[q_ids[:, None] == ids[None, :]] = -np.inf
                take = np.argpartition(-near, min(k, len(ids)) - 1, axis=1)[:, :k]
                strings = part.column(2).flatten().to_numpy().reshape(part.num_rows, -1)
                held = best(held, (np.take_along_axis(near, take, axis=1), ids[take], forest.shared(q_strings[:, None, :], strings[take])))
        yield from packed(held)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                held = best(held, opened(row))
        yield from packed(held)

    fields = "scores binary, ids binary, depths binary"
    rows = points.select("vec_id", "vector", "strings").mapInArrow(search, fields).repartition(8).mapInArrow(merge, fields).collect()
    held = None
    for row in rows:
        held = best(held, opened(tuple(map(bytes, row))))
    if held is None:
        return 0
    true = held[0] > -np.inf
    for level in range(forest.levels, 0, -1):
        found = ((held[2] >= level) & true).sum(axis=1)[true.any(axis=1)] / true.sum(axis=1)[true.any(axis=1)]
        if len(found) > 1 and found.mean() - 2 * found.std(ddof=1) / np.sqrt(len(found)) >= recall:
            return level
    return 0


def passes(deepest: int, most: int = PASSES) -> list[int]:
    """The levels that queries stop at: the deepest allowed, and some above it, evenly spread; the root comes on top."""
    return sorted({1 + round((deepest - 1) * k / max(1, most - 1)) for k in range(most)} if deepest > 1 else {deepest} - {0})


def stop_levels(points: DataFrame, queries: DataFrame, forest: Forest, candidates: int, deepest: int) -> DataFrame:
    """(query_id, level): the deepest of the levels, none below `deepest`, at which the query's subtrees in all trees hold enough vectors, or 0."""
    levels = passes(deepest)
    if not levels:
        return queries.select(F.col("vec_id").alias("query_id"), F.lit(0).alias("level"))
    shorten = F.expr(f"string div {forest.scale(deepest)}").alias("string")
    lowest = points.select(F.posexplode("strings").alias("tree", "string")).select("tree", shorten).groupBy("tree", "string").agg(F.count(F.lit(1)).alias("n"))
    asked = queries.select(F.col("vec_id").alias("query_id"), F.posexplode("strings").alias("tree", "string")).select("query_id", "tree", shorten)
    found = None
    for level in levels:
        prefix = F.expr(f"string div {1 << (deepest - level)}L").alias("prefix")
        sizes = lowest.select("tree", prefix, "n").groupBy("tree", "prefix").agg(F.sum("n").alias("n"))
        held = asked.select("query_id", "tree", prefix).join(sizes, ["tree", "prefix"]).groupBy("query_id").agg(F.sum("n").alias("n")).where(F.col("n") >= candidates)
        at = held.select("query_id", F.lit(level).alias("level"))
        found = at if found is None else found.unionByName(at)
    best = found.groupBy("query_id").agg(F.max("level").alias("level"))
    return queries.select(F.col("vec_id").alias("query_id")).distinct().join(best, "query_id", "left").select("query_id", F.coalesce("level", F.lit(0)).alias("level"))


def blocks(rows: DataFrame, size: int) -> DataFrame:
    """(tree, prefix, ids, vectors): sorted rows packed, at most `size` of one subtree to a block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[int, int, int, bytes, bytes]] = []  # pieces of the block that is open

        def flush() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([held[0][0]], pa.int32()), pa.array([held[0][1]], pa.int64()), pa.array([b"".join(h[3] for h in held)], pa.binary()), pa.array([b"".join(h[4] for h in held)], pa.binary())], ["tree", "prefix", "ids", "vectors"])

        for batch in batches:
            tree, prefix, ids = (batch.column(i).to_numpy() for i in range(3))
            vectors = batch.column(3)
            fresh = np.flatnonzero(np.concatenate(([True], (tree[1:] != tree[:-1]) | (prefix[1:] != prefix[:-1])))) if len(tree) else np.zeros(0, int)
            for first, last in zip(fresh.tolist(), [*fresh[1:].tolist(), len(tree)], strict=True):
                key = (int(tree[first]), int(prefix[first]))
                while first < last:
                    if held and (held[0][:2] != key or sum(h[2] for h in held) >= size):
                        yield flush()
                        held = []
                    n = min(last - first, size - sum(h[2] for h in held))
                    held.append((*key, n, ids[first : first + n].tobytes(), b"".join(vectors.slice(first, n).to_pylist())))
                    first += n
        if held:
            yield flush()

    order = ["tree", "prefix", "string", "vec_id"]  # the prefix begins the string: arrays sorted by string
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.select(*order, "vector").repartitionByRange(parts, *order).sortWithinPartitions(*order)
    return dealt.select("tree", "prefix", "vec_id", "vector").mapInArrow(run, "tree int, prefix bigint, ids binary, vectors binary")


def score_blocks(pairs: DataFrame, k: int, width: int, single: bool) -> DataFrame:
    """(query_id, vec_id, score): the k best of each block pair for each of its queries."""

    kind = np.float32 if single else np.float64

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        queries, found, scores = [], [], []
        for q_ids, q_raw, p_ids, p_raw in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
            q_ids, p_ids = np.frombuffer(q_ids, np.int64), np.frombuffer(p_ids, np.int64)
            q, p = (np.frombuffer(raw, kind).reshape(-1, width).astype(np.float64) for raw in (q_raw, p_raw))
            near = q @ p.T
            near[q_ids[:, None] == p_ids[None, :]] = -np.inf
            take = min(k, len(p_ids))
            # everything as near as the k-th, so that ties are settled by id later
            least = -np.partition(-near, take - 1, axis=1)[:, take - 1]
            row, column = np.nonzero((near >= least[:, None] - 1e-9 * np.abs(least[:, None])) & (near > -np.inf))
            # the matrix product may round differently from block to block; the score itself is one fixed sum
            queries.append(q_ids[row])
            found.append(p_ids[column])
            scores.append(np.einsum("ij,ij->i", q[row], p[column]))
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (queries, found, scores)], ["query_id", "vec_id", "score"])

    return map_arrow(pairs.select("q_ids", "q_vectors", "ids", "vectors"), run, "query_id bigint, vec_id bigint, score double", rows=16)


def _first_copies(vectors: DataFrame, keep: int) -> DataFrame:
    """Of many equal vectors only the `keep` smallest ids can be among a query's nearest; the rest stay out of the index.

    Equal vectors are as near to any query, and ties go to smaller ids, so this leaves every answer as it is.
    """
    digest = F.xxhash64("vector")
    copies = vectors.withColumn("print", digest).withColumn("other", F.xxhash64(F.lit(5), "vector"))
    crowded = copies.groupBy("print", "other").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > keep)
    listed = written(copies.join(crowded.select("print", "other"), ["print", "other"], "left_semi").select("vec_id", "print", "other", "vector"), "forest-crowded")
    if not listed.head(1):
        return vectors
    # the smallest ids of each crowd: first within slices of it, then of what the slices leave
    sliced = listed.withColumn("slice", F.pmod(F.xxhash64("vec_id"), F.lit(64)))
    within = Window.partitionBy("print", "other", "slice").orderBy("vec_id")
    some = sliced.withColumn("r", F.row_number().over(within)).where(F.col("r") <= keep).drop("r", "slice")
    best = some.withColumn("r", F.row_number().over(Window.partitionBy("print", "other").orderBy("vec_id"))).where(F.col("r") <= keep).select("vec_id", "vector")
    rest = copies.join(crowded.select("print", "other"), ["print", "other"], "left_anti").select("vec_id", "vector")
    return rest.unionByName(best)


def nearest(
    vectors: DataFrame,
    queries: DataFrame,
    k: int = 20,
    id_col: str = "vec_id",
    vector_col: str = "embedding",
    trees: int = TREES,
    candidates: int = CANDIDATES,
    recall: float = RECALL,
    exact: bool = False,
) -> DataFrame:
    """query_id, rank, vec_id, score: each query's k nearest found, nearest first; at least `recall` of the true ones on the average.

    With `exact` every query ends at the root, and the true nearest are found.
    """
    points, width = of_one_width(usable(vectors, id_col, vector_col).distinct())
    asked = usable(queries, id_col, vector_col).distinct()
    asked = asked.where(F.size("vector") == width) if width else asked
    if width is None or not asked.head(1):
        return vectors.sparkSession.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double")
    longest = points.agg(F.max(F.sqrt(F.aggregate("vector", F.lit(0.0), lambda s, x: s + x * x)))).first()[0]
    forest = Forest(width, longest, trees)
    single = dict(vectors.dtypes)[vector_col] == "array<float>"
    points = written(hash_strings(_first_copies(points, k + 1), forest, False, single), "forest-points")
    question = written(hash_strings(asked, forest, True, single), "forest-question")
    total = points.count()
    enough = max(candidates, round(PER_ROOT * total**0.5)) if candidates >= CANDIDATES else candidates
    # where not even all vectors of all trees are enough candidates, every query ends at the root
    deepest = deepest_level(points, question, forest, k, single, recall) if not exact and total * trees >= enough else 0
    levels = written(stop_levels(points, question, forest, enough, deepest), "forest-levels")
    found = None
    for level in sorted(r["level"] for r in levels.select("level").distinct().collect()):  # at most PASSES and the root
        own = question.join(levels.where(F.col("level") == level).select(F.col("query_id").alias("vec_id")), "vec_id", "left_semi")
        if level:
            prefix = F.expr(f"string div {forest.scale(level)}L").alias("prefix")
            at = lambda df: df.select("vec_id", "vector", F.posexplode("strings").alias("tree", "string")).select("vec_id", "vector", "tree", "string", prefix)  # noqa: B023, E731
            p, q = at(points), at(own)
            if level > 1:  # deep down most subtrees are nobody's; just below the root all are asked for
                p = p.join(q.select("tree", "prefix").distinct(), ["tree", "prefix"], "left_semi")
        else:  # at the root all vectors stand, in groups that all its queries meet
            groups = max(1, min(-(-total // GROUP), 1 << 20), min(total // BLOCK, 32))
            dealt = lambda df, group: df.select("vec_id", "vector", F.lit(0).alias("tree"), F.lit(0).cast("bigint").alias("string"), group.cast("bigint").alias("prefix"))
            p = dealt(points, F.pmod(F.xxhash64("vec_id"), F.lit(groups)))
            q = dealt(own.withColumn("group", F.explode(F.sequence(F.lit(0), F.lit(groups - 1)))), F.col("group"))
        q_blocks = blocks(q, QUERY_BLOCK).withColumnsRenamed({"ids": "q_ids", "vectors": "q_vectors"})
        part = score_blocks(blocks(p, BLOCK).join(q_blocks, ["tree", "prefix"]), k, width, single)
        found = part if found is None else found.unionByName(part)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    distinct = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    return distinct.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
