"""Keys, functional and inclusion dependencies: checks, discovery, catalog, and how far they miss on noisy data.

Candidate lattices are metadata and live on the driver; counting is Spark's. Every level of a lattice is one aggregation.
"""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from dataclasses import replace
from functools import reduce
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tabqa.operators.store import Store
from tabqa.session import written


def project(df: DataFrame, attrs: Sequence[str]) -> DataFrame:
    """Projection with set semantics."""
    return df.select(*attrs).distinct()


def _distinct(attrs: Sequence[str]):
    """Number of distinct tuples, nulls being values."""
    return F.count_distinct(F.struct(*(F.struct(F.col(f"`{a}`").isNull().alias("n"), F.col(f"`{a}`").alias("v")) for a in attrs)))


# Functional dependencies and keys ------------------------------------------------------------------------------------


def fd_violations(df: DataFrame, lhs: Sequence[str], rhs: Sequence[str]) -> DataFrame:
    """Left sides that go with several right sides, and with how many."""
    return df.select(*lhs, *rhs).distinct().groupBy(*lhs).agg(F.count(F.lit(1)).alias("n_rhs")).where("n_rhs > 1")


def fd_holds(df: DataFrame, lhs: Sequence[str], rhs: Sequence[str]) -> bool:
    return not fd_violations(df, lhs, rhs).head(1)


def is_key(df: DataFrame, attrs: Sequence[str]) -> bool:
    """Do the attributes tell all distinct rows apart?"""
    rows = df.distinct()
    found = rows.agg(F.count(F.lit(1)).alias("n"), _distinct(attrs).alias("d")).first()
    return found["n"] == found["d"]


#: Sets counted in one scan.
COUNTED_AT_ONCE = 64
#: Size of an estimating sketch (its logarithm), its relative error, and by how many of them a set may fall short before it is counted exactly.
SKETCH_LOG, ESTIMATE_ERROR, ESTIMATE_MARGIN = 13, 0.01, 5


def _hash_of(attrs: Sequence[str], seed: int = 0) -> Column:
    """64 bits of a tuple, nulls being values."""
    return F.xxhash64(F.lit(seed), *(x for a in attrs for x in (F.col(f"`{a}`").isNull(), F.col(f"`{a}`"))))


def minimal_keys(df: DataFrame, max_size: int | None = None, attrs: Sequence[str] | None = None, approx: bool = True) -> list[tuple[str, ...]]:
    """All minimal keys (up to a size, if one is given), level by level; a set is tried only if none of its parts is a key.

    Each level is a scan or a few: the sets' distinct counts are estimated by sketches, many at once, and only sets whose estimate comes
    within a margin of the number of rows are counted, by digests of 128 bits. Without `approx` all are. The search ends where every set of a level
    is a key or holds one. Of a table with at most one row every single attribute is reported.
    """
    attrs = list(attrs or df.columns)
    rows = df.select(*(F.col(f"`{a}`") for a in attrs)).distinct().persist()
    try:
        n, keys = rows.count(), []
        if n <= 1:
            return [(a,) for a in attrs]
        asked = [(a,) for a in attrs]
        while asked and (max_size is None or len(asked[0]) <= max_size):
            near = asked
            if approx:
                near = []
                for at in range(0, len(asked), COUNTED_AT_ONCE):
                    part = asked[at : at + COUNTED_AT_ONCE]
                    rough = rows.agg(*(F.hll_sketch_estimate(F.hll_sketch_agg(_hash_of(c), SKETCH_LOG)).alias(f"c{i}") for i, c in enumerate(part))).first()
                    near += [c for i, c in enumerate(part) if rough[i] * (1 + ESTIMATE_MARGIN * ESTIMATE_ERROR) + 4 >= n]
            found = []
            for at in range(0, len(near), 24):  # each distinct set copies the rows, so a few at a time, as digests of 128 bits
                part = near[at : at + 24]
                counts = rows.agg(*(F.count_distinct(_hash_of(c), _hash_of(c, 7)).alias(f"c{i}") for i, c in enumerate(part))).first()
                found += [c for i, c in enumerate(part) if counts[i] == n]
            keys += found
            asked = _next_level(set(asked) - set(found), attrs)
        return keys
    finally:
        rows.unpersist()


#: Values (rows times columns) of a bucket of rows, as wished and at most.
BUCKET_VALUES, MOST_BUCKET_VALUES = 2_000_000, 12_000_000


def _least(sets: Iterable[int]) -> list[int]:
    """Sets of bits that hold no other one."""
    out: list[int] = []
    for s in sorted(set(sets), key=int.bit_count):
        if not any(s & o == o for o in out):
            out.append(s)
    return out


def _open_sets(most: Sequence[int], whole: int, within: int, max_size: int, base: list[int] | None = None) -> list[int]:
    """The least sets that hold one of `base` (the empty set), are within `within` and in none of the sets `most` of the columns `whole`."""
    out = [0] if base is None else base
    for told in most:
        missing = whole & ~told & within
        bits = [1 << i for i in range(missing.bit_length()) if missing >> i & 1]
        kept = [s for s in out if s & ~told]
        out = _least([*kept, *(s | b for s in out if not s & ~told for b in bits if (s | b).bit_count() <= max_size)])
    return out


def _most_agreed(codes: np.ndarray, rows: np.ndarray, pivot: int, within: int, known: list[int], max_size: int) -> tuple[int, list[int]]:
    """From digests of values (columns, rows) and of whole rows: a bucket's distinct rows, and sets to add to the known ones, each being what two rows agree in.

    Then a set of columns `within` that holds the pivot tells the rows apart just if it is in none of them.
    """
    n_columns = len(codes)
    whole = (1 << n_columns) - 1
    sums = lambda s: codes[[i for i in range(n_columns) if s >> i & 1]].sum(axis=0, dtype=np.uint64)
    codes = codes[:, np.unique(rows, return_index=True)[1]]
    told, tried = set(known), set()
    while True:
        asked = [s for s in _open_sets(sorted(told, key=int.bit_count, reverse=True), whole, within, max_size, [1 << pivot]) if s not in tried]
        if not asked:
            return codes.shape[1], sorted(told - set(known))
        for s in asked:
            if any(s & ~t == 0 for t in told):  # one found since agrees in it
                continue
            tried.add(s)
            digests = sums(s)
            ordered = np.sort(digests)
            if not (ordered[1:] == ordered[:-1]).any():
                continue
            places = np.argsort(digests, kind="stable")
            again = np.flatnonzero(digests[places[1:]] == digests[places[:-1]])
            same = codes[:, places[again]] == codes[:, places[again + 1]]
            masks = np.unique((np.int64(1) << np.arange(n_columns, dtype=np.int64)) @ same.astype(np.int64))
            told.update(m & within for m in map(int, masks) if s & ~m == 0)


def minimal_keys_large(df: DataFrame, max_size: int | None = None, attrs: Sequence[str] | None = None) -> list[tuple[str, ...]]:
    """What `minimal_keys` finds, for relations of many rows: rows are shuffled once for each of a few columns, not for each set.

    Rows that agree in a set agree in each of its columns. So rows are dealt into buckets by one column, and a bucket settles all sets that hold the column:
    two rows that agree in a set show that it is no key, nor any other set of columns in which they agree. Sets without that column are left to the next one, which takes
    what was found along. Columns of too few values to be dealt by (a bucket would be too large) are last; sets of these only
    are searched by counting, if all of them together tell the rows apart. Values are compared by digests of 64 bits each, nulls being values.
    """
    attrs = list(attrs or df.columns)
    if len(attrs) > 62:
        raise ValueError("a set of columns is a number of 62 bits")
    k = len(attrs)
    whole, largest = (1 << k) - 1, min(max_size or k, k)
    coded = df.select(*(F.xxhash64(F.lit(i), F.col(f"`{a}`").isNull(), F.col(f"`{a}`")).alias(f"h{i}") for i, a in enumerate(attrs)), _hash_of(attrs).alias("row"))
    n = coded.count()
    # the power of two of buckets that gives them the wished size, and what it comes to for each column
    buckets = 1 << max(0, (n * k // BUCKET_VALUES).bit_length())
    place = lambda c: F.pmod(c, F.lit(buckets)).cast("int")
    dealt = coded.select(F.explode(F.array(*(F.struct(F.lit(i).alias("i"), place(F.col(f"h{i}")).alias("b")) for i in range(k)))).alias("x")).groupBy("x.i", "x.b").agg(F.count(F.lit(1)).alias("n"))
    sizes = {r["i"]: r["n"] for r in dealt.groupBy("i").agg(F.max("n").alias("n")).collect()}

    def settle(pivot: int, within: int, known: list[int]) -> list:
        columns = [i for i in range(k) if within >> i & 1]

        def run(table: pa.Table) -> pa.Table:
            codes = np.zeros((k, len(table)), np.uint64)
            for i in columns:
                codes[i] = table[f"h{i}"].to_numpy().view(np.uint64)
            n_rows, found = _most_agreed(codes, table["row"].to_numpy(), pivot, within, known, largest)
            return pa.table({"n": pa.array([n_rows] + [0] * len(found), pa.int64()), "told": pa.array([0, *found], pa.int64())})

        left = coded.select("row", *(f"h{i}" for i in columns), place(F.col(f"h{pivot}")).alias("bucket"))
        return left.groupBy("bucket").applyInArrow(run, "n long, told long").groupBy("told").agg(F.sum("n").alias("n")).collect()

    told: set[int] = set()
    seen, within, keys = 0, whole, []
    for pivot in sorted(sizes, key=lambda i: (sizes[i], i)):
        if sizes[pivot] * k > MOST_BUCKET_VALUES or (told and any(within & ~t == 0 for t in told)):
            break
        found = settle(pivot, within, sorted(told))
        seen = seen or sum(r["n"] for r in found)
        told = set(_largest([*told, *(r["told"] for r in found)]))
        if seen <= 1:
            return [(a,) for a in attrs]
        keys += _open_sets(sorted(told, key=int.bit_count, reverse=True), whole, within, largest, [1 << pivot])
        within &= ~(1 << pivot)
    named = lambda s: tuple(a for i, a in enumerate(attrs) if s >> i & 1)
    if within and not any(within & ~t == 0 for t in told):
        left = named(within)
        rows = df.select(*(F.col(f"`{a}`") for a in attrs)).distinct()
        if within == whole or rows.count() == rows.select(*(F.col(f"`{a}`") for a in left)).distinct().count():
            keys += [sum(1 << attrs.index(a) for a in c) for c in minimal_keys(df, max_size, left)]
    return [named(s) for s in sorted(_least(keys), key=lambda s: (s.bit_count(), [i for i in range(k) if s >> i & 1]))]


def _largest(sets: Iterable[int]) -> list[int]:
    """Sets of bits that are in no other one."""
    out: list[int] = []
    for s in sorted(set(sets), key=int.bit_count, reverse=True):
        if not any(s & ~o == 0 for o in out):
            out.append(s)
    return out


def _next_level(rest: set[tuple[str, ...]], attrs: Sequence[str]) -> list[tuple[str, ...]]:
    """The sets of one attribute more all of whose parts are in `rest`."""
    place = {a: i for i, a in enumerate(attrs)}
    larger = [(*c, a) for c in rest for a in attrs[place[c[-1]] + 1 :]]
    return sorted((c for c in larger if all(c[:i] + c[i + 1 :] in rest for i in range(len(c)))), key=lambda c: [place[a] for a in c])


def find_fds(df: DataFrame, max_lhs: int = 2, attrs: Sequence[str] | None = None) -> list[tuple[tuple[str, ...], str]]:
    """Minimal functional dependencies with one attribute on the right: X gives A when X and X with A count the same."""
    attrs = list(attrs or df.columns)
    rows = df.select(*attrs).distinct().persist()
    try:
        counts: dict[frozenset[str], int] = {}

        def count(sets: list[frozenset[str]]) -> None:
            new = [s for s in dict.fromkeys(sets) if s not in counts]
            for at in range(0, len(new), 16):
                part = new[at : at + 16]
                found = rows.agg(*(_distinct(sorted(s)).alias(f"c{i}") for i, s in enumerate(part))).first()
                counts.update({s: found[i] for i, s in enumerate(part)})

        out: list[tuple[tuple[str, ...], str]] = []
        for size in range(1, max_lhs + 1):
            asked = [(x, a) for x in combinations(attrs, size) for a in attrs if a not in x and not any(b == a and set(y) <= set(x) for y, b in out)]
            count([frozenset(x) for x, _ in asked] + [frozenset((*x, a)) for x, a in asked])
            out += [(x, a) for x, a in asked if counts[frozenset(x)] == counts[frozenset((*x, a))]]
        return out
    finally:
        rows.unpersist()


#: Sets of one size that a printed table's search looks at; a table with more is told to be incomplete.
MOST_SETS = 20_000


def _codes(group: pd.DataFrame) -> tuple[list[str], np.ndarray]:
    """A table's attributes, and its distinct rows with each value as a number; a missing cell is a value."""
    wide = group.pivot_table(index="row_id", columns="attr_id", values="val_norm", aggfunc="first", dropna=False).fillna("\x00").drop_duplicates()
    attrs = sorted(wide.columns)
    return attrs, np.stack([np.unique(wide[a].to_numpy(str), return_inverse=True)[1] for a in attrs], 1) if len(attrs) else np.zeros((0, 0), int)


def _n_tuples(codes: np.ndarray, places: Sequence[int]) -> int:
    """Distinct tuples of some columns of codes."""
    number = np.zeros(len(codes), np.int64)
    for i in places:
        number = np.unique(number * (int(codes[:, i].max()) + 1) + codes[:, i], return_inverse=True)[1] if len(codes) else number
    return int(number.max()) + 1 if len(codes) else 0


def minimal_keys_batch(cells: DataFrame, max_size: int | None = None, eps: float = 0.0) -> DataFrame:
    """(table_id, key_id, attr_id, is_composite, is_minimal, is_complete): minimal keys of many printed tables, each lattice in one task.

    A printed table is one document's page or so; its values come as codes. All minimal keys are found, or those up to
    `max_size`; a search that comes to more than MOST_SETS sets of a size stops there. `is_complete` tells of a table that its search
    wasn't cut so. A table that has no key so small gets one larger minimal key. With `eps` a set is a key if deleting that share of the
    rows makes it one.
    """

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        attrs, codes = _codes(group)
        n = len(codes)
        tells = lambda c: n <= 1 or _n_tuples(codes, c) >= n * (1 - eps)
        keys, asked, complete = [], [(i,) for i in range(len(attrs))], True
        while asked and (max_size is None or len(asked[0]) <= max_size):
            if len(asked) > MOST_SETS:
                complete = False
                break
            told = {c: tells(c) for c in asked}
            keys += [c for c, is_told in told.items() if is_told]
            rest = {c for c, is_told in told.items() if not is_told}  # only sets without a key in them go on
            asked = [(*c, a) for c in rest for a in range(c[-1] + 1, len(attrs))]
            asked = sorted(c for c in asked if all(c[:i] + c[i + 1 :] in rest for i in range(len(c))))
        complete &= not asked
        minimal = True
        if not keys:  # parts are taken away as long as what is left still is a key
            held = tuple(range(len(attrs)))
            minimal = tells(held)
            for a in reversed(range(len(attrs))):
                if tells(less := tuple(x for x in held if x != a)):
                    held = less
            keys = [held]
        rows = [(key[0], f"{key[0]}#k{i}", attrs[a], len(k) > 1, minimal, complete) for i, k in enumerate(keys) for a in k]
        return pd.DataFrame(rows, columns=["table_id", "key_id", "attr_id", "is_composite", "is_minimal", "is_complete"])

    plain = cells.select("table_id", "row_id", "attr_id", F.coalesce("val_norm", F.lit("\x00")).alias("val_norm"))
    return plain.groupBy("table_id").applyInPandas(run, "table_id string, key_id string, attr_id string, is_composite boolean, is_minimal boolean, is_complete boolean")


#: Attributes on the left side of a functional dependency of the catalog, at most.
MOST_LEFT = 3


def find_fds_batch(cells: DataFrame, max_lhs: int = MOST_LEFT, eps: float = 0.0) -> DataFrame:
    """(table_id, fd_id, lhs_attr, n_lhs, rhs_attr): minimal functional dependencies of many printed tables, each lattice in one task.

    Left sides have at most `max_lhs` attributes, and are no keys: what a key determines, looking up its row gives. With `eps` a dependency
    holds if deleting that share of the rows makes it hold.
    """

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        attrs, codes = _codes(group)
        n, out = len(codes), []
        held: dict[int, list[frozenset[int]]] = {a: [] for a in range(len(attrs))}

        def holds(lhs: tuple[int, ...], a: int) -> bool:
            if not eps:
                return _n_tuples(codes, lhs) == _n_tuples(codes, (*lhs, a))
            kept = pd.DataFrame(codes[:, [*lhs, a]]).value_counts().groupby(level=list(range(len(lhs)))).max().sum()
            return kept >= n * (1 - eps)

        level = [(i,) for i in range(len(attrs))]
        while level and len(level[0]) <= max_lhs and len(level) <= MOST_SETS:
            open_ = []
            for lhs in level:
                if _n_tuples(codes, lhs) == n:
                    continue
                open_.append(lhs)
                for a in range(len(attrs)):
                    if a not in lhs and not any(x <= set(lhs) for x in held[a]) and holds(lhs, a):
                        held[a].append(frozenset(lhs))
                        out.append((lhs, a))
            rest = set(open_)
            larger = [(*c, a) for c in open_ for a in range(c[-1] + 1, len(attrs))]
            level = [c for c in larger if all(c[:i] + c[i + 1 :] in rest for i in range(len(c)))]
        rows = [(key[0], f"{key[0]}#f{i}", attrs[x], len(lhs), attrs[a]) for i, (lhs, a) in enumerate(out) for x in lhs]
        return pd.DataFrame(rows, columns=["table_id", "fd_id", "lhs_attr", "n_lhs", "rhs_attr"])

    plain = cells.select("table_id", "row_id", "attr_id", F.coalesce("val_norm", F.lit("\x00")).alias("val_norm"))
    return plain.groupBy("table_id").applyInPandas(run, "table_id string, fd_id string, lhs_attr string, n_lhs int, rhs_attr string")


# Inclusions ----------------------------------------------------------------------------------------------------------


def unary_inclusions(cells: DataFrame, scope: str = "document", eps: float = 0.0) -> DataFrame:
    """(lhs_table, lhs_attr, rhs_table, rhs_attr): attributes whose values all occur in another table's attribute.

    Within a document, or over the corpus. An attribute can be included only in those that hold its rarest value, the one that
    fewest attributes have; only these candidates are counted. So no value gives all pairs of the attributes that hold it. With `eps` that share of the
    distinct values may be missing; then any of the rarest values up to that share may be the one missing, and the candidates are those of
    the rarest ones together.
    """
    held = cells.where("val_norm IS NOT NULL").select((F.col("doc_id") if scope == "document" else F.lit("*")).alias("doc"), "val_norm", "table_id", "attr_id").distinct()
    spread = held.groupBy("doc", "val_norm").agg(F.count(F.lit(1)).alias("spread"))
    own = ["doc", "table_id", "attr_id"]
    counted = held.join(spread, ["doc", "val_norm"])
    sizes = counted.groupBy(*own).agg(F.count(F.lit(1)).alias("n"))
    if eps:
        place = F.row_number().over(Window.partitionBy(*own).orderBy("spread", "val_norm"))
        rare = counted.withColumn("place", place).join(sizes, own).where(F.col("place") <= F.floor(F.lit(eps) * F.col("n")) + 1).select(*own, "val_norm")
    else:
        rare = counted.groupBy(*own).agg(F.min_by("val_norm", F.struct("spread", "val_norm")).alias("val_norm"))
    other = held.select("doc", "val_norm", F.col("table_id").alias("rhs_table"), F.col("attr_id").alias("rhs_attr"))
    asked = rare.join(other, ["doc", "val_norm"]).where("table_id <> rhs_table").select(*own, "rhs_table", "rhs_attr").distinct()
    both = asked.join(held, own).join(other, ["doc", "val_norm", "rhs_table", "rhs_attr"]).groupBy(*own, "rhs_table", "rhs_attr").agg(F.count(F.lit(1)).alias("shared"))
    found = both.join(sizes, own).where(F.col("shared") >= F.col("n") * (1 - eps))
    return found.select(F.col("table_id").alias("lhs_table"), F.col("attr_id").alias("lhs_attr"), "rhs_table", "rhs_attr")


def composite_inclusions(cells: DataFrame, unary: DataFrame, max_arity: int = 2) -> DataFrame:
    """(ind_id, lhs_table, rhs_table, pos, lhs_attr, rhs_attr, arity): sets of attribute pairs whose tuples are included, a row for each pair.

    Level by level: candidates of a level add a unary inclusion between the same tables to a set that holds, and all candidates of a level
    are checked in one job. Tuples with a missing part don't count.
    """
    one = unary.select("lhs_table", "rhs_table", "lhs_attr", "rhs_attr")
    level = one.select("lhs_table", "rhs_table", F.array("lhs_attr").alias("lhs"), F.array("rhs_attr").alias("rhs"))
    values = cells.where("val_norm IS NOT NULL").select("row_id", F.col("attr_id").alias("attr"), "val_norm")
    out = None
    for arity in range(2, max_arity + 1):
        wider = level.join(one, ["lhs_table", "rhs_table"]).where(F.col("lhs_attr") > F.element_at("lhs", -1)).where(~F.array_contains("rhs", F.col("rhs_attr")))
        asked = wider.select("lhs_table", "rhs_table", F.concat("lhs", F.array("lhs_attr")).alias("lhs"), F.concat("rhs", F.array("rhs_attr")).alias("rhs"))
        asked = asked.withColumn("ind_id", F.concat(F.array_join("lhs", "+"), F.lit(">"), F.array_join("rhs", "+")))

        def tuples(side: str, asked: DataFrame = asked, arity: int = arity) -> DataFrame:
            wanted = asked.select("ind_id", F.posexplode(side).alias("pos", "attr"))
            held = wanted.join(values, "attr").groupBy("ind_id", "row_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "val_norm"))), lambda x: x["val_norm"]).alias("held"))
            return held.where(F.size("held") == arity).select("ind_id", "held").distinct()

        missed = tuples("lhs").join(tuples("rhs"), ["ind_id", "held"], "left_anti").select("ind_id").distinct()
        level = asked.join(tuples("lhs").select("ind_id").distinct(), "ind_id", "left_semi").join(missed, "ind_id", "left_anti")
        rows = level.select("ind_id", "lhs_table", "rhs_table", F.posexplode(F.arrays_zip("lhs", "rhs")).alias("pos", "pair"))
        rows = rows.select("ind_id", "lhs_table", "rhs_table", "pos", F.col("pair.lhs").alias("lhs_attr"), F.col("pair.rhs").alias("rhs_attr"), F.lit(arity).alias("arity"))
        out = rows if out is None else out.unionByName(rows)
    return out


def inclusion_misses(r: DataFrame, u: Sequence[str], s: DataFrame, v: Sequence[str]) -> DataFrame:
    """Distinct tuples of r that s lacks."""
    left = r.select(*(F.col(c).alias(f"c{i}") for i, c in enumerate(u))).distinct()
    right = s.select(*(F.col(c).alias(f"c{i}") for i, c in enumerate(v))).distinct()
    return left.join(right, left.columns, "left_anti")


def inclusion_holds(r: DataFrame, u: Sequence[str], s: DataFrame, v: Sequence[str]) -> bool:
    return not inclusion_misses(r, u, s, v).head(1)


def nary_inclusions(tables: dict[str, DataFrame], unary: Sequence[tuple[str, str, str, str]], max_arity: int = 2) -> list[tuple[str, tuple[str, ...], str, tuple[str, ...]]]:
    """Inclusions of several attribute pairs, level by level from unary ones (table, attr, table, attr)."""
    out = [(a, (x,), b, (y,)) for a, x, b, y in unary]
    level = out
    for _ in range(2, max_arity + 1):
        asked = []
        for a, xs, b, ys in level:
            for c, (x,), d, (y,) in out[: len(unary)]:
                if (a, b) == (c, d) and x > xs[-1] and y not in ys:
                    asked.append((a, (*xs, x), b, (*ys, y)))
        level = [c for c in asked if inclusion_holds(tables[c[0]], c[1], tables[c[2]], c[3])]
        out = out + level
    return out


def foreign_keys(inclusions: DataFrame, keys: DataFrame) -> DataFrame:
    """Unary inclusions whose right side is a key of its table."""
    single = keys.where("NOT is_composite").select(F.col("table_id").alias("rhs_table"), F.col("attr_id").alias("rhs_attr"))
    return inclusions.join(single, ["rhs_table", "rhs_attr"], "left_semi")


def joinable(a: DataFrame, x: str, b: DataFrame, y: str) -> DataFrame:
    """One row: distinct values of both sides, those in common, and how much of each side they are."""
    left, right = a.select(F.col(x).alias("v")).distinct(), b.select(F.col(y).alias("v")).distinct()
    marked = left.withColumn("l", F.lit(1)).join(right.withColumn("r", F.lit(1)), "v", "full")
    counted = marked.agg(F.count("l").alias("n_left"), F.count("r").alias("n_right"), F.count_if(F.col("l").isNotNull() & F.col("r").isNotNull()).alias("n_both"))
    return counted.select("n_left", "n_right", "n_both", (F.col("n_both") / F.col("n_left")).alias("left_held"), (F.col("n_both") / F.col("n_right")).alias("right_held"))


def check_consistency(tables: dict[str, DataFrame], fds: Sequence[tuple] = (), keys: Sequence[tuple] = (), inclusions: Sequence[tuple] = ()) -> DataFrame:
    """(dependency, violations) of declared dependencies: (table, lhs, rhs), (table, attrs), (table, attrs, table, attrs)."""
    count = lambda df, what: df.agg(F.count(F.lit(1)).alias("violations")).select(F.lit(what).alias("dependency"), "violations")
    out = [count(fd_violations(tables[t], l, r), f"{t}: {','.join(l)} -> {','.join(r)}") for t, l, r in fds]
    out += [count(tables[t].distinct().groupBy(*a).agg(F.count(F.lit(1)).alias("n")).where("n > 1"), f"{t}: key {','.join(a)}") for t, a in keys]
    out += [count(inclusion_misses(tables[r], u, tables[s], v), f"{r}.{','.join(u)} in {s}.{','.join(v)}") for r, u, s, v in inclusions]
    return reduce(DataFrame.unionByName, out)


def fd_holds_across(r: DataFrame, u: Sequence[str], s: DataFrame, v: Sequence[str], via: tuple[Sequence[str], Sequence[str]]) -> DataFrame:
    """One row: does u of r determine v of s, rows being aligned by an inclusion of r's attributes in s's?"""
    renamed = s.select(*(F.col(c).alias(f"__{c}") for c in dict.fromkeys((*via[1], *v))))
    aligned = r.join(renamed, [F.col(a) == F.col(f"__{b}") for a, b in zip(*via, strict=True)])
    return fd_violations(aligned, u, [f"__{c}" for c in v]).agg(F.count(F.lit(1)).alias("violations")).select((F.col("violations") == 0).alias("holds"), "violations")


# How far a dependency misses --------------------------------------------------------------------------------------------


def fd_error(df: DataFrame, lhs: Sequence[str], rhs: Sequence[str]) -> DataFrame:
    """One row: the least share of rows to delete so that the dependency holds."""
    each = df.groupBy(*lhs, *rhs).agg(F.count(F.lit(1)).alias("n"))
    best = each.groupBy(*lhs).agg(F.max("n").alias("kept"), F.sum("n").alias("n"))
    return best.agg((1 - F.sum("kept") / F.sum("n")).alias("error"))


def key_error(df: DataFrame, attrs: Sequence[str]) -> DataFrame:
    return df.agg((1 - _distinct(attrs) / F.count(F.lit(1))).alias("error"))


def inclusion_error(r: DataFrame, u: Sequence[str], s: DataFrame, v: Sequence[str]) -> DataFrame:
    """One row: the share of distinct left tuples that the right side lacks."""
    total = r.select(*u).distinct().agg(F.count(F.lit(1)).alias("n"))
    misses = inclusion_misses(r, u, s, v).agg(F.count(F.lit(1)).alias("m"))
    return total.crossJoin(F.broadcast(misses)).select(F.when(F.col("n") > 0, F.col("m") / F.col("n")).otherwise(0.0).alias("error"))


# Catalog -------------------------------------------------------------------------------------------------------------


def build_catalog(store: Store, max_size: int | None = None, scope: str = "document", eps: float = 0.0, max_arity: int = 2, max_lhs: int = MOST_LEFT) -> Store:
    """The store with its keys, inclusions (of one attribute, and of several) and functional dependencies, found once, offline.

    With `eps` dependencies of noisy tables count if they miss by no more than that share.
    """
    keys = written(minimal_keys_batch(store.cells, max_size, eps), "keys")
    pairs = written(unary_inclusions(store.cells, scope, eps), "inclusions")
    linked = pairs.join(foreign_keys(pairs, keys).withColumn("is_fk", F.lit(True)), pairs.columns, "left").withColumn("is_fk", F.coalesce("is_fk", F.lit(False)))
    inds = written(linked.withColumn("ind_id", F.concat_ws(">", "lhs_attr", "rhs_attr")), "inds")
    composites = written(composite_inclusions(store.cells, pairs, max_arity), "composites")
    fds = written(find_fds_batch(store.cells, max_lhs, eps), "fds")
    return replace(store, keys=keys, inds=inds, composites=composites, fds=fds)


def keys_frame(spark: SparkSession, name: str, keys: list[tuple[str, ...]]) -> DataFrame:
    return spark.createDataFrame([(name, ",".join(sorted(k)), len(k)) for k in keys], "table_id string, attrs string, size int")
