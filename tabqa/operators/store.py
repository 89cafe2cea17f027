"""The universal store: every row of every table as cells of one fixed schema, with its metadata and search index."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tabqa.functions.text import TAU, most_edits, normalize_value, number_of, qgrams, tokens_of
from tabqa.session import written

#: Class and its direct superclass.
SUBCLASS = (("CompositeKey", "Key"), ("Key", "Dependency"), ("InclusionDependency", "Dependency"))


@dataclass
class Index:
    """postings (val_norm, doc_id, table_id, row_id, attr_id), sorted by value; values (val_norm, n_postings, length, n_grams, weak);
    grams (gram, val_norm, length, n_grams) of the values that aren't weak; tokens (token, val_norm)."""

    postings: DataFrame
    values: DataFrame
    grams: DataFrame
    tokens: DataFrame


@dataclass
class Store:
    """tables (table_id, doc_id, label, caption, page_begin, page_end, family), attrs (attr_id, table_id, ord, label, parent_label),
    cells (doc_id, table_id, row_id, attr_id, ord, val_raw, val_norm, val_num), and, once found, the catalog: keys, inds, composites
    (inclusions of several attribute pairs, a row for each pair) and fds; and, once built, the search index."""

    tables: DataFrame
    attrs: DataFrame
    cells: DataFrame
    keys: DataFrame | None = None
    inds: DataFrame | None = None
    composites: DataFrame | None = None
    fds: DataFrame | None = None
    index: Index | None = None

    def part(self, condition: str) -> Store:
        """The tables for which the condition on table_id holds, without index and composite dependencies."""
        some = lambda df: df.where(condition) if df is not None else None
        both = [condition.replace("table_id", f"{side}_table") for side in ("lhs", "rhs")]
        inds = self.inds.where(f"({both[0]}) AND ({both[1]})") if self.inds is not None else None
        return Store(some(self.tables), some(self.attrs), some(self.cells), some(self.keys), inds, None, some(self.fds))

    def rows(self) -> DataFrame:
        """(table_id, row_id, row_map): rows put together again."""
        return self.cells.groupBy("table_id", "row_id").agg(F.map_from_entries(F.collect_list(F.struct("attr_id", "val_raw"))).alias("row_map"))

    def triples(self) -> DataFrame:
        """(s, p, o): everything the store holds, attributes being predicates of their rows."""
        link = lambda df, s, p, o: df.select(F.col(s).alias("s"), F.lit(p).alias("p"), F.col(o).cast("string").alias("o")).where("o IS NOT NULL")
        parts = [
            link(self.tables, "doc_id", "hasTable", "table_id"), link(self.tables, "table_id", "hasCaption", "caption"), link(self.tables, "table_id", "label", "label"), link(self.tables, "table_id", "hasID", "table_id"),
            link(self.tables, "table_id", "pageNumBegin", "page_begin"), link(self.tables, "table_id", "pageNumEnd", "page_end"),
            link(self.attrs, "table_id", "hasAttribute", "attr_id"), link(self.attrs, "attr_id", "label", "label"), link(self.attrs, "attr_id", "hasParentLabel", "parent_label"),
            link(self.cells.select("table_id", "row_id").distinct(), "table_id", "hasRow", "row_id"), self.cells.select(F.col("row_id").alias("s"), F.col("attr_id").alias("p"), F.col("val_raw").alias("o")).where("o IS NOT NULL"),
        ]
        if self.keys is not None:
            parts += [link(self.keys.select("table_id", "key_id").distinct(), "table_id", "hasDependency", "key_id"), link(self.keys, "key_id", "hasComponent", "attr_id")]
        if self.inds is not None:
            parts += [link(self.inds, "lhs_table", "hasDependency", "ind_id"), link(self.inds, "ind_id", "firstComponent", "lhs_attr"), link(self.inds, "ind_id", "secondComponent", "rhs_attr")]
        if self.composites is not None:  # a pair of a set of pairs is a node of its own
            pairs = self.composites.withColumn("pair", F.concat_ws("#", "ind_id", F.col("pos").cast("string")))
            parts += [link(pairs.select("lhs_table", "ind_id").distinct(), "lhs_table", "hasDependency", "ind_id"), link(pairs, "ind_id", "hasAttributePair", "pair"), link(pairs, "pair", "firstComponent", "lhs_attr"), link(pairs, "pair", "secondComponent", "rhs_attr")]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out

    def validate(self) -> DataFrame:
        """(violation, subject): tables without attribute, row or dependency; keys with too few components; open pairs."""
        lack = lambda what, other: self.tables.join(other, "table_id", "left_anti").select(F.lit(what).alias("violation"), F.col("table_id").alias("subject"))
        out = lack("table without attribute", self.attrs).unionByName(lack("table without row", self.cells))
        if self.keys is not None:
            out = out.unionByName(lack("table without dependency", self.keys))
            sizes = self.keys.groupBy("key_id", "is_composite").agg(F.count_distinct("attr_id").alias("n"))
            wrong = sizes.where("(is_composite AND n < 2) OR (NOT is_composite AND n <> 1)")
            out = out.unionByName(wrong.select(F.lit("components of key").alias("violation"), F.col("key_id").alias("subject")))
        if self.inds is not None:
            out = out.unionByName(self.inds.where("lhs_attr IS NULL OR rhs_attr IS NULL").select(F.lit("open pair").alias("violation"), F.col("ind_id").alias("subject")))
        return out


def load_store(flat: DataFrame, tables: DataFrame, attrs: DataFrame) -> Store:
    """From (table_id, row_no, values), table metadata (table_id, doc_id, caption, page_begin, page_end, family) and
    attributes (table_id, ord, label[, parent_label]); values of places without an attribute aren't stored.

    Ids are made of document, table and place, so a repeated load gives the same ones.
    """
    metadata = tables.select("table_id", "doc_id", F.col("table_id").alias("label"), "caption", "page_begin", "page_end", "family")
    named = attrs.select(F.concat_ws("#", "table_id", F.concat(F.lit("a"), F.col("ord"))).alias("attr_id"), "table_id", "ord", "label", (F.col("parent_label") if "parent_label" in attrs.columns else F.lit(None).cast("string")).alias("parent_label"))
    placed = flat.select("table_id", F.concat_ws("#", "table_id", F.concat(F.lit("r"), F.col("row_no"))).alias("row_id"), F.posexplode("values").alias("ord", "val_raw"))
    cells = placed.join(named.select("table_id", "ord", "attr_id"), ["table_id", "ord"]).join(metadata.select("table_id", "doc_id"), "table_id")
    cells = cells.select("doc_id", "table_id", "row_id", "attr_id", "ord", "val_raw", normalize_value(F.col("val_raw")).alias("val_norm"))
    return Store(metadata, named, cells.withColumn("val_num", number_of(F.col("val_norm"))))


def constant_columns(flat: DataFrame) -> DataFrame:
    """(table_id, ord): columns of unfolded tables that hold one value throughout, where the table has more rows than one."""
    cells = flat.select("table_id", F.posexplode("values").alias("ord", "v"))
    return cells.groupBy("table_id", "ord").agg(F.count_distinct(F.coalesce("v", F.lit("\x00"))).alias("n"), F.count(F.lit(1)).alias("rows")).where("n = 1 AND rows > 1").select("table_id", "ord")


def held(store: Store) -> Store:
    """The store's frames written to the shared folder and read back, cells sorted by table and row, so that a table's cells lie together."""
    cells = store.cells.repartitionByRange("table_id", "row_id").sortWithinPartitions("table_id", "row_id")
    return Store(written(store.tables, "store-tables"), written(store.attrs, "store-attrs"), written(cells, "store-cells"))


def indexed(store: Store, q: int = 2, tau: float = TAU) -> Store:
    """The store with its search index, written. Postings are sorted by value, so that a look-up of some values reads
    the files, and of these the row groups, that can hold them."""
    postings = written(value_postings(store).repartitionByRange("val_norm").sortWithinPartitions("val_norm"), "index-postings")
    values = written(sized(value_dictionary(store), F.col("val_norm"), tau, q), "index-values")
    grams = written(gram_postings(values, q).repartitionByRange("gram").sortWithinPartitions("gram", "length"), "index-grams")
    tokens = written(token_postings(values).repartitionByRange("token").sortWithinPartitions("token"), "index-tokens")
    return replace(store, index=Index(postings, values, grams, tokens))


def value_postings(store: Store) -> DataFrame:
    """(val_norm, doc_id, table_id, row_id, attr_id): the inverted list of every value."""
    return store.cells.where("val_norm IS NOT NULL").select("val_norm", "doc_id", "table_id", "row_id", "attr_id")


def value_dictionary(store: Store) -> DataFrame:
    """(val_norm, n_postings): distinct values with the length of their lists; strict look-ups start from the rarest."""
    return store.cells.where("val_norm IS NOT NULL").groupBy("val_norm").agg(F.count(F.lit(1)).alias("n_postings"))


def sized(texts: DataFrame, text: Column, tau: float = TAU, q: int = 2) -> DataFrame:
    """The texts with length, number of distinct grams, and whether they are weak.

    An edit changes at most q grams, so two texts of likeness tau or more share a gram if the longer one has more
    distinct grams than the allowed edits can change. Weak texts have no more (they repeat few letters).
    """
    out = texts.withColumns({"length": F.length(text), "n_grams": F.size(qgrams(text, q))})
    return out.withColumn("weak", F.col("n_grams") <= q * most_edits(F.col("length"), tau))


def token_postings(values: DataFrame) -> DataFrame:
    """(token, val_norm): full-text look-ups go through distinct values, which are far fewer than cells."""
    return values.select(F.explode(tokens_of(F.col("val_norm"))).alias("token"), "val_norm")


def gram_postings(values: DataFrame, q: int = 2) -> DataFrame:
    """(gram, val_norm, length, n_grams) of `sized` values that aren't weak."""
    return values.where("NOT weak").select(F.explode(qgrams(F.col("val_norm"), q)).alias("gram"), "val_norm", "length", "n_grams")


def similar(asked: DataFrame, values: DataFrame, grams: DataFrame, tau: float = TAU, q: int = 2) -> DataFrame:
    """(asked, val_norm): the pairs of distinct texts that can have a likeness of tau by edits; those left out can't.

    Texts meet at a gram; pairs that share fewer grams than the edits must leave are dropped by their counts. Weak texts, of which there
    are few, are met by length alone.
    """
    a = sized(asked.select(F.col("asked")).distinct(), F.col("asked"), tau, q).withColumnsRenamed({"length": "a_length", "n_grams": "a_grams", "weak": "a_weak"})
    fits = f"least(a_length, length) >= {tau} * greatest(a_length, length) - 1e-9"
    edits = most_edits(F.greatest("a_length", "length"), tau)
    met = a.where("NOT a_weak").select("asked", "a_length", "a_grams", F.explode(qgrams(F.col("asked"), q)).alias("gram")).join(grams, "gram").where(fits)
    shared = met.groupBy("asked", "val_norm").agg(F.count(F.lit(1)).alias("shared"), F.first("a_length").alias("a_length"), F.first("a_grams").alias("a_grams"), F.first("length").alias("length"), F.first("n_grams").alias("n_grams"))
    strong = shared.where(F.col("shared") >= F.greatest("a_grams", "n_grams") - q * edits).select("asked", "val_norm")
    lengths = F.sequence(F.ceil(F.col("a_length") * tau - 1e-9).cast("int"), F.floor(F.col("a_length") / tau + 1e-9).cast("int"))
    by_length = a.withColumn("length", F.explode(lengths)).drop("a_length", "a_grams")
    weak = by_length.join(values.select("val_norm", "length", "weak"), "length").where("a_weak OR weak").select("asked", "val_norm")
    return strong.unionByName(weak)


def class_closure(spark: SparkSession, subclasses: DataFrame | None = None) -> DataFrame:
    """(sub, super): every class with itself and all classes above it; of the store's own classes, or of others (sub, super).

    Level by level until nothing is new, so neither depth nor rows have a limit (a recursive query has both), and circles end.
    """
    given = spark.createDataFrame(list(SUBCLASS), "sub string, super string") if subclasses is None else subclasses
    direct = written(given.select("sub", "super").distinct(), "subclasses")
    whole = level = direct
    above = direct.select(F.col("sub").alias("super"), F.col("super").alias("next"))
    while not (level := written(level.join(above, "super").select("sub", F.col("next").alias("super")).distinct().join(whole, ["sub", "super"], "left_anti"), "superclasses")).isEmpty():
        whole = whole.unionByName(level)
    return whole.unionByName(direct.select("sub", F.col("sub").alias("super"))).unionByName(direct.select(F.col("super").alias("sub"), "super")).distinct()


def objects_to_cells(objects: DataFrame, id_col: str, json_col: str, table_id: str) -> DataFrame:
    """An object graph as cells: an object is a row, its properties are cells."""
    return objects.select(F.lit(table_id).alias("table_id"), F.col(id_col).cast("string").alias("row_id"), F.explode(F.from_json(json_col, "map<string,string>")).alias("attr_id", "val_raw"))
