"""Line deduplication with sharded cuckoo filters over exact reference counts.

A reference table holds, for every line key, in how many documents it stands and the smallest of their ids. Keys of
two or more documents also have a fingerprint in the cuckoo filter of their shard. Inserting documents adds to the
counts and inserts the fingerprints of keys that reach two; deleting documents subtracts and deletes the
fingerprints of keys that fall below two, so the state is the one that the remaining documents would give.
A line is looked up in the filter first; only lines that pass are joined with the exact table. Filters that are small together
are sent to all tasks; larger ones meet the keys of their shards, dealt by shard and, against hot lines, by slices of the documents.

A key is the line stripped of ASCII white space with A-Z lower-cased; keys shorter than `min_chars` code points
are never dropped. Keys travel as 128-bit digests. A null or empty text is one empty line. Rows that repeat a doc_id count
as one document and get the same decisions. A null doc_id is one document that comes before all others. Other columns stay as they
are, whatever their names, but for those named like the counts that the result has: these give way.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tabqa.llm.common import ASCII_SPACE, Rewritten, as_rows, ascii_lower, map_arrow, utf8_rows
from tabqa.session import written

MIN_CHARS = 10
#: Shards of the reference table; each has a filter of its own.
SHARDS = 64
KEYS_PER_SHARD = 200_000
#: Filters are sent to every executor up to this size, measured before; beyond it keys go to where their filter is.
FILTERS_BROADCAST_BYTES = 48 << 20
#: Slices of the documents in which a shard's keys meet its filter.
SLICES = 8
NULL_ID = -(1 << 63)
SLOTS = 4


class CuckooFilter:
    """16-bit fingerprints in buckets of four slots; each key has two buckets, either found from the other."""

    def __init__(self, buckets: int, table: np.ndarray | None = None):
        self.buckets = buckets
        self.table = np.zeros((buckets, SLOTS), np.uint16) if table is None else table

    @classmethod
    def for_keys(cls, n: int) -> CuckooFilter:
        """Room for n keys at a load of at most 0.8; the number of buckets is a power of two."""
        return cls(1 << max(2, int(n / (0.8 * SLOTS))).bit_length())

    @staticmethod
    def _mixed(values: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            x = values.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
            x ^= x >> np.uint64(32)
            x *= np.uint64(0xD6E8FEB86659FD93)
            return x ^ (x >> np.uint64(32))

    def places(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Fingerprints and both buckets of 64-bit keys."""
        mixed = self._mixed(keys)
        prints = ((mixed >> np.uint64(48)).astype(np.uint16)) | np.uint16(1)
        first = (mixed & np.uint64(self.buckets - 1)).astype(np.int64)
        return prints, first, first ^ self._step(prints)

    def _step(self, prints: np.ndarray) -> np.ndarray:
        return (self._mixed(prints) & np.uint64(self.buckets - 1)).astype(np.int64)

    def _ranked(self, buckets: np.ndarray, prints: np.ndarray, wanted: Callable[[np.ndarray, np.ndarray], np.ndarray], by_print: bool) -> tuple[np.ndarray, np.ndarray]:
        """Gives each entry the next wanted slot of its bucket in turn: which entries got one, and which slots."""
        order = np.lexsort((prints, buckets)) if by_print else np.argsort(buckets, kind="stable")
        at, p = buckets[order], prints[order]
        fresh = np.concatenate(([True], (at[1:] != at[:-1]) | ((p[1:] != p[:-1]) if by_print else False)))
        first = np.flatnonzero(fresh)
        turn = np.arange(len(at)) - first[np.cumsum(fresh) - 1]
        fits = np.cumsum(wanted(self.table[at], p[:, None]), axis=1)
        got = turn < fits[:, -1]
        return order[got], (fits[got] == turn[got][:, None] + 1).argmax(axis=1)

    def insert(self, keys: np.ndarray) -> bool:
        """Adds keys; False when one finds no place, and the filter must be built larger."""
        prints, first, second = self.places(keys)
        left = np.arange(len(keys))
        for bucket in (first, second):  # all that find a free slot at once, then those that must move others
            if len(left):
                done, slots = self._ranked(bucket[left], prints[left], lambda held, p: held == 0, False)
                self.table[bucket[left[done]], slots] = prints[left[done]]
                left = np.delete(left, done)
        for p, at in zip(prints[left].tolist(), second[left].tolist(), strict=True):
            now = p
            for kick in range(500):
                slot = (kick + now) % SLOTS
                now, self.table[at, slot] = int(self.table[at, slot]), now
                at = int(at ^ self._step(np.array([now], np.uint16))[0])
                free = np.flatnonzero(self.table[at] == 0)
                if len(free):
                    self.table[at, free[0]] = now
                    break
            else:
                return False
        return True

    def delete(self, keys: np.ndarray) -> None:
        """Removes one fingerprint for each key; only keys that were inserted may be given."""
        prints, first, second = self.places(keys)
        left = np.arange(len(keys))
        for bucket in (first, second):
            if len(left):
                done, slots = self._ranked(bucket[left], prints[left], lambda held, p: held == p, True)
                self.table[bucket[left[done]], slots] = 0
                left = np.delete(left, done)

    def contains(self, keys: np.ndarray) -> np.ndarray:
        prints, first, second = self.places(keys)
        return (self.table[first] == prints[:, None]).any(axis=1) | (self.table[second] == prints[:, None]).any(axis=1)

    def to_bytes(self) -> bytes:
        return self.table.tobytes()

    @classmethod
    def from_bytes(cls, raw: bytes, to_change: bool = False) -> CuckooFilter:
        """A filter to look up in, without a copy of its cells; or one to change."""
        table = np.frombuffer(raw, np.uint16).reshape(-1, SLOTS)
        return cls(len(table), table.copy() if to_change else table)


def build_filter(keys: np.ndarray) -> CuckooFilter:
    """A filter of these keys, doubled until all have a place."""
    built = CuckooFilter.for_keys(len(keys))
    while not built.insert(keys):
        built = CuckooFilter(built.buckets * 2)
    return built


_SPACE = ASCII_SPACE.encode()


def line_key(line: bytes, min_chars: int = MIN_CHARS) -> bytes | None:
    """The digest of a line's key, or None where the key is too short to count."""
    key = ascii_lower(line.strip(_SPACE))
    if len(key) < min_chars or (not key.isascii() and len(key.decode("utf-8", "replace")) < min_chars):
        return None
    return hashlib.blake2b(key, digest_size=16).digest()


def _longs(digests: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    pairs = np.frombuffer(b"".join(digests), np.int64).reshape(-1, 2)
    return pairs[:, 0], pairs[:, 1]


def _identified(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.coalesce(F.col(id_col).cast("bigint"), F.lit(NULL_ID)).alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def line_keys(docs: DataFrame, min_chars: int = MIN_CHARS, filters: list[tuple[int, bytes]] | None = None, shards: int = SHARDS) -> DataFrame:
    """(doc_id, k1, k2) of every document's distinct keys; with filters, only of those a filter holds."""
    shared = None if filters is None else docs.sparkSession.sparkContext.broadcast(dict(filters))
    opened: dict[int, CuckooFilter] = {}  # of a task

    def run(batch: pa.RecordBatch) -> pa.RecordBatch | None:
        rows, digests = [], []
        for i, raw in enumerate(utf8_rows(batch.column(1))):
            found = {k for line in raw.split(b"\n") if (k := line_key(line, min_chars)) is not None}
            rows += [i] * len(found)
            digests += found
        if not digests:
            return None
        k1, k2 = _longs(digests)
        at = np.array(rows)
        if shared is not None:
            keep, shard = np.zeros(len(k1), bool), k1 % shards
            for s in np.unique(shard).tolist():
                if s not in opened and s in shared.value:
                    opened[s] = CuckooFilter.from_bytes(shared.value[s])
                if s in opened:
                    own = np.flatnonzero(shard == s)
                    keep[own] = opened[s].contains(k1[own])
            k1, k2, at = k1[keep], k2[keep], at[keep]
        return pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(at)), pa.array(k1), pa.array(k2)], ["doc_id", "k1", "k2"])

    return map_arrow(docs, run, "doc_id bigint, k1 bigint, k2 bigint", rows=2048)


def reference_counts(keys: DataFrame) -> DataFrame:
    """The exact table: k1, k2, refs (documents that hold the key), first_doc. Pre-aggregated before the shuffle."""
    return keys.groupBy("k1", "k2").agg(F.count(F.lit(1)).alias("refs"), F.min("doc_id").alias("first_doc"))


@dataclass
class LineStore:
    """References (k1, k2, refs, first_doc) and filters (shard, cells) of the keys with two or more references.

    `holders` keeps every (doc_id, k1, k2), so that a deletion can find the next smallest document; a store that is only looked up in
    has none. There are `shards` or more filters, so that each has about KEYS_PER_SHARD keys at most.
    """

    holders: DataFrame | None
    references: DataFrame
    filters: DataFrame
    shards: int = SHARDS

    @classmethod
    def build(cls, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, shards: int = SHARDS) -> LineStore:
        holders = written(line_keys(_identified(docs, id_col, text_col), min_chars).distinct(), "line-holders")
        return cls._filtered(holders, written(reference_counts(holders), "line-references"), shards)

    @classmethod
    def _filtered(cls, holders: DataFrame | None, references: DataFrame, shards: int) -> LineStore:
        """The store with filters made anew, in as many shards as the keys need."""
        shards = max(shards, -(-references.where("refs >= 2").count() // KEYS_PER_SHARD))
        return cls(holders, references, written(shard_filters(references, shards), "line-filters"), shards)

    def strip(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, digest: bool = False, counts: tuple[str, str] = ("n_lines", "n_dropped")) -> DataFrame:
        """Documents of the store without the lines that one of smaller id has."""
        dropped = drops(_identified(docs, id_col, text_col), self.references, self.filters, self.shards, min_chars)
        return strip_lines(docs, dropped, min_chars, digest, id_col, text_col, counts)

    def insert(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS) -> LineStore:
        """The store with these documents too; documents it already holds add nothing."""
        new = line_keys(_identified(docs, id_col, text_col), min_chars).distinct().join(self.holders, ["doc_id", "k1", "k2"], "left_anti")
        new = written(new, "line-new")
        merged = self.references.unionByName(reference_counts(new)).groupBy("k1", "k2").agg(F.sum("refs").alias("refs"), F.min("first_doc").alias("first_doc"))
        return self._after(written(self.holders.unionByName(new), "line-holders"), written(merged, "line-references"))

    def delete(self, doc_ids: DataFrame, id_col: str = "doc_id") -> LineStore:
        """The store without these documents."""
        gone = doc_ids.select(F.coalesce(F.col(id_col).cast("bigint"), F.lit(NULL_ID)).alias("doc_id")).distinct()
        holders = written(self.holders.join(gone, "doc_id", "left_anti"), "line-holders")
        touched = self.holders.join(gone, "doc_id", "left_semi").select("k1", "k2").distinct()
        recounted = reference_counts(holders.join(touched, ["k1", "k2"], "left_semi"))
        kept = self.references.join(touched, ["k1", "k2"], "left_anti")
        return self._after(holders, written(kept.unionByName(recounted), "line-references"))

    def _after(self, holders: DataFrame, references: DataFrame) -> LineStore:
        """Filters changed by what has come to two references or fallen below; made anew in more shards once they are crowded."""
        if references.where("refs >= 2").count() > 2 * self.shards * KEYS_PER_SHARD:
            return self._filtered(holders, references, self.shards)
        was = self.references.where("refs >= 2").select("k1", "k2", F.lit(-1).alias("change"))
        now = references.where("refs >= 2").select("k1", "k2", F.lit(1).alias("change"))
        moved = was.unionByName(now).groupBy("k1", "k2").agg(F.sum("change").alias("change")).where("change <> 0")
        shards = self.shards
        moved = moved.withColumn("shard", F.pmod("k1", F.lit(shards)))

        def change(key: tuple, changes: pd.DataFrame, held: pd.DataFrame) -> pd.DataFrame:
            cells = CuckooFilter.from_bytes(held["cells"].iloc[0], True) if len(held) else CuckooFilter.for_keys(len(changes))
            cells.delete(changes.loc[changes["change"] < 0, "k1"].to_numpy(np.int64))
            kept = cells.table.copy()
            added = changes.loc[changes["change"] > 0, "k1"].to_numpy(np.int64)
            if not cells.insert(added):  # too full: the caller builds this shard anew
                cells = CuckooFilter(cells.buckets, kept)
                return pd.DataFrame({"shard": [key[0]], "cells": [b""]})
            return pd.DataFrame({"shard": [key[0]], "cells": [cells.to_bytes()]})

        filters = written(moved.groupBy("shard").cogroup(self.filters.groupBy("shard")).applyInPandas(change, "shard bigint, cells binary"), "line-filters")
        full = filters.where("length(cells) = 0").select("shard")
        anew = shard_filters(references.join(full, F.pmod("k1", F.lit(shards)) == full["shard"], "left_semi"), shards)
        return LineStore(holders, references, filters.where("length(cells) > 0").unionByName(anew), shards)


def shard_filters(references: DataFrame, shards: int = SHARDS) -> DataFrame:
    """(shard, cells): a cuckoo filter for each shard of the keys that two or more documents hold."""

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"shard": [key[0]], "cells": [build_filter(group["k1"].to_numpy(np.int64)).to_bytes()]})

    shared = references.where("refs >= 2").select("k1", F.pmod("k1", F.lit(shards)).alias("shard"))
    return shared.groupBy("shard").applyInPandas(run, "shard bigint, cells binary")


def sift(keys: DataFrame, filters: DataFrame, shards: int, slices: int = SLICES) -> DataFrame:
    """The keys that their shard's filter holds, for filters too large to send: a filter goes before the keys of its shard, in each slice."""
    asked = keys.select(F.pmod("k1", F.lit(shards)).alias("shard"), F.pmod(F.xxhash64("doc_id"), F.lit(slices)).cast("bigint").alias("slice"), F.lit(None).cast("binary").alias("cells"), "doc_id", "k1", "k2")
    none = [F.lit(0).cast("bigint").alias(c) for c in ("doc_id", "k1", "k2")]
    sent = filters.select(F.col("shard").cast("bigint").alias("shard"), F.explode(F.array(*(F.lit(i).cast("bigint") for i in range(slices)))).alias("slice"), "cells", *none)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, None
        for batch in batches:
            shard, part = (batch.column(i).to_numpy() for i in range(2))
            cells, k1 = batch.column(2), batch.column(4).to_numpy()
            keep = np.zeros(len(k1), bool)
            edges = np.flatnonzero(np.concatenate(([True], (shard[1:] != shard[:-1]) | (part[1:] != part[:-1])))) if len(k1) else np.zeros(0, int)
            for i, j in zip(edges.tolist(), [*edges[1:].tolist(), len(k1)], strict=True):
                if (shard[i], part[i]) != now:
                    now, held = (shard[i], part[i]), CuckooFilter.from_bytes(cells[i].as_py()) if cells[i].is_valid else None
                if held is not None:
                    keep[i:j] = held.contains(k1[i:j])
            keep &= ~cells.is_valid().to_numpy(zero_copy_only=False)
            if keep.any():
                yield pa.RecordBatch.from_arrays([batch.column(i).filter(pa.array(keep)) for i in (3, 4, 5)], ["doc_id", "k1", "k2"])

    dealt = asked.unionByName(sent).repartition("shard", "slice").sortWithinPartitions("shard", "slice", F.col("cells").isNull())
    return dealt.mapInArrow(run, "doc_id bigint, k1 bigint, k2 bigint")


def drops(docs: DataFrame, references: DataFrame, filters: DataFrame, shards: int, min_chars: int = MIN_CHARS) -> DataFrame:
    """(doc_id, keys): for each document the keys whose lines it loses. Lines pass the filters, then the exact join."""
    total = filters.agg(F.sum(F.length("cells"))).first()[0] or 0
    if total <= FILTERS_BROADCAST_BYTES:
        asked = line_keys(docs, min_chars, [(r["shard"], bytes(r["cells"])) for r in filters.collect()], shards)
    else:
        asked = sift(line_keys(docs, min_chars), filters, shards)
    found = asked.join(references.where("refs >= 2"), ["k1", "k2"]).where("doc_id <> first_doc")
    return found.groupBy("doc_id").agg(F.collect_set(F.struct("k1", "k2")).alias("keys"))


def strip_lines(
    docs: DataFrame, dropped: DataFrame, min_chars: int = MIN_CHARS, digest: bool = False, id_col: str = "doc_id", text_col: str = "text", counts: tuple[str, str] = ("n_lines", "n_dropped")
) -> DataFrame:
    """All columns of the documents with the remaining lines as text, or their digest, and the counts: lines before, and lines dropped."""
    keyed = as_rows(docs, id=F.coalesce(F.col(f"`{id_col}`").cast("bigint"), F.lit(NULL_ID)))
    joined = keyed.join(dropped.select(F.col("doc_id").alias("id"), "keys"), "id", "left").select("row", "keys")
    out = Rewritten(docs, text_col, counts)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts, lines, losses = [], [], []
        for raw, keys in zip(utf8_rows(out.texts(batch)), batch.column(1).to_pylist(), strict=True):
            parts = raw.split(b"\n")
            gone = {int(k["k1"]).to_bytes(8, "little", signed=True) + int(k["k2"]).to_bytes(8, "little", signed=True) for k in keys} if keys else ()
            kept = [p for p in parts if line_key(p, min_chars) not in gone] if gone else parts
            left = b"\n".join(kept)
            texts.append(hashlib.sha256(left).hexdigest() if digest else left.decode("utf-8", "replace"))
            lines.append(len(parts))
            losses.append(len(parts) - len(kept))
        return out.batch(batch, texts, lines, losses)

    return map_arrow(joined, run, out.schema)


def dedup_lines(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    min_chars: int = MIN_CHARS,
    digest: bool = False,
    shards: int = SHARDS,
    counts: tuple[str, str] = ("n_lines", "n_dropped"),
) -> DataFrame:
    """Documents without the lines that a document of smaller id already has.

    The exact table and the filters are built from the whole input and written before they are read.
    """
    # a document's repeated rows may each emit a key, so here "two documents" is told by the least and greatest id
    shared = written(plain_references(line_keys(_identified(docs, id_col, text_col), min_chars)), "line-references")
    return LineStore._filtered(None, shared, shards).strip(docs, id_col, text_col, min_chars, digest, counts)


def plain_references(keys: DataFrame) -> DataFrame:
    """Exact references of the keys that two or more documents hold."""
    return keys.groupBy("k1", "k2").agg(F.count(F.lit(1)).alias("refs"), F.min("doc_id").alias("first_doc"), F.max("doc_id").alias("last_doc")).where("first_doc <> last_doc").drop("last_doc")


#: DuckDB SQL for the query over `documents`.
ORACLE_SQL = r"""
WITH l AS (SELECT doc_id, t, generate_subscripts(t, 1) AS i, unnest(t) AS line FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS t FROM documents)),
k AS (SELECT doc_id, i, line, translate(regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
r AS (SELECT key, min(doc_id) AS first_doc FROM k WHERE length(key) >= 10 GROUP BY key HAVING count(DISTINCT doc_id) >= 2)
SELECT k.doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (WHERE r.first_doc < k.doc_id)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(CASE WHEN r.first_doc < k.doc_id THEN NULL ELSE line END, chr(10) ORDER BY i), '')) AS kept_sha256
FROM k LEFT JOIN r USING (key) GROUP BY k.doc_id
"""
