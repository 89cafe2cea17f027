"""Packing token sequences: first-fit decreasing over a tournament tree of bin capacities.

Documents become ids (with an end id) and are cut at the sequence length; full pieces are sequences of their own.
The rest is dealt into groups at random (by a hash of document, position and the row's place in its input), and every group is packed on its own: its pieces, longest
first, each go to the first bin with room, which the tree of greatest free capacities finds in logarithmic time.
Groups hold the pieces of about `group_rows` documents whatever the size of the table, so no task grows with it; a long document's pieces are spread over all groups.

A null or empty text gives the end id alone. Repeated rows are packed each on its own. A null doc_id is kept as it is. Further columns take no part. An empty
table gives no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tabqa.llm.bpe import MergeQueueEncoder
from tabqa.llm.common import map_arrow

SEQUENCE = 4096
END_ID = 2
GROUP_ROWS = 2_000


class CapacityTree:
    """A tournament tree: leaves are bins' free capacities, inner nodes the greater of two children."""

    def __init__(self, bins: int, capacity: int):
        self.leaves = 1 << max(0, bins - 1).bit_length()
        self.tree = [capacity] * (2 * self.leaves)

    def first_with(self, need: int) -> int:
        """The leftmost bin with so much room, or -1."""
        tree, at = self.tree, 1
        if tree[1] < need:
            return -1
        while at < self.leaves:
            at *= 2
            if tree[at] < need:
                at += 1
        return at - self.leaves

    def take(self, bin_: int, amount: int) -> int:
        """Uses room in a bin; returns what was free before."""
        tree, at = self.tree, bin_ + self.leaves
        free = tree[at]
        tree[at] -= amount
        at //= 2
        while at:
            best = max(tree[2 * at], tree[2 * at + 1])
            if tree[at] == best:
                break
            tree[at] = best
            at //= 2
        return free


def first_fit_decreasing(lengths: np.ndarray, capacity: int = SEQUENCE) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each piece; equal lengths keep the order they come in."""
    order = np.argsort(-lengths, kind="stable")
    tree = CapacityTree(len(lengths), capacity)
    bins, offsets = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    for at, need in zip(order.tolist(), lengths[order].tolist(), strict=True):
        bins[at] = found = tree.first_with(need)
        offsets[at] = capacity - tree.take(found, need)
    return bins, offsets


def pieces(docs: DataFrame, vocabulary: str, capacity: int = SEQUENCE, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The pieces of every document: doc_id, start, length, ids_crc32, doc_tokens, and place: which row of its task's input it comes from."""
    end = end_id.to_bytes(4, "little")
    seen = [0]  # rows of a task so far

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        coder = MergeQueueEncoder.load(vocabulary)
        rows, starts, lengths, sums, totals = [], [], [], [], []
        for i, raw in enumerate(coder.encoded_ids_many(batch.column(1).to_pylist())):
            raw += end
            n = len(raw) // 4
            for start in range(0, n, capacity):
                part = raw[4 * start : 4 * (start + capacity)]
                rows.append(i)
                starts.append(start)
                lengths.append(len(part) // 4)
                sums.append(zlib.crc32(part))
                totals.append(n)
        places = [seen[0] + i for i in rows]
        seen[0] += batch.num_rows
        return pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(rows, pa.int32())), *(pa.array(x, pa.int64()) for x in (starts, lengths, sums, totals, places))], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "place"])

    kind = dict(docs.dtypes)[id_col]
    return map_arrow(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")), run, f"doc_id {kind}, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, place bigint", rows=384)


def pack(parts: DataFrame, groups: int, capacity: int = SEQUENCE) -> DataFrame:
    """Pieces with sequence_id and offset; sequence ids are distinct over all groups.

    A piece's group is a hash of what it is and of its place, so rows repeated very often, or without an id, are spread like any others.
    """

    def run(key: tuple, batches: Iterator[pd.DataFrame] | pd.DataFrame) -> pd.DataFrame:
        group = batches.sort_values(["doc_id", "start", "ids_crc32"], kind="stable", na_position="first").reset_index(drop=True)
        bins, offsets = first_fit_decreasing(group["length"].to_numpy(np.int64), capacity)
        return group.drop(columns=["part_group", "place"]).assign(sequence_id=(np.int64(key[0]) << np.int64(32)) + bins, offset=offsets)

    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in parts.schema.fields if f.name != "place")
    dealt = parts.withColumn("part_group", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32", "place", F.lit(77)), F.lit(groups)))
    return dealt.groupBy("part_group").applyInPandas(run, f"{fields}, sequence_id bigint, offset bigint")


def pack_documents(docs: DataFrame, vocabulary: str, capacity: int = SEQUENCE, group_rows: int = GROUP_ROWS, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All documents in sequences of at most `capacity` ids; a row for each piece."""
    groups = max(1, -(-docs.count() // group_rows))
    return pack(pieces(docs, vocabulary, capacity, end_id, id_col, text_col), groups, capacity)
