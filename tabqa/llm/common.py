"""What the operators of this subpackage share."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType

#: The ASCII white space of the contracts: blank, tab, line feed, vertical tab, form feed, return.
ASCII_SPACE = " \t\n\x0b\x0c\r"
#: A word of the contracts.
WORD_BYTES = rb"[^\x20\x09-\x0D]+"
_UPPER = bytes(range(ord("A"), ord("Z") + 1))
_LOWER_TABLE = bytes.maketrans(_UPPER, _UPPER.lower())


def ascii_lower(raw: bytes) -> bytes:
    """A-Z lower-cased, every other byte as it is."""
    return raw.translate(_LOWER_TABLE)


def utf8_rows(column: pa.Array | pa.ChunkedArray) -> Iterator[bytes]:
    """The texts of an Arrow column as UTF-8; null gives an empty text."""
    for value in column.cast(pa.large_binary()).to_pylist():
        yield value or b""


def slices(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    """Record batches cut small, so that a worker holds few long texts at once."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def map_arrow(df: DataFrame, run: Callable[[pa.RecordBatch], pa.RecordBatch | None], schema: str | StructType, rows: int = 512) -> DataFrame:
    """mapInArrow with a function of one small batch."""

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, rows):
            out = run(part)
            if out is not None and out.num_rows:
                yield out

    return df.mapInArrow(apply, schema)


def held_out(id_column: str, folds: int, fold: int = 1) -> Column:
    """True where crc32 of the id's text leaves the named remainder; false for a null id."""
    return F.coalesce(F.crc32(F.col(id_column).cast("string").cast("binary")) % F.lit(folds) == F.lit(fold), F.lit(False))


def as_rows(docs: DataFrame, **more: Column) -> DataFrame:
    """(row, …): all columns as one, so that none of their names can clash with those of `more`."""
    return docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), *(c.alias(name) for name, c in more.items()))


class Rewritten:
    """The columns of documents with a new text and some counts; a column named like a count gives way to it."""

    def __init__(self, docs: DataFrame, text_col: str, counts: Sequence[str]):
        taken = {c.lower() for c in counts}
        self.at = docs.columns.index(text_col)
        self.kept = [i for i, c in enumerate(docs.columns) if c.lower() not in taken]
        fields = [docs.schema.fields[i] for i in self.kept]
        self.schema = StructType([StructField(f.name, StringType()) if f.name == text_col else f for f in fields] + [StructField(c, LongType()) for c in counts])
        self.names = self.schema.names

    def texts(self, batch: pa.RecordBatch) -> pa.Array:
        return batch.column(0).field(self.at)

    def batch(self, batch: pa.RecordBatch, texts: list[str], *counts: list[int]) -> pa.RecordBatch:
        columns = batch.column(0).flatten()
        columns[self.at] = pa.array(texts, pa.string())
        return pa.RecordBatch.from_arrays([*(columns[i] for i in self.kept), *(pa.array(c, pa.int64()) for c in counts)], self.names)


def unused(docs: DataFrame, *names: str) -> list[str]:
    """The names, lengthened until no column of the documents has them."""
    held = {c.lower() for c in docs.columns}
    out = []
    for name in names:
        while name.lower() in held:
            name += "_"
        held.add(name.lower())
        out.append(name)
    return out
