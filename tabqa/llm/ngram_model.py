"""An n-gram language model (words, pairs, triples) in Elias-Fano trie levels.

The words are an Elias-Fano sequence of their hashes. A level of pairs or triples holds, for each context (a place in the level
above), its successors' word ids, ascending and packed in as many bits as a word id needs; monotone Elias-Fano pointers tell where each
context's successors begin. A successor is searched between its context's two pointers. Beside the successors stand their quantised
probabilities. Levels are cut into files of bounded size; the files lie in the shared folder, and the tasks that score map them into
memory. Only the files' names and bounds pass through the driver, and the totals of contexts that several files share.

Smoothing is interpolated absolute discounting: p(w|h) = (c - D) / c(h) + D * n(h) / c(h) * p(w|h'), where n(h) counts the distinct
successors of h: the distance between its pointers. The first part is what an entry stores; c(h) follows from h's own entry. Every pair
and triple counts, from its first occurrence on. A word's own probability is the smoothed one of the base score.

Counting passes over all training documents. Each task counts its documents' keys (context * words + word) and passes them on in
sorted, delta-coded arrays by key range; the task that merges a range writes its file. The ranges come from a sample of keys, as those of any
sort do; they decide the files' sizes, and nothing else. A context that very many words follow is cut like any other run of keys.

A null or empty text is the end token alone. Without training documents every probability is that of the base formula with
no counts. Repeated rows count each.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import _parse_datatype_string

from tabqa.llm.anchors import Prints
from tabqa.llm.common import ascii_lower, map_arrow, slices, utf8_rows
from tabqa.llm.elias_fano import EliasFano, bits_at, pack_bits
from tabqa.session import discard, free_shuffles, scratch_folder, written

DISCOUNT = 0.75
#: Keys of one file of a level, about.
FILE_KEYS = 1_000_000
#: Keys that a task holds before it counts them and passes them on.
HELD_KEYS = 2_000_000
#: Keys that the bounds of the ranges are taken from, about.
BOUND_KEYS = 200_000
#: Bytes of files that a task keeps which it could not map into memory.
KEPT_BYTES = 256 << 20
END = np.int64(1)
#: Logarithms of probabilities lie between this and 0.
_LEAST_LOG = -12.0
_SCALE = 65535 / _LEAST_LOG


def word_hashes(raw: bytes) -> np.ndarray:
    """63-bit hashes of a text's words, A-Z lower-cased, and the end token."""
    text = b" ".join(ascii_lower(raw).split())
    if not text:
        return np.array([END])
    blanks = np.flatnonzero(np.frombuffer(text, np.uint8) == 32)
    starts, ends = np.concatenate(([0], blanks + 1)), np.concatenate((blanks, [len(text)]))
    return np.append((Prints(text).of(starts, ends) >> np.uint64(1)).astype(np.int64), END)


def quantise(shares: np.ndarray) -> np.ndarray:
    """Logarithms of probabilities in sixteen bits."""
    return np.clip(np.round(np.log10(shares) * _SCALE), 0, 65535).astype(np.uint16)


_SHARES = 10.0 ** (np.arange(1 << 16) / _SCALE)


_KINDS = ["<u8", "<i8", "<u2", "<i4"]


# Files -------------------------------------------------------------------------------------------------------------


def _store(folder: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(folder if "://" in folder else f"file://{folder}" if folder.startswith("/") else folder.replace("file:", "file://", 1))


def _publish(folder: str, arrays: list[np.ndarray]) -> str:
    """Writes arrays one after another, 8-byte aligned, under a name made of their content.

    The file appears under its name when it is whole; a task that runs twice writes the same file again.
    """
    head = [len(arrays)]
    parts = []
    for a in arrays:
        raw = np.ascontiguousarray(a).tobytes()
        head += [len(a), _KINDS.index(a.dtype.str)]
        parts.append(raw + b"\0" * (-len(raw) % 8))
    blob = np.array([*head, *([0] * (64 - len(head)))], np.int64).tobytes() + b"".join(parts)
    where, base = _store(folder)
    where.create_dir(base, recursive=True)
    name = hashlib.blake2b(blob, digest_size=16).hexdigest()
    part = f"{base}/.{name}.{np.random.default_rng().integers(1 << 62)}"
    with where.open_output_stream(part) as out:
        out.write(blob)
    where.move(part, f"{base}/{name}")
    return name


def _open(folder: str, name: str) -> list[np.ndarray]:
    """The file's arrays: memory-mapped from a mounted folder, read from any other store."""
    where, base = _store(folder)
    raw = np.asarray(np.memmap(f"{base}/{name}", np.uint8, "r")) if isinstance(where, fs.LocalFileSystem) else np.frombuffer(where.open_input_file(f"{base}/{name}").read(), np.uint8)
    head = raw[:512].view(np.int64)
    out, at = [], 512
    for k in range(int(head[0])):
        n, kind = int(head[1 + 2 * k]), np.dtype(_KINDS[int(head[2 + 2 * k])])
        size = n * kind.itemsize
        out.append(raw[at : at + size].view(kind))
        at += size + (-size % 8)
    return out


_OPENED: dict[tuple[str, str], tuple] = {}


def _opened(folder: str, name: str, made: Callable[[list[np.ndarray]], tuple]) -> tuple:
    """An opened file. Mapped ones stay; of others the latest stay, up to KEPT_BYTES, however many a level has."""
    key = (folder, name)
    held = _OPENED.pop(key, None)
    if held is None:
        arrays = _open(folder, name)
        mapped = isinstance(_store(folder)[0], fs.LocalFileSystem)
        held = (0 if mapped else sum(a.nbytes for a in arrays), made(arrays))
        over = sum(size for size, _ in _OPENED.values()) + held[0] - KEPT_BYTES
        for old in [k for k, (size, _) in _OPENED.items() if size] if over > 0 else []:
            over -= _OPENED.pop(old)[0]
            if over <= 0:
                break
    _OPENED[key] = held
    return held[1]


# Counting ----------------------------------------------------------------------------------------------------------

_COUNTED = "range bigint, n bigint, keys binary, counts binary"


def _planes(values: np.ndarray) -> bytes:
    """Integers with their lowest bytes first, then their second ones, and so on: the upper ones are mostly 0 and compress."""
    return np.ascontiguousarray(values).view(np.uint8).reshape(len(values), -1).T.tobytes()


def _from_planes(raw: bytes, kind: str) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(size, -1).T).reshape(-1).view(kind)


def _counted(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys ascending, with how often they occur."""
    keys = np.sort(keys)
    first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    return keys[first], np.diff(np.append(first, len(keys)))


def _merged(runs: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Runs of ascending keys with counts as one; equal keys' counts are summed."""
    if len(runs) == 1:
        return runs[0]
    keys, counts = (np.concatenate([r[k] for r in runs]) for k in (0, 1))
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order].astype(np.int64)
    first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    return keys[first], np.add.reduceat(counts, first)


def _ranged(keys: np.ndarray, counts: np.ndarray, bounds: np.ndarray) -> pa.RecordBatch:
    """Counted ascending keys, one row for each range that has any."""
    cuts = np.concatenate(([0], np.searchsorted(keys, bounds), [len(keys)]))
    held = np.flatnonzero(cuts[1:] > cuts[:-1])
    parts = [(int(cuts[k]), int(cuts[k + 1])) for k in held]
    deltas = [_planes(np.diff(keys[i:j], prepend=0)) for i, j in parts]
    return pa.RecordBatch.from_arrays(
        [pa.array(held), pa.array([j - i for i, j in parts], pa.int64()), pa.array(deltas, pa.binary()), pa.array([_planes(counts[i:j].astype(np.int64)) for i, j in parts], pa.binary())],
        ["range", "n", "keys", "counts"],
    )


def range_bounds(rows: DataFrame, keys_of: Callable[[pa.RecordBatch], np.ndarray], tokens: int, ranges: int) -> np.ndarray:
    """What parts the keys into ranges of about equal size, told from the distinct keys of a sample of the rows."""
    if ranges < 2 or not tokens:
        return np.zeros(0, np.int64)
    share = min(1.0, BOUND_KEYS / tokens)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        keys = np.unique(keys_of(batch))
        keys = keys[:: len(keys) // (BOUND_KEYS // 10) + 1]  # of very long texts every so many
        return pa.RecordBatch.from_arrays([pa.array([keys.tobytes()], pa.binary())], ["keys"])

    sample = rows.sample(False, share, 29) if share < 1 else rows
    found = map_arrow(sample, run, "keys binary", 4096).collect()
    keys = np.unique(np.concatenate([np.frombuffer(r["keys"], np.int64) for r in found])) if found else np.zeros(0, np.int64)
    return np.unique(keys[np.linspace(0, len(keys), ranges + 1).astype(int)[1:-1]]) if len(keys) >= ranges else keys


def count_keys(rows: DataFrame, keys_of: Callable[[pa.RecordBatch], np.ndarray], bounds: np.ndarray, publish: Callable[[np.ndarray, np.ndarray], list], schema: str) -> list:
    """What `publish` makes of each range's ascending keys and their counts over all rows; `keys_of` gives the keys of a batch."""
    kinds = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in slices(batches, 512):
            keys = keys_of(batch)
            held.append(keys)
            size += len(keys)
            if size > HELD_KEYS:
                yield _ranged(*_counted(np.concatenate(held)), bounds)
                held, size = [], 0
        if size:
            yield _ranged(*_counted(np.concatenate(held)), bounds)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, runs = None, []

        def flush() -> Iterator[pa.RecordBatch]:
            made = [publish(*part) for part in _parts(*_merged(runs))]
            yield pa.RecordBatch.from_pylist(made, kinds)

        for batch in batches:
            for number, _, keys, counts in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if now is not None and number != now:
                    yield from flush()
                    runs = []
                now = number
                runs.append((np.cumsum(_from_planes(keys, "<i8")), _from_planes(counts, "<i8")))
        if runs:
            yield from flush()

    sent = rows.mapInArrow(run, _COUNTED).repartitionById(len(bounds) + 1, F.col("range").cast("int")).sortWithinPartitions("range")
    return sent.mapInArrow(merge, schema).collect()


def _parts(keys: np.ndarray, counts: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """A range, cut where it is more than one file should hold."""
    for part in np.array_split(np.arange(len(keys)), max(1, len(keys) // (2 * FILE_KEYS))):
        yield keys[part[0] : part[-1] + 1], counts[part[0] : part[-1] + 1]


# Levels ------------------------------------------------------------------------------------------------------------


@dataclass
class Words:
    """The words' hashes, ascending, with their counts. `first` and `start`: each file's first hash, and how many words lie before it."""

    folder: str
    names: list[str] = field(default_factory=list)
    first: list[int] = field(default_factory=list)
    start: list[int] = field(default_factory=list)
    size: int = 0
    tokens: int = 0

    @classmethod
    def build(cls, rows: DataFrame, keys_of: Callable[[pa.RecordBatch], np.ndarray], folder: str, ranges: int) -> Words:
        def publish(keys: np.ndarray, counts: np.ndarray) -> dict:
            coded = EliasFano.build(keys - keys[0])
            meta = np.array([coded.n, coded.low_bits, coded.steps, int(keys[0])], np.int64)
            return {"name": _publish(folder, [meta, coded.lows, coded.uppers, coded.zeros.astype(np.int32), counts.astype(np.int64)]), "first": int(keys[0]), "n": len(keys), "tokens": int(counts.sum())}

        # hashes are spread evenly already
        bounds = np.array([(k << 63) // ranges for k in range(1, ranges)], np.int64)
        found = sorted(count_keys(rows, keys_of, bounds, publish, "name string, first bigint, n bigint, tokens bigint"), key=lambda r: r["first"])
        out = cls(folder, [r["name"] for r in found], [r["first"] for r in found])
        for r in found:
            out.start.append(out.size)
            out.size += r["n"]
            out.tokens += r["tokens"]
        return out

    def _file(self, k: int) -> tuple[EliasFano, int, np.ndarray]:
        def made(arrays: list[np.ndarray]) -> tuple:
            meta, lows, uppers, zeros, counts = arrays
            return EliasFano(int(meta[0]), int(meta[1]), lows, uppers, zeros.astype(np.int64), int(meta[2])), int(meta[3]), counts

        return _opened(self.folder, self.names[k], made)

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """The words' places, -1 where the level lacks them; each distinct one is searched once."""
        distinct, back = np.unique(hashes, return_inverse=True)
        place = np.full(len(distinct), -1, np.int64)
        for k, i, j in _by_file(self.first, distinct):
            sequence, base, _ = self._file(k)
            at = sequence.find(distinct[i:j] - base)
            place[i:j] = np.where(at >= 0, at + self.start[k], -1)
        return place[back]

    def counts(self, places: np.ndarray) -> np.ndarray:
        distinct, back = np.unique(places, return_inverse=True)
        out = np.zeros(len(distinct), np.int64)
        for k, i, j in _by_file(self.start, distinct):
            out[i:j] = self._file(k)[2][distinct[i:j] - self.start[k]]
        return out[back]


def _by_file(firsts: list[int], ascending: np.ndarray) -> Iterator[tuple[int, int, int]]:
    """(file, i, j): the file that each stretch of ascending values falls in; values before the first file are left out."""
    cuts = np.append(np.searchsorted(ascending, np.array(firsts, np.int64)), len(ascending))
    for k in np.flatnonzero(cuts[1:] > cuts[:-1]).tolist():
        yield k, int(cuts[k]), int(cuts[k + 1])


@dataclass
class Successors:
    """A level of pairs or triples. `first`, `context` and `start`: each file's first key, its first context, and how many entries lie before it.

    A context that several files hold is in `fans` with the number of all its successors, and in `parts` with the share of its total that each file has.
    """

    folder: str
    words: int
    names: list[str] = field(default_factory=list)
    first: list[int] = field(default_factory=list)
    context: list[int] = field(default_factory=list)
    start: list[int] = field(default_factory=list)
    size: int = 0
    fans: dict[int, int] = field(default_factory=dict)
    parts: dict[int, dict[int, float]] = field(default_factory=dict)

    @classmethod
    def build(cls, rows: DataFrame, keys_of: Callable[[pa.RecordBatch], np.ndarray], folder: str, words: int, bounds: np.ndarray, discount: float) -> Successors:
        width = max(1, words - 1).bit_length()

        def publish(keys: np.ndarray, counts: np.ndarray) -> dict:
            context = keys // words
            begins = np.flatnonzero(np.concatenate(([True], context[1:] != context[:-1])))
            held = context[begins]
            totals = np.add.reduceat(counts.astype(np.int64), begins)
            fans = np.diff(np.append(begins, len(keys)))
            # a pointer for each context from the first to the last, also for those that nothing follows
            dense = np.zeros(int(held[-1] - held[0]) + 2, np.int64)
            dense[held - held[0] + 1] = fans
            pointers = EliasFano.build(np.cumsum(dense))
            meta = np.array([pointers.n, pointers.low_bits, pointers.steps, width], np.int64)
            codes = quantise((counts - discount) / np.repeat(totals, fans))
            name = _publish(folder, [meta, pointers.lows, pointers.uppers, pointers.zeros.astype(np.int32), pack_bits(keys - context * words, width), codes])
            ends = [[int(held[k]), int(totals[k]), int(fans[k])] for k in {0, len(held) - 1}]
            return {"name": name, "first": int(keys[0]), "context": int(held[0]), "n": len(keys), "ends": ends}

        found = sorted(count_keys(rows, keys_of, bounds, publish, "name string, first bigint, context bigint, n bigint, ends array<array<bigint>>"), key=lambda r: r["first"])
        out = cls(folder, words, [r["name"] for r in found], [r["first"] for r in found], [r["context"] for r in found])
        ends: dict[int, list[tuple[int, int, int]]] = {}
        for k, r in enumerate(found):
            out.start.append(out.size)
            out.size += r["n"]
            for context, total, fan in r["ends"]:
                ends.setdefault(context, []).append((k, total, fan))
        for context, held in ends.items():
            if len(held) > 1:
                out.fans[context] = sum(fan for _, _, fan in held)
                for k, total, _ in held:
                    out.parts.setdefault(k, {})[context] = total / sum(t for _, t, _ in held)
        return out

    def _file(self, k: int) -> tuple[EliasFano, int, np.ndarray, np.ndarray]:
        """Pointers, bits of a word, words, and codes of the entries."""

        def made(arrays: list[np.ndarray]) -> tuple:
            meta, lows, uppers, zeros, packed, codes = arrays
            return EliasFano(int(meta[0]), int(meta[1]), lows, uppers, zeros.astype(np.int64), int(meta[2])), int(meta[3]), packed, codes

        return _opened(self.folder, self.names[k], made)

    def find(self, context: np.ndarray, word: np.ndarray) -> np.ndarray:
        """The place of each context's successor `word`, -1 where it has none such."""
        distinct, back = np.unique(context * self.words + word, return_inverse=True)
        place = np.full(len(distinct), -1, np.int64)
        for k, i, j in _by_file(self.first, distinct):
            pointers, width, packed, _ = self._file(k)
            own = distinct[i:j] // self.words
            wanted = (distinct[i:j] - own * self.words).astype(np.uint64)
            own -= self.context[k]
            inside = np.flatnonzero(own < pointers.n - 1)
            one, which = _runs_of(own[inside])
            ends = pointers.at(np.append(one, one + 1))
            left, end = ends[: len(one)][which], ends[len(one) :][which]
            right, sought = end.copy(), wanted[inside]
            open_ = np.flatnonzero(left < right)
            while len(open_):  # halves what is left of each context's successors, which ascend
                a, b = left[open_], right[open_]
                middle = (a + b) >> 1
                below = bits_at(packed, middle, width) < sought[open_]
                a, b = np.where(below, middle + 1, a), np.where(below, b, middle)
                left[open_], right[open_] = a, b
                open_ = open_[a < b]
            hit = np.flatnonzero(left < end)
            hit = hit[bits_at(packed, left[hit], width) == sought[hit]]
            place[i + inside[hit]] = left[hit] + self.start[k]
        return place[back]

    def fan(self, context: np.ndarray) -> np.ndarray:
        """How many distinct successors each context has."""
        distinct, back = np.unique(context, return_inverse=True)
        out = np.zeros(len(distinct), np.int64)
        for k, i, j in _by_file(self.context, distinct):
            pointers = self._file(k)[0]
            own = distinct[i:j] - self.context[k]
            inside = np.flatnonzero(own < pointers.n - 1)
            ends = pointers.at(np.append(own[inside], own[inside] + 1))
            out[i + inside] = ends[len(inside) :] - ends[: len(inside)]
        for i in _held(distinct, self.fans):
            out[i] = self.fans[int(distinct[i])]
        return out[back]

    def share(self, context: np.ndarray, place: np.ndarray) -> np.ndarray:
        """The probability that the entry at each place stores, as a part of its context's total; 0 for -1."""
        out = np.zeros(len(place))
        held = np.flatnonzero(place >= 0)
        distinct, at, back = np.unique(place[held], return_index=True, return_inverse=True)
        shares = np.zeros(len(distinct))
        for k, i, j in _by_file(self.start, distinct):
            shares[i:j] = _SHARES[self._file(k)[3][distinct[i:j] - self.start[k]]]
            if k in self.parts:
                own = context[held[at[i:j]]]
                for c, part in self.parts[k].items():
                    shares[i:j][own == c] *= part
        out[held] = shares[back]
        return out


def _held(ascending: np.ndarray, known: dict[int, int]) -> list[int]:
    """Where ascending values are keys of a small dict."""
    if not known or not len(ascending):
        return []
    keys = np.array(sorted(known), np.int64)
    return np.flatnonzero(keys[np.minimum(np.searchsorted(keys, ascending), len(keys) - 1)] == ascending).tolist()


def _runs_of(ascending: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct values of an ascending array, and which of them each is."""
    fresh = np.concatenate(([True], ascending[1:] != ascending[:-1])) if len(ascending) else np.zeros(0, bool)
    return ascending[fresh], np.cumsum(fresh) - 1


# The model ---------------------------------------------------------------------------------------------------------


def _joined(texts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """All tokens of some texts, and where each text begins."""
    return np.concatenate(texts), np.concatenate(([0], np.cumsum([len(t) for t in texts])[:-1]))


def _read(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All numbers of a column as `_packed` wrote them, and where each text begins."""
    column = column.cast(pa.binary())
    ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(column.buffers()[2], np.uint8)[ends[0] : ends[-1]]
    sizes, at = np.zeros(len(column), np.int64), ends[:-1] - ends[0]
    # a text's first byte tells how many bytes its numbers have
    width = int(raw[at[0]]) if len(at) else 1
    if (raw[at] != width).any():
        raise ValueError("numbers of different widths in one batch")
    sizes = (np.diff(ends) - 1) // width
    keep = np.ones(len(raw), bool)
    keep[at] = False
    values = np.zeros((int(sizes.sum()), 8), np.uint8)
    values[:, :width] = raw[keep].reshape(-1, width)
    return values.view(np.int64).reshape(-1) - 1, np.cumsum(sizes) - sizes


def _packed(values: np.ndarray, begins: np.ndarray, width: int) -> pa.Array:
    """Each text's numbers (-1 or more, below 2 ** (8 * width) - 1), in `width` bytes each after one that tells the width."""
    sizes = np.diff(np.append(begins, len(values)))
    ends = np.concatenate(([0], np.cumsum(sizes * width + 1)))
    raw = np.full(int(ends[-1]), width, np.uint8)
    keep = np.ones(len(raw), bool)
    keep[ends[:-1]] = False
    raw[keep] = np.ascontiguousarray(values + 1).view(np.uint8).reshape(-1, 8)[:, :width].reshape(-1)
    return pa.Array.from_buffers(pa.binary(), len(begins), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(raw)])


def _bytes_for(size: int) -> int:
    return (size.bit_length() + 7) // 8


def _pair_ends(ids: np.ndarray, begins: np.ndarray) -> np.ndarray:
    """Second tokens of the neighbouring known words."""
    inside = np.ones(len(ids), bool)
    inside[begins] = False
    second = np.flatnonzero(inside)
    return second[(ids[second] >= 0) & (ids[second - 1] >= 0)]


@dataclass
class NgramModel:
    """Three levels; the words' level knows how many training tokens there are."""

    words: Words
    pairs: Successors
    triples: Successors
    discount: float

    @property
    def tokens(self) -> int:
        return self.words.tokens

    def places(self, ids: np.ndarray, begins: np.ndarray) -> np.ndarray:
        """For each token the place of its pair with the token before, -1 where the model has none."""
        second = _pair_ends(ids, begins)
        out = np.full(len(ids), -1, np.int64)
        out[second] = self.pairs.find(ids[second - 1], ids[second])
        return out

    def _interpolated(self, p: np.ndarray, level: Successors, context: np.ndarray, total: np.ndarray, share: np.ndarray) -> np.ndarray:
        """The share of the entry itself, and what its context leaves times the shorter context's probability."""
        fan = level.fan(context)
        return np.where(fan > 0, self.discount * fan / np.maximum(total, 1.0), 1.0) * p + share

    def score(self, ids: np.ndarray, places: np.ndarray, begins: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For each text: known tokens, the base score, and the model's log10 probability."""
        known = np.flatnonzero(ids >= 0)
        counts = np.zeros(len(ids))
        counts[known] = self.words.counts(ids[known])
        single = (counts + 0.5) / (self.tokens + 0.5 * (self.words.size + 1))
        inside = np.ones(len(ids), bool)
        inside[begins] = False
        p, pair_counts = single.copy(), np.zeros(len(ids))
        after = np.flatnonzero(inside)
        after = after[ids[after - 1] >= 0]
        first, total = ids[after - 1], counts[after - 1]
        share = self.pairs.share(first, places[after])
        pair_counts[after] = np.round(share * total + self.discount)
        p[after] = self._interpolated(p[after], self.pairs, first, total, share)
        third = np.flatnonzero(inside[1:] & (places[:-1] >= 0)) + 1 if len(places) else np.zeros(0, np.int64)
        context, at = places[third - 1], np.full(len(third), -1, np.int64)
        whole = np.flatnonzero(ids[third] >= 0)
        at[whole] = self.triples.find(context[whole], ids[third[whole]])
        p[third] = self._interpolated(p[third], self.triples, context, pair_counts[third - 1], self.triples.share(context, at))
        sums = [np.add.reduceat(x, begins) for x in ((ids >= 0).astype(np.int64), np.log10(single), np.log10(np.minimum(p, 1.0)))]
        return sums[0], sums[1], sums[2]


def _with_ids(docs: DataFrame, words: Words, keep: list[str], text_col: str) -> DataFrame:
    """The kept columns and the documents as word ids."""
    width = _bytes_for(words.size + 1)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        hashes, begins = _joined([word_hashes(raw) for raw in utf8_rows(batch.column(0))])
        return pa.RecordBatch.from_arrays([*batch.columns[1:], _packed(words.find(hashes), begins, width)], [*keep, "ids"])

    chosen = docs.select(F.col(text_col).cast("string").alias("__text"), *keep)
    return map_arrow(chosen, run, ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in chosen.schema.fields[1:]), "ids binary"]))


def _with_places(rows: DataFrame, model: NgramModel) -> DataFrame:
    """The rows with the places of their pairs."""
    at, width = rows.columns.index("ids"), _bytes_for(model.pairs.size + 1)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        ids, begins = _read(batch.column(at))
        return pa.RecordBatch.from_arrays([*batch.columns, _packed(model.places(ids, begins), begins, width)], [*batch.schema.names, "places"])

    return map_arrow(rows, run, ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields), "places binary"]), 1024)


def train_and_score(docs: DataFrame, training: str, keep: list[str], text_col: str = "text", discount: float = DISCOUNT) -> tuple[NgramModel, DataFrame]:
    """The model of the documents for which `training` (SQL over the kept columns) holds, and the scores of all.

    The scores have the kept columns, n_tokens, n_known, train_tokens, base_score and score. The documents as word ids, and then
    with the places of their pairs, are written to the shared folder, so that each text is read twice and each pair searched once.
    """
    spark = docs.sparkSession
    folder = f"{scratch_folder(spark)}/ngrams-{np.random.default_rng().integers(1 << 62)}"
    learned = docs.where(training).select(F.col(text_col).cast("string").alias("text"))
    # about eight bytes a token, of which a range takes as many as a file has keys
    size = learned.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    words = Words.build(learned, lambda batch: np.concatenate([word_hashes(raw) for raw in utf8_rows(batch.column(0))]), folder, max(8, min(size // (64 * FILE_KEYS), 4096)))
    ranges = max(8, -(-words.tokens // FILE_KEYS))
    many = max(1, words.size)
    free_shuffles(spark)
    ids = written(_with_ids(docs, words, keep, text_col), "ngram-ids", "zstd")

    def pair_keys(batch: pa.RecordBatch) -> np.ndarray:
        ids, begins = _read(batch.column(0))
        second = _pair_ends(ids, begins)
        return ids[second - 1] * many + ids[second]

    rows = ids.where(training).select("ids")
    pairs = Successors.build(rows, pair_keys, folder, many, range_bounds(rows, pair_keys, words.tokens, ranges), discount)
    if max(many, pairs.size) >= 1 << 31 or pairs.size * many >= 1 << 62:
        raise ValueError("too many words and pairs for keys of 62 bits")
    model = NgramModel(words, pairs, Successors(folder, many), discount)
    free_shuffles(spark)
    both = written(_with_places(ids, model), "ngram-places", "zstd")
    discard(ids)

    def triple_keys(batch: pa.RecordBatch) -> np.ndarray:
        ids, _ = _read(batch.column(0))
        places, _ = _read(batch.column(1))
        third = np.flatnonzero((places[1:] >= 0) & (places[:-1] >= 0)) + 1  # a text's first token ends no pair
        return places[third - 1] * many + ids[third]

    rows = both.where(training).select("ids", "places")
    triples = Successors.build(rows, triple_keys, folder, many, range_bounds(rows, triple_keys, words.tokens, ranges), discount)
    whole = NgramModel(words, pairs, triples, discount)
    return whole, _scores(both, whole, keep)


def _scores(rows: DataFrame, model: NgramModel, keep: list[str]) -> DataFrame:
    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        ids, begins = _read(batch.column(0))
        places = _read(batch.column(1))[0]
        known, base, score = model.score(ids, places, begins)
        lengths = np.diff(np.append(begins, len(ids)))
        return pa.RecordBatch.from_arrays([*batch.columns[2:], pa.array(lengths), pa.array(known), pa.array(np.full(len(begins), model.tokens)), pa.array(base), pa.array(score)], [*keep, "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    chosen = rows.select("ids", "places", *keep)
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in chosen.schema.fields[2:])
    return map_arrow(chosen, run, f"{fields}, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double", 1024)


def score_documents(docs: DataFrame, model: NgramModel, keep: list[str], text_col: str = "text") -> DataFrame:
    """Scores of further documents by a model there is."""
    return _scores(_with_places(_with_ids(docs, model.words, keep, text_col), model), model, keep)
