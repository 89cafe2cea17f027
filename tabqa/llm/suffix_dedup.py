"""Repeated byte strings by threshold-bounded interval expansion on a Burrows-Wheeler transform.

A byte goes when a string of `window` bytes that covers it also starts anywhere else in the corpus. The core works on a block of
strings: from the intervals of the transform's rows, breadth-first backward extension derives the common prefixes of
neighbouring suffixes by increasing value, and stops at `window`; the neighbours left without a value share at least so
many bytes.

What reaches a block is chosen by content. Every window belongs to an anchor, and all its copies to anchors with the same gram
(module anchors). The distributed plan:

1. Count (gram, context) over all documents, equal ones summed before the shuffle. A context found twice is repeated
   throughout; a gram with one context found once is unique.
2. For grams with several contexts, fetch one copy of each. Contexts are trimmed to what can match at all; equal trimmed ones
   are one, with their number; what still differs goes through the transform, in blocks of bounded size. A gram
   with more contexts than a block takes is settled by counting its windows' hashes in a distributed aggregation.
3. Every document gets the repeated windows of its contexts, and drops the bytes they cover.

Matches never cross documents. A null text is empty. Repeated rows repeat each other's strings. A null doc_id is an id like
any other. Texts shorter than `window` stay whole. Equal 64-bit digests count as equal strings. Other columns stay as they are,
whatever their names, but for those named like the counts that the result has: these give way.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tabqa.llm.anchors import Prints, anchors, signatures
from tabqa.llm.common import Rewritten, as_rows, map_arrow, slices, utf8_rows
from tabqa.session import free_shuffles, scratch, written

WINDOW = 200
NULL_ID = -(1 << 63)
#: Bytes of a block.
BLOCK_BYTES = 1 << 20
#: Contexts of one gram that a block takes; grams with more are counted by windows.
MOST_CONTEXTS = 400


def suffix_order(block: np.ndarray, depth: int) -> np.ndarray:
    """Suffixes of a block in order of their first `depth` symbols, ties by place. 0 is a separator, unlike any other.

    The block ends with a separator. Seven symbols are compared at once, then ranks of twice the length.
    """
    n, at = len(block), np.arange(len(block))
    packed, cut = np.zeros(n, np.int64), np.zeros(n, bool)
    padded = np.concatenate((block.astype(np.int64), np.zeros(7, np.int64)))
    for k in range(7):
        symbol = padded[k : k + n]
        cut |= symbol == 0
        packed = (packed << 9) | np.where(cut, 0, symbol)
    order = np.lexsort((np.where(cut, at, -1), packed))
    fresh = np.concatenate(([True], (packed[order][1:] != packed[order][:-1]) | cut[order][1:]))
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(fresh, at, 0))
    reach = 7
    while reach < depth:
        last = np.append(fresh[1:], True)
        open_at = np.flatnonzero(~(fresh & last))  # places in order whose suffix is not alone
        if not len(open_at):
            break
        suffix = order[open_at]
        key = rank[suffix] * n + rank[np.minimum(suffix + reach, n - 1)]
        by = np.argsort(key, kind="stable")
        order[open_at] = suffix[by]
        key = key[by]
        fresh[open_at] = np.concatenate(([True], key[1:] != key[:-1]))
        starts = np.maximum.accumulate(np.where(fresh[open_at], open_at, 0))
        rank[order[open_at]] = starts
        reach *= 2
    return order


def shared_neighbours(block: np.ndarray, order: np.ndarray, depth: int) -> np.ndarray:
    """For each place of the order: does its suffix share `depth` symbols or more with the one before?"""
    n = len(order)
    before = block[order - 1].astype(np.int64)  # the transform: the symbol before each suffix
    separators = int((block == 0).sum())
    to_row = np.empty(n, np.int64)  # where the extended suffix stands
    to_row[np.argsort(before, kind="stable")] = np.arange(n)
    known = np.zeros(n + 1, bool)
    known[: separators + 1] = True
    known[n] = True
    low, high = np.array([0]), np.array([n - 1])
    for length in range(depth):
        if not len(low):
            break
        sizes = high - low + 1
        owner = np.repeat(np.arange(len(low)), sizes)
        rows = np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes) + low[owner]
        symbol = before[rows]
        inner = symbol > 0
        rows, owner, symbol = to_row[rows[inner]], owner[inner], symbol[inner]
        by = np.argsort(rows)
        rows, group = rows[by], owner[by] * 512 + symbol[by]
        edge = np.flatnonzero(group[1:] != group[:-1])
        new_low, new_high = rows[np.concatenate(([0], edge + 1))] if len(rows) else rows, rows[np.append(edge, len(rows) - 1)] if len(rows) else rows
        fresh = ~known[new_high + 1]
        low, high = new_low[fresh], new_high[fresh]
        known[high + 1] = True
        if not length:  # each separator's own suffix is extended too
            low, high = np.append(low, np.arange(separators)), np.append(high, np.arange(separators))
        order_of = np.argsort(low)
        low, high = low[order_of], high[order_of]
    return ~known[:n]


def repeated_starts(strings: list[bytes], depth: int) -> list[np.ndarray]:
    """For each string the places where a substring of `depth` bytes starts that starts elsewhere in the strings too."""
    lengths = np.array([len(s) for s in strings])
    block = np.zeros(int(lengths.sum()) + len(strings), np.int16)
    starts = np.concatenate(([0], np.cumsum(lengths + 1)[:-1]))
    for at, s in zip(starts.tolist(), strings, strict=True):
        block[at : at + len(s)] = np.frombuffer(s, np.uint8).astype(np.int16) + 1
    order = suffix_order(block, depth)
    shared = shared_neighbours(block, order, depth)
    hit = shared | np.append(shared[1:], False)
    places = np.sort(order[hit])
    owner = np.searchsorted(starts, places, "right") - 1
    cuts = np.searchsorted(owner, np.arange(len(strings) + 1))
    return [places[cuts[i] : cuts[i + 1]] - starts[i] for i in range(len(strings))]


def _common(a: bytes, b: bytes) -> int:
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    return int(np.argmax(np.frombuffer(a, np.uint8, n) != np.frombuffer(b, np.uint8, n)))


def _reaches(parts: list[bytes]) -> list[int]:
    """The longest common prefix of each with any other: that with a neighbour in sorted order."""
    out = [0] * len(parts)
    order = sorted(range(len(parts)), key=parts.__getitem__)
    for i, j in zip(order, order[1:]):
        n = _common(parts[i], parts[j])
        out[i], out[j] = max(out[i], n), max(out[j], n)
    return out


def settle(grams: list[list[tuple[bytes, int, bool]]], window: int = WINDOW) -> list[list[np.ndarray]]:
    """Repeated windows of the contexts of some grams.

    A context is its bytes, the gram's place, and whether all its windows are known to be repeated. Returns
    for each the first bytes of repeated windows; those of known ones are not asked for.
    """
    out: list[list[np.ndarray]] = []
    strings: list[bytes] = []
    asked: list[tuple[int, int, int, int]] = []
    for contexts in grams:
        found = [np.zeros(0, np.int64)] * len(contexts)
        left, right = _reaches([c[:at][::-1] for c, at, _ in contexts]), _reaches([c[at:] for c, at, _ in contexts])
        trimmed: dict[tuple[bytes, int], list[tuple[int, int]]] = {}
        for i, (c, at, _) in enumerate(contexts):
            if left[i] + right[i] >= window:
                trimmed.setdefault((c[at - left[i] : at + right[i]], left[i]), []).append((i, at - left[i]))
        for (string, _), members in trimmed.items():
            if len(members) > 1 or any(contexts[i][2] for i, _ in members):
                for i, shift in members:
                    found[i] = shift + np.arange(len(string) - window + 1)
        if len(trimmed) > 1:
            for (string, _), members in trimmed.items():
                if len(members) == 1 and not contexts[members[0][0]][2]:
                    asked.append((len(out), members[0][0], members[0][1], len(strings)))
                strings.append(string)
        out.append(found)
    if asked:
        starts = repeated_starts(strings, window)
        for g, i, shift, k in asked:
            out[g][i] = shift + starts[k]
    return out


def _runs(starts: np.ndarray) -> list[int]:
    """Sorted places as first and last of each run of neighbours, flat."""
    if not len(starts):
        return []
    edge = np.flatnonzero(np.diff(starts) > 1)
    return np.stack((starts[np.concatenate(([0], edge + 1))], starts[np.append(edge, len(starts) - 1)]), 1).ravel().tolist()


def _longs(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64) if x.dtype == np.uint64 else x.astype(np.int64))


def context_counts(docs: DataFrame, window: int) -> DataFrame:
    """(g, c, n, doc_id): occurrences of each context, and a document that holds it; summed batch by batch first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, 4096):
            ids = np.array(batch.column(0).to_pylist(), np.int64)
            grams, contexts, owners = [], [], []
            for i, raw in enumerate(utf8_rows(batch.column(1))):
                if (found := signatures(raw, window)) is not None:
                    grams.append(found[0])
                    contexts.append(found[1])
                    owners.append(np.full(len(found[0]), i))
            if not grams:
                continue
            g, c, owner = np.concatenate(grams), np.concatenate(contexts), np.concatenate(owners)
            order = np.lexsort((c, g))
            g, c, owner = g[order], c[order], owner[order]
            first = np.flatnonzero(np.concatenate(([True], (g[1:] != g[:-1]) | (c[1:] != c[:-1]))))
            yield pa.RecordBatch.from_arrays([_longs(g[first]), _longs(c[first]), _longs(np.diff(np.append(first, len(g)))), _longs(ids[owner[first]])], ["g", "c", "n", "doc_id"])

    return docs.mapInArrow(run, "g bigint, c bigint, n bigint, doc_id bigint")


def document_contexts(docs: DataFrame, window: int) -> DataFrame:
    """(doc_id, g, c): the distinct contexts of every document."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch | None:
        grams, contexts, owners = [], [], []
        for i, raw in enumerate(utf8_rows(batch.column(1))):
            if (found := signatures(raw, window)) is not None:
                pair = np.unique(np.stack((found[0], found[1]), 1), axis=0)
                grams.append(pair[:, 0])
                contexts.append(pair[:, 1])
                owners.append(np.full(len(pair), i))
        if not grams:
            return None
        return pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(np.concatenate(owners))), _longs(np.concatenate(grams)), _longs(np.concatenate(contexts))], ["doc_id", "g", "c"])

    return map_arrow(docs, run, "doc_id bigint, g bigint, c bigint")


def fetch_contexts(docs: DataFrame, asked: DataFrame, window: int) -> DataFrame:
    """(g, c, known, crowded, at, context) of the asked contexts (g, c, n, doc_id, variants)."""
    wanted = asked.groupBy("doc_id").agg(F.collect_list(F.struct("g", "c", (F.col("n") > 1).alias("known"), (F.col("variants") > MOST_CONTEXTS).alias("crowded"))).alias("wanted"))
    joined = docs.join(wanted, "doc_id").select("text", "wanted")

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = []
        for raw, wanted in zip(utf8_rows(batch.column(0)), batch.column(1).to_pylist(), strict=True):
            left = {(w["g"], w["c"]): w for w in wanted}
            found = anchors(raw, window)
            if found is None:
                continue
            _, at, first, last = found
            g, c, _, _ = signatures(raw, window)
            for i, pair in enumerate(zip(g.view(np.int64).tolist(), c.view(np.int64).tolist(), strict=True)):
                if (w := left.pop(pair, None)) is not None:
                    rows.append((*pair, w["known"], w["crowded"], int(at[i] - first[i]), raw[first[i] : last[i] + window]))
        kinds = [pa.int64(), pa.int64(), pa.bool_(), pa.bool_(), pa.int64(), pa.binary()]
        return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kind) for k, kind in enumerate(kinds)], ["g", "c", "known", "crowded", "at", "context"])

    return map_arrow(joined, run, "g bigint, c bigint, known boolean, crowded boolean, at bigint, context binary")


def settle_blocks(contexts: DataFrame, window: int) -> DataFrame:
    """(g, c, runs) of the contexts not known to be repeated throughout, a block of grams at a time."""

    def block(rows: list[tuple]) -> pa.RecordBatch:
        grams: dict[int, dict[int, tuple]] = {}
        for g, c, known, at, context in rows:
            grams.setdefault(g, {})[c] = (context, at, known)
        found = settle([list(v.values()) for v in grams.values()], window)
        out = [(g, c, _runs(starts)) for (g, members), each in zip(grams.items(), found, strict=True) for c, starts in zip(members, each, strict=True) if len(starts) and not members[c][2]]
        return pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], pa.int64()), pa.array([o[1] for o in out], pa.int64()), pa.array([o[2] for o in out], pa.list_(pa.int32()))], ["g", "c", "runs"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0
        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                if size > BLOCK_BYTES and row[0] != held[-1][0]:
                    yield block(held)
                    held, size = [], 0
                held.append(row)
                size += len(row[4])
        if held:
            yield block(held)

    dealt = contexts.select("g", "c", "known", "at", "context").repartition("g").sortWithinPartitions("g")
    return dealt.mapInArrow(run, "g bigint, c bigint, runs array<int>")


#: Crowded contexts to a shard, about.
SHARD_CONTEXTS = 2_000
_PLACED = "shard bigint, a binary, b binary, c binary, d binary"


def _dealt(shard: np.ndarray, *columns: np.ndarray) -> pa.RecordBatch:
    """Rows of numbers packed by shard: one row of the frame for each shard that has any."""
    order = np.argsort(shard, kind="stable")
    shard = shard[order]
    first = np.flatnonzero(np.concatenate(([True], shard[1:] != shard[:-1])))
    last = np.append(first[1:], len(shard))
    packed = [[x[order][i:j].tobytes() for i, j in zip(first, last, strict=True)] for x in columns]
    packed += [[b""] * len(first)] * (4 - len(columns))
    return pa.RecordBatch.from_arrays([pa.array(shard[first].astype(np.int64)), *(pa.array(x, pa.binary()) for x in packed)], ["shard", "a", "b", "c", "d"])


def _by_shard(packed: DataFrame, work, schema: str) -> DataFrame:
    """Gathers each shard's numbers in one task and hands them to `work`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def flush() -> Iterator[pa.RecordBatch]:
            if held and (made := work(*(np.frombuffer(b"".join(h[k] for h in held), np.int64) for k in range(1, 5)))) is not None:
                yield made

        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                if held and row[0] != held[-1][0]:
                    yield from flush()
                    held = []
                held.append(row)
        yield from flush()

    return packed.repartition("shard").sortWithinPartitions("shard").mapInArrow(run, schema)


def settle_crowded(contexts: DataFrame, window: int) -> DataFrame:
    """The same for grams of very many contexts: every window's hash meets its equals in a shard.

    Windows and repeated places travel as packed arrays, a row for each shard and batch.
    """
    contexts = contexts.select("g", "c", "known", "context")
    shards = max(64, contexts.count() // SHARD_CONTEXTS)

    def spread(batch: pa.RecordBatch) -> pa.RecordBatch | None:
        rows, hashes, places = [], [], []
        for i, (known, context) in enumerate(zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)):
            starts = np.arange(len(context) - window + 1)
            hashes.append(Prints(context).of(starts, starts + window).view(np.int64))
            places.append(np.full(len(starts), -1) if known else starts)
            rows.append(np.full(len(starts), i))
        if not rows:
            return None
        row, h = np.concatenate(rows), np.concatenate(hashes)
        g, c = batch.column(0).to_numpy()[row], batch.column(1).to_numpy()[row]
        return _dealt(h % shards, h, g, c, np.concatenate(places))

    def repeated(h: np.ndarray, g: np.ndarray, c: np.ndarray, place: np.ndarray) -> pa.RecordBatch | None:
        order = np.argsort(h, kind="stable")
        ordered = h[order]
        same = ordered[1:] == ordered[:-1]
        hit = order[np.append(same, False) | np.concatenate(([False], same))]
        hit = hit[place[hit] >= 0]
        return _dealt((g[hit] ^ c[hit]) % shards, g[hit], c[hit], place[hit]) if len(hit) else None

    def gathered(g: np.ndarray, c: np.ndarray, place: np.ndarray, _: np.ndarray) -> pa.RecordBatch:
        order = np.lexsort((place, c, g))
        g, c, place = g[order], c[order], place[order]
        first = np.flatnonzero(np.concatenate(([True], (g[1:] != g[:-1]) | (c[1:] != c[:-1]))))
        runs = [_runs(np.unique(x)) for x in np.split(place, first[1:])]
        return pa.RecordBatch.from_arrays([pa.array(g[first]), pa.array(c[first]), pa.array(runs, pa.list_(pa.int32()))], ["g", "c", "runs"])

    return _by_shard(_by_shard(map_arrow(contexts, spread, _PLACED, 1024), repeated, _PLACED), gathered, "g bigint, c bigint, runs array<int>")


def removals(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """(doc_id, found): for every document its contexts with repeated windows; null runs: all of them."""
    spread = Window.partitionBy("g")
    counts = context_counts(docs, window).repartition("g").groupBy("g", "c").agg(F.sum("n").alias("n"), F.min("doc_id").alias("doc_id"))
    with scratch():
        counts = written(counts.withColumn("variants", F.count(F.lit(1)).over(spread)).where("n > 1 OR variants > 1"), "suffix-counts")
        contexts = written(fetch_contexts(docs, counts.where("variants > 1"), window), "suffix-contexts")
        runs = settle_blocks(contexts.where("NOT crowded"), window).unionByName(settle_crowded(contexts.where("crowded"), window))
        whole = counts.where("n > 1").select("g", "c", F.lit(None).cast("array<int>").alias("runs"))
        found = written(whole.unionByName(runs), "suffix-found", keep=True)
    free_shuffles(docs.sparkSession)
    return document_contexts(docs, window).join(found, ["g", "c"]).groupBy("doc_id").agg(F.collect_list(F.struct("g", "c", "runs")).alias("found"))


def covered(raw: bytes, found: list[dict] | None, window: int = WINDOW) -> list[tuple[int, int]]:
    """The maximal stretches of a text that its repeated windows cover."""
    if not found or (own := signatures(raw, window)) is None:
        return []
    by = {(f["g"], f["c"]): f["runs"] for f in found}
    g, c, first, last = own
    spans: list[tuple[int, int]] = []
    for pair, a, b in zip(zip(g.view(np.int64).tolist(), c.view(np.int64).tolist(), strict=True), first.tolist(), last.tolist(), strict=True):
        if pair not in by:
            continue
        runs = by[pair]
        for lo, hi in [(0, b - a)] if runs is None else zip(runs[::2], runs[1::2], strict=True):
            lo, hi = a + lo, a + hi + window
            if spans and lo <= spans[-1][1]:
                spans[-1] = (spans[-1][0], max(hi, spans[-1][1]))
            else:
                spans.append((lo, hi))
    return spans


def without(raw: bytes, spans: list[tuple[int, int]]) -> bytes:
    out, at = [], 0
    for lo, hi in spans:
        out.append(raw[at:lo])
        at = hi
    return b"".join([*out, raw[at:]])


def whole_letters(raw: bytes, spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans drawn in so that they neither start nor end inside a character."""
    out = []
    for lo, hi in spans:
        while lo < hi and raw[lo] & 0xC0 == 0x80:
            lo += 1
        while hi > lo and hi < len(raw) and raw[hi] & 0xC0 == 0x80:
            hi -= 1
        if hi > lo:
            out.append((lo, hi))
    return out


def dedup_substrings(
    docs: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", digest: bool = False, counts: tuple[str, str, str] = ("n_bytes", "n_removed", "n_spans")
) -> DataFrame:
    """All columns of the documents, with the counts: bytes before, bytes removed, and removed spans; the text is what remains, or its digest.

    As text, spans are drawn in to whole characters; digests are of the remaining bytes exactly.
    """
    key = F.coalesce(F.col(f"`{id_col}`").cast("bigint"), F.lit(NULL_ID))
    plain = docs.select(key.alias("doc_id"), F.col(f"`{text_col}`").cast("string").alias("text"))
    found = removals(plain, window).select(F.col("doc_id").alias("id"), "found")
    joined = as_rows(docs, id=key).join(found, "id", "left").select("row", "found")
    out = Rewritten(docs, text_col, counts)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts, sizes, removed, runs = [], [], [], []
        for raw, found in zip(utf8_rows(out.texts(batch)), batch.column(1).to_pylist(), strict=True):
            spans = covered(raw, found, window)
            if not digest:
                spans = whole_letters(raw, spans)
            left = without(raw, spans)
            texts.append(hashlib.sha256(left).hexdigest() if digest else left.decode("utf-8", "replace"))
            sizes.append(len(raw))
            removed.append(len(raw) - len(left))
            runs.append(len(spans))
        return out.batch(batch, texts, sizes, removed, runs)

    return map_arrow(joined, run, out.schema)
