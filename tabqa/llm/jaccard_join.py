"""N-gram Jaccard join with adaptive multi-match prefixes.

A document is its set of distinct word shingles. All sets are sorted by one global order, frequent shingles last. Two sets of
similarity t or more, of sizes m and n, share at least t*max(m, n) shingles; so if a prefix of n - ceil(t*n) + k
shingles is taken from each, they share k of them. Each document takes the k of least estimated cost: a longer prefix
is read more often, but fewer others share k shingles of it. A pair is verified when it shares the smaller of both k.

The distributed plan:

1. One pass makes each document's set id (a digest of the set; equal sets are one from here on) and counts shingles in a
   sketch of fixed size, which gives the frequency classes of the global order.
2. A second pass emits prefix shingles. Sorted by shingle and size they form runs of sets whose sizes can match; runs of one
   set end here. The first set of a run is its pivot. Pivots and sets that meet often enough are verified, and
   the links found give first components. So a large group of near copies costs a comparison for each of its sets.
3. Only sets of different first components are compared further. A short run gives its pairs, counted over all shingles, so
   only pairs with enough matches go on. A long run gives a cluster, cut into blocks that meet two by two. All are verified
   exactly on whole sets; of the links of a group a spanning forest leaves the task.
4. Components come from alternating stars.

A null or empty text, or one without words, has an empty set and links with nothing. Texts with fewer words than a shingle
have the whole sequence as their one shingle. Repeated rows are equal sets. Equal 64-bit digests count as equal shingles.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tabqa.llm.anchors import Prints
from tabqa.llm.common import ascii_lower, map_arrow, slices, utf8_rows
from tabqa.llm.components import connected
from tabqa.session import free_shuffles, scratch, written

NULL_ID = -(1 << 63)
#: Counters of the frequency sketch, in bits.
SKETCH_BITS = 21
#: Sets in a block; a task compares two blocks.
BLOCK = 64
#: Longest multi-match considered.
MOST_MATCHES = 6
def shingle_set(raw: bytes, words: int) -> np.ndarray:
    """Sorted digests of a text's distinct shingles of so many words, A-Z lower-cased."""
    text = b" ".join(ascii_lower(raw).split())  # bytes split at exactly the contract's white space
    if not text:
        return np.zeros(0, np.uint64)
    blanks = np.flatnonzero(np.frombuffer(text, np.uint8) == 32)
    starts, ends = np.concatenate(([0], blanks + 1)), np.concatenate((blanks, [len(text)]))
    if len(starts) >= words:
        starts, ends = starts[: len(starts) - words + 1], ends[words - 1 :]
    else:
        starts, ends = starts[:1], ends[-1:]
    return np.unique(Prints(text).of(starts, ends))


def set_id(tokens: np.ndarray) -> int:
    """A set's id; 0 is the empty set."""
    return int.from_bytes(hashlib.blake2b(tokens.tobytes(), digest_size=8).digest(), "little", signed=True) or 1 if len(tokens) else 0


def required(n: np.ndarray | int, percent: int):
    """The least overlap of a set of n with a partner: ceil(t * n)."""
    return (percent * n + 99) // 100


def global_order(tokens: np.ndarray, classes: np.ndarray) -> np.ndarray:
    """The set in the global order: frequency class, then digest."""
    return tokens[np.argsort(classes[(tokens >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)], kind="stable")]


def choose_matches(ordered: np.ndarray, classes: np.ndarray, percent: int) -> int:
    """The multi-match k of least cost.

    Reading k's prefix costs the frequencies of its shingles; at most a k-th of these postings' sum are sets that share
    k of them, and each of those costs a verification in proportion to the set.
    """
    n = len(ordered)
    need = int(required(n, percent))
    frequency = np.exp2(classes[(ordered[: n - need + MOST_MATCHES] >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)].astype(np.float64)) - 1
    read = np.cumsum(frequency)
    best, least = 1, np.inf
    for k in range(1, min(MOST_MATCHES, need) + 1):
        seen = float(read[n - need + k - 1])
        cost = seen + seen / k * n / 16
        if cost < least:
            best, least = k, cost
    return best


def set_table(docs: DataFrame, words: int) -> DataFrame:
    """(doc_id, sid, n) of every row."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets = [shingle_set(raw, words) for raw in utf8_rows(batch.column(1))]
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array([set_id(s) for s in sets], pa.int64()), pa.array([len(s) for s in sets], pa.int64())], ["doc_id", "sid", "n"])

    return map_arrow(docs, run, "doc_id bigint, sid bigint, n bigint")


def frequency_classes(docs: DataFrame, words: int) -> np.ndarray:
    """The class of each sketch counter: the binary logarithm of how far it stands above its share of rare shingles.

    Every task counts all shingles of its documents in one sketch of fixed size; the sketches are added up piece by piece.
    What reaches the driver is one sketch, however large the table is.
    """
    size, piece = 1 << SKETCH_BITS, 1 << 15

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(size, np.int64)
        for batch in slices(batches, 1024):
            places = [shingle_set(raw, words) >> np.uint64(64 - SKETCH_BITS) for raw in utf8_rows(batch.column(1))]
            counts += np.bincount(np.concatenate(places).astype(np.int64), minlength=size)
        if counts.any():  # a byte is enough for what a task adds to telling frequent from rare
            small = np.minimum(counts, 255).astype(np.uint8)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(size // piece)), pa.array([small[i : i + piece].tobytes() for i in range(0, size, piece)], pa.binary())], ["piece", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, raw in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                sums[k] = sums.get(k, 0) + np.frombuffer(raw, np.uint8).astype(np.int64)
        for k, total in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([k]), pa.array([total.tobytes()], pa.binary())], ["piece", "counts"])

    kind = "piece bigint, counts binary"
    rows = docs.mapInArrow(count, kind).repartition("piece").mapInArrow(add, kind).collect()
    counts = np.zeros(size, np.int64)
    for r in rows:
        counts[r["piece"] * piece : (r["piece"] + 1) * piece] = np.frombuffer(r["counts"], np.int64)
    mean = counts.sum() / size
    above = np.where(counts > max(3.0, mean + 4 * np.sqrt(mean)), counts - mean, 0)
    return np.log2(1 + above).astype(np.uint8)


def prefixes(docs: DataFrame, words: int, percent: int, classes: np.ndarray) -> DataFrame:
    """(token, sid, n, k): the prefix shingles of every set; a task emits a set that it meets again only once."""
    sent = docs.sparkSession.sparkContext.broadcast(classes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        met: set[int] = set()
        for batch in slices(batches):
            tokens, sids, sizes, matches = [], [], [], []
            for raw in utf8_rows(batch.column(1)):
                whole = shingle_set(raw, words)
                sid = set_id(whole)
                if not sid or sid in met:
                    continue
                if len(met) > 1_000_000:
                    met.clear()
                met.add(sid)
                ordered = global_order(whole, sent.value)
                k = choose_matches(ordered, sent.value, percent)
                part = ordered[: len(whole) - int(required(len(whole), percent)) + k]
                tokens.append(part)
                sids.append(np.full(len(part), sid, np.int64))
                sizes.append(np.full(len(part), len(whole), np.int64))
                matches.append(np.full(len(part), k, np.int64))
            if tokens:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x).view(np.int64)) for x in (tokens, sids, sizes, matches)], ["token", "sid", "n", "k"])

    return docs.mapInArrow(run, "token bigint, sid bigint, n bigint, k bigint")


def matches_needed(n: np.ndarray, k: np.ndarray, m: np.ndarray, j: np.ndarray, percent: int) -> np.ndarray:
    """Prefix shingles that two sets of sizes n and m with multi-matches k and j must share to be similar.

    At least the smaller multi-match. And since all common shingles up to the end of the prefix that ends first are in both
    prefixes, the overlap is at most the shared ones and the rest of one of the sets.
    """
    overlap = (percent * (n + m) + 99 + percent) // (100 + percent)
    rest = np.maximum(required(n, percent) - k, required(m, percent) - j)
    return np.maximum(np.minimum(k, j), overlap - rest)


def shared_posts(posts: DataFrame, percent: int) -> DataFrame:
    """The postings of shingles that two or more sets of matching sizes have, with the run's first set, size and match.

    The postings are sorted by shingle and size, and streamed; a run ends where the shingle changes or the size leaps by
    more than the threshold allows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros((4, 0), np.int64)  # the last posting, whose run may go on
        first = None  # the first posting of that run, once it has been passed on
        for batch in batches:
            rows = np.hstack([held, np.stack([c.to_numpy() for c in batch.columns])])
            if not rows.shape[1]:
                continue
            token, n, sid, _ = rows
            fresh = np.concatenate(([True], (token[1:] != token[:-1]) | (100 * n[:-1] < percent * n[1:])))
            start = np.maximum.accumulate(np.where(fresh, np.arange(len(token)), 0))
            lead = rows[:, start]
            if first is not None:  # the run at the front began earlier
                lead[:, : int(np.flatnonzero(fresh[1:])[0]) + 1 if fresh[1:].any() else None] = first[:, None]
            alone = fresh & np.append(fresh[1:], True)
            alone[0] &= first is None
            alone[-1] = True  # told with the next batch, or at the end
            out = ~alone
            if out.any():
                yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(x[out])) for x in (*rows, *lead[1:])], _SHARED)
            held = rows[:, -1:]
            first = lead[:, -1] if not fresh[-1] or (first is not None and rows.shape[1] == 1) else None
        if first is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(x)) for x in (*held, *first[1:, None])], _SHARED)

    sorted_posts = posts.select("token", "n", "sid", "k").repartition("token").sortWithinPartitions("token", "n", "sid")
    return sorted_posts.mapInArrow(run, ", ".join(f"{c} bigint" for c in _SHARED))


_SHARED = ["token", "n", "sid", "k", "pivot_n", "pivot", "pivot_k"]


def meetings(posts: DataFrame, percent: int) -> DataFrame:
    """(kind, a, b, label, need) of sets of different labels, from (token, n, sid, k, label).

    Runs of up to `BLOCK` sets give their pairs (kind 0) with the matches the pair needs. Longer runs give (first set, set,
    label), a row for each set (kind 1). No more than a short run is held.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [np.zeros(0, np.int64)] * 5
        crowd = None  # token, size, first set of a long run that is open

        def emit(kind: int, a: np.ndarray, b: np.ndarray, label: np.ndarray, need: np.ndarray) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(a), kind, np.int32)), *(pa.array(x.astype(np.int64)) for x in (a, b, label, need))], ["kind", "a", "b", "label", "need"])

        def pairs(token: np.ndarray, n: np.ndarray, sid: np.ndarray, k: np.ndarray, label: np.ndarray, run_of: np.ndarray) -> Iterator[pa.RecordBatch]:
            for d in range(1, BLOCK):
                i = np.flatnonzero(run_of[d:] == run_of[:-d]) if len(run_of) > d else np.zeros(0, np.int64)
                if not len(i):
                    return
                j = i + d
                fit = (100 * n[i] >= percent * n[j]) & (label[i] != label[j])
                i, j = i[fit], j[fit]
                if len(i):
                    yield emit(0, np.minimum(sid[i], sid[j]), np.maximum(sid[i], sid[j]), np.zeros(len(i)), matches_needed(n[i], k[i], n[j], k[j], percent))

        for batch in batches:
            token, n, sid, k, label = (np.concatenate((h, batch.column(c).to_numpy())) for c, h in enumerate(held))
            if not len(token):
                continue
            fresh = np.concatenate(([True], (token[1:] != token[:-1]) | (100 * n[:-1] < percent * n[1:])))
            if crowd is not None and token[0] == crowd[0] and 100 * crowd[1] >= percent * n[0]:
                own = int(np.flatnonzero(fresh[1:])[0]) + 1 if fresh[1:].any() else len(token)
                yield emit(1, np.full(own, crowd[2]), sid[:own], label[:own], np.ones(own))
                crowd = (token[own - 1], n[own - 1], crowd[2])
                token, n, sid, k, label, fresh = (x[own:] for x in (token, n, sid, k, label, fresh))
                if not len(token):
                    held = [np.zeros(0, np.int64)] * 5
                    continue
            crowd = None
            starts = np.flatnonzero(fresh)
            lengths = np.diff(np.append(starts, len(token)))
            run_of = np.repeat(np.arange(len(starts)), lengths)
            open_at = int(starts[-1])
            long = lengths > BLOCK
            if long.any():
                own = long[run_of]
                yield emit(1, sid[starts][run_of[own]], sid[own], label[own], np.ones(int(own.sum())))
            if long[-1]:
                crowd, held = (token[-1], n[-1], sid[open_at]), [np.zeros(0, np.int64)] * 5
            else:
                held = [x[open_at:] for x in (token, n, sid, k, label)]
            own = ~long[run_of]
            own[open_at:] = False
            yield from pairs(*(x[own] for x in (token, n, sid, k, label, run_of)))
        if len(held[0]):
            yield from pairs(*held, np.zeros(len(held[0]), np.int64))

    sorted_posts = posts.select("token", "n", "sid", "k", "label").repartition("token").sortWithinPartitions("token", "n", "sid")
    found = sorted_posts.mapInArrow(run, "kind int, a bigint, b bigint, label bigint, need bigint")
    return found.groupBy("kind", "a", "b", "label").agg(F.count(F.lit(1)).alias("shared"), F.max("need").alias("need")).where("kind = 1 OR shared >= need")


def _pairs(rows: np.ndarray, tokens: np.ndarray, n: int) -> np.ndarray:
    """How many tokens each two of n rows share, from (row, token) entries."""
    names, column, count = np.unique(tokens, return_inverse=True, return_counts=True)
    shared = count[column] > 1
    rows, column = rows[shared], column[shared]
    out = np.zeros((n, n), np.float32)
    order = np.argsort(column, kind="stable")
    rows, column = rows[order], np.unique(column[order], return_inverse=True)[1] if len(order) else column
    step = max(1, (1 << 22) // max(1, n))  # columns at a time, so that the matrix stays small
    for at in range(0, int(column[-1]) + 1 if len(column) else 0, step):
        a, b = np.searchsorted(column, [at, at + step])
        part = np.zeros((n, step), np.float32)
        part[rows[a:b], column[a:b] - at] = 1
        out += part @ part.T
    return out


def star_links(pivot: np.ndarray, sids: list[int], sets: list[np.ndarray], percent: int) -> list[int]:
    """Which of the sets are linked with the pivot."""
    out = []
    for sid, own in zip(sids, sets, strict=True):
        at = np.minimum(np.searchsorted(pivot, own), len(pivot) - 1)
        overlap = int((pivot[at] == own).sum())
        if 100 * overlap >= percent * (len(pivot) + len(own) - overlap):
            out.append(sid)
    return out


def block_links(sids: np.ndarray, labels: np.ndarray, left: np.ndarray, right: np.ndarray, sets: list[np.ndarray], percent: int, classes: np.ndarray) -> list[tuple[int, int]]:
    """A spanning forest of the links between sets of different labels on the block pair's two sides."""
    n = len(sets)
    sizes = np.array([len(s) for s in sets])
    small, large = np.minimum.outer(sizes, sizes), np.maximum.outer(sizes, sizes)
    asked = (left[:, None] & right[None, :]) & (labels[:, None] != labels[None, :]) & (100 * small >= percent * large)
    asked |= asked.T
    touched = np.flatnonzero(asked.any(axis=1))
    if not len(touched):
        return []
    asked = asked[np.ix_(touched, touched)]
    sids, sizes, sets, n = sids[touched], sizes[touched], [sets[i] for i in touched], len(touched)
    ordered = [global_order(s, classes) for s in sets]
    k = np.array([choose_matches(o, classes, percent) for o in ordered])
    parts = [o[: len(o) - int(required(len(o), percent)) + m] for o, m in zip(ordered, k, strict=True)]
    shared = _pairs(np.repeat(np.arange(n), [len(p) for p in parts]), np.concatenate(parts), n)
    asked &= shared >= matches_needed(sizes[:, None], k[:, None], sizes[None, :], k[None, :], percent)
    touched = np.flatnonzero(asked.any(axis=1))
    if not len(touched):
        return []
    overlap = _pairs(np.repeat(np.arange(len(touched)), sizes[touched]), np.concatenate([sets[i] for i in touched]), len(touched)).astype(np.int64)
    union = sizes[touched][:, None] + sizes[touched][None, :] - overlap
    linked = asked[np.ix_(touched, touched)] & (100 * overlap >= percent * union)
    root = list(range(len(touched)))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    out = []
    for i, j in np.argwhere(np.triu(linked)):
        a, b = find(int(i)), find(int(j))
        if a != b:
            root[max(a, b)] = min(a, b)
            out.append((int(sids[touched[i]]), int(sids[touched[j]])))
    return out


def _files(rows: DataFrame) -> int:
    """How many files so many rows of a few numbers are worth."""
    return max(1, rows.count() // 50_000)


def stars(pairs: DataFrame) -> DataFrame:
    """Group rows of pairs (a, b): each a with up to about `BLOCK` of its partners."""
    files = _files(pairs)
    degree = written(pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / F.lit(BLOCK)).alias("parts")).coalesce(files), "join-degrees")
    dealt = pairs.join(degree, "a").select("a", "b", F.pmod(F.xxhash64("b", F.lit(9)), F.col("parts")).alias("i"))
    zero = F.lit(0).cast("bigint")
    row = lambda sid, left: (F.col("a").alias("pivot"), "i", F.lit(-1).cast("bigint").alias("j"), F.col(sid).alias("sid"), zero.alias("label"), F.lit(left).alias("left"), F.lit(not left).alias("right"))
    return dealt.select(*row("b", False)).unionByName(dealt.select("a", "i").distinct().select(*row("a", True)))


def block_pairs(members: DataFrame) -> DataFrame:
    """Group rows of clusters (pivot, sid, label): their blocks, two by two.

    A label with many members has blocks of its own, and two such blocks of one label don't meet.
    """
    files = _files(members)
    counts = written(members.groupBy("pivot", "label").agg(F.count(F.lit(1)).alias("n")).coalesce(files), "join-labels")
    large = F.col("n") * 2 >= BLOCK
    sizes = written(counts.groupBy("pivot").agg(F.sum(F.when(~large, F.col("n")).otherwise(0)).alias("mixed"), F.count(F.lit(1)).alias("labels")).where("labels > 1").coalesce(files), "join-mixed")
    parts = F.ceil(F.when(large, F.col("n")).otherwise(F.col("mixed")) / F.lit(BLOCK))
    own = F.when(large, F.col("label")).otherwise(F.lit(0))
    placed = members.join(counts, ["pivot", "label"]).join(sizes, "pivot").select("pivot", "sid", "label", own.alias("pure"), F.xxhash64(own, F.pmod(F.xxhash64("sid", "pivot"), parts)).alias("block"))
    placed = written(placed.coalesce(files), "join-placed")
    blocks = written(placed.select("pivot", "block", "pure").distinct().coalesce(files), "join-blocks")
    other = blocks.select("pivot", F.col("block").alias("j"), F.col("pure").alias("other"))
    met = blocks.withColumnRenamed("block", "i").join(other, "pivot").where("i <= j AND (pure = 0 OR other = 0 OR pure <> other)").select("pivot", "i", "j")
    met = written(met.coalesce(files), "join-block-pairs")
    one = placed.join(met.withColumn("block", F.col("i")), ["pivot", "block"]).select("pivot", "i", "j", "sid", "label", F.lit(True).alias("left"), (F.col("i") == F.col("j")).alias("right"))
    two = placed.join(met.where("i <> j").withColumn("block", F.col("j")), ["pivot", "block"]).select("pivot", "i", "j", "sid", "label", F.lit(False).alias("left"), F.lit(True).alias("right"))
    return one.unionByName(two)


#: Bits of the filter that tells which documents' sets are wanted; a fixed size, and only a first sieve before an exact join.
SIEVE_BITS = 22


def fetch_sets(docs: DataFrame, needed: DataFrame, words: int) -> DataFrame:
    """(sid, tokens) of the needed (sid, doc_id), and of some others that the sieve lets pass."""
    sieve = np.zeros(1 << SIEVE_BITS, bool)
    sieve[needed.select(F.pmod(F.xxhash64("doc_id"), F.lit(1 << SIEVE_BITS)).alias("bit")).distinct().toPandas()["bit"].to_numpy(np.int64)] = True
    sent = docs.sparkSession.sparkContext.broadcast(np.packbits(sieve))
    passing = docs.select("doc_id", "text", F.pmod(F.xxhash64("doc_id"), F.lit(1 << SIEVE_BITS)).alias("bit"))

    def run(batch: pa.RecordBatch) -> pa.RecordBatch | None:
        bit = batch.column(2).to_numpy()
        wanted = (sent.value[bit >> 3] >> (7 - (bit & 7))) & 1 == 1
        if not wanted.any():
            return None
        sets = [shingle_set(raw, words) for raw in utf8_rows(batch.column(1).filter(pa.array(wanted)))]
        return pa.RecordBatch.from_arrays([pa.array([set_id(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], ["sid", "tokens"])

    return map_arrow(passing, run, "sid bigint, tokens binary").join(needed.select("sid"), "sid", "left_semi")


def verify(groups: DataFrame, docs: DataFrame, holders: DataFrame, words: int, percent: int, classes: np.ndarray) -> DataFrame:
    """(a, b): the links that the groups' exact comparisons find."""
    groups = written(groups, "join-groups")
    needed = written(groups.select("sid").distinct().join(holders, "sid").coalesce(_files(groups)), "join-needed")
    sets = fetch_sets(docs, needed, words)
    sent = docs.sparkSession.sparkContext.broadcast(classes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def flush() -> pa.RecordBatch:
            once = list({h[3]: h for h in held}.values())
            sets = [np.frombuffer(h[7], np.uint64) for h in once]
            if held[0][2] == -1:
                at = next(i for i, h in enumerate(once) if h[5])
                pivot, pivot_set = once[at][3], sets[at]
                links = [(pivot, sid) for sid in star_links(pivot_set, [h[3] for h in once if not h[5]], [s for h, s in zip(once, sets, strict=True) if not h[5]], percent)]
            else:
                links = block_links(np.array([h[3] for h in once]), np.array([h[4] for h in once]), np.array([h[5] for h in once]), np.array([h[6] for h in once]), sets, percent, sent.value)
            return pa.RecordBatch.from_arrays([pa.array([x[0] for x in links], pa.int64()), pa.array([x[1] for x in links], pa.int64())], ["a", "b"])

        for batch in slices(batches, 256):
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if held and row[:3] != held[0][:3]:
                    yield flush()
                    held = []
                held.append(row)
        if held:
            yield flush()

    whole = groups.join(sets, "sid").select("pivot", "i", "j", "sid", "label", "left", "right", "tokens")
    return whole.repartition("pivot", "i", "j").sortWithinPartitions("pivot", "i", "j").mapInArrow(run, "a bigint, b bigint")


def links(docs: DataFrame, table: DataFrame, words: int, percent: int) -> DataFrame:
    """(a, b): links between sets whose components are those of all links."""
    classes = frequency_classes(docs, words)
    shared = written(shared_posts(prefixes(docs, words, percent, classes), percent), "join-shared")
    holders = written(table.where("n > 0").groupBy("sid").agg(F.min("doc_id").alias("doc_id")), "join-holders")
    # first round: pivots. The matches of other runs aren't seen here, so half of those needed let a pair pass
    overlap = f"({percent} * (n + pivot_n) + {99 + percent}) div {100 + percent}"
    rest = f"greatest(({percent} * n + 99) div 100 - k, ({percent} * pivot_n + 99) div 100 - pivot_k)"
    met = shared.where("sid <> pivot").groupBy("pivot", "sid", "n", "k", "pivot_n", "pivot_k").agg(F.count(F.lit(1)).alias("shared"))
    near = met.where(f"2 * shared >= greatest(least(k, pivot_k), {overlap} - {rest}) AND 100 * least(n, pivot_n) >= {percent} * greatest(n, pivot_n)")
    with scratch():
        first = written(verify(stars(written(near.select(F.col("pivot").alias("a"), F.col("sid").alias("b")), "join-near")), docs, holders, words, percent, classes), "join-links", keep=True)
    with scratch():
        labels = written(connected(first).select(F.col("node").alias("sid"), F.col("component").alias("label")), "join-first", keep=True)
    free_shuffles(docs.sparkSession)
    labelled = shared.select("token", "n", "sid", "k").join(labels, "sid", "left").withColumn("label", F.coalesce("label", "sid"))
    second = written(meetings(labelled, percent), "join-meetings")
    members = second.where("kind = 1").select(F.col("a").alias("pivot"), F.col("b").alias("sid"), "label").distinct()
    groups = stars(second.where("kind = 0").select("a", "b")).unionByName(block_pairs(written(members.coalesce(_files(second)), "join-members")))
    return first.unionByName(verify(groups, docs, holders, words, percent, classes))


def join_documents(docs: DataFrame, words: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles and component_id (smallest doc_id reachable by links) of every row."""
    plain = docs.select(F.coalesce(F.col(id_col).cast("bigint"), F.lit(NULL_ID)).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    table = written(set_table(plain, words), "join-table")
    full = table.where("n > 0").select("doc_id", "sid")
    with scratch():
        with scratch():
            found = written(connected(links(plain, table, words, percent)), "join-components", keep=True)
        least = written(full.groupBy("sid").agg(F.min("doc_id").alias("first_doc")), "join-least")
        named = least.join(found, F.col("sid") == F.col("node"), "left").select("sid", "first_doc", F.coalesce("component", "sid").alias("component"))
        smallest = named.groupBy("component").agg(F.min("first_doc").alias("component_id"))
        by_set = written(named.join(smallest, "component").select("sid", "component_id"), "join-by-set", keep=True)
    back = lambda c: F.nullif(c, F.lit(NULL_ID))
    out = table.join(by_set, "sid", "left")
    return out.select(back(F.col("doc_id")).alias("doc_id"), F.col("n").alias("n_shingles"), back(F.coalesce("component_id", "doc_id")).alias("component_id"))


#: DuckDB SQL for the query over `documents` (four words, 85 per cent).
ORACLE_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, CASE WHEN len(ws) < 4 THEN array_to_string(ws, ' ') ELSE array_to_string(list_slice(ws, i, i + 3), ' ') END AS g
      FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 1) + 1)) AS i FROM w WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
r(doc_id, reached) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.doc_id, l.b FROM r JOIN l ON l.a = r.reached)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, min(r.reached) AS component_id
FROM documents d LEFT JOIN n USING (doc_id) JOIN r ON r.doc_id = d.doc_id GROUP BY ALL
"""
