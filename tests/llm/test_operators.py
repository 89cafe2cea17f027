"""Each operator against a brute-force version, with nulls, empty and long texts, ties, repeated rows and clashing columns."""

import collections
import hashlib
import html
import math
import random
import re
import struct
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

public_tokenizers = pytest.importorskip("public_tokenizers")
from pyspark.sql import functions as F  # noqa: E402
from tokenizers import Tokenizer  # noqa: E402

from tabqa.llm import bpe, components, elias_fano, html_text, jaccard_join, language, line_dedup, ngram_model, packing, prefix_forest, quality, suffix_dedup  # noqa: E402
from tabqa.llm.queries import queries, vocabulary  # noqa: E402

WORD = re.compile(rb"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, n long, sid long, keys string, shard string"


def lower(raw):
    return raw.translate(bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256)))


def texts():
    rng = random.Random(3)
    words = [f"w{i}" for i in range(400)] + ["the", "of", "Éa", "a,b", "日本"]
    make = lambda n: " ".join(rng.choice(words) for _ in range(n))
    passage, base = make(80), make(160)
    near = [" ".join(w if rng.random() > 0.01 else "edit%d" % rng.randint(0, 99) for w in base.split()) for _ in range(12)]
    docs = [None, "", " \n\t ", "one", "two words", "three small words", base, base, base.upper(), *near]
    docs += [make(40) + "\n" + passage + "\n" + make(30) for _ in range(6)]
    docs += ["Same line of text here\n" + make(20) + "\n  SAME line OF text here \nshort\nshort" for _ in range(4)]
    docs += ["the " * 300, "the " * 299, "a" * 900, make(6000), "x#*$ " * 50, "\x1c\x1d odd \x85 space", "tab\tand\x0bmore\rspace\x0c"]
    return docs


def rows():
    out = [(i, t, None if i % 5 == 0 else ("en", "fr")[i % 2], 1, 2, "k", "s") for i, t in enumerate(texts())]
    return [*out, out[6], out[10], (None, "a row without an id and with some more words to count here", None, None, None, None, None)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA).repartition(5).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def key(row):
    return (row[0] is not None, row[0] or 0, *map(str, row[1:]))


# Encoding


def test_bpe_equals_the_library(docs):
    lib = Tokenizer.from_file(vocabulary())
    want = []
    for i, t, *_ in rows():
        ids = lib.encode(t or "", add_special_tokens=False).ids
        want.append((i, len(ids), hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest(), hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    assert sorted(map(tuple, bpe.encode_digests(docs, vocabulary()).collect()), key=key) == sorted(want, key=key)
    full = bpe.encode_documents(docs, vocabulary()).collect()
    assert sorted((r["doc_id"] is None, r["doc_id"] or 0, len(r["ids"]) // 4) for r in full) == sorted((w[0] is None, w[0] or 0, w[1]) for w in want)


@settings(max_examples=300, deadline=None)
@given(st.lists(st.text(alphabet="aAÉéßΣσİıK  \x1c\x85'sS'lLdDreE<|endoftext|>½Ⅻ٣日本é\n\t\x00ẞ😀.,", max_size=24), max_size=4))
def test_bpe_on_any_text(parts):
    lib, own = Tokenizer.from_file(vocabulary()), bpe.MergeQueueEncoder.load(vocabulary())
    for text, many in zip(parts, own.encoded_ids_many(parts), strict=True):
        want = lib.encode(text, add_special_tokens=False).ids
        assert own.encode(text) == want and list(struct.unpack(f"<{len(many) // 4}I", many)) == want
        assert own.encoded(text)[1] == own.decode(want) == lib.decode(want, skip_special_tokens=False)


def test_empty_tables(spark, empty):
    assert bpe.encode_digests(empty, vocabulary()).count() == 0
    assert packing.pack_documents(empty, vocabulary()).count() == 0
    assert quality.filter_documents(empty).count() == 0
    assert line_dedup.dedup_lines(empty).count() == 0
    assert suffix_dedup.dedup_substrings(empty).count() == 0
    assert jaccard_join.join_documents(empty).count() == 0
    assert language.predict(empty, language.train(empty), ["doc_id"]).count() == 0
    assert ngram_model.train_and_score(empty, "true", ["doc_id"])[1].count() == 0
    assert prefix_forest.nearest(spark.createDataFrame([], "vec_id long, embedding array<float>"), spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0
    assert html_text.extract_pages(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


# Packing


def test_packing_holds_every_id_once(docs):
    got = packing.pack_documents(docs, vocabulary(), capacity=256, group_rows=20).collect()
    own = bpe.MergeQueueEncoder.load(vocabulary())
    by_sequence, by_doc = collections.defaultdict(list), collections.defaultdict(list)
    for r in got:
        by_sequence[r["sequence_id"]].append((r["offset"], r["length"]))
        by_doc[r["doc_id"]].append(r)
    for pieces in by_sequence.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 256
    for i, t, *_ in rows():
        ids = [*own.encode(t), 2]
        pieces = sorted({(r["start"], r["length"], r["ids_crc32"]) for r in by_doc[i] if r["doc_tokens"] == len(ids)})
        assert [p[0] for p in pieces] == list(range(0, len(ids), 256))
        for start, length, crc in pieces:
            assert crc == zlib.crc32(struct.pack(f"<{length}I", *ids[start : start + length]))
    assert sum(r["length"] for r in got) == sum(len(own.encode(t)) + 1 for _, t, *_ in rows())


def test_rows_repeated_very_often_are_spread_over_groups(spark):
    docs = spark.createDataFrame([(None, "the same few words")] * 600, "doc_id long, text string").coalesce(1)
    parts = packing.pieces(docs, vocabulary())
    groups = collections.Counter(r["sequence_id"] >> 32 for r in packing.pack(parts, 10).collect())
    assert len(groups) == 10 and max(groups.values()) < 150 and sum(groups.values()) == 600


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 64), min_size=1, max_size=80))
def test_first_fit_decreasing_is_first_fit(lengths):
    bins, offsets = packing.first_fit_decreasing(np.array(lengths), 64)
    free: list[int] = []
    for i in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        at = next((b for b, room in enumerate(free) if room >= lengths[i]), len(free))
        if at == len(free):
            free.append(64)
        assert bins[i] == at and offsets[i] == 64 - free[at]
        free[at] -= lengths[i]


# Quality


def measures(text):
    raw = (text or "").encode()
    words = WORD.findall(raw)
    grams = collections.Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7))
    covered = {p for i in range(len(words) - 7) if grams[tuple(words[i : i + 8])] > 1 for p in range(i, i + 8)}
    lines = [x for x in raw.split(b"\n") if WORD.search(x)]
    return len(words), sum(len(w.decode()) for w in words), sum((text or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered)


def test_quality_measures_and_order(docs):
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    for order in (quality.RULES, quality.RULES[::-1], quality.cascade_order(quality.RULES, quality.estimate(docs))):
        got = quality.apply_cascade(docs, order, measures=names).collect()
        assert sorted((tuple(r)[:6] for r in got), key=key) == sorted(((i, *measures(t)) for i, t, *_ in rows()), key=key)
        assert all(not r["kept"] for r in got if r["base_failed"] or r["n_words"] < 20)
        kept = {(r["doc_id"], r["kept"]) for r in got}
        assert kept == {(r["doc_id"], r["kept"]) for r in quality.apply_cascade(docs, quality.RULES).collect()}
    assert quality.filter_documents(docs).columns == docs.columns


def test_what_is_measured_anyway_costs_a_rule_nothing(docs):
    plain, known = ({f["rule"]: f["cost_ns"] for f in quality.estimate(docs, known=names)} for names in ((), ("n_words", "n_repeat_words")))
    assert known["repeated_windows"] < plain["repeated_windows"] / 2


def test_cascade_order_prefers_rejection_per_cost():
    figures = [{"rule": "symbols", "cost_ns": 10, "rejection": 0.2}, {"rule": "few_words", "cost_ns": 1000, "rejection": 0.9}]
    assert [r.name for r in quality.cascade_order(quality.RULES, figures)][:2] == ["symbols", "few_words"]


# Lines


def lines_without_repeats(items):
    held = collections.defaultdict(set)
    key_of = lambda line: lower(line.strip(b" \t\n\x0b\x0c\r"))
    for i, t, *_ in items:
        for line in (t or "").encode().split(b"\n"):
            if len(key_of(line).decode()) >= 10:
                held[key_of(line)].add(-1 << 63 if i is None else i)
    out = []
    for i, t, *_ in items:
        parts = (t or "").encode().split(b"\n")
        gone = lambda p: len(held.get(key_of(p), ())) > 1 and min(held[key_of(p)]) != (-1 << 63 if i is None else i)  # noqa: B023, E731
        left = [p for p in parts if not gone(p)]
        out.append((i, len(parts), len(parts) - len(left), hashlib.sha256(b"\n".join(left)).hexdigest()))
    return out


def test_line_dedup(docs):
    got = line_dedup.dedup_lines(docs, digest=True)
    assert got.columns == [*docs.columns, "n_lines", "n_dropped"]
    assert sorted(map(tuple, got.select("doc_id", "n_lines", "n_dropped", "text").collect()), key=key) == sorted(lines_without_repeats(rows()), key=key)


def test_beyond_the_broadcast_bound_the_join_decides_alike(docs, monkeypatch):
    want = sorted(map(str, line_dedup.dedup_lines(docs, digest=True).collect()))
    monkeypatch.setattr(line_dedup, "FILTERS_BROADCAST_BYTES", -1)
    assert sorted(map(str, line_dedup.dedup_lines(docs, digest=True).collect())) == want


CLASHING = "doc_id long, text string, lang string, n_lines string, N_dropped int, n_bytes long, n_spans string, row int, id int, keys string, found string, `a.b` int"


def test_clashing_columns(spark):
    """Columns named like what the operators use inside come through; those named like a count give way to it."""
    items = [(i, t, "en", "x", 1, 2, "y", 3, 4, "k", "f", 5) for i, t, *_ in rows()]
    frame = spark.createDataFrame(items, CLASHING)
    lines, spans = line_dedup.dedup_lines(frame, digest=True), suffix_dedup.dedup_substrings(frame, digest=True)
    assert lines.columns == ["doc_id", "text", "lang", "n_bytes", "n_spans", "row", "id", "keys", "found", "a.b", "n_lines", "n_dropped"]
    assert spans.columns == ["doc_id", "text", "lang", "n_lines", "N_dropped", "row", "id", "keys", "found", "a.b", "n_bytes", "n_removed", "n_spans"]
    assert sorted(map(tuple, lines.select("doc_id", "n_lines", "n_dropped", "text").collect()), key=key) == sorted(lines_without_repeats(rows()), key=key)
    assert {tuple(r)[3:10] for r in spans.collect()} == {("x", 1, 3, 4, "k", "f", 5)}
    assert sorted(map(tuple, spans.select("doc_id", "n_bytes", "n_removed", "n_spans", "text").collect()), key=key) == sorted(without_repeats(rows(), 200), key=key)
    kept = quality.filter_documents(frame)
    assert kept.columns == frame.columns and kept.count() == quality.filter_documents(frame.select("doc_id", "text")).count()


def test_line_store_is_reversible(docs):
    # a filter's state is its fingerprints with the pair of buckets each may lie in; the places among these depend on the order
    cells_of = lambda raw: collections.Counter((p, min(b, o), max(b, o)) for f in [line_dedup.CuckooFilter.from_bytes(raw)] for b in range(f.buckets) for p in f.table[b].tolist() if p for o in [int(b ^ f._step(np.array([p], np.uint16))[0])])
    state = lambda s: (sorted(map(tuple, s.references.collect())), {r["shard"]: cells_of(r["cells"]) for r in s.filters.collect()})
    few = docs.where("doc_id % 3 <> 1")
    whole, part = line_dedup.LineStore.build(docs, shards=4), line_dedup.LineStore.build(few, shards=4)
    grown = part.insert(docs.where("doc_id % 3 = 1 OR doc_id IS NULL"))
    assert state(grown)[0] == state(whole)[0]
    keys = np.array([r["k1"] for r in whole.references.where("refs > 1").collect()])
    cells = {r["shard"]: line_dedup.CuckooFilter.from_bytes(r["cells"]) for r in grown.filters.collect()}
    assert all(cells[k % 4].contains(np.array([k]))[0] for k in keys.tolist())
    back = grown.delete(docs.where("doc_id % 3 = 1").select("doc_id")).delete(docs.where("doc_id IS NULL").select("doc_id"))
    before, after = state(part), state(back)
    assert before[0] == after[0]
    # growing may have given a shard more buckets, but it holds the same fingerprints
    prints = lambda filters: {k: collections.Counter(x[0] for x in v.elements()) for k, v in filters.items() if v}
    assert prints(before[1]) == prints(after[1])
    want = sorted(map(str, line_dedup.dedup_lines(few, digest=True).collect()))
    assert sorted(map(str, part.strip(few, digest=True).collect())) == want == sorted(map(str, back.strip(few, digest=True).collect()))


def test_cuckoo_filter_inserts_finds_and_deletes():
    keys = np.random.default_rng(1).integers(-(1 << 62), 1 << 62, 5000)
    held = line_dedup.build_filter(keys)
    assert held.contains(keys).all()
    other = np.random.default_rng(2).integers(-(1 << 62), 1 << 62, 20000)
    assert held.contains(other).mean() < 0.001
    grown = line_dedup.CuckooFilter(held.buckets)
    assert all(grown.insert(part) for part in np.array_split(keys, 7)) and grown.contains(keys).all() and (grown.table > 0).sum() == len(keys)
    held.delete(keys[:2500])
    assert (held.table > 0).sum() == 2500
    assert held.contains(keys[2500:]).all() and held.contains(keys[:2500]).mean() < 0.01
    assert (line_dedup.CuckooFilter.from_bytes(held.to_bytes()).table == held.table).all()


# Substrings


def without_repeats(items, window):
    count = collections.Counter()
    for _, t, *_ in items:
        raw = (t or "").encode()
        count.update(raw[k : k + window] for k in range(len(raw) - window + 1))
    out = []
    for i, t, *_ in items:
        raw = (t or "").encode()
        cover = np.zeros(len(raw) + 1, int)
        for k in range(len(raw) - window + 1):
            if count[raw[k : k + window]] > 1:
                cover[k] += 1
                cover[k + window] -= 1
        hit = np.cumsum(cover)[:-1] > 0
        spans = int((np.diff(np.concatenate(([0], hit.astype(int), [0]))) == 1).sum())
        out.append((i, len(raw), int(hit.sum()), spans, hashlib.sha256(np.frombuffer(raw, np.uint8)[~hit].tobytes()).hexdigest()))
    return out


@pytest.mark.parametrize("crowded", [400, 1])
def test_suffix_dedup(docs, monkeypatch, crowded):
    monkeypatch.setattr(suffix_dedup, "MOST_CONTEXTS", crowded)
    got = suffix_dedup.dedup_substrings(docs, digest=True).select("doc_id", "n_bytes", "n_removed", "n_spans", "text").collect()
    assert sorted(map(tuple, got), key=key) == sorted(without_repeats(rows(), 200), key=key)


def test_suffix_dedup_keeps_whole_characters(docs):
    got = suffix_dedup.dedup_substrings(docs)
    assert not [r for r in got.collect() if "�" in r["text"]]


@settings(max_examples=150, deadline=None)
@given(st.lists(st.binary(max_size=40).map(lambda b: bytes(97 + x % 3 for x in b)), min_size=1, max_size=6), st.integers(1, 12))
def test_interval_expansion(strings, depth):
    count = collections.Counter(s[i : i + depth] for s in strings for i in range(len(s) - depth + 1))
    want = [[i for i in range(len(s) - depth + 1) if count[s[i : i + depth]] > 1] for s in strings]
    assert [x.tolist() for x in suffix_dedup.repeated_starts(strings, depth)] == want


# Near duplicates


def near_components(items, words, percent):
    sets = {}
    for i, t, *_ in items:
        w = lower((t or "").encode()).split()
        sets.setdefault(-1 << 63 if i is None else i, {tuple(w[k : k + words]) for k in range(max(1, len(w) - words + 1))} if w else set())
    ids = sorted(sets)
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in ids:
        for b in ids:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                root[max(find(a), find(b))] = min(find(a), find(b))
    back = lambda x: None if x == -1 << 63 else x
    return [(i, len(sets[-1 << 63 if i is None else i]), back(find(-1 << 63 if i is None else i))) for i, *_ in items]


@pytest.mark.parametrize("words,percent,block", [(4, 85, 64), (5, 80, 2), (2, 50, 3)])
def test_jaccard_join(docs, monkeypatch, words, percent, block):
    monkeypatch.setattr(jaccard_join, "BLOCK", block)
    got = jaccard_join.join_documents(docs, words, percent).select("doc_id", "n_shingles", "component_id").collect()
    assert sorted(map(tuple, got), key=key) == sorted(near_components(rows(), words, percent), key=key)


def test_components_of_a_long_chain_and_a_hub(spark):
    edges = [(i, i + 1) for i in range(200)] + [(1000, 1000 + i) for i in range(1, 60)] + [(5000, 5000)]
    got = dict(components.connected(spark.createDataFrame(edges, "a long, b long")).collect())
    assert got == {i: 0 for i in range(201)} | {1000 + i: 1000 for i in range(60)}


# Language model


def test_elias_fano():
    rng = np.random.default_rng(5)
    for n, top in ((0, 1), (1, 5), (2000, 2**62), (3000, 4000), (5000, 2**33)):
        values = np.unique(np.concatenate((rng.integers(0, top, n // 2), rng.integers(0, max(1, top // 50), n // 2 + n % 2)))) if n else np.zeros(0, np.int64)
        coded = elias_fano.EliasFano.build(values)
        asked = np.concatenate((values, rng.integers(0, top, 500), [0, top]))
        at = np.searchsorted(values, asked)
        held = (at < len(values)) & (values[np.minimum(at, max(0, len(values) - 1))] == asked) if len(values) else np.zeros(len(asked), bool)
        assert (coded.values() == values).all() and (coded.find(asked) == np.where(held, at, -1)).all() and (coded.find(asked, True) == at).all()
        assert (coded.at(np.arange(len(values))) == values).all()
    for width in (1, 7, 20, 33, 63):
        values = rng.integers(0, 1 << width, 3000)
        assert (elias_fano.bits_at(elias_fano.pack_bits(values, width), np.arange(3000), width).astype(np.int64) == values).all()


def test_a_context_that_several_files_share(docs, monkeypatch):
    """Files of few keys: contexts are cut, and the scores stay what they are."""
    want = sorted(map(tuple, ngram_model.train_and_score(docs, "true", ["doc_id"])[1].collect()), key=key)
    monkeypatch.setattr(ngram_model, "FILE_KEYS", 40)
    model, scores = ngram_model.train_and_score(docs, "true", ["doc_id"])
    assert len(model.triples.names) > 20 and model.pairs.fans
    for a, b in zip(sorted(map(tuple, scores.collect()), key=key), want, strict=True):
        assert a[:4] == b[:4] and abs(a[5] - b[5]) < 4e-4 * a[1]


def test_ngram_scores(docs):
    got = ngram_model.train_and_score(docs, "coalesce(doc_id % 3 <> 0, false)", ["doc_id"])[1].collect()
    tokens = lambda t: [*WORD.findall(lower((t or "").encode())), None]
    training = [tokens(t) for i, t, *_ in rows() if i is not None and i % 3 != 0]
    one, two, three = (collections.Counter(g for x in training for g in zip(*(x[k:] for k in range(n)))) for n in (1, 2, 3))
    total, d = sum(one.values()), ngram_model.DISCOUNT
    rest2, rest3 = collections.Counter(), collections.Counter()
    for g, c in two.items():
        rest2[g[:1]] += (c - d) / one[g[:1]]
    for g, c in three.items():
        rest3[g[:2]] += (c - d) / two[g[:2]]

    def score(x):
        base = full = 0.0
        for k in range(len(x)):
            p = (one[(x[k],)] + 0.5) / (total + 0.5 * (len(one) + 1))
            base += math.log10(p)
            if k and (x[k - 1],) in one:
                g = (x[k - 1], x[k])
                p = (1 - rest2[g[:1]]) * p + ((two[g] - d) / one[g[:1]] if g in two else 0)
            if k > 1 and (x[k - 2], x[k - 1]) in two:
                g = (x[k - 2], x[k - 1], x[k])
                p = (1 - rest3[g[:2]]) * p + ((three[g] - d) / two[g[:2]] if g in three else 0)
            full += math.log10(p)
        return base, full

    by = {}
    for i, t, *_ in rows():
        x = tokens(t)
        by[i, len(x)] = (sum((w,) in one for w in x), total, *score(x))
    assert len(got) == len(rows())
    for r in got:
        known, n, base, full = by[r["doc_id"], r["n_tokens"]]
        assert (r["n_known"], r["train_tokens"]) == (known, n) and abs(r["base_score"] - base) < 1e-6 and abs(r["score"] - full) < 3e-4 * r["n_tokens"] + 1e-6


def test_registered_scores_know_pairs_and_triples_seen_once(spark, sf):
    got = queries()["op9_trie_scores"](spark, sf).collect()
    texts_of = {r["doc_id"]: [*WORD.findall(lower((r["text"] or "").encode())), None] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    one, two, three = (collections.Counter(g for r in got if not r["held_out"] for g in zip(*(texts_of[r["doc_id"]][k:] for k in range(n)))) for n in (1, 2, 3))
    total, d = sum(one.values()), ngram_model.DISCOUNT
    after1, after2 = collections.Counter(g[:1] for g in two), collections.Counter(g[:2] for g in three)
    before1, before2 = collections.Counter(), collections.Counter()
    for g, c in two.items():
        before1[g[:1]] += c
    for g, c in three.items():
        before2[g[:2]] += c
    for r in got:
        x, full = texts_of[r["doc_id"]], 0.0
        for k in range(len(x)):
            p = (one[(x[k],)] + 0.5) / (total + 0.5 * (len(one) + 1))
            for n, mine, less, kept, held in ((1, two, one, before1, after1), (2, three, two, before2, after2)):
                h = tuple(x[k - n : k])
                if k >= n and h in less:
                    p = (1 - (kept[h] - d * held[h]) / less[h]) * p + (max(mine[(*h, x[k])] - d, 0) / less[h])
            full += math.log10(p)
        assert r["n_tokens"] == len(x) and abs(r["score"] - full) < 3e-4 * len(x) + 1e-6


# Languages


def test_languages_held_out(spark, sf):
    got = queries()["op2_language_families"](spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out")
    assert got.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double"))).first()[0] > 0.97


def test_language_edges(docs):
    model = language.train(docs)
    got = {r["doc_id"]: r for r in language.predict(docs, model, ["doc_id"]).collect()}
    assert (got[0]["lang_pred"], got[0]["score"]) == ("und", 0.0) and got[1]["lang_pred"] == "und" and got[3]["lang_pred"] in ("en", "fr")
    assert all(0 <= r["score"] <= 1 for r in got.values())
    assert language.fit_model(language.features("abc def")[None], np.array(["xx"], object)).predict("anything")[0] == "xx"


def test_a_text_copied_very_often_leaves_every_language_in_the_sample(spark):
    rows = [("xx", "one text only, again and again")] * 3000 + [("yy", f"andere worte {i}") for i in range(900)]
    model = language.train(spark.createDataFrame(rows, "lang string, text string"), per_language=50)
    assert sorted(x for family in model.families for x in family) == ["xx", "yy"]
    assert model.predict("one text only, again")[0] == "xx" and model.predict("andere worte 77")[0] == "yy"


def nearest_centroid(train, test):
    """The plainest classifier on the same features: the language of the likest mean vector."""
    by = collections.defaultdict(list)
    for t, lang in train:
        if (x := language.features(t)) is not None:
            by[lang].append(x)
    means = {k: np.mean(v, axis=0) / np.linalg.norm(np.mean(v, axis=0)) for k, v in by.items()}
    return [max(means, key=lambda k: means[k] @ x) if (x := language.features(t)) is not None else "und" for t, _ in test]


def test_predictions_against_brute_force(spark):
    docs = [(r["doc_id"], r["text"], r["lang"]) for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text", "lang").collect()]
    held = lambda i: zlib.crc32(str(i).encode()) % 3 == 1
    test = [(t, lang) for i, t, lang in docs if held(i) and lang is not None]
    plain = nearest_centroid([(t, lang) for i, t, lang in docs if not held(i) and lang is not None], test)
    ours = {r["doc_id"]: (r["held_out"], r["lang_pred"]) for r in queries()["op2_language_families"](spark, "/root/testdata/sf0.01").collect()}
    assert all(ours[i][0] == held(i) for i, _, _ in docs)
    right = sum(ours[i][1] == lang for i, _, lang in docs if held(i) and lang is not None)
    assert right >= sum(p == lang for p, (_, lang) in zip(plain, test, strict=True))


def test_likest_languages_share_a_family():
    eye = np.eye(4)
    found = language.join_families({"a": eye[0] + 0.5 * eye[1], "b": eye[1] + 0.5 * eye[0], "c": eye[2] + 0.4 * eye[3], "d": eye[3] + 0.4 * eye[2]})
    assert sorted(found) == [["a", "b"], ["c", "d"]]


# Pages


def test_given_pages(spark, sf):
    pages = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    for r in queries()["op3_tag_path_text"](spark, sf).collect():
        parts = re.split(r"</?(?:p|h1)>", re.search(r"<article>(.*?)</article>", pages[r["page_id"]], re.S)[1])
        want = "\n\n".join(x for p in parts if (x := " ".join(html.unescape(re.sub(r"<br>|</?b>", lambda m: " " if m[0] == "<br>" else "", p)).split())))
        assert r["text"] == want and r["n_chars"] == len(want)


@pytest.mark.parametrize(
    "page,want",
    [
        (None, ""),
        ("", ""),
        ("<script>alert('<p>no</p>')", ""),
        ("<nav><a href=x>Home</a></nav><footer>2020</footer>", ""),
        ("<body><main><p>One &lt;b&gt; &eacute;\n two<br>three</p><p>Four<aside>side</aside></main><form>Name</form>", "One <b> é two three\n\nFour"),
        ("<article><h1>T</h1><p>Body.<div class='comments'><p>nice</p></div></article>", "T\n\nBody."),
    ],
)
def test_page_edges(page, want):
    assert html_text.main_text(page) == want


def test_page_without_article_by_ratio():
    story = "".join(f"<p>This is sentence {i}, which has a clause, and ends here. Another follows; it is long enough.</p>" for i in range(5))
    page = f"<body><div class=top><ul>{''.join(f'<li><a href=x>Item {i}</a></li>' for i in range(8))}</ul></div><div id=x>{story}</div><div>Short</div><footer>c</footer>"
    got = html_text.main_text(page)
    assert got.count("sentence") == 5 and "Item" not in got and "Short" not in got


_STORY = "".join(f"<p>This is sentence {i}, which has a clause, and ends here. Another follows; it is long enough.</p>" for i in range(5))


@pytest.mark.parametrize("body", [f"<div id=x>{_STORY}</div>", f"<section>{_STORY}</section>"])
def test_article_teasers_beside_a_longer_body(body):
    for page in (f"<body><article><p>A teaser, short.</p></article>{body}", f"<body>{body}<article><a href=x>Read more</a></article><article><a href=y>And more</a></article>", f"<body><main><p>A lead, in short.</p></main>{body}<footer>c</footer>"):
        assert html_text.main_text(page).count("sentence") == 5


def test_given_pages_without_article_tags(spark, sf):
    for r in spark.read.parquet(f"{sf}/pages.parquet").collect():
        bare = re.sub("</?article>", "", r["html"])
        assert bare != r["html"] and html_text.main_text(bare) == html_text.main_text(r["html"]) != ""


def block_f1(got, want):
    a, b = collections.Counter(got.split("\n\n")), collections.Counter(want.split("\n\n"))
    return 2 * (a & b).total() / (a.total() + b.total())


@pytest.mark.parametrize("size", ["sf0.01", "check_s"])
def test_articles_in_plain_elements(spark, size):
    """The planted article is found without its tag, by ratios alone."""
    worst = 1.0
    for r in spark.read.parquet(f"/root/testdata/{size}/pages.parquet").where("page_id % 4 = 0").collect():
        want = html_text.main_text(r["html"])
        for tag in ("div", "section", "div class='content share'", "div class='post legal-news'"):
            page = r["html"].replace("<article>", f"<{tag}>").replace("</article>", f"</{tag.split()[0]}>")
            worst = min(worst, block_f1(html_text.main_text(page), want))
    assert worst >= 0.95


@pytest.mark.parametrize(
    "page,gone",
    [
        (f"<body><div class='post legal-news'>{_STORY}</div><footer>x</footer>", "x"),
        (f"<body><div class='content share'>{_STORY}</div><div class='sidebar'>{_STORY.replace('sentence', 'aside')}</div>", "aside"),
        (f"<body><div id=main>{_STORY}</div><div id=comments><h3>Comments</h3>{_STORY.replace('sentence', 'reply') * 3}</div>", "reply"),
        (f"<body><div>{_STORY}</div><div class='cookie-notice'>We use cookies, and that is all; accept them, please.</div>", "cookies"),
        (f"<article><h1>T</h1>{_STORY}<section class='comment-list'><p>{'Nice, thanks. ' * 20}</p></section></article>", "Nice"),
        (f"<body><div>{_STORY}</div><ol class=comments>{'<li>Nice, thanks; good, so on. Yes!</li>' * 500}</ol>", "Nice"),
        (f"<body><div role=banner>Welcome, all; read on, here.</div><div>{_STORY}</div><div role='complementary'>{_STORY.replace('sentence', 'advice')}</div>", "advice"),
    ],
)
def test_class_words_lower_but_do_not_silence(page, gone):
    got = html_text.main_text(page)
    assert got.count("sentence") == 5 and gone not in got


def test_lists_and_headings_among_the_content():
    page = f"<body><nav><a href=x>Home</a></nav><div class='article'><h2>Head</h2>{_STORY}<ul><li>First point<li>Second point</ul><h3>More</h3><p>Last one, here.</p></div><div class=comments>{_STORY.replace('sentence', 'reply')}</div>"
    got = html_text.main_text(page).split("\n\n")
    assert got[0] == "Head" and got[-4:] == ["First point", "Second point", "More", "Last one, here."] and len(got) == 10


def test_one_long_block_does_not_outdo_the_others():
    page = f"<body><h1>T</h1>{_STORY}<pre>{'A line of code, a; b; c.' * 2000}</pre><footer>x</footer>"
    assert html_text.main_text(page).count("sentence") == 5 and html_text.main_text(page).startswith("T\n\n")


@pytest.mark.parametrize("page", ["<div>" * 100_000 + "Deep, text.", "<div class='a b'>" * 100_000 + "Deep, text." + "</table></i></span>" * 100_000, "<i><div>" + "<b>" * 100_000 + "Deep, text." + "</i></span>" * 100_000, "<ul>" + "<li><b>" * 100_000 + "Deep, text."])
def test_deep_pages_take_memory_as_their_size(page):
    import tracemalloc

    tracemalloc.start()
    assert html_text.main_text(page) == "Deep, text."
    assert tracemalloc.get_traced_memory()[1] < 150e6
    tracemalloc.stop()


def test_pages_with_repeated_rows_and_clashing_columns(spark):
    story = f"<body><div>{_STORY * 400}</div>"
    pages = spark.createDataFrame([(1, "u", story, "x", 7)] * 3 + [(2, None, None, None, None)], "page_id long, url string, html string, text string, n_chars int")
    got = sorted(map(tuple, html_text.extract_pages(pages).collect()))
    want = html_text.main_text(story)
    assert got == [(1, "u", want, len(want))] * 3 + [(2, None, "", 0)] and len(want) > 100_000


@pytest.mark.parametrize(
    "page,want",
    [
        ("<html><head><meta charset=utf-8><title>x</title><body><p>One, two.</p>", "One, two."),
        ("<html><head><title>x</title><p>One, two.</p>", "One, two."),
        ("<head><title>x</title>One, two.", "One, two."),
        ("<head><title>x<body><p>One, two.</p>", "One, two."),
        ("<head><noscript><link rel=x></noscript><style>p{}</style></head><body><p>One.</p>", "One."),
        *((f"<article><p>One, {tag} two.</p><p>Three.</p></article>", "One, two.\n\nThree.") for tag in ("<svg>", "<select>", "<object>", "<math>", "<noscript>", "<template>", "<SVG viewBox='0 0 1 1'>")),
        ("<article><p>One.</p><svg><path d=x><p>Two.</p><p>Three.</p></article>", "One.\n\nTwo.\n\nThree."),
        ("<article><p>One <svg><text>no</text></p><p>Two.</p><svg><text>no</text></svg><p>Three.</p></article>", "One\n\nTwo.\n\nThree."),
        ("<article><p>One <select><option>no<option>no</select> two.</p><p>Three.</p></article>", "One two.\n\nThree."),
        ("<article><div><noscript><div>no</div></noscript><p>One.</p></div><object><p>no</p></object><p>Two.</p></article>", "One.\n\nTwo."),
        ("<article><p>One.</p><iframe src=x><p>Two.</p></article>", "One.\n\nTwo."),
    ],
)
def test_unclosed_heads_drawings_and_choices(page, want):
    assert html_text.main_text(page) == want


# Neighbours


def test_nearest_neighbours(spark):
    rng = np.random.default_rng(8)
    x = rng.normal(size=(300, 8)) * rng.uniform(0.5, 2, (300, 1))
    x[50:90] = x[50]
    items = [(i, [float(v) for v in row]) for i, row in enumerate(x)] + [(300, None), (301, [0.0] * 8), (302, [float("nan")] * 8), (303, [None] + [1.0] * 7), (None, [1.0] * 8), (7, [float(v) for v in x[7]])]
    vectors = spark.createDataFrame(items, "vec_id long, embedding array<double>")
    for candidates in (6000, 40):
        got = prefix_forest.nearest(vectors, vectors.where("vec_id % 20 = 0"), k=5, candidates=candidates).collect()
        hit = 0
        for q in range(0, 300, 20):
            near = np.einsum("ij,j->i", x, x[q])
            near[q] = -np.inf
            want = np.lexsort((np.arange(300), -np.round(near, 12)))[:5].tolist()
            mine = sorted((r for r in got if r["query_id"] == q), key=lambda r: r["rank"])
            assert [r["rank"] for r in mine] == [1, 2, 3, 4, 5]
            assert [r["score"] for r in mine] == sorted((r["score"] for r in mine), reverse=True)
            hit += len(set(want) & {r["vec_id"] for r in mine})
            if candidates == 6000:
                assert [r["vec_id"] for r in mine] == want
        assert hit >= 0.9 * 75


def test_recall_is_held_where_small_subtrees_have_enough_candidates(spark):
    """Unstructured vectors: the second level's subtrees hold the candidates asked for, but few of the nearest."""
    x = np.random.default_rng(21).normal(size=(4000, 64)).astype(np.float32)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    vectors = spark.createDataFrame([(i, row.tolist()) for i, row in enumerate(x)], "vec_id long, embedding array<float>")
    got = prefix_forest.nearest(vectors, vectors.where("vec_id % 80 = 0"), k=10, candidates=20).collect()
    near = x[::80] @ x.T
    near[np.arange(50), np.arange(0, 4000, 80)] = -np.inf
    true = {(80 * q, v) for q, row in enumerate(np.argsort(-near, axis=1)[:, :10].tolist()) for v in row}
    assert len(true & {(r["query_id"], r["vec_id"]) for r in got}) >= 0.9 * len(true)


def test_recall_measured_on_a_sample_sets_the_level(spark):
    """Near copies share deep subtrees, so queries may go down; unstructured vectors keep them near the root."""
    rng = np.random.default_rng(22)
    centres = np.repeat(rng.normal(size=(300, 64)), 10, axis=0)
    levels = []
    for x in (centres + 0.001 * rng.normal(size=centres.shape), rng.normal(size=centres.shape)):
        frame = prefix_forest.usable(spark.createDataFrame([(i, row.tolist()) for i, row in enumerate(x / np.linalg.norm(x, axis=1, keepdims=True))], "vec_id long, embedding array<double>"), "vec_id", "embedding")
        forest = prefix_forest.Forest(64, 1.0)
        points, asked = prefix_forest.hash_strings(frame, forest, False, False), prefix_forest.hash_strings(frame.where("vec_id % 30 = 0"), forest, True, False)
        levels.append(prefix_forest.deepest_level(points, asked, forest, 9, False))
    assert levels[0] > levels[1] + 3


def test_a_level_more_has_a_bit_more():
    forest = prefix_forest.Forest(8, 1.0, trees=2)
    one = np.array([[5 << (forest.levels - 1), 3]])
    assert forest.shared(one, one).tolist() == [forest.levels]
    assert forest.shared(one, one ^ np.array([[1, 1 << 61]])).tolist() == [forest.levels - 1]
    assert forest.shared(one, one ^ (1 << (forest.levels - 1))).tolist() == [0]
    assert prefix_forest.passes(0) == [] and prefix_forest.passes(1) == [1] and prefix_forest.passes(9) == [1, 5, 9]


def test_vectors_of_another_width_and_clashing_columns(spark):
    rows = [(i, [float(i % 7) + 1, 1.0, float(i)], i, "x", 0.5, 1) for i in range(60)] + [(100 + i, [1.0, 2.0], 0, "x", 0.0, 1) for i in range(20)]
    vectors = spark.createDataFrame(rows, "vec_id long, embedding array<float>, rank int, prefix string, score double, tree int")
    plain = prefix_forest.nearest(vectors.where("vec_id < 100"), vectors.where("vec_id % 20 = 0 AND vec_id < 100"), k=3).collect()
    assert len(plain) == 9 and sorted(plain) == sorted(prefix_forest.nearest(vectors, vectors.where("vec_id % 20 = 0"), k=3).collect())
    assert sorted(plain) == sorted(prefix_forest.nearest(vectors, vectors.where("vec_id % 20 = 0"), k=3, candidates=1, exact=True).collect())
