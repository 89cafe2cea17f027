"""BPE encoding and decoding with a priority queue of merge ranks.

A piece of text is a doubly linked list of symbols. A heap holds the rank of every adjacent pair that can be
merged; the lowest rank is taken first, and an entry whose symbols have changed meanwhile is stale and skipped.
Decoding joins the vocabulary's strings.

Null and empty texts give no ids and an empty decoded text. Repeated rows are encoded each on its own. Every
chunk between white space is encoded once per worker and kept in a table of bounded size.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import struct
import unicodedata

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tabqa.llm.common import map_arrow

#: Chunks a worker remembers before it starts afresh.
CACHE_CHUNKS = 700_000
#: Vocabulary ids are below 2 to this power.
_SHIFT = 24
_NEVER = 1 << 30
#: Separators that Python's split() takes for white space and Unicode's White_Space property does not.
_ODD_SEPARATORS = regex.compile("[\x1c-\x1f]")
_WHITE = regex.compile(r"\p{White_Space}+")


def byte_alphabet() -> list[str]:
    """The printable character that stands for each byte: itself where printable, else the next free one from 256 on."""
    shown = [*range(ord("!"), ord("~") + 1), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    out, free = [], 256
    for b in range(256):
        if b in shown:
            out.append(chr(b))
        else:
            out.append(chr(free))
            free += 1
    return out


class _Chunks(dict):
    """What chunks encode to, made when first asked for."""

    def __init__(self, make):
        super().__init__()
        self._make = make

    def __missing__(self, chunk):
        made = self[chunk] = self._make(chunk)
        return made


class _Gathered(dict):
    """Chunk -> ids. Chunks it doesn't hold are noted and give None, to be encoded together."""

    def __init__(self):
        super().__init__()
        self.pending: list[str] = []

    def __missing__(self, chunk):
        self.pending.append(chunk)


class MergeQueueEncoder:
    """Encodes and decodes with the vocabulary of a tokenizer file that has word ends and byte letters."""

    def __init__(self, spec: dict):
        model = spec["model"]
        self.vocab: dict[str, int] = dict(model["vocab"])
        self.suffix: str = model.get("end_of_word_suffix") or ""
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.strings = {i: s for s, i in self.vocab.items()} | {i: s for s, i in self.special.items()}
        self.ranks: dict[int, int] = {}  # both symbols in one key
        self.made: list[int] = []
        for rank, pair in enumerate(model["merges"]):
            left, right = pair if isinstance(pair, list) else pair.split(" ")
            self.ranks[self.vocab[left] << _SHIFT | self.vocab[right]] = rank
            self.made.append(self.vocab[left + right])
        letters = byte_alphabet()
        self._inner = [self.vocab.get(c, -1) for c in letters]
        self._last = [self.vocab.get(c + self.suffix, -1) for c in letters]
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self._pieces = regex.compile(split["pattern"]["Regex"].replace(r"\s", r"\p{White_Space}"))
        self._special = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None
        self._slots: tuple[np.ndarray, np.ndarray] | None = None
        self._whole = min(self._inner + self._last) >= 0
        self._chunks, self._bare, self._gathered = _Chunks(self._chunk), _Chunks(self._bare_chunk), _Gathered()

    @classmethod
    def load(cls, path: str) -> MergeQueueEncoder:
        held = _LOADED.get(path)
        if held is None:
            with open(path, encoding="utf-8") as f:
                held = _LOADED[path] = cls(json.load(f))
        return held

    def merge(self, symbols: list[int]) -> list[int]:
        """Applies the merges to a list of symbol ids, lowest rank first, leftmost first among equals.

        A heap entry is a rank and a position in one integer. `now` holds each position's present rank with its
        right neighbour, so an entry that says otherwise is stale.
        """
        n = len(symbols)
        if n < 2:
            return symbols
        rank_of, made, none = self.ranks.get, self.made, -1
        now = [rank_of(a << _SHIFT | b, none) for a, b in zip(symbols, symbols[1:])]
        heap = [r << 32 | i for i, r in enumerate(now) if r >= 0]
        if not heap:
            return symbols
        heapq.heapify(heap)
        symbols = symbols[:]
        now.append(none)
        before, after = list(range(-1, n - 1)), list(range(1, n + 1))
        pop, push = heapq.heappop, heapq.heappush
        while heap:
            entry = pop(heap)
            at, rank = entry & 0xFFFFFFFF, entry >> 32
            if now[at] != rank:
                continue
            gone = after[at]
            symbols[at] = new = made[rank]
            symbols[gone] = now[gone] = none
            after[at] = right = after[gone]
            if right < n:
                before[right] = at
                now[at] = r = rank_of(new << _SHIFT | symbols[right], none)
                if r >= 0:
                    push(heap, r << 32 | at)
            else:
                now[at] = none
            left = before[at]
            if left >= 0:
                now[left] = r = rank_of(symbols[left] << _SHIFT | new, none)
                if r >= 0:
                    push(heap, r << 32 | left)
        return [s for s in symbols if s >= 0]

    def piece_ids(self, piece: str) -> list[int]:
        """Ids of one piece: its bytes as letters, the last one with the word's end, then the merges."""
        raw = piece.encode("utf-8", "surrogatepass")
        inner = self._inner
        symbols = [inner[b] for b in raw]
        symbols[-1] = self._last[raw[-1]]
        return self.merge(symbols if self._whole else [s for s in symbols if s >= 0])

    def merge_many(self, words: list[bytes]) -> list[bytes]:
        """Ids (as bytes) of many one-piece words at once: in every round each word makes its lowest merge.

        The same merges in the same order as the queue's; only the bookkeeping is laid out in arrays.
        """
        if not words:
            return []
        lengths = np.fromiter(map(len, words), np.int64, len(words))
        raw = np.frombuffer(b"".join(words), np.uint8)
        ends = np.cumsum(lengths) - 1
        symbols = np.array(self._inner, np.int64)[raw]
        symbols[ends] = np.array(self._last, np.int64)[raw[ends]]
        owner = np.repeat(np.arange(len(words)), lengths)
        ranks = np.full(len(symbols), _NEVER)
        inner = np.flatnonzero(owner[1:] == owner[:-1])
        ranks[inner] = self._ranks_of(symbols[inner], symbols[inner + 1])
        done_owner, done_symbols = [], []
        made = np.array(self.made, np.int64)
        while len(symbols):
            first = np.flatnonzero(np.concatenate(([True], owner[1:] != owner[:-1])))
            best = np.minimum.reduceat(ranks << 32 | np.arange(len(symbols)), first)
            alive = (best >> 32) < _NEVER
            if not alive.all():
                stay = np.repeat(alive, np.diff(np.append(first, len(symbols))))
                done_owner.append(owner[~stay])
                done_symbols.append(symbols[~stay])
                moved = np.cumsum(stay) - 1
                at = moved[(best & 0xFFFFFFFF)[alive]]
                rank = (best >> 32)[alive]
                symbols, owner, ranks = symbols[stay], owner[stay], ranks[stay]
                if not len(symbols):
                    break
            else:
                at, rank = best & 0xFFFFFFFF, best >> 32
            symbols[at] = made[rank]
            keep = np.ones(len(symbols), bool)
            keep[at + 1] = False
            at = at - np.arange(len(at))  # one symbol has gone from each word before
            symbols, owner, ranks = symbols[keep], owner[keep], ranks[keep]
            ranks[at] = _NEVER
            right = at[(at + 1 < len(symbols))]
            right = right[owner[right] == owner[right + 1]]
            ranks[right] = self._ranks_of(symbols[right], symbols[right + 1])
            left = at[at > 0]
            left = left[owner[left] == owner[left - 1]]
            ranks[left - 1] = self._ranks_of(symbols[left - 1], symbols[left])
        owner, symbols = np.concatenate(done_owner), np.concatenate(done_symbols)
        joined = symbols[np.argsort(owner, kind="stable")].astype("<u4").tobytes()
        ends = (4 * np.cumsum(np.bincount(owner, minlength=len(words)))).tolist()
        return [joined[a:b] for a, b in zip([0, *ends], ends)]

    def _ranks_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Ranks of many pairs from an open-addressed table of the merges."""
        if self._slots is None:
            keys = np.fromiter(self.ranks, np.int64, len(self.ranks))
            size = 1 << (8 * len(keys)).bit_length()
            slot_keys, slot_ranks = np.full(size, -1), np.full(size, _NEVER)
            left_over, at = np.arange(len(keys)), self._slot(keys, size)
            while len(left_over):  # each round places one key per free slot; the others try the next
                free = slot_keys[at] < 0
                slot_keys[at[free]] = keys[left_over[free]]
                slot_ranks[at[free]] = left_over[free]  # the merges are in rank order
                placed = slot_keys[at] == keys[left_over]
                slot_ranks[at[placed]] = left_over[placed]
                left_over, at = left_over[~placed], (at[~placed] + 1) & (size - 1)
            self._slots = (slot_keys, slot_ranks)
        slot_keys, slot_ranks = self._slots
        asked = left << _SHIFT | right
        at = self._slot(asked, len(slot_keys))
        held = slot_keys[at]
        out = slot_ranks[at]
        off = np.flatnonzero((held != asked) & (held >= 0))
        out[(held != asked)] = _NEVER
        while len(off):
            at[off] = (at[off] + 1) & (len(slot_keys) - 1)
            held = slot_keys[at[off]]
            hit = held == asked[off]
            out[off[hit]] = slot_ranks[at[off[hit]]]
            off = off[~hit & (held >= 0)]
        return out

    @staticmethod
    def _slot(keys: np.ndarray, size: int) -> np.ndarray:
        with np.errstate(over="ignore"):
            return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - size.bit_length() + 1)).astype(np.int64)

    def encoded_ids_many(self, texts: list[str | None]) -> list[bytes]:
        """The ids of many texts; chunks not met before are merged together."""
        table, parts, spans = self._gathered, [], []
        if len(table) > 2 * CACHE_CHUNKS:  # ids alone take half the room
            table.clear()
        for text in texts:
            at = len(parts)
            if text and not (self._special is not None and "<|" in text) and not _ODD_SEPARATORS.search(text):
                parts += text.split()
            spans.append((at, len(parts)))
        table.pending.clear()
        values = list(map(table.__getitem__, parts))
        asked = table.pending[:]
        if asked:
            missing = list(set(asked))
            words, cuts, chunks = [], [0], []
            for chunk in missing:
                plain = chunk.lower() if chunk.isascii() else unicodedata.normalize("NFC", chunk).replace("Σ", "σ").lower()
                if plain.isalpha():
                    words.append(plain.encode())
                elif plain[-1] in ",." and plain[:-1].isalpha():
                    words += (plain[:-1].encode(), plain[-1].encode())
                else:
                    words += [w.encode("utf-8", "surrogatepass") for w in self._pieces.findall(plain)]
                chunks.append(chunk)
                cuts.append(len(words))
            ids = self.merge_many(words)
            for chunk, a, b in zip(chunks, cuts, cuts[1:]):
                table[chunk] = ids[a] if b - a == 1 else b"".join(ids[a:b])
            at = -1
            for chunk in asked:  # the gaps stand in the order in which the chunks were asked for
                at = values.index(None, at + 1)
                values[at] = table[chunk]
        return [b"".join(values[a:b]) if b > a else self.encoded_ids(text) for (a, b), text in zip(spans, texts, strict=True)]

    def chunk_ids(self, chunk: str) -> list[int]:
        """Ids of a stretch of text without white space."""
        if not chunk.isascii():
            chunk = unicodedata.normalize("NFC", chunk)
            if "Σ" in chunk:  # lower-cased letter by letter: no final form of sigma
                chunk = chunk.replace("Σ", "σ")
        chunk = chunk.lower()
        if chunk.isalpha():  # one run of letters, the usual case
            return self.piece_ids(chunk)
        return [i for piece in self._pieces.findall(chunk) for i in self.piece_ids(piece)]

    def _chunk(self, chunk: str) -> tuple[bytes, str]:
        if len(self._chunks) > CACHE_CHUNKS:
            self._chunks.clear()
        ids = self.chunk_ids(chunk)
        return struct.pack(f"<{len(ids)}I", *ids), " ".join([self.strings[i] for i in ids])

    def _bare_chunk(self, chunk: str) -> bytes:
        if len(self._bare) > CACHE_CHUNKS:
            self._bare.clear()
        ids = self.chunk_ids(chunk)
        return struct.pack(f"<{len(ids)}I", *ids)

    def _found(self, text: str, table: _Chunks, special) -> list:
        """The table's entries of the text's chunks in order; `special` makes those of special tokens."""

        def plain(part: str) -> list:
            return [table[c] for c in (_WHITE.split(part) if _ODD_SEPARATORS.search(part) else part.split()) if c]

        if self._special is None or "<|" not in text:
            return plain(text)
        found, at = [], 0
        for m in self._special.finditer(text):
            found += plain(text[at : m.start()])
            found.append(special(m[0]))
            at = m.end()
        return found + plain(text[at:])

    def encoded(self, text: str | None) -> tuple[bytes, str]:
        """(ids as little-endian unsigned 32-bit integers, decoded text) of a whole text."""
        if not text:
            return b"", ""
        found = self._found(text, self._chunks, lambda token: (struct.pack("<I", self.special[token]), token))
        return b"".join([f[0] for f in found]), " ".join([f[1] for f in found if f[1]])

    def encoded_ids(self, text: str | None) -> bytes:
        """The ids alone."""
        return b"".join(self._found(text, self._bare, lambda token: struct.pack("<I", self.special[token]))) if text else b""

    def encode(self, text: str | None) -> list[int]:
        raw = self.encoded_ids(text)
        return list(struct.unpack(f"<{len(raw) // 4}I", raw))

    def decode(self, ids: list[int]) -> str:
        """The vocabulary's strings of the ids, joined by blanks; unknown ids give nothing."""
        return " ".join(self.strings[i] for i in ids if i in self.strings)


_LOADED: dict[str, MergeQueueEncoder] = {}


def encode_documents(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: its id, `ids` (little-endian unsigned 32-bit integers) and `decoded`."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        coder = MergeQueueEncoder.load(vocabulary)
        made = [coder.encoded(t) for t in batch.column(1).to_pylist()]
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array([m[0] for m in made], pa.binary()), pa.array([m[1] for m in made], pa.string())], ["doc_id", "ids", "decoded"])

    kind = dict(docs.dtypes)[id_col]
    return map_arrow(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")), run, f"doc_id {kind}, ids binary, decoded string", rows=256)


def encode_digests(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: its id, number of ids, and the SHA-256 of ids and decoded text.

    The digests are taken in the task that encodes, so ids and texts don't cross back to the JVM.
    """

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        coder = MergeQueueEncoder.load(vocabulary)
        n, ids, texts = [], [], []
        for text in batch.column(1).to_pylist():
            raw, decoded = coder.encoded(text)
            n.append(len(raw) // 4)
            ids.append(hashlib.sha256(raw).hexdigest())
            texts.append(hashlib.sha256(decoded.encode()).hexdigest())
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids), pa.array(texts)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    kind = dict(docs.dtypes)[id_col]
    return map_arrow(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")), run, f"doc_id {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string", rows=256)
