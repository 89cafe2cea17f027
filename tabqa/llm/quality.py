"""Quality rules as a short-circuit cascade.

Every rule says what it rejects. On a sample each rule's mean cost and share of rejected documents are measured on
the executors; the rules then run in order of rejection per cost, and a document leaves at the first rule that
rejects it. Measures are taken from a document lazily, so what a cheap rule has decided, a dear one never computes.
The order changes the cost only: a document is kept when no rule rejects it, whatever the order.

A null or empty text has no words and fails the rule of fewest words. Repeated rows are judged each on its own.
"""

from __future__ import annotations

import re
import time
from collections.abc import Callable, Sequence
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tabqa.llm.common import WORD_BYTES, as_rows, map_arrow, utf8_rows

_WORD = re.compile(WORD_BYTES)
_SYMBOLS = b"#*$%&|<>"
_LETTERLESS = re.compile(rb"(?<![^\x20\x09-\x0D])[\x21-\x40\x5B-\x60\x7B-\x7F]+(?![^\x20\x09-\x0D])")
WINDOW = 8


class Measured:
    """A text and its measures, each computed when first asked for."""

    def __init__(self, raw: bytes):
        self.raw = raw

    @cached_property
    def words(self) -> list[bytes]:
        return _WORD.findall(self.raw)

    @cached_property
    def n_words(self) -> int:
        return len(self.words)

    @cached_property
    def word_chars(self) -> int:
        joined = b"".join(self.words)
        return len(joined) if joined.isascii() else len(joined.decode("utf-8", "replace"))

    @cached_property
    def n_symbols(self) -> int:
        return len(self.raw) - len(self.raw.translate(None, _SYMBOLS))

    @cached_property
    def n_exclaims(self) -> int:
        return self.raw.count(b"!")

    @cached_property
    def n_letterless(self) -> int:
        """Words of ASCII characters without a letter."""
        return len(_LETTERLESS.findall(self.raw))

    @cached_property
    def _lines(self) -> tuple[int, int]:
        lines = [x for x in self.raw.split(b"\n") if _WORD.search(x)]
        return len(lines), len(lines) - len(set(lines))

    @property
    def n_lines(self) -> int:
        return self._lines[0]

    @property
    def n_dup_lines(self) -> int:
        return self._lines[1]

    @cached_property
    def n_repeat_words(self) -> int:
        """Words inside windows of eight words that occur twice or more in the text."""
        n = self.n_words - WINDOW + 1
        if n < 2:
            return 0
        numbers: dict[bytes, int] = {}
        ids = np.fromiter((numbers.setdefault(w, len(numbers)) for w in self.words), np.int64, self.n_words)
        with np.errstate(over="ignore"):
            mixed = (ids.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
            mixed ^= mixed >> np.uint64(29)
            sketch = np.zeros(n, np.uint64)
            for k in range(WINDOW):
                sketch = sketch * np.uint64(0xBF58476D1CE4E5B9) + mixed[k : k + n]
        ordered = np.sort(sketch)
        if not (ordered[1:] == ordered[:-1]).any():
            return 0
        ranks, width = ids, 1
        while width < WINDOW:  # exact: the ranks of windows of twice the width
            pairs = ranks[:-width] * (len(self.words) + 1) + ranks[width:]
            ranks = np.unique(pairs, return_inverse=True)[1]
            width *= 2
        twice = np.bincount(ranks)[ranks] > 1
        edge = np.zeros(self.n_words + 1, np.int64)
        at = np.flatnonzero(twice)
        np.add.at(edge, at, 1)
        np.add.at(edge, at + WINDOW, -1)
        return int((np.cumsum(edge[:-1]) > 0).sum())


@dataclass(frozen=True)
class Rule:
    name: str
    rejects: Callable[[Measured], bool]


#: The rules of the query. Thresholds are whole percentages so that SQL can state them exactly.
BASE_RULES: tuple[Rule, ...] = (
    Rule("few_words", lambda d: d.n_words < 20),
    Rule("repeated_windows", lambda d: 100 * d.n_repeat_words > 30 * d.n_words),
)
RULES: tuple[Rule, ...] = (
    *BASE_RULES,
    Rule("symbols", lambda d: 100 * d.n_symbols > 10 * d.n_words),
    Rule("exclaims", lambda d: 100 * d.n_exclaims > 30 * d.n_words),
    Rule("letterless_words", lambda d: 100 * d.n_letterless > 40 * d.n_words),
    Rule("duplicate_lines", lambda d: 100 * d.n_dup_lines > 40 * d.n_lines),
    Rule("short_words", lambda d: 10 * d.word_chars < 20 * d.n_words),
    Rule("long_words", lambda d: 10 * d.word_chars > 150 * d.n_words),
)
#: Documents whose rules are timed; a parameter of the estimate.
SAMPLE_ROWS = 4_000


def estimate(docs: DataFrame, rules: Sequence[Rule] = RULES, text_col: str = "text", sample_rows: int = SAMPLE_ROWS, seed: int = 11, known: Sequence[str] = ()) -> list[dict]:
    """Mean cost in nanoseconds and rejected share of each rule, over a sample of about `sample_rows` documents.

    Each rule is timed on a fresh document, so that its cost holds all measures it needs, but for those that are `known`, which are
    taken of every document whatever the rules. An empty table gives
    no figures, and the rules keep the order they are written in.
    """
    total = docs.count()
    if not total:
        return []
    rules, known = tuple(rules), tuple(known)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        cost, rejected, seen = [0] * len(rules), [0] * len(rules), 0
        for raw in utf8_rows(batch.column(0)):
            seen += 1
            for k, rule in enumerate(rules):
                doc = Measured(raw)
                for name in known:
                    getattr(doc, name)
                began = time.perf_counter_ns()
                rejected[k] += bool(rule.rejects(doc))
                cost[k] += time.perf_counter_ns() - began
        return pa.RecordBatch.from_pydict({"rule": list(range(len(rules))), "cost": cost, "rejected": rejected, "seen": [seen] * len(rules)}, pa.schema([("rule", pa.int32()), ("cost", pa.int64()), ("rejected", pa.int64()), ("seen", pa.int64())]))

    sample = docs.select(F.col(text_col).cast("string").alias("text")).sample(False, min(1.0, sample_rows / total), seed)
    sums = map_arrow(sample, run, "rule int, cost bigint, rejected bigint, seen bigint").groupBy("rule").agg(*(F.sum(c).alias(c) for c in ("cost", "rejected", "seen"))).collect()
    return [{"rule": rules[r.rule].name, "cost_ns": r.cost / r.seen, "rejection": r.rejected / r.seen} for r in sorted(sums)]


def cascade_order(rules: Sequence[Rule], figures: Sequence[dict]) -> list[Rule]:
    """Rules by rejection per cost, highest first; rules without figures last; ties as written."""
    worth = {f["rule"]: f["rejection"] / max(f["cost_ns"], 1.0) for f in figures}
    return sorted(rules, key=lambda r: -worth.get(r.name, -1.0))


def apply_cascade(docs: DataFrame, rules: Sequence[Rule] = RULES, id_col: str = "doc_id", text_col: str = "text", measures: Sequence[str] = (), base: Sequence[Rule] = BASE_RULES) -> DataFrame:
    """`doc_id`, the measures asked for, `base_failed` and `kept` of every document.

    The cascade decides `kept`. Measures that are asked for are taken of every document, so the rules that need no others cost nothing
    more; what the other rules need, a document that a rule before them rejects is spared.
    """
    order, base, measures = tuple(rules), tuple(base), tuple(measures)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        columns: list[list] = [[] for _ in measures]
        failed, kept = [], []
        for raw in utf8_rows(batch.column(1)):
            doc = Measured(raw)
            for column, name in zip(columns, measures, strict=True):
                column.append(getattr(doc, name))
            kept.append(not any(rule.rejects(doc) for rule in order))
            failed.append(not kept[-1] and any(rule.rejects(doc) for rule in base))
        return pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, pa.int64()) for c in columns), pa.array(failed, pa.bool_()), pa.array(kept, pa.bool_())], ["doc_id", *measures, "base_failed", "kept"])

    kind = dict(docs.dtypes)[id_col]
    schema = ", ".join([f"doc_id {kind}", *(f"{m} bigint" for m in measures), "base_failed boolean", "kept boolean"])
    return map_arrow(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")), run, schema)


def filter_documents(docs: DataFrame, rules: Sequence[Rule] = RULES, text_col: str = "text") -> DataFrame:
    """The documents no rule rejects, with all their columns."""
    order = tuple(cascade_order(rules, estimate(docs, rules, text_col)))
    at, names = docs.columns.index(text_col), docs.columns

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = batch.column(0)
        keep = [not any(rule.rejects(doc) for rule in order) for doc in map(Measured, utf8_rows(rows.field(at)))]
        return pa.RecordBatch.from_arrays(rows.filter(pa.array(keep, pa.bool_())).flatten(), names)

    return map_arrow(as_rows(docs), run, docs.schema)


#: DuckDB SQL for the query over `documents`.
ORACLE_SQL = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws,
             list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM d),
n AS (SELECT doc_id, t, ws, len(ws) AS n_words, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::BIGINT AS word_chars,
             (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
             (length(t) - length(replace(t, '!', '')))::BIGINT AS n_exclaims,
             len(list_filter(ws, lambda x: regexp_full_match(x, '[\x21-\x40\x5B-\x60\x7B-\x7F]+'))) AS n_letterless,
             len(ls) AS n_lines, (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines FROM w),
g AS (SELECT doc_id, i, list_slice(ws, i, i + 7) AS gram FROM (SELECT doc_id, ws, unnest(range(1, n_words - 6)) AS i FROM n WHERE n_words >= 8)),
r AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, gram) AS c FROM g) WHERE c > 1),
c AS (SELECT doc_id, count(DISTINCT p) AS n_repeat_words FROM (SELECT doc_id, unnest(range(i, i + 8)) AS p FROM r) GROUP BY doc_id),
m AS (SELECT n.*, coalesce(c.n_repeat_words, 0)::BIGINT AS n_repeat_words FROM n LEFT JOIN c USING (doc_id))
SELECT doc_id, n_words::BIGINT AS n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AS base_failed,
       NOT (n_words < 20 OR 100 * n_repeat_words > 30 * n_words OR 100 * n_symbols > 10 * n_words OR 100 * n_exclaims > 30 * n_words
            OR 100 * n_letterless > 40 * n_words OR 100 * n_dup_lines > 40 * n_lines OR 10 * word_chars < 20 * n_words OR 10 * word_chars > 150 * n_words) AS kept
FROM m
"""
