"""Language identification by hierarchical discrimination.

Languages are first joined into families by the likeness of their letter statistics, or taken from a given map. A
text's family is predicted first; one-versus-one linear support vector machines then tell the languages of that
family apart. Features are hashed counts of three- and four-byte runs of the lower-cased text, other characters than
letters being blanks.

Learning takes a bounded sample: at most `per_language` labelled texts of each language. Every text is
predicted from the whole of it. A null text, or one without a letter, gives `und` and score 0. Rows without a label
are predicted all the same. Without any labelled row every prediction is `und`.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tabqa.llm.common import map_arrow

#: Distinct texts of each language that training looks at, at most; a parameter.
PER_LANGUAGE = 400
#: Hash buckets of the features.
BUCKETS = 4096
UNKNOWN = "und"
_LETTER = regex.compile(r"\p{L}")
_BLANKED = np.full(256, 32, np.uint8)
for _b in [*range(97, 123), *range(128, 256)]:
    _BLANKED[_b] = _b


def features(text: str | None) -> np.ndarray | None:
    """The text's feature vector of length one, or None where there is no letter."""
    if not text or not _LETTER.search(text):
        return None
    letters = _BLANKED[np.frombuffer(f" {text.lower()} ".encode("utf-8", "replace"), np.uint8)].astype(np.uint32)
    counts = np.zeros(BUCKETS, np.float64)
    three = (letters[:-2] << np.uint32(16)) | (letters[1:-1] << np.uint32(8)) | letters[2:]
    with np.errstate(over="ignore"):
        counts += np.bincount((three * np.uint32(0x9E3779B1)) >> np.uint32(20), minlength=BUCKETS)
        if len(letters) > 3:
            four = (three[:-1] << np.uint32(8)) | letters[3:]
            counts += np.bincount((four * np.uint32(0x85EBCA77)) >> np.uint32(20), minlength=BUCKETS)
    counts = np.sqrt(counts)
    return counts / np.linalg.norm(counts)


def fit_svm(x: np.ndarray, y: np.ndarray, c: float = 4.0, epochs: int = 30, seed: int = 5) -> np.ndarray:
    """A linear support vector machine (hinge loss, bias as a constant feature) by dual coordinate ascent."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w, alpha, norms = np.zeros(x.shape[1]), np.zeros(len(x)), (x * x).sum(axis=1)
    order = np.random.default_rng(seed)
    for _ in range(epochs):
        moved = 0.0
        for i in order.permutation(len(x)):
            gradient = y[i] * (x[i] @ w) - 1
            new = min(max(alpha[i] - gradient / norms[i], 0.0), c)
            if new != alpha[i]:
                w += (new - alpha[i]) * y[i] * x[i]
                moved = max(moved, abs(new - alpha[i]))
                alpha[i] = new
        if moved < 1e-3:
            break
    return w


def join_families(centroids: dict[str, np.ndarray], families: int | None = None) -> list[list[str]]:
    """Average-linkage clusters of the languages' mean vectors; by default about the square root of their number."""
    groups = [[k] for k in sorted(centroids)]
    families = families or max(1, round(len(groups) ** 0.5))

    def near(a: list[str], b: list[str]) -> float:
        return float(np.mean([centroids[p] @ centroids[q] / (np.linalg.norm(centroids[p]) * np.linalg.norm(centroids[q])) for p in a for q in b]))

    while len(groups) > families:
        i, j = max(combinations(range(len(groups)), 2), key=lambda p: (near(groups[p[0]], groups[p[1]]), -p[0], -p[1]))
        groups[i] += groups.pop(j)
    return [sorted(g) for g in groups]


@dataclass
class Voters:
    """One-versus-one machines over some classes."""

    classes: list[str]
    pairs: list[tuple[int, int]] = field(default_factory=list)
    weights: np.ndarray = field(default_factory=lambda: np.zeros((0, BUCKETS + 1)))

    @classmethod
    def fit(cls, x: np.ndarray, labels: np.ndarray, classes: list[str]) -> Voters:
        pairs = list(combinations(range(len(classes)), 2))
        rows = []
        for a, b in pairs:
            own = np.isin(labels, [classes[a], classes[b]])
            rows.append(fit_svm(x[own], np.where(labels[own] == classes[a], 1.0, -1.0)))
        return cls(classes, pairs, np.array(rows) if rows else np.zeros((0, BUCKETS + 1)))

    def vote(self, x: np.ndarray) -> tuple[str, float]:
        """The class with most votes, ties to the greater sum of margins, and its certainty."""
        if len(self.classes) == 1:
            return self.classes[0], 1.0
        margins = self.weights[:, :-1] @ x + self.weights[:, -1]
        votes, sums, least = np.zeros(len(self.classes)), np.zeros(len(self.classes)), np.full(len(self.classes), np.inf)
        for (a, b), m in zip(self.pairs, margins, strict=True):
            votes[a if m >= 0 else b] += 1
            sums[a] += m
            sums[b] -= m
            least[a], least[b] = min(least[a], m), min(least[b], -m)
        best = max(range(len(self.classes)), key=lambda k: (votes[k], sums[k], -k))
        return self.classes[best], float(1 / (1 + np.exp(-3 * least[best])))


@dataclass
class LanguageModel:
    families: list[list[str]]
    top: Voters | None
    within: list[Voters]

    def predict(self, text: str | None) -> tuple[str, float]:
        x = features(text)
        if x is None or self.top is None:
            return UNKNOWN, 0.0
        family, p = self.top.vote(x)
        language, q = self.within[int(family)].vote(x)
        return language, p * q


def fit_model(x: np.ndarray, labels: np.ndarray, families: list[list[str]] | None = None) -> LanguageModel:
    """Families (given, or found), a vote between families, and votes within each."""
    if not len(labels):
        return LanguageModel([], None, [])
    families = families or join_families({k: x[labels == k].mean(axis=0) for k in np.unique(labels).tolist()})
    family_of = {language: str(i) for i, group in enumerate(families) for language in group}
    top = Voters.fit(x, np.array([family_of[v] for v in labels.tolist()]), [str(i) for i in range(len(families))])
    return LanguageModel(families, top, [Voters.fit(x, labels, group) for group in families])


def train(labelled: DataFrame, per_language: int = PER_LANGUAGE, text_col: str = "text", label_col: str = "lang", families: list[list[str]] | None = None) -> LanguageModel:
    """Fits on a sample of labelled rows: of each language the `per_language` distinct texts of least hash, all of them where there are fewer.

    So the sample is the same in every run, copies of a text count once, and no language is left out. Feature vectors are made on
    the executors; the driver gets about 16 KB for each sampled text.
    """
    rows = labelled.select(F.col(text_col).cast("string").alias("text"), F.col(label_col).cast("string").alias("lang")).where("lang IS NOT NULL").where(F.col("text").rlike(r"\p{L}"))
    rows = rows.withColumn("hash", F.xxhash64("text", F.lit(3)))
    # the least hashes of each language: first within slices of it, then of what the slices leave
    sliced = rows.select("lang", "hash").distinct().withColumn("slice", F.pmod("hash", F.lit(32)))
    for by in (["lang", "slice"], ["lang"]):
        sliced = sliced.withColumn("r", F.row_number().over(Window.partitionBy(*by).orderBy("hash"))).where(F.col("r") <= per_language).drop("r")
    # sent to all tasks: at most `per_language` hashes a language. Of a text's copies one is taken, already before the shuffle
    chosen = F.broadcast(sliced.select("lang", "hash"))
    sample = rows.join(chosen, ["lang", "hash"], "left_semi").groupBy("lang", "hash").agg(F.min("text").alias("text")).select("text", "lang")

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        made = [(lang, x) for text, lang in zip(*(c.to_pylist() for c in batch.columns), strict=True) if (x := features(text)) is not None]
        return pa.RecordBatch.from_arrays([pa.array([m[0] for m in made], pa.string()), pa.array([m[1].astype(np.float32).tobytes() for m in made], pa.binary())], ["lang", "x"])

    got = sorted((r["lang"], bytes(r["x"])) for r in map_arrow(sample, run, "lang string, x binary").collect())
    x = np.array([np.frombuffer(v, np.float32) for _, v in got], np.float64).reshape(len(got), BUCKETS)
    return fit_model(x, np.array([k for k, _ in got], object), families)


def predict(docs: DataFrame, model: LanguageModel, keep: list[str], text_col: str = "text") -> DataFrame:
    """The kept columns with `lang_pred` and `score`."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        made = [model.predict(t) for t in batch.column(0).to_pylist()]
        return pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array([m[0] for m in made], pa.string()), pa.array([m[1] for m in made], pa.float64())], [*keep, "lang_pred", "score"])

    chosen = docs.select(F.col(text_col).cast("string").alias("__text"), *keep)
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in chosen.schema.fields[1:])
    return map_arrow(chosen, run, f"{fields}, lang_pred string, score double")
