"""Families of layouts: training, cross-validation and hold-out of eight classifiers, and assigning a family to a grid.

Inputs are nine numbers of some hundred grids, so a model's parameters are a driver's matter; scoring is column expressions
or Spark ML. Folds are by hash, stratified by family, so every run has the same ones. The models that are written here (Gaussian naive
Bayes, linear discriminant, nearest neighbours) take any numeric features and label.
"""

from __future__ import annotations

from collections.abc import Sequence
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np
from pyspark.ml import Pipeline
from pyspark.ml.classification import DecisionTreeClassifier, LinearSVC, LogisticRegression, MultilayerPerceptronClassifier, NaiveBayes, OneVsRest, RandomForestClassifier
from pyspark.ml.feature import StandardScaler, StringIndexer, VectorAssembler
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

FEATURES = [f"f{i}" for i in range(1, 10)]
ALGORITHMS = ("logreg", "lindisc", "knn", "tree", "gnb", "svc", "mlp", "forest")
#: Share of the greatest variance that is added to every variance.
SMOOTHING = 1e-9
RIDGE = 1e-6
#: Rows of a training set that the models take to the driver, at most. Families are learned from some hundred grids.
MOST_TRAINING = 100_000


def with_folds(features: DataFrame, k: int = 5, holdout: float = 0.15) -> DataFrame:
    """Adds `fold`: -1 for the held-out grids of each family, else 0..k-1, by the order of the ids' digests."""
    order = Window.partitionBy("family").orderBy(F.md5(F.col("table_id").cast("binary")), "table_id")
    ranked = features.withColumn("r", F.row_number().over(order) - 1).withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("family")))
    out = F.round(F.col("n") * holdout)
    return ranked.withColumn("fold", F.when(F.col("r") < out, F.lit(-1)).otherwise(F.pmod(F.col("r") - out, F.lit(k)).cast("int"))).drop("r", "n")


def gaussian_parameters(train: DataFrame, features: Sequence[str] = FEATURES, label: str = "family") -> DataFrame:
    """(family, prior, m1.., v1..): one aggregation."""
    total = train.agg(F.count(F.lit(1)).alias("total"), *(F.var_pop(f).alias(f"w{i}") for i, f in enumerate(features, 1)))
    classes = train.groupBy(F.col(label).alias("family")).agg(F.count(F.lit(1)).alias("n"), *(F.avg(f).alias(f"m{i}") for i, f in enumerate(features, 1)), *(F.var_pop(f).alias(f"v{i}") for i, f in enumerate(features, 1)))
    numbers = range(1, len(features) + 1)
    most = F.greatest(*(F.col(f"w{i}") for i in numbers)) if len(features) > 1 else F.col("w1")
    joined = classes.crossJoin(F.broadcast(total)).withColumn("eps", F.lit(SMOOTHING) * most + F.lit(1e-12))  # one row
    return joined.select("family", (F.col("n") / F.col("total")).alias("prior"), *(F.col(f"m{i}") for i in numbers), *((F.col(f"v{i}") + F.col("eps")).alias(f"v{i}") for i in numbers))


def gaussian_predict(rows: DataFrame, parameters: DataFrame, features: Sequence[str] = FEATURES, id_col: str = "table_id") -> DataFrame:
    """(id, predicted, log_density): the family of greatest log density; parameters are as many rows as families."""
    density = F.ln("prior")
    for i, f in enumerate(features, 1):
        density = density - 0.5 * (F.ln(F.lit(2 * np.pi) * F.col(f"v{i}")) + F.pow(F.col(f) - F.col(f"m{i}"), 2) / F.col(f"v{i}"))
    scored = rows.select(id_col, *features).crossJoin(F.broadcast(parameters.withColumnRenamed("family", "predicted"))).withColumn("s", density)
    return scored.groupBy(id_col).agg(F.max_by("predicted", F.struct("s", "predicted")).alias("predicted"), F.max("s").alias("log_density"))


def _matrix(train: DataFrame, features: Sequence[str] = FEATURES, label: str = "family") -> tuple[np.ndarray, np.ndarray]:
    rows = train.select(F.col(label).alias("y"), *features).limit(MOST_TRAINING + 1).collect()
    if len(rows) > MOST_TRAINING:
        raise ValueError(f"more than {MOST_TRAINING} training rows: fit on a sample")
    return np.array([[r[f] for f in features] for r in rows], float), np.array([r["y"] for r in rows])


def discriminant_predict(rows: DataFrame, train: DataFrame, features: Sequence[str] = FEATURES, label: str = "family", id_col: str = "table_id") -> DataFrame:
    """Linear discriminant with a pooled within-class covariance; scoring is a weighted sum of columns."""
    x, y = _matrix(train, features, label)
    classes = sorted(set(y.tolist()))
    means = np.array([x[y == c].mean(axis=0) for c in classes])
    pooled = sum((x[y == c] - m).T @ (x[y == c] - m) for c, m in zip(classes, means, strict=True)) / len(x) + RIDGE * np.eye(x.shape[1])
    weights = np.linalg.solve(pooled, means.T).T
    scores = [F.lit(float(np.log((y == c).mean()) - 0.5 * w @ m)) + sum((F.col(f) * float(v) for f, v in zip(features, w, strict=True)), F.lit(0.0)) for c, w, m in zip(classes, weights, means, strict=True)]
    best = F.array_max(F.array(*(F.struct(s.alias("s"), F.lit(c).alias("c")) for s, c in zip(scores, classes, strict=True))))
    return rows.select(id_col, best["c"].alias("predicted"))


def knn_predict(rows: DataFrame, train: DataFrame, k: int = 5, features: Sequence[str] = FEATURES, label: str = "family", id_col: str = "table_id") -> DataFrame:
    """Vote of the k nearest training rows by z-scores; ties go to the class of the nearest, of equally near ones to the smaller id.

    The training set, whose size is checked, is sent to all tasks. A row is no neighbour of its own.
    """
    x, _ = _matrix(train, features, label)
    mean, spread = x.mean(axis=0), np.where(x.std(axis=0) > 0, x.std(axis=0), 1.0)
    z = lambda name: F.array(*((F.col(f) - float(m)) / float(s) for f, m, s in zip(features, mean, spread, strict=True))).alias(name)
    asked = rows.select(id_col, z("a"))
    held = train.select(F.col(id_col).alias("near_id"), F.col(label).alias("family"), z("b"))
    far = F.aggregate(F.zip_with("a", "b", lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda s, v: s + v)
    pairs = asked.crossJoin(F.broadcast(held)).where(F.col(id_col) != F.col("near_id")).withColumn("d", F.round(far, 9))
    near = pairs.withColumn("r", F.row_number().over(Window.partitionBy(id_col).orderBy("d", "near_id"))).where(F.col("r") <= k)
    votes = near.groupBy(id_col, "family").agg(F.count(F.lit(1)).alias("n"), F.min("r").alias("first"))
    return votes.groupBy(id_col).agg(F.max_by("family", F.struct("n", -F.col("first"))).alias("predicted"))


def _ml_predict(features: DataFrame, train: DataFrame, algorithm: str, seed: int) -> DataFrame:
    train = train.select("family", *FEATURES).coalesce(1)  # some hundred rows: a task for each step of a fit
    classes = train.select("family").distinct().count()
    index = StringIndexer(inputCol="family", outputCol="label", stringOrderType="alphabetAsc").fit(train)
    stages = [VectorAssembler(inputCols=FEATURES, outputCol="raw"), StandardScaler(inputCol="raw", outputCol="x", withMean=True)]
    made = {
        "logreg": lambda: LogisticRegression(featuresCol="x", maxIter=40),
        "tree": lambda: DecisionTreeClassifier(featuresCol="x", seed=seed),
        "forest": lambda: RandomForestClassifier(featuresCol="x", seed=seed),
        "gnb": lambda: NaiveBayes(featuresCol="x", modelType="gaussian"),
        "svc": lambda: OneVsRest(featuresCol="x", classifier=LinearSVC(featuresCol="x", maxIter=12, tol=1e-3, regParam=0.01), parallelism=4),
        "mlp": lambda: MultilayerPerceptronClassifier(featuresCol="x", layers=[len(FEATURES), 12, classes], maxIter=80, seed=seed),
    }[algorithm]()
    model = Pipeline(stages=[*stages, made]).fit(index.transform(train).select("label", *FEATURES))
    names = F.array(*(F.lit(x) for x in index.labels))
    return model.transform(features.select("table_id", *FEATURES)).select("table_id", F.element_at(names, F.col("prediction").cast("int") + 1).alias("predicted"))


def predict(features: DataFrame, train: DataFrame, algorithm: str = "gnb", seed: int = 42) -> DataFrame:
    """(table_id, predicted) by one of the eight algorithms."""
    if algorithm == "gnb":
        return gaussian_predict(features, gaussian_parameters(train)).select("table_id", "predicted")
    if algorithm == "lindisc":
        return discriminant_predict(features, train)
    if algorithm == "knn":
        return knn_predict(features, train)
    if algorithm not in ALGORITHMS:
        raise ValueError(f"no such algorithm: {algorithm}")
    return _ml_predict(features, train, algorithm, seed)


@dataclass
class Scores:
    algorithm: str
    fold: int
    n: int
    n_right: int

    @property
    def accuracy(self) -> float:
        return self.n_right / self.n if self.n else 0.0


def gathered(folded: DataFrame) -> DataFrame:
    """The labelled features as rows of the driver, in one partition: what models are fitted on many times. Their number is checked."""
    rows = folded.select("table_id", "family", "fold", *FEATURES).limit(MOST_TRAINING + 1).collect()
    if len(rows) > MOST_TRAINING:
        raise ValueError(f"more than {MOST_TRAINING} training rows: fit on a sample")
    return folded.sparkSession.createDataFrame(rows, "table_id string, family string, fold int, " + ", ".join(f"{f} double" for f in FEATURES)).coalesce(1)


def cv_scores(folded: DataFrame, algorithms: tuple[str, ...] = ALGORITHMS, k: int = 5, at_once: int = 8) -> list[Scores]:
    """How many grids of each fold of the training part each algorithm tells right, fitted on the other folds.

    A fit is many short steps over few rows, so several fits run beside each other.
    """
    held = gathered(folded)

    def score(job: tuple[str, int]) -> Scores:
        algorithm, fold = job
        train, test = held.where(f"fold NOT IN (-1, {fold})"), held.where(f"fold = {fold}")
        truth = {r["table_id"]: r["family"] for r in test.select("table_id", "family").collect()}
        found = {r["table_id"]: r["predicted"] for r in predict(test, train, algorithm).collect()}
        return Scores(algorithm, fold, len(truth), sum(found.get(t) == f for t, f in truth.items()))

    with ThreadPoolExecutor(at_once) as pool:
        return list(pool.map(score, [(a, f) for a in algorithms for f in range(k)]))


def holdout_accuracy(folded: DataFrame, algorithm: str = "gnb") -> DataFrame:
    """One row: grids held out, and how many of them get their family."""
    train, test = folded.where("fold >= 0"), folded.where("fold = -1")
    met = predict(test, train, algorithm).join(test.select("table_id", "family"), "table_id")
    return met.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("predicted") == F.col("family")).alias("n_right"), F.avg((F.col("predicted") == F.col("family")).cast("double")).alias("accuracy"))


def assign_family(features: DataFrame, parameters: DataFrame, min_log_density: float = -1e4, fallback: str = "plain_listing") -> DataFrame:
    """(table_id, family): the adopted model's choice; grids unlike all families get the fallback."""
    found = gaussian_predict(features, parameters)
    return found.select("table_id", F.when(F.col("log_density") < min_log_density, F.lit(fallback)).otherwise(F.col("predicted")).alias("family"))
