"""Learned deciders: boosting, bagging, linear SVM; tuning; ensembles over balanced bags.

Labelled pairs are few by nature and the fits are small.  They come from a training region; which places that is,
and that the study area lies apart from it, is the caller's part.
"""

from __future__ import annotations

import math
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
from pyspark.ml.classification import GBTClassifier, LinearSVC, LogisticRegression, RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.operators import resample

FEATURES = ("s_name", "s_addr")
GRIDS = {
    "gb": [{"maxDepth": 2, "maxIter": 10}, {"maxDepth": 3, "maxIter": 10}],
    "bag": [{"maxDepth": 3, "numTrees": 10}, {"maxDepth": 5, "numTrees": 10}],
    "rf": [{"maxDepth": 3, "numTrees": 10}, {"maxDepth": 5, "numTrees": 10}],
    "svm": [{"regParam": 0.001}, {"regParam": 0.01}],
}


def estimator(learner: str, params: dict, weighted: bool = False, seed: int = 1):  # noqa: ANN201
    common = {"featuresCol": "x", "labelCol": "label"}
    if learner == "gb":
        return GBTClassifier(**common, seed=seed, stepSize=0.2, **({"weightCol": "weight"} if weighted else {}), **params)
    if learner in ("bag", "rf"):
        # bagging looks at every feature in every node; the forest at a random subset
        return RandomForestClassifier(**common, seed=seed, bootstrap=True, subsamplingRate=1.0, featureSubsetStrategy="all" if learner == "bag" else "sqrt", **params)
    if learner == "svm":
        return LinearSVC(**common, standardization=False, maxIter=20, **({"weightCol": "weight"} if weighted else {}), **params)
    raise ValueError(learner)


def _vectors(df: DataFrame, features: tuple[str, ...] = FEATURES) -> DataFrame:
    return VectorAssembler(inputCols=list(features), outputCol="x").transform(df)


#: Distinct rows of a boosting task.
PER_TASK = 50_000


def counted(rows: DataFrame, *keep: str) -> DataFrame:
    """Rows alike in features and label once, with their number as ``weight``; dealt by value, the same under any
    layout.  Boosting draws no bootstraps, so it sees the same training set in fewer rows and in several tasks."""
    out = rows.groupBy(*keep, *FEATURES, "label").agg(F.count("*").cast("double").alias("weight")).cache()
    tasks = -(-out.count() // PER_TASK) or 1
    dealt = _vectors(out).repartition(tasks, *FEATURES, "label").sortWithinPartitions(*keep, *FEATURES, "label").cache()
    dealt.count()
    out.unpersist()
    return dealt


@dataclass
class Model:
    """A fitted classifier; SVM margins become probabilities by a sigmoid fitted on the training rows."""

    fitted: object
    sigmoid: tuple[float, float] | None = None

    def prob(self, df: DataFrame, name: str) -> DataFrame:
        out = self.fitted.transform(df)
        if self.sigmoid is None:
            p = vector_to_array("probability")[1]
        else:
            a, b = self.sigmoid
            p = 1 / (1 + F.exp(-(F.lit(a) * vector_to_array("rawPrediction")[1] + F.lit(b))))
        return out.withColumn(name, p).drop("probability", "rawPrediction", "prediction")


def fit(train: DataFrame, learner: str, params: dict | None = None, seed: int = 1, weighted: bool = False, calibrated: bool = True) -> Model:
    """One model on one training set, in one partition so that bootstraps don't depend on the layout."""
    if learner == "gb":
        rows = counted(train)
        fitted = estimator(learner, params or GRIDS[learner][0], True, seed).fit(rows)
        rows.unpersist()
        return Model(fitted)
    rows = train
    if weighted:
        rows = rows.join(F.broadcast(resample.class_weights(train).select("label", "weight")), "label")
    rows = _vectors(rows).orderBy("a", "b").coalesce(1).cache()
    fitted = estimator(learner, params or GRIDS[learner][0], weighted, seed).fit(rows)
    sigmoid = None
    if learner == "svm" and calibrated:
        margins = fitted.transform(rows).withColumn("margin", vector_to_array("rawPrediction")[1]).drop("rawPrediction", "prediction", "x")
        lr = LogisticRegression(featuresCol="x", labelCol="label", maxIter=50, **({"weightCol": "weight"} if weighted else {})).fit(VectorAssembler(inputCols=["margin"], outputCol="x").transform(margins))
        sigmoid = (float(lr.coefficients[0]), float(lr.intercept))
    rows.unpersist()
    return Model(fitted, sigmoid)


def balanced_of(pred: DataFrame, cut: float = 0.5) -> float:
    """Balanced accuracy of rows with label and prob, and weight if rows stand for several."""
    weight = F.col("weight") if "weight" in pred.columns else F.lit(1.0)
    right = F.when((F.col("prob") >= cut).cast("int") == F.col("label"), weight).otherwise(0.0)
    r = pred.groupBy("label").agg((F.sum(right) / F.sum(weight)).alias("right")).collect()
    return sum(x["right"] for x in r) / max(1, len(r))


#: Fits that run beside each other; each is a few small jobs that leave most of a cluster idle.
FITS_AT_ONCE = 6


def tune(train: DataFrame, learner: str, grid: list[dict] | None = None, folds: int = 5, seed: int = 1, weighted: bool = False) -> tuple[dict, list[tuple[dict, float]]]:
    """The grid point of the best mean balanced accuracy over the folds, and every point's mean.

    ``weighted`` fits the folds with class weights, as the final model is.
    """
    grid = grid or GRIDS[learner]
    if len(grid) == 1:
        return grid[0], []
    boosted = learner == "gb"
    dealt = resample.folds(train, folds)
    dealt = counted(dealt, "fold") if boosted else dealt.cache()
    dealt.count()

    def score(task: tuple[int, int]) -> float:
        point, k = task
        if boosted:
            fitted = estimator(learner, grid[point], True, seed).fit(dealt.where(F.col("fold") != k))
            said = fitted.transform(dealt.where(F.col("fold") == k))
            return balanced_of(said.select("label", "weight", F.col("prediction").alias("prob")))
        model = fit(dealt.where(F.col("fold") != k).drop("fold"), learner, grid[point], seed, weighted, calibrated=False)
        # the class a fold model decides needs no probability
        said = model.fitted.transform(_vectors(dealt.where(F.col("fold") == k)))
        return balanced_of(said.select("label", F.col("prediction").alias("prob")))

    tasks = [(point, k) for point in range(len(grid)) for k in range(folds)]
    with ThreadPoolExecutor(FITS_AT_ONCE) as pool:
        got = list(pool.map(score, tasks))
    dealt.unpersist()
    scores = [(params, sum(got[i * folds : (i + 1) * folds]) / folds) for i, params in enumerate(grid)]
    return max(scores, key=lambda s: s[1])[0], scores


@dataclass
class Ensemble:
    """Mean probability of one model per balanced bag."""

    models: list[Model] = field(default_factory=list)
    cut: float = 0.5

    def predict(self, df: DataFrame) -> DataFrame:
        out = _vectors(df)
        for i, m in enumerate(self.models):
            out = m.prob(out, f"p{i}")
        mean = sum((F.col(f"p{i}") for i in range(len(self.models))), F.lit(0.0)) / len(self.models)
        out = out.withColumn("prob", mean).drop("x", *[f"p{i}" for i in range(len(self.models))])
        return out.withColumn("score", F.col("prob")).withColumn("prediction", (F.col("prob") >= self.cut).cast("int"))

    score = predict


def fit_plain(train: DataFrame, learner: str, grid: list[dict] | None = None, folds: int = 5) -> Ensemble:
    """Without resampling; the SVM carries class weights."""
    params, _ = tune(train, learner, grid, folds, weighted=learner == "svm")
    return Ensemble([fit(train, learner, params, weighted=learner == "svm")])


def fit_rebalanced(train: DataFrame, learner: str, n_bags: int = 5, size: int | str = "sqrt", grid: list[dict] | None = None, folds: int = 5) -> Ensemble:
    """One tuned model on each of several balanced sets."""
    bags = resample.balanced_sets(train, n_bags, size).cache()
    bags.count()  # once, before the bags are read beside each other

    def one(i: int) -> Model:
        bag = bags.where(F.col("bag_id") == i)
        params, _ = tune(bag, learner, grid, folds)
        return fit(bag, learner, params, seed=i + 1)

    with ThreadPoolExecutor(n_bags) as pool:
        models = list(pool.map(one, range(n_bags)))
    bags.unpersist()
    return Ensemble(models)


def gb_reference(x: np.ndarray, y: np.ndarray, rounds: int = 10) -> tuple[list[float], callable]:
    """Stage-wise boosting of stumps with a line search for the step, for small tests: losses by round, predictor.

    Starts from the constant of least log loss; each stump fits the negative gradient by least squares, and the
    step along it is the best of a fine search.
    """
    n = len(y)
    base = math.log((y.sum() + 1e-9) / (n - y.sum() + 1e-9))
    f, stumps, losses = np.full(n, base), [], []
    loss = lambda z: float(np.mean(np.logaddexp(0, z) - y * z))
    losses.append(loss(f))
    for _ in range(rounds):
        residual = y - 1 / (1 + np.exp(-f))
        best = None
        for j in range(x.shape[1]):
            for t in np.unique(x[:, j])[:-1]:
                left = x[:, j] <= t
                a, b = residual[left].mean(), residual[~left].mean()
                sse = ((residual - np.where(left, a, b)) ** 2).sum()
                if best is None or sse < best[0] - 1e-12:
                    best = (sse, j, t, a, b)
        if best is None:
            break
        _, j, t, a, b = best
        h = np.where(x[:, j] <= t, a, b)
        step = min(np.linspace(0, 8, 81), key=lambda s: loss(f + s * h))
        f = f + step * h
        stumps.append((j, t, a * step, b * step))
        losses.append(loss(f))
    return losses, lambda z: 1 / (1 + np.exp(-(base + sum(np.where(z[:, j] <= t, a, b) for j, t, a, b in stumps))))
