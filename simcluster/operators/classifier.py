"""Classifiers that rank clusters by the probability of a high similarity index."""

from __future__ import annotations

import warnings
from dataclasses import dataclass

from pyspark.ml import Model
from pyspark.ml.classification import DecisionTreeClassifier, GBTClassifier, LogisticRegression, MultilayerPerceptronClassifier, NaiveBayes, RandomForestClassifier
from pyspark.ml.evaluation import BinaryClassificationEvaluator
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .features import NAMES, assemble

ALGORITHMS = ("logistic", "random_forest", "gbt", "naive_bayes", "decision_tree", "mlp")


@dataclass
class Scheduler:
    """A trained classifier; without one (a single class in training) all clusters have the same score."""

    model: Model | None
    prior: float
    n_features: int
    algorithm: str


def _estimator(algorithm: str, n_features: int, weight: str | None, seed: int):
    w = {"weightCol": weight} if weight else {}
    made = {
        "logistic": lambda: LogisticRegression(regParam=0.001, maxIter=100, **w),
        "random_forest": lambda: RandomForestClassifier(numTrees=60, maxDepth=6, seed=seed, **w),
        "gbt": lambda: GBTClassifier(maxIter=20, maxDepth=3, seed=seed, **w),
        "naive_bayes": lambda: NaiveBayes(modelType="gaussian", **w),
        "decision_tree": lambda: DecisionTreeClassifier(maxDepth=5, seed=seed, **w),
        "mlp": lambda: MultilayerPerceptronClassifier(layers=[n_features, 8, 2], maxIter=100, seed=seed),
    }
    return made[algorithm]()


def train_scheduler(rows: DataFrame, algorithm: str = "logistic", n_features: int = 16, balance: str = "none", seed: int = 3) -> Scheduler:
    """Fit on rows with features f1.. and label. balance: none, weights, or truncate to the smaller class."""
    counts = {r["label"]: r["n"] for r in rows.groupBy("label").agg(F.count("*").alias("n")).collect()}
    total = sum(counts.values())
    if len(counts) < 2:
        warnings.warn("training rows are of one class: all clusters get the same score", stacklevel=2)
        return Scheduler(None, counts.get(1.0, 0) / total if total else 0.0, n_features, algorithm)
    weight = None
    if balance == "weights":
        weight = "class_weight"
        rows = rows.withColumn(weight, F.when(F.col("label") == 1.0, total / (2 * counts[1.0])).otherwise(total / (2 * counts[0.0])))
    elif balance == "truncate":
        rows = rows.withColumn("_n", F.row_number().over(Window.partitionBy("label").orderBy("cid"))).filter(F.col("_n") <= min(counts.values())).drop("_n")
    model = _estimator(algorithm, n_features, weight, seed).fit(assemble(rows, n_features))
    return Scheduler(model, counts[1.0] / total, n_features, algorithm)


def score(scheduler: Scheduler, features: DataFrame) -> DataFrame:
    """cid and w, the probability of a high index."""
    if scheduler.model is None:
        return features.select("cid", F.lit(scheduler.prior).alias("w"))
    return scheduler.model.transform(assemble(features, scheduler.n_features)).select("cid", F.get(vector_to_array("probability"), 1).alias("w"))


def reliability(scored: DataFrame, bins: int = 10) -> DataFrame:
    """Per step of w: clusters, mean w and share of label 1."""
    at = F.least(F.floor(F.col("w") * bins), F.lit(bins - 1)).cast("int")
    return scored.groupBy(at.alias("bin")).agg(F.count("*").alias("clusters"), F.avg("w").alias("mean_w"), F.avg("label").alias("share"))


def importances(scheduler: Scheduler) -> dict[str, float]:
    """Weight of each feature: coefficients or tree importances; empty for other models."""
    model = scheduler.model
    values = getattr(model, "coefficients", None) if scheduler.algorithm == "logistic" else getattr(model, "featureImportances", None)
    return dict(zip(NAMES, map(float, values.toArray()), strict=False)) if values is not None else {}


def quality(scored: DataFrame) -> dict[str, float]:
    """Area under the curve and log loss of scores with labels."""
    auc = BinaryClassificationEvaluator(rawPredictionCol="w", labelCol="label").evaluate(scored)
    p = F.least(F.greatest("w", F.lit(1e-9)), F.lit(1 - 1e-9))
    loss = scored.agg(F.avg(-(F.col("label") * F.log(p) + (1 - F.col("label")) * F.log(1 - p)))).head()[0]
    return {"auc": auc, "log_loss": loss}
