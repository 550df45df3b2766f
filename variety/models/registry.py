"""All families by name. ``fit`` takes rows with array features and a label, and returns something with ``transform``."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from typing import Any

import numpy as np
import pandas as pd
from pyspark.ml import classification as C
from pyspark.ml import regression as R
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.dense import matrix, moments
from ..operators.sampling import balanced_weights
from . import learners as L
from .boosting import fit_boost

#: Untuned parameters, for families that are used as they come.
DEFAULTS: dict[str, dict[str, Any]] = {
    "logistic": {"reg": 0.01, "l1_ratio": 0.0, "iterations": 100},
    "svm_linear": {"c": 1.0},
    "svm_rbf": {"c": 1.0, "gamma": "scale", "features": 512},
    "svm_poly": {"c": 1.0, "gamma": "scale", "degree": 2, "coef0": 0.1},
    "discriminant": {"shrinkage": 0.0},
    "linear_regression": {"reg": 0.01, "l1_ratio": 0.5},
    "mlp_builtin": {"layers": [64], "iterations": 60},
    "mlp": {"layers": [32], "dropout": 0.0, "lr": 3e-3, "activation": "relu", "batch": 64, "epochs": 20},
    "tree": {"depth": 5},
    "forest": {"trees": 20, "depth": 5},
    "adaboost": {"n": 10, "lr": 1.0, "depth": 1},
    "leafwise_boost": {"rounds": 10, "lr": 0.3, "leaves": 15, "depth": 6},
    "second_order_boost": {"rounds": 10, "lr": 0.3, "leaves": 64, "depth": 6, "batch": 64},
    "gbt": {"rounds": 10, "depth": 5},
    "naive_bayes": {},
    "factorization": {"factors": 2, "reg": 0.1, "iterations": 100, "lr": 0.05},
    "majority": {},
}


@dataclass
class Scored:
    """A model whose prediction is a function of the feature matrix."""

    predict: Any
    facts: dict[str, Any]

    def transform(self, df: DataFrame) -> DataFrame:
        predict = self.predict

        def run(frames: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for x in frames:
                yield pd.Series(predict(matrix(x)).astype(float)) if len(x) else pd.Series([], dtype=float)

        return df.withColumn("prediction", F.pandas_udf(run, "double")(F.col("features")))


@dataclass
class Vectored:
    """A Spark ML model behind array features."""

    model: Any

    def transform(self, df: DataFrame) -> DataFrame:
        out = self.model.transform(df.withColumn("_x", array_to_vector("features")))
        return out.drop("_x", "rawPrediction", "probability")


def _spark(estimator, df: DataFrame) -> Vectored:
    return Vectored(estimator.setFeaturesCol("_x").setLabelCol("label").fit(df.withColumn("_x", array_to_vector("features"))))


def fourier_map(d: int, n: int, gamma: float, seed: int = 42):
    """Random features whose products approach exp(-gamma |x - z|^2)."""
    rng = np.random.default_rng(seed)
    omega, shift = rng.normal(scale=np.sqrt(2 * gamma), size=(d, n)), rng.uniform(0, 2 * np.pi, n)
    return lambda x: np.sqrt(2 / n) * np.cos(x @ omega + shift)


#: A polynomial with more monomials is sketched.
MOST_MONOMIALS = 20_000


def sketched_map(d: int, gamma: float, degree: int, coef0: float, n: int = 2048, seed: int = 42):
    """Random features whose products approach (gamma <x, z> + coef0)^degree: circular convolutions of signed sums, one a factor."""
    rng = np.random.default_rng(seed)
    scale = np.append(np.full(d, np.sqrt(gamma)), np.sqrt(coef0))
    sums = np.zeros((degree, d + 1, n))
    for one in sums:
        one[np.arange(d + 1), rng.integers(0, n, d + 1)] = rng.choice([-1.0, 1.0], d + 1)

    def sketch(x):
        x = np.c_[x, np.ones(len(x))] * scale
        spectrum = np.fft.rfft(x @ sums[0])
        for one in sums[1:]:
            spectrum *= np.fft.rfft(x @ one)
        return np.fft.irfft(spectrum, n)

    return sketch


def polynomial_map(d: int, gamma: float, degree: int, coef0: float):
    """All monomials up to the degree, weighted so that products are (gamma <x, z> + coef0)^degree; of too many, a sketch."""
    from itertools import combinations_with_replacement
    from math import comb, factorial

    if sum(comb(d + size - 1, size) for size in range(degree + 1) if coef0 or size == degree) > MOST_MONOMIALS:
        return sketched_map(d, gamma, degree, coef0)
    terms, scale = [], []
    for size in range(degree + 1):
        outer = comb(degree, size) * gamma**size * coef0 ** (degree - size)
        if outer > 0:
            for t in combinations_with_replacement(range(d), size):
                ways = factorial(size)
                for i in set(t):
                    ways //= factorial(t.count(i))
                terms.append(t)
                scale.append(np.sqrt(outer * ways))
    return lambda x: np.stack([s * np.prod(x[:, list(t)], axis=1) if t else np.full(len(x), s) for t, s in zip(terms, scale, strict=True)], axis=1)


def mapped(df: DataFrame, f) -> DataFrame:
    def run(frames: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for x in frames:
            yield pd.Series(list(f(matrix(x)))) if len(x) else pd.Series([], dtype=object)

    return df.withColumn("features", F.pandas_udf(run, "array<double>")(F.col("features")))


def gamma_of(df: DataFrame, rule) -> float:
    if not isinstance(rule, str):
        return float(rule)
    d = len(df.select("features").first()[0])
    if rule == "auto":
        return 1.0 / d
    return 1.0 / (d * float(df.select(F.explode("features").alias("v")).agg(F.var_pop("v")).first()[0]))


def fit_svm(df: DataFrame, c: float = 1.0, iterations: int = 100) -> Vectored:
    n = df.count()
    return _spark(C.LinearSVC(regParam=1.0 / (c * max(n, 1)), maxIter=iterations, weightCol="weight"), balanced_weights(df, "label"))


@dataclass
class Mapped:
    map: Any
    inner: Vectored

    def transform(self, df: DataFrame) -> DataFrame:
        rows = df.withColumn("_own", F.col("features"))
        return self.inner.transform(mapped(rows, self.map)).withColumn("features", F.col("_own")).drop("_own")


def fit_discriminant(df: DataFrame, shrinkage: float = 0.0) -> Scored:
    """Class means and pooled covariance from one moment pass a class."""
    classes = [r[0] for r in df.select("label").distinct().orderBy("label").collect()]
    n, means, inner = [], [], 0.0
    for c in classes:
        k, s, g = moments(df.where(F.col("label") == c), "features")
        n.append(k)
        means.append(s / k)
        inner = inner + g - np.outer(s, s) / k
    w, b = L.discriminant(np.stack(means), np.array(n) / sum(n), inner / max(sum(n) - len(n), 1), shrinkage)
    labels = np.array(classes, float)
    return Scored(lambda x: labels[(x @ w + b).argmax(axis=1)], {"means": np.stack(means), "priors": np.array(n) / sum(n)})


def fit_mlp(df: DataFrame, layers, dropout: float, lr: float, activation: str, batch: int, epochs: int, classes: int = 2, seed: int = 42) -> Scored:
    """A job an epoch: each partition trains its copy, and copies are averaged by their rows."""
    d = len(df.select("features").first()[0])
    net = L.init_mlp([d, *layers, classes], activation, seed)
    shapes = [w.shape for w, _ in net]
    pack = lambda n: np.concatenate([p.ravel() for layer in n for p in layer])

    def unpack(v):
        out, at = [], 0
        for a, b in shapes:
            out.append((v[at : at + a * b].reshape(a, b).copy(), v[at + a * b : at + a * b + b].copy()))
            at += a * b + b
        return out

    vector = pack(net)
    rows = df.select("features", "label").persist()
    for epoch in range(epochs):

        def train(frames, vector=vector, epoch=epoch):
            parts = [f for f in frames if len(f)]
            if parts:
                f = pd.concat(parts)
                x, y = matrix(f["features"]), f["label"].to_numpy(float)
                own = unpack(vector)
                L.mlp_epoch(own, L.new_state(own), x, y, activation, dropout, lr, batch, np.random.default_rng(seed + epoch))
                yield pd.DataFrame({"n": [len(f)], "v": [pack(own)]})

        got = rows.mapInPandas(train, "n long, v array<double>").collect()
        vector = sum(r["n"] * np.array(r["v"]) for r in got) / sum(r["n"] for r in got)
    rows.unpersist()
    net = unpack(vector)
    return Scored(lambda x: L.mlp_scores(net, x, activation).argmax(axis=1), {"units": sum(layers)})


def fit_adaboost(df: DataFrame, n: int = 10, lr: float = 1.0, depth: int = 1, classes: int = 2) -> Scored:
    """Multi-class weight form: each round a weighted tree, its say from its weighted error. Weights are written once in a while, to keep plans short."""
    rows = df.select("features", "label", array_to_vector("features").alias("_x")).withColumn("weight", F.lit(1.0)).persist()
    says, trees = [], []
    for i in range(n):
        tree = C.DecisionTreeClassifier(maxDepth=depth, weightCol="weight", featuresCol="_x", labelCol="label").fit(rows)
        scored = tree.transform(rows).withColumn("miss", (F.col("prediction") != F.col("label")).cast("int"))
        t = scored.agg(F.sum("weight").alias("t"), F.sum(F.col("weight") * F.col("miss")).alias("m")).first()
        error = t["m"] / t["t"]
        if error >= 1 - 1 / classes:
            break
        say = lr * (np.log((1 - max(error, 1e-10)) / max(error, 1e-10)) + np.log(classes - 1))
        says.append(float(say))
        trees.append(tree)
        if error <= 0:
            break
        rows = scored.select("features", "label", "_x", (F.col("weight") * F.exp(F.lit(float(say)) * F.col("miss")) / F.lit(float(t["t"]))).alias("weight"))
        rows = rows.persist() if i % 3 == 2 else rows
    return AdaBoosted(trees, says, classes)


@dataclass
class AdaBoosted:
    trees: list
    says: list[float]
    classes: int

    def transform(self, df: DataFrame) -> DataFrame:
        out = df.withColumn("_x", array_to_vector("features"))
        votes = []
        for i, t in enumerate(self.trees):
            out = t.setPredictionCol(f"_p{i}").setRawPredictionCol(f"_r{i}").setProbabilityCol(f"_q{i}").transform(out)
            votes.append(F.col(f"_p{i}"))
        totals = [sum((F.when(v == c, s).otherwise(0.0) for v, s in zip(votes, self.says, strict=True)), F.lit(0.0)) for c in range(self.classes)]
        best = F.array_position(F.array(*totals), F.greatest(*totals)) - 1
        return out.withColumn("prediction", best.cast("double")).drop("_x", *(f"_{k}{i}" for i in range(len(votes)) for k in "prq"))


def fit(family: str, df: DataFrame, params: dict | None = None, task: str = "binary", classes: int = 2):
    """A fitted model of the family; missing parameters are the untuned ones."""
    p = DEFAULTS[family] | (params or {})
    df = df.withColumn("label", F.col("label").cast("double"))
    if family == "logistic":
        return _spark(C.LogisticRegression(regParam=p["reg"], elasticNetParam=p["l1_ratio"], maxIter=int(p["iterations"])), df)
    if family == "svm_linear":
        return fit_svm(df, p["c"])
    if family == "svm_rbf":
        f = fourier_map(len(df.select("features").first()[0]), p["features"], gamma_of(df, p["gamma"]))
        return Mapped(f, fit_svm(mapped(df, f), p["c"]))
    if family == "svm_poly":
        f = polynomial_map(len(df.select("features").first()[0]), gamma_of(df, p["gamma"]), int(p["degree"]), p["coef0"])
        return Mapped(f, fit_svm(mapped(df, f), p["c"], 30))
    if family == "discriminant":
        return fit_discriminant(df, p["shrinkage"])
    if family == "linear_regression":
        return _spark(R.LinearRegression(regParam=p["reg"], elasticNetParam=p["l1_ratio"]), df)
    if family == "mlp_builtin":
        d = len(df.select("features").first()[0])
        return _spark(C.MultilayerPerceptronClassifier(layers=[d, *p["layers"], classes], maxIter=p["iterations"], seed=42), df)
    if family == "mlp":
        return fit_mlp(df, p["layers"], p["dropout"], p["lr"], p["activation"], int(p["batch"]), int(p["epochs"]), classes)
    if family == "tree":
        kind = R.DecisionTreeRegressor if task == "regression" else C.DecisionTreeClassifier
        return _spark(kind(maxDepth=int(p["depth"]), minInstancesPerNode=int(p.get("min_split", 1)), minInfoGain=p.get("min_gain", 0.0)), df)
    if family == "forest":
        kind = R.RandomForestRegressor if task == "regression" else C.RandomForestClassifier
        return _spark(kind(numTrees=int(p["trees"]), maxDepth=int(p["depth"]), featureSubsetStrategy=p.get("subset", "auto"), seed=42), df)
    if family == "gbt":
        kind = R.GBTRegressor if task == "regression" else C.GBTClassifier
        return _spark(kind(maxIter=int(p["rounds"]), maxDepth=int(p["depth"]), seed=42), df)
    if family == "naive_bayes":
        return _spark(C.NaiveBayes(modelType="gaussian"), df)
    if family == "factorization":
        kind = R.FMRegressor if task == "regression" else C.FMClassifier
        if task != "regression" and classes > 2:
            raise ValueError("factorisation machines separate two classes")
        return _spark(kind(factorSize=int(p["factors"]), regParam=p["reg"], maxIter=int(p["iterations"]), stepSize=p["lr"], seed=42), df)
    if family == "adaboost":
        return fit_adaboost(df, int(p["n"]), p["lr"], int(p["depth"]), classes)
    if family in ("leafwise_boost", "second_order_boost"):
        return fit_boost(df, task=task, classes=classes, **{k: v for k, v in p.items()})
    if family == "majority":
        top = df.agg(F.avg("label") if task == "regression" else F.mode("label")).first()[0] or 0.0
        return Scored(lambda x: np.full(len(x), float(top)), {"value": top})
    raise ValueError(f"unknown family {family}")
