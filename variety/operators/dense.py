"""Preparation of dense vectors: moments, standardising, a principal-component map fitted once and frozen."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def matrix(column: pd.Series) -> np.ndarray:
    return np.stack(column.to_numpy()).astype(np.float64) if len(column) else np.zeros((0, 0))


def moments(df: DataFrame, col: str) -> tuple[int, np.ndarray, np.ndarray]:
    """(rows, sum, sum of outer products). Each task sends one d by d matrix; they are added in a tree of groups."""

    def partial(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n, s, g = 0, 0.0, 0.0
        for frame in frames:
            if len(frame):
                x = matrix(frame[col])
                n, s, g = n + len(x), s + x.sum(axis=0), g + x.T @ x
        if n:
            yield pd.DataFrame({"part": [int(np.abs(s[0] * 1e6)) % 16], "n": [n], "s": [s], "g": [g.ravel()]})

    def added(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n, s, g = 0, 0.0, 0.0
        for frame in frames:
            for row in frame.itertuples():
                n, s, g = n + row.n, s + np.asarray(row.s), g + np.asarray(row.g)
        if n:
            yield pd.DataFrame({"part": [0], "n": [n], "s": [s], "g": [g]})

    schema = "part int, n long, s array<double>, g array<double>"
    parts = df.select(col).where(F.col(col).isNotNull()).mapInPandas(partial, schema).repartition(16, "part").mapInPandas(added, schema).collect()
    if not parts:
        return 0, np.zeros(0), np.zeros((0, 0))
    s = sum(np.asarray(r["s"]) for r in parts)
    return sum(r["n"] for r in parts), s, sum(np.asarray(r["g"]) for r in parts).reshape(len(s), len(s))


def covariance(df: DataFrame, col: str) -> np.ndarray:
    n, s, g = moments(df, col)
    return (g - np.outer(s, s) / n) / max(n - 1, 1)


def correlation(df: DataFrame, col: str) -> np.ndarray:
    c = covariance(df, col)
    sd = np.sqrt(np.maximum(np.diag(c), 1e-300))
    return c / np.outer(sd, sd)


def project(col: str, w: np.ndarray) -> Column:
    """x times W as one narrow expression, without centring."""
    return F.array(*(F.aggregate(F.zip_with(F.col(col), F.array(*(F.lit(float(v)) for v in w[:, j])), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v) for j in range(w.shape[1])))


@dataclass(frozen=True)
class FrozenPca:
    """Components (d by k) that later samples are mapped with, unchanged."""

    components: np.ndarray
    mean: np.ndarray
    explained: np.ndarray
    total: float

    def transform(self, df: DataFrame, col: str, to: str = "projected", center: bool = False) -> DataFrame:
        w, shift = self.components, self.mean @ self.components if center else 0.0

        def mapped(frames: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for x in frames:
                yield pd.Series(list(matrix(x) @ w - shift)) if len(x) else pd.Series([], dtype=object)

        return df.withColumn(to, F.pandas_udf(mapped, "array<double>")(F.col(col)))

    def report(self) -> dict[str, float]:
        k = self.components.shape[1]
        gram = self.components.T @ self.components
        return {"k": k, "explained": float(self.explained.sum() / self.total), "off_orthonormal": float(np.abs(gram - np.eye(k)).max())}


def fit_pca(df: DataFrame, col: str, k: int | None = None, min_explained: float = 0.95, method: str = "exact", seed: int = 42) -> FrozenPca:
    """Eigenvectors of the covariance; the sign makes each one's largest entry positive.

    ``randomized`` multiplies the covariance by a random block first, which spares the full decomposition of large d.
    """
    n, s, g = moments(df, col)
    mean = s / n
    c = (g - np.outer(s, s) / n) / max(n - 1, 1)
    if method == "randomized" and k:
        q = np.random.default_rng(seed).normal(size=(len(s), min(len(s), k + 8)))
        for _ in range(6):
            q, _ = np.linalg.qr(c @ q)
        values, small = np.linalg.eigh(q.T @ c @ q)
        vectors = q @ small
    else:
        values, vectors = np.linalg.eigh(c)
    order = np.argsort(-values)
    values, vectors = values[order], vectors[:, order]
    total = float(np.trace(c))
    k = k or int(np.searchsorted(np.cumsum(values) / total, min_explained - 1e-12) + 1)
    w = vectors[:, :k]
    w = w * np.where(w[np.abs(w).argmax(axis=0), np.arange(k)] < 0, -1.0, 1.0)
    return FrozenPca(w, mean, values[:k], total)
