"""Votes of several models over one scan."""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def weights(scores: dict[str, float], kind: str = "accuracy") -> dict[str, float]:
    """Each model's weight: its validation accuracy, 1, or the log odds of its accuracy."""
    if kind == "uniform":
        return dict.fromkeys(scores, 1.0)
    if kind == "log_odds":
        return {k: math.log(max(v, 1e-6) / max(1 - v, 1e-6)) for k, v in scores.items()}
    return dict(scores)


def top_k(scores: dict[str, float], k: int) -> list[str]:
    return sorted(scores, key=lambda m: (-scores[m], m))[:k]


def hard_vote(members: dict[str, float], classes: int) -> Column:
    """The class of the largest summed weight; ties go to the smaller class. Columns are the members' predictions."""
    totals = F.array(*(sum((F.when(F.col(m) == c, w).otherwise(0.0) for m, w in members.items()), F.lit(0.0)) for c in range(classes)))
    return (F.array_position(totals, F.array_max(totals)) - 1).cast("int")


def soft_vote(members: dict[str, float], classes: int) -> Column:
    """The class of the largest weighted mean probability. Columns are arrays of class probabilities."""
    totals = F.array(*(sum((F.get(F.col(m), F.lit(c)) * w for m, w in members.items()), F.lit(0.0)) for c in range(classes)))
    return (F.array_position(totals, F.array_max(totals)) - 1).cast("int")


def out_of_fold(train: DataFrame, make: Callable[[DataFrame], object], to: str, fold: str = "fold", folds: int = 3) -> DataFrame:
    """``train`` with the prediction, named ``to``, of a model that ``make`` fitted on the other folds."""
    parts = [make(train.where(F.col(fold) != k)).transform(train.where(F.col(fold) == k)) for k in range(folds)]
    return reduce(DataFrame.unionByName, parts).withColumnRenamed("prediction", to)


def stack(df: DataFrame, members: list[str], label: str):
    """A logistic model over members' scores, which ``df`` holds and which must be out of fold."""
    from ..models.registry import fit

    rows = df.withColumn("features", F.array(*(F.col(m).cast("double") for m in members))).withColumn("label", F.col(label))
    return fit("logistic", rows)


def lift(ensemble: float, members: dict[str, float]) -> float:
    return ensemble - max(members.values())
