"""Accuracy, overfitting and cost measures from prediction tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def confusion(df: DataFrame, label: str = "label", prediction: str = "prediction", by: tuple[str, ...] = (), normalized: bool = False) -> DataFrame:
    """Counts of (label, prediction); the share within the label too, if asked."""
    counts = df.groupBy(*by, F.col(label).alias("label"), F.col(prediction).alias("prediction")).agg(F.count(F.lit(1)).alias("n"))
    if normalized:
        row = Window.partitionBy(*by, "label")
        counts = counts.withColumn("share", F.round(F.col("n") / F.sum("n").over(row), 6))
    return counts


def per_class(df: DataFrame, label: str = "label", prediction: str = "prediction", by: tuple[str, ...] = ()) -> DataFrame:
    """Support, precision, recall and F1 of each class that is a label or a prediction."""
    cells = confusion(df, label, prediction, by)
    # a cell counts for its label's support and for its prediction's, so no class is lost
    sides = F.array(
        F.struct(F.col("label").alias("c"), F.col("n").alias("support"), F.lit(0).cast("long").alias("predicted"), F.when(F.col("label") == F.col("prediction"), F.col("n")).otherwise(0).alias("hit")),
        F.struct(F.col("prediction").alias("c"), F.lit(0).cast("long").alias("support"), F.col("n").alias("predicted"), F.lit(0).cast("long").alias("hit")),
    )
    sums = cells.select(*by, F.explode(sides).alias("x")).groupBy(*by, F.col("x.c").alias("class")).agg(*(F.sum(f"x.{c}").alias(c) for c in ("support", "predicted", "hit")))
    f1 = F.coalesce(F.try_divide(2 * F.col("hit"), F.col("support") + F.col("predicted")), F.lit(0.0))
    return sums.select(*by, "class", "support", "predicted", F.coalesce(F.try_divide(F.col("hit"), F.col("predicted")), F.lit(0.0)).alias("precision"), F.coalesce(F.try_divide(F.col("hit"), F.col("support")), F.lit(0.0)).alias("recall"), f1.alias("f1"), "hit")


def classification(df: DataFrame, label: str = "label", prediction: str = "prediction", by: tuple[str, ...] = ()) -> DataFrame:
    classes = per_class(df, label, prediction, by)
    seen = F.col("support") > 0
    return classes.groupBy(*by).agg(
        F.sum("support").alias("n"),
        F.round(F.sum("hit") / F.sum("support"), 6).alias("accuracy"),
        F.round(F.sum(F.col("f1") * F.col("support")) / F.sum("support"), 6).alias("f1_weighted"),
        F.round(F.avg(F.when(seen | (F.col("predicted") > 0), F.col("f1"))), 6).alias("f1_macro"),
    )


def gap(df: DataFrame, split: str = "split", label: str = "label", prediction: str = "prediction") -> DataFrame:
    """Train and test accuracy and their signed difference."""
    hit = (F.col(label) == F.col(prediction)).cast("int")
    rows = df.agg(F.avg(F.when(F.col(split) == "train", hit)).alias("tr"), F.avg(F.when(F.col(split) == "test", hit)).alias("te"))
    return rows.select(F.round("tr", 6).alias("train_accuracy"), F.round("te", 6).alias("test_accuracy"), F.round(F.col("tr") - F.col("te"), 6).alias("gap"))


def collapse(df: DataFrame, label: str = "label", prediction: str = "prediction") -> DataFrame:
    """Share of the most predicted class, share of the most frequent label, and how many classes are never found."""
    classes = per_class(df, label, prediction)
    return classes.agg(
        F.round(F.max("predicted") / F.sum("predicted"), 6).alias("largest_prediction"),
        F.round(F.max("support") / F.sum("support"), 6).alias("largest_label"),
        F.count_if((F.col("support") > 0) & (F.col("hit") == 0)).alias("lost_classes"),
    )


def regression(df: DataFrame, label: str = "label", prediction: str = "prediction", by: tuple[str, ...] = ()) -> DataFrame:
    """MAE, RMSE and R2. RMSE is never below MAE."""
    e = F.col(prediction) - F.col(label)
    sums = df.where(F.col(label).isNotNull() & F.col(prediction).isNotNull()).groupBy(*by).agg(
        F.count(F.lit(1)).alias("n"), F.avg(F.abs(e)).alias("mae"), F.avg(e * e).alias("mse"), F.var_pop(label).alias("v")
    )
    return sums.select(*by, "n", F.round("mae", 6).alias("mae"), F.round(F.sqrt("mse"), 6).alias("rmse"), F.round(1 - F.try_divide(F.col("mse"), F.col("v")), 6).alias("r2"))


def scaling_slope(df: DataFrame, n: str = "n", seconds: str = "seconds") -> DataFrame:
    """The power of n that time grows with: the slope of both logarithms."""
    return df.agg(F.round(F.regr_slope(F.log(seconds), F.log(n)), 6).alias("power"))


def summarize_trials(ledger: DataFrame) -> DataFrame:
    """Mean and spread of the folds' scores of each trial, and the trial's rank; ties, to nine places, go to the smaller trial."""
    means = ledger.groupBy("trial").agg(F.avg("score").alias("m"), F.stddev_samp("score").alias("sd"), F.count(F.lit(1)).alias("folds"))
    rank = F.row_number().over(Window.orderBy(F.desc(F.round("m", 9)), "trial"))
    return means.select("trial", F.round("m", 6).alias("mean_score"), F.round("sd", 6).alias("sd_score"), "folds", rank.alias("place"))
