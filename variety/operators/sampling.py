"""Stratified and nested samples, splits and folds that survive any partitioning.

A row's place is a hash of its key, so a sample needs one narrow scan, smaller samples lie
in larger ones, and only the exact mode counts.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform

RHOS = (2, 8, 15, 30, 45)
HISTOGRAM = 4096


def rho_bucket(u: Column, rhos: tuple[int, ...] = RHOS) -> Column:
    """The smallest percentage whose sample holds the row; 100 for none."""
    return reduce(lambda rest, r: F.when(u < r / 100, r).otherwise(rest), sorted(rhos, reverse=True), F.lit(100))


def nested_samples(df: DataFrame, key: str, rhos: tuple[int, ...] = RHOS, seed: str = "sample") -> DataFrame:
    """One relation with ``u`` and ``rho_bucket``: the sample of r percent is ``rho_bucket <= r``."""
    return df.withColumn("u", uniform(seed, key)).withColumn("rho_bucket", rho_bucket(F.col("u"), rhos))


def stratified(df: DataFrame, key: str, label: str, rho: float, mode: str = "hash", seed: str = "sample") -> DataFrame:
    """A sample that keeps class shares: in expectation (hash), or to the row (exact).

    Exact quotas come from a histogram of u in each class: whole buckets below the quota, and the one
    that crosses it ranked by (u, key), so that no class is sorted as a whole.
    """
    rows = df.withColumn("u", uniform(seed, key))
    if mode == "hash":
        return rows.where(F.col("u") < rho)
    rows = rows.withColumn("_bucket", F.floor(F.col("u") * HISTOGRAM).cast("int"))
    counts = rows.groupBy(label, "_bucket").agg(F.count(F.lit(1)).alias("_n"))
    running = Window.partitionBy(label).orderBy("_bucket")
    whole = Window.partitionBy(label)
    counts = counts.withColumns({"_to": F.sum("_n").over(running), "_quota": F.floor(F.sum("_n").over(whole) * rho + 0.5)})
    counts = counts.withColumn("_room", F.col("_quota") - F.col("_to") + F.col("_n")).where("_room > 0").select(label, "_bucket", "_n", "_room")
    placed = rows.join(F.broadcast(counts), [label, "_bucket"])  # at most HISTOGRAM rows a class
    rank = F.row_number().over(Window.partitionBy(label, "_bucket").orderBy("u", key))
    edge = placed.where("_n > _room").withColumn("_rank", rank).where("_rank <= _room").drop("_rank")
    return placed.where("_n <= _room").unionByName(edge).drop("_bucket", "_n", "_room")


def uniform_sample(df: DataFrame, key: str, rho: float, seed: str = "uniform") -> DataFrame:
    return df.where(uniform(seed, key) < rho)


def sample_by(df: DataFrame, label: str, rho: float, classes: list, seed: int = 42) -> DataFrame:
    """Spark's own stratified sampling; unlike the others it depends on the layout."""
    return df.sampleBy(label, dict.fromkeys(classes, rho), seed)


def proportion_drift(df: DataFrame, key: str, label: str, rhos: tuple[int, ...] = RHOS) -> DataFrame:
    """Each class's share in the whole and in each nested sample, and their difference."""
    rows = nested_samples(df, key, rhos)
    counts = rows.groupBy(label).agg(F.count(F.lit(1)).alias("n"), *(F.count_if(F.col("rho_bucket") <= r).alias(f"n_{r}") for r in rhos))
    every = counts.agg(F.sum("n").alias("t"), *(F.sum(f"n_{r}").alias(f"t_{r}") for r in rhos))
    share = counts.join(F.broadcast(every))
    parts = [F.struct(F.lit(r).alias("rho"), (F.col("n") / F.col("t")).alias("share"), F.try_divide(F.col(f"n_{r}"), F.col(f"t_{r}")).alias("sampled")) for r in rhos]
    out = share.select(label, F.explode(F.array(*parts)).alias("p"))
    return out.select(label, "p.rho", F.round("p.share", 6).alias("share"), F.round("p.sampled", 6).alias("sampled"), F.round(F.abs(F.col("p.share") - F.col("p.sampled")), 6).alias("drift"))


def holdout(df: DataFrame, key, test: float = 0.2, seed: str = "split") -> DataFrame:
    """``split`` of train or test. A key of several columns, or a hash of the content, keeps groups on one side."""
    keys = [key] if isinstance(key, str) else key
    return df.withColumn("split", F.when(uniform(seed, *keys) < test, "test").otherwise("train"))


def official(df: DataFrame, column: str, test: tuple = ("test",), valid: tuple = ()) -> DataFrame:
    """The split that the data come with: ``split`` of test or valid where ``column`` has one of those values, train elsewhere, nulls too."""
    named = F.when(F.col(column).isin(*test), "test")
    return df.withColumn("split", (named.when(F.col(column).isin(*valid), "valid") if valid else named).otherwise("train"))


def holdout_continuous(df: DataFrame, key: str, target: str, bins: int = 10, test: float = 0.2, seed: str = "split") -> DataFrame:
    """A split that is exact to a row in each of ``bins`` quantile bins of the target."""
    cuts = df.agg(F.percentile_approx(target, [i / bins for i in range(1, bins)], 10_000)).first()[0]
    place = reduce(lambda rest, c: rest + F.when(F.col(target) > c, 1).otherwise(0), cuts or [], F.lit(0))
    rows = df.withColumn("_bin", place)
    picked = stratified(rows, key, "_bin", test, "exact", seed).select(F.col(key).alias("_k")).withColumn("_t", F.lit(True))
    return rows.join(picked, rows[key] == picked["_k"], "left").withColumn("split", F.when(F.col("_t"), "test").otherwise("train")).drop("_k", "_t", "_bin")


def folds(df: DataFrame, key: str, n: int, seed: str = "fold") -> DataFrame:
    return df.withColumn("fold", F.floor(uniform(seed, key) * n).cast("int"))


def validation_flag(df: DataFrame, key: str, share: float, seed: str = "valid") -> DataFrame:
    return df.withColumn("is_valid", uniform(seed, key) < share)


def balanced_weights(df: DataFrame, label: str) -> DataFrame:
    """``weight`` of n / (classes * rows of the class)."""
    counts = df.groupBy(label).agg(F.count(F.lit(1)).alias("_n"))
    every = Window.partitionBy()
    counts = counts.withColumn("weight", F.sum("_n").over(every) / (F.count(F.lit(1)).over(every) * F.col("_n"))).drop("_n")
    return df.join(F.broadcast(counts), label)
