"""Hybrid rows: leakage audits, log and multi-hot columns, smoothed target encoding, reputation of people."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

K_MIN, F_SCALE = 20.0, 10.0


def prune(df: DataFrame, reasons: dict[str, str]) -> DataFrame:
    """Without the columns named, each with its reason; the scan no longer reads them."""
    return df.drop(*reasons)


def identifier_audit(df: DataFrame, cols: list[str], least: float = 0.95) -> DataFrame:
    """Distinct share of each column; near 1 it identifies rows and can't generalise."""
    counts = df.agg(F.count(F.lit(1)).alias("n"), *(F.count_distinct(c).alias(c) for c in cols))
    parts = F.array(*(F.struct(F.lit(c).alias("column_name"), F.col(c).alias("distinct_values")) for c in cols))
    rows = counts.select("n", F.explode(parts).alias("p")).select("p.*", F.round(F.try_divide(F.col("p.distinct_values"), F.col("n")), 6).alias("share"))
    return rows.withColumn("identifier", F.col("share") >= least)


def lam(n: Column, k_min: float = K_MIN, f: float = F_SCALE) -> Column:
    return 1 / (1 + F.exp(-(n - k_min) / f))


def blend(n: Column, mean: Column, overall: Column, k_min: float = K_MIN, f: float = F_SCALE) -> Column:
    """The category's mean and the overall mean, by the sigmoid of its count; unseen categories have the overall mean."""
    return F.when(F.coalesce(n, F.lit(0)) > 0, lam(n, k_min, f) * mean + (1 - lam(n, k_min, f)) * overall).otherwise(overall)


def target_encode(df: DataFrame, key: str, target: str, mode: str = "train_mean", fold: str | None = None, k_min: float = K_MIN, f: float = F_SCALE, m: float | None = None, train: str | None = None) -> DataFrame:
    """``df`` with ``encoded``.

    train_mean: over all training rows, the row included. leave_one_out: less the row itself. out_of_fold: less the
    row's fold, by total less fold, without rescans. ``m`` replaces the sigmoid by n / (n + m). ``train`` is a
    condition for the rows that statistics may see.
    """
    seen = F.expr(train) if train else F.lit(True)
    y = F.when(seen, F.col(target))
    keys = [key] + ([fold] if mode == "out_of_fold" else [])
    stats = df.groupBy(*keys).agg(F.count(y).alias("_n"), F.coalesce(F.sum(y), F.lit(0.0)).alias("_s"))
    total = df.agg(F.count(y).alias("_gn"), F.coalesce(F.sum(y), F.lit(0.0)).alias("_gs"))
    if mode == "out_of_fold":
        by_key = Window.partitionBy(key)
        stats = stats.withColumns({"_tn": F.sum("_n").over(by_key), "_ts": F.sum("_s").over(by_key)})
        own = df.groupBy(fold).agg(F.count(y).alias("_fn"), F.coalesce(F.sum(y), F.lit(0.0)).alias("_fs"))
        rows = df.join(stats, keys, "left").join(F.broadcast(own), fold).join(F.broadcast(total))
        n, s = F.col("_tn") - F.col("_n"), F.col("_ts") - F.col("_s")
        gn, gs = F.col("_gn") - F.col("_fn"), F.col("_gs") - F.col("_fs")
    else:
        rows = df.join(stats, key, "left").join(F.broadcast(total))
        n, s, gn, gs = (F.col(c) for c in ("_n", "_s", "_gn", "_gs"))
        if mode == "leave_one_out":
            here = F.when(seen & F.col(target).isNotNull(), 1).otherwise(0)
            n, s = n - here, s - here * F.coalesce(F.col(target), F.lit(0.0))
            gn, gs = gn - here, gs - here * F.coalesce(F.col(target), F.lit(0.0))
    mean, overall = F.try_divide(s, n), F.try_divide(gs, gn)
    if m is None:
        value = blend(n, mean, overall, k_min, f)
    else:
        value = F.when(n + m > 0, (s + m * overall) / (n + m)).otherwise(overall)
    return rows.withColumn("encoded", value).drop("_n", "_s", "_tn", "_ts", "_fn", "_fs", "_gn", "_gs")


def target_encode_classes(df: DataFrame, key: str, target: str, classes: list, k_min: float = K_MIN, f: float = F_SCALE, train: str | None = None) -> DataFrame:
    """``df`` with ``encoded``, an array of a smoothed share for each of ``classes``: one grouped count of all classes and one join.

    Where the target is null a row counts for no class and in no total. Unseen and null categories have the overall shares.
    """
    y = F.when(F.expr(train), F.col(target)) if train else F.col(target)
    totals = lambda p: [F.count(y).alias(f"{p}n"), F.array(*(F.count_if(y.eqNullSafe(F.lit(c))) for c in classes)).alias(f"{p}c")]
    rows = df.join(df.groupBy(key).agg(*totals("_")).where(F.col(key).isNotNull()), key, "left").join(F.broadcast(df.agg(*totals("_g"))))
    share = [blend(F.col("_n"), F.try_divide(F.get("_c", F.lit(i)), F.col("_n")), F.try_divide(F.get("_gc", F.lit(i)), F.col("_gn")), k_min, f) for i in range(len(classes))]
    return rows.withColumn("encoded", F.array(*share)).drop("_n", "_c", "_gn", "_gc")


def multi_hot(values: str, vocabulary: list[str]) -> Column:
    """A 0/1 array over the sorted vocabulary; unknown values are ignored, a null list is empty."""
    return F.transform(F.array(*(F.lit(v) for v in sorted(vocabulary))), lambda g: F.coalesce(F.array_contains(F.col(values), g), F.lit(False)).cast("int"))


def skew_report(df: DataFrame, cols: list[str]) -> DataFrame:
    parts = df.agg(*(f(c).alias(f"{n}_{c}") for c in cols for n, f in (("mean", F.avg), ("max", F.max), ("skew", F.skewness))), *(F.skewness(F.log1p(c)).alias(f"logskew_{c}") for c in cols))
    rows = F.array(*(F.struct(F.lit(c).alias("column_name"), *(F.round(f"{n}_{c}", 6).alias(a) for n, a in (("mean", "mean_value"), ("max", "max_value"), ("skew", "skew_before"), ("logskew", "skew_after")))) for c in cols))
    return parts.select(F.explode(rows).alias("r")).select("r.*")


def reputation(df: DataFrame, row: str, people: str, target: str, mode: str = "train_mean", fold: str | None = None, day: str | None = None, name: str = "cast") -> DataFrame:
    """row, <name>_reputation and <name>_experience: mean over a row's people of each one's mean target, and of the number of rows behind it.

    People that are unknown have the overall mean and a count of 0; a row without people has both too.
    ``as_of`` sees only rows of earlier days. Rows without a target take part in no statistic.
    """
    keep = [c for c in (fold, day) if c]
    members = df.select(row, target, *keep, F.explode_outer(F.array_distinct(people)).alias("_p"))
    overall = F.broadcast(df.agg(F.avg(target).alias("_g")))
    known = members.where("_p is not null")
    y = F.col(target)
    if mode == "as_of":
        daily = known.groupBy("_p", day).agg(F.count(y).alias("_n"), F.coalesce(F.sum(y), F.lit(0.0)).alias("_s"))
        before = Window.partitionBy("_p").orderBy(day).rowsBetween(Window.unboundedPreceding, -1)
        stats = daily.select("_p", day, F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("n"), F.coalesce(F.sum("_s").over(before), F.lit(0.0)).alias("s"))
        rows = members.join(stats, ["_p", day], "left")
    elif mode == "out_of_fold":
        parts = known.groupBy("_p", fold).agg(F.count(y).alias("_n"), F.coalesce(F.sum(y), F.lit(0.0)).alias("_s"))
        each = Window.partitionBy("_p")
        stats = parts.select("_p", fold, (F.sum("_n").over(each) - F.col("_n")).alias("n"), (F.sum("_s").over(each) - F.col("_s")).alias("s"))
        rows = members.join(stats, ["_p", fold], "left")
    else:
        stats = known.groupBy("_p").agg(F.count(y).alias("n"), F.coalesce(F.sum(y), F.lit(0.0)).alias("s"))
        rows = members.join(stats, "_p", "left")
        if mode == "leave_one_out":
            here = F.when(y.isNotNull(), 1).otherwise(0)
            rows = rows.withColumns({"n": F.col("n") - here, "s": F.col("s") - F.coalesce(y, F.lit(0.0))})
    rows = rows.join(overall)
    value = F.coalesce(F.when(F.col("n") > 0, F.col("s") / F.col("n")), F.col("_g"))
    return rows.groupBy(row).agg(F.avg(value).alias(f"{name}_reputation"), F.avg(F.coalesce(F.col("n"), F.lit(0))).alias(f"{name}_experience"))


def assemble(df: DataFrame, blocks: dict[str, list[str]], to: str = "features") -> tuple[DataFrame, dict[str, tuple[int, int]]]:
    """One dense vector of the blocks' columns (numbers or arrays of known size), and each block's first and end index."""
    first = df.select(*(F.size(c).alias(c) if t.startswith("array") else F.lit(1).alias(c) for cols in blocks.values() for c in cols for t in [dict(df.dtypes)[c]])).first()
    spans, at = {}, 0
    for block, cols in blocks.items():
        width = sum(first[c] for c in cols) if first else 0
        spans[block] = (at, at + width)
        at += width
    kinds = dict(df.dtypes)
    parts = [F.col(c).cast("array<double>") if kinds[c].startswith("array") else F.array(F.col(c).cast("double")) for cols in blocks.values() for c in cols]
    return df.withColumn(to, F.concat(*parts)), spans
