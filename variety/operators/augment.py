"""Synthetic rows for small classes, from training rows only; a synthetic row stays in its parent's fold and split."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import uniform

# Phrases and the two stand-in lexicons.
SUFFIXES = ("en general", "como se esperaba", "segun lo previsto")
FORWARD = {"hotel": ("hotel", "inn"), "bueno": ("good", "nice"), "malo": ("bad", "poor"), "comida": ("food", "meal"), "la": ("the",), "de": ("of",), "que": ("that", "which"), "no": ("not",)}
BACK = {"hotel": ("hotel",), "inn": ("posada",), "good": ("bueno",), "nice": ("agradable",), "bad": ("malo",), "poor": ("pobre",), "food": ("comida",), "meal": ("alimento",), "the": ("la", "el"), "of": ("de",), "that": ("que",), "which": ("cual", "que"), "not": ("no",)}


def minority(df: DataFrame, label: str, ratio: float = 0.5) -> DataFrame:
    """Classes with fewer rows than ``ratio`` times the largest class."""
    counts = df.groupBy(label).agg(F.count(F.lit(1)).alias("n"))
    return counts.join(F.broadcast(counts.agg(F.max("n").alias("n_max")))).select(label, "n", "n_max", (F.col("n") < F.col("n_max") * ratio).alias("minority"))


def truncate(toks: Column, u: Column, min_tokens: int = 30, max_frac: float = 0.3) -> Column:
    """A prefix of long token lists: up to ``max_frac`` of the tail goes."""
    return F.when(F.size(toks) >= min_tokens, F.slice(toks, 1, F.greatest(F.ceil(F.size(toks) * (1 - u * max_frac)).cast("int"), F.lit(1)))).otherwise(toks)


def suffix(c: Column, u: Column, phrases: tuple[str, ...] = SUFFIXES) -> Column:
    return F.concat(c, F.lit(" "), F.get(F.array(*(F.lit(p) for p in phrases)), F.floor(u * len(phrases)).cast("int")))


def substitute(toks: Column, lexicon: dict[str, tuple[str, ...]], key: Column, seed: str) -> Column:
    """Each token's translation, chosen by a hash among its options; unknown tokens stay."""
    table = F.create_map(*(x for k, v in lexicon.items() for x in (F.lit(k), F.array(*(F.lit(w) for w in v)))))

    def one(t: Column, i: Column) -> Column:
        options = F.try_element_at(table, t)
        return F.coalesce(F.get(options, F.pmod(F.xxhash64(F.lit(seed), key, i), F.size(options)).cast("int")), t)

    return F.transform(toks, one)


def back_translate(toks: Column, key: Column, there=FORWARD, back=BACK) -> Column:
    """There and back again by two independent models; shipped as two lexicons, open to any function of the same form."""
    return substitute(substitute(toks, there, key, "there"), back, key, "back")


def pivot_paraphrase(toks: Column, key: Column, beams: int = 4, score: Callable[[Column], Column] | None = None) -> Column:
    """Of ``beams`` different round trips the one with the best score, by default the most tokens changed."""
    options = [back_translate(toks, F.xxhash64(key, F.lit(b))) for b in range(beams)]
    rank = score or (lambda c: F.size(F.array_except(c, toks)))
    best = F.array_max(F.array(*(F.struct(rank(o).alias("s"), F.lit(-b).alias("b"), o.alias("o")) for b, o in enumerate(options))))
    return best["o"]


def superset(df: DataFrame, key: str, label: str, make: Callable[[DataFrame], DataFrame], target: float = 0.5, cap: int = 5, train: str = "split = 'train'") -> DataFrame:
    """The rows and their synthetic children, with ``origin`` and ``copy``. Each small class is filled up to ``target`` of the largest."""
    counts = df.where(train).groupBy(label).agg(F.count(F.lit(1)).alias("_n"))
    counts = counts.join(F.broadcast(counts.agg(F.max("_n").alias("_m"))))
    copies = F.least(F.lit(cap), F.ceil(F.lit(target) * F.col("_m") / F.col("_n")).cast("int") - 1)
    counts = counts.select(label, copies.alias("_c")).where("_c > 0")
    grown = df.where(train).join(F.broadcast(counts), label).withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("_c")))).drop("_c")
    made = make(grown).withColumn("origin", F.lit("synthetic"))
    return df.withColumns({"copy": F.lit(0), "origin": F.lit("original")}).unionByName(made.select(*df.columns, "copy", "origin"))


def undersample(df: DataFrame, key: str, label: str, seed: str = "under") -> DataFrame:
    """Each class down to the smallest, in expectation."""
    counts = df.groupBy(label).agg(F.count(F.lit(1)).alias("_n"))
    share = counts.join(F.broadcast(counts.agg(F.min("_n").alias("_m")))).select(label, (F.col("_m") / F.col("_n")).alias("_s"))
    return df.join(F.broadcast(share), label).where(uniform(seed, key) < F.col("_s")).drop("_s")


def oversample(df: DataFrame, key: str, label: str, cap: int = 5) -> DataFrame:
    """Copies of small classes, up to ``cap`` times."""
    return superset(df.withColumn("_all", F.lit(True)), key, label, lambda g: g, 1.0, cap, "_all").drop("_all")
