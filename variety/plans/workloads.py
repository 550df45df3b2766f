"""The three kinds of data on the given tables: dense vectors, reviews, hybrid rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..operators.sampling import folds, holdout, nested_samples
from ..operators.text import title_body
from ..sources.tables import load

#: Bounds that scale an order's revenue to 1..10.
REVENUE = (0.0, 400_000.0)


def dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, features, y_lin, y_xor, y_noise, u, rho_bucket, split, fold. ``label`` itself doesn't depend on the vector."""
    rows = load(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("features"), (F.col("label") % 2).alias("y_noise"))
    signs = F.array(*(F.lit((-1.0) ** j / (1 + j % 8)) for j in range(64)))
    total = F.aggregate(F.zip_with("features", signs, lambda x, a: x * a), F.lit(0.0), lambda s, v: s + v)
    rows = rows.withColumns({"y_lin": (total > 0).cast("int"), "y_xor": (F.get("features", F.lit(0)) * F.get("features", F.lit(1)) > 0).cast("int")})
    return folds(holdout(nested_samples(rows, "vec_id"), "vec_id"), "vec_id", 3)


def reviews(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, text, title, body, type, stars, content_hash, split. Copies of a text are on one side of the split."""
    docs, labels = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
    title, body = title_body(F.col("text"))
    stars = F.expr("CASE WHEN quality = 0 AND toxic = 1 THEN 1 WHEN quality = 0 THEN 2 WHEN toxic = 1 THEN 3 WHEN n_chars < 800 THEN 4 ELSE 5 END")
    rows = docs.join(labels, "doc_id").select("doc_id", "text", title.alias("title"), body.alias("body"), F.col("lang").alias("type"), stars.alias("stars"), F.md5(F.col("text").cast("binary")).alias("content_hash"))
    return holdout(rows, "content_hash")


def order_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A row an order: category, lists of brands, suppliers and parts, a long-tailed count, a target that its lines make and one that nothing makes."""
    lines = load(spark, sf_dir, "lineitem").join(load(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand", "p_name"), "l_partkey")
    per = lines.groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(
        F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"),
        F.sort_array(F.collect_set("p_brand")).alias("brands"),
        F.sort_array(F.collect_set("l_suppkey")).alias("suppliers"),
        F.sort_array(F.collect_set("l_partkey")).alias("parts"),
        F.min_by("l_suppkey", F.struct("l_linenumber", "l_suppkey")).alias("lead_supplier"),
        F.count(F.lit(1)).alias("n_lines"),
        F.max_by("p_name", F.struct("l_extendedprice", "p_name")).alias("title"),
    )
    nation = load(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_name").alias("nation"))
    customer = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey").join(F.broadcast(nation), "c_nationkey")
    rows = load(spark, sf_dir, "orders").join(customer, "o_custkey").join(per, "o_orderkey", "left")
    low, high = REVENUE
    scaled = F.when(F.col("revenue").isNotNull(), 1 + 9 * F.least(F.greatest((F.col("revenue") - low) / (high - low), F.lit(0.0)), F.lit(1.0)))
    empty = lambda c: F.coalesce(F.col(c), F.array().cast("array<string>" if c == "brands" else "array<bigint>")).alias(c)
    rows = rows.select("o_orderkey", "o_custkey", "nation", "c_nationkey", "o_orderdate", "o_orderpriority", scaled.alias("y_rev"), F.col("o_totalprice").alias("y_noise"), empty("brands"), empty("suppliers"), empty("parts"), "lead_supplier", F.coalesce("n_lines", F.lit(0)).alias("n_lines"), "title")
    return folds(holdout(rows, "o_orderkey"), "o_orderkey", 5)


def rule_predictions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, label, prediction, split: quality told from the share of punctuation."""
    docs = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id")
    marks = F.length("text") - F.length(F.regexp_replace("text", "[^A-Za-z0-9 \\n]", ""))
    share = marks / F.greatest(F.length("text"), F.lit(1))
    rows = docs.select("doc_id", F.col("quality").alias("label"), (share < 0.1).cast("int").alias("prediction"), F.when(uniform("split", "doc_id") < 0.2, "test").otherwise("train").alias("split"))
    return rows
