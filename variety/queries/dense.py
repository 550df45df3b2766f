"""Dense vectors: moments, standardising, the frozen map, planted labels."""

import numpy as np
from pyspark.sql import functions as F

from ..models.registry import gamma_of
from ..operators import dense as D
from ..plans import workloads as W
from ..sources.tables import load
from .registry import query

LONG = "v AS (SELECT vec_id, i, CAST(embedding[i] AS DOUBLE) AS x FROM (SELECT vec_id, embedding, unnest(range(1, 65)) AS i FROM embeddings))"


def _vectors(spark, d):
    return load(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("features"))


@query("dense_moments", f"WITH {LONG} SELECT CAST(i - 1 AS INTEGER) AS i, round(sum(x), 6) AS total, round(sum(x * x), 6) AS squares FROM v GROUP BY 1")
def _(spark, d):
    n, s, g = D.moments(_vectors(spark, d), "features")
    return spark.createDataFrame([(i, float(s[i]), float(g[i, i])) for i in range(len(s))], "i int, s double, q double").select("i", F.round("s", 6).alias("total"), F.round("q", 6).alias("squares"))


@query(
    "dense_covariance",
    f"WITH {LONG} SELECT CAST(a.i - 1 AS INTEGER) AS i, CAST(b.i - 1 AS INTEGER) AS j, round(covar_samp(a.x, b.x), 6) AS cov FROM v a JOIN v b ON a.vec_id = b.vec_id AND a.i <= b.i AND a.i <= 8 AND b.i <= 8 GROUP BY 1, 2",
)
def _(spark, d):
    c = D.covariance(_vectors(spark, d), "features")
    return spark.createDataFrame([(i, j, float(c[i, j])) for i in range(8) for j in range(i, 8)], "i int, j int, c double").select("i", "j", F.round("c", 6).alias("cov"))


@query(
    "dense_standardize",
    """WITH m AS (SELECT avg(l_quantity) AS a, stddev_samp(l_quantity) AS s, avg(l_tax) AS b, stddev_samp(l_tax) AS t FROM lineitem)
    SELECT round(min((l_quantity - a) / s), 6) AS low_quantity, round(max((l_quantity - a) / s), 6) AS high_quantity, round(min((l_tax - b) / t), 6) AS low_tax, round(max((l_tax - b) / t), 6) AS high_tax FROM lineitem CROSS JOIN m""",
)
def _(spark, d):
    rows = load(spark, d, "lineitem")
    m = F.broadcast(rows.agg(F.avg("l_quantity").alias("a"), F.stddev_samp("l_quantity").alias("s"), F.avg("l_tax").alias("b"), F.stddev_samp("l_tax").alias("t")))
    q, t = (F.col("l_quantity") - F.col("a")) / F.col("s"), (F.col("l_tax") - F.col("b")) / F.col("t")
    return rows.join(m).agg(F.round(F.min(q), 6).alias("low_quantity"), F.round(F.max(q), 6).alias("high_quantity"), F.round(F.min(t), 6).alias("low_tax"), F.round(F.max(t), 6).alias("high_tax"))


@query(
    "dense_project_fixed_w",
    f"WITH {LONG} SELECT vec_id, round(sum(CASE WHEN i % 2 = 1 THEN x ELSE -x END), 5) AS p0, round(sum(CASE WHEN i <= 32 THEN x ELSE -x END), 5) AS p1 FROM v GROUP BY vec_id",
)
def _(spark, d):
    w = np.stack([[1.0 if i % 2 == 0 else -1.0 for i in range(64)], [1.0 if i < 32 else -1.0 for i in range(64)]], axis=1)
    p = _vectors(spark, d).withColumn("p", D.project("features", w))
    return p.select("vec_id", F.round(F.get("p", F.lit(0)), 5).alias("p0"), F.round(F.get("p", F.lit(1)), 5).alias("p1"))


@query("dense_pca_explained")
def _(spark, d):
    rows = W.dense(spark, d).where("rho_bucket <= 45")
    got = [("exact", D.fit_pca(rows, "features").report()), ("randomized", D.fit_pca(rows, "features", k=16, method="randomized").report())]
    return spark.createDataFrame([(m, int(r["k"]), round(r["explained"], 4), r["off_orthonormal"] < 1e-8) for m, r in got], "method string, k int, explained double, orthonormal boolean")


@query("dense_pca_frozen")
def _(spark, d):
    rows = W.dense(spark, d)
    frozen = D.fit_pca(rows.where("rho_bucket <= 45"), "features", k=8)
    out = frozen.transform(rows, "features")
    return out.groupBy("rho_bucket").agg(*(F.round(F.var_samp(F.get("projected", F.lit(i))), 6).alias(f"var_{i}") for i in range(3)), F.count(F.lit(1)).alias("n"))


@query("dense_pca_refit")
def _(spark, d):
    rows = W.dense(spark, d)
    got = [(r, D.fit_pca(rows.where(F.col("rho_bucket") <= r), "features", k=8).report()) for r in (15, 45)]
    return spark.createDataFrame([(r, round(x["explained"], 4)) for r, x in got], "rho int, explained double")


@query("dense_correlation")
def _(spark, d):
    c = np.abs(D.correlation(_vectors(spark, d), "features"))
    np.fill_diagonal(c, 0)
    return spark.createDataFrame([(round(float(c.max()), 6),)], "largest double")


@query("dense_gamma_rules", f"WITH {LONG} SELECT round(1 / (64 * var_pop(x)), 6) AS scale_gamma, round(1 / 64.0, 6) AS auto_gamma FROM v")
def _(spark, d):
    rows = _vectors(spark, d)
    return spark.createDataFrame([(gamma_of(rows, "scale"), gamma_of(rows, "auto"))], "s double, a double").select(F.round("s", 6).alias("scale_gamma"), F.round("a", 6).alias("auto_gamma"))


@query(
    "dense_planted_labels",
    f"""WITH {LONG}, t AS (SELECT vec_id, sum(x * (CASE WHEN i % 2 = 1 THEN 1.0 ELSE -1.0 END) / (1 + (i - 1) % 8)) AS s FROM v GROUP BY vec_id)
    SELECT e.vec_id, CAST(s > 0 AS INTEGER) AS y_lin, CAST(CAST(embedding[1] AS DOUBLE) * CAST(embedding[2] AS DOUBLE) > 0 AS INTEGER) AS y_xor, CAST(label % 2 AS INTEGER) AS y_noise FROM embeddings e JOIN t ON t.vec_id = e.vec_id""",
)
def _(spark, d):
    return W.dense(spark, d).select("vec_id", "y_lin", "y_xor", F.col("y_noise").cast("int").alias("y_noise"))
