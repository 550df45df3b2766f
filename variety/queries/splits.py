"""Samples, splits and folds."""

from pyspark.sql import functions as F

from ..functions.hashing import uniform_sql
from ..operators import sampling as S
from ..sources.tables import load
from .registry import query

RHOS_SQL = "(VALUES (2), (8), (15), (30), (45)) r(rho)"


@query("samp_hash_rho", f"SELECT label, rho, count(*) AS n FROM embeddings JOIN {RHOS_SQL} ON {uniform_sql('sample', 'vec_id')} < rho / 100.0 GROUP BY label, rho")
def _(spark, d):
    rows = S.nested_samples(load(spark, d, "embeddings").select("vec_id", "label"), "vec_id").where("rho_bucket < 100")
    return rows.select("label", F.explode(F.filter(F.array(*map(F.lit, S.RHOS)), lambda r: r >= F.col("rho_bucket"))).alias("rho")).groupBy("label", "rho").agg(F.count(F.lit(1)).alias("n"))


@query(
    "samp_exact_rho",
    f"""WITH r AS (SELECT doc_id, quality, row_number() OVER (PARTITION BY quality ORDER BY {uniform_sql("sample", "doc_id")}, doc_id) AS k, count(*) OVER (PARTITION BY quality) AS n FROM labels)
    SELECT doc_id, quality FROM r WHERE k <= floor(n * 0.02 + 0.5)""",
)
def _(spark, d):
    return S.stratified(load(spark, d, "labels"), "doc_id", "quality", 0.02, "exact").select("doc_id", "quality")


@query(
    "samp_nested_buckets",
    f"""WITH r AS (SELECT l_orderkey, {uniform_sql("sample", "l_orderkey")} AS u FROM lineitem)
    SELECT CAST(CASE WHEN u < 0.02 THEN 2 WHEN u < 0.08 THEN 8 WHEN u < 0.15 THEN 15 WHEN u < 0.3 THEN 30 WHEN u < 0.45 THEN 45 ELSE 100 END AS INTEGER) AS rho_bucket, count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM r GROUP BY 1""",
)
def _(spark, d):
    rows = S.nested_samples(load(spark, d, "lineitem").select("l_orderkey"), "l_orderkey")
    return rows.groupBy("rho_bucket").agg(F.count(F.lit(1)).alias("n"), F.sum("l_orderkey").alias("keys"))


@query(
    "samp_proportion_drift",
    f"""WITH u AS (SELECT lang, {uniform_sql("sample", "doc_id")} AS u FROM documents), t AS (SELECT count(*) AS n FROM u),
    w AS (SELECT lang, count(*) AS n FROM u GROUP BY lang), s AS (SELECT rho, lang, count(*) AS n FROM u JOIN {RHOS_SQL} ON u < rho / 100.0 GROUP BY rho, lang), st AS (SELECT rho, sum(n) AS n FROM s GROUP BY rho)
    SELECT w.lang, r.rho, round(w.n / t.n, 6) AS share, round(coalesce(s.n, 0) / st.n, 6) AS sampled, round(abs(w.n / t.n - coalesce(s.n, 0) / st.n), 6) AS drift
    FROM w CROSS JOIN t CROSS JOIN {RHOS_SQL} JOIN st ON st.rho = r.rho LEFT JOIN s ON s.rho = r.rho AND s.lang = w.lang""",
)
def _(spark, d):
    return S.proportion_drift(load(spark, d, "documents").select("doc_id", "lang"), "doc_id", "lang")


@query("samp_uniform", f"SELECT count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM events WHERE {uniform_sql('uniform', 'event_id')} < 0.15")
def _(spark, d):
    return S.uniform_sample(load(spark, d, "events"), "event_id", 0.15).agg(F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("ids"))


@query("samp_sampleby")
def _(spark, d):
    rows = load(spark, d, "events")
    classes = [r[0] for r in rows.select("event_type").distinct().collect()]
    return S.sample_by(rows, "event_type", 0.15, classes).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


SPLIT = f"CASE WHEN {uniform_sql('split', 'doc_id')} < 0.2 THEN 'test' ELSE 'train' END"


@query("split_holdout_stratified", f"SELECT {SPLIT} AS split, quality, count(*) AS n FROM labels GROUP BY 1, 2")
def _(spark, d):
    return S.holdout(load(spark, d, "labels"), "doc_id").groupBy("split", "quality").agg(F.count(F.lit(1)).alias("n"))


@query("split_quantile_bins")
def _(spark, d):
    return S.holdout_continuous(load(spark, d, "orders").select("o_orderkey", "o_totalprice"), "o_orderkey", "o_totalprice").groupBy("split").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("o_totalprice"), 2).alias("mean_price"))


@query(
    "split_grouped_no_leak",
    f"""WITH h AS (SELECT md5(text) AS h FROM documents), s AS (SELECT h, CASE WHEN {uniform_sql("split", "h")} < 0.2 THEN 'test' ELSE 'train' END AS split FROM h)
    SELECT (SELECT count(*) FROM s WHERE split = 'test') AS test_rows, (SELECT count(*) FROM (SELECT h FROM s GROUP BY h HAVING count(DISTINCT split) > 1)) AS leaked""",
)
def _(spark, d):
    rows = S.holdout(load(spark, d, "documents").select(F.md5(F.col("text").cast("binary")).alias("h")), "h")
    each = rows.groupBy("h").agg(F.count_if(F.col("split") == "test").alias("t"), F.count_distinct("split").alias("s"))
    return each.agg(F.sum("t").alias("test_rows"), F.count_if(F.col("s") > 1).alias("leaked"))


for _n in (2, 3):

    @query(f"fold_assign_{_n}", f"SELECT vec_id, CAST(floor({uniform_sql('fold', 'vec_id')} * {_n}) AS INTEGER) AS fold FROM embeddings")
    def _(spark, d, n=_n):
        return S.folds(load(spark, d, "embeddings"), "vec_id", n).select("vec_id", "fold")


@query("split_validation_flag", f"SELECT count(*) AS n FROM lineitem WHERE {uniform_sql('valid', 'l_orderkey')} < 0.1")
def _(spark, d):
    return S.validation_flag(load(spark, d, "lineitem").select("l_orderkey"), "l_orderkey", 0.1).where("is_valid").agg(F.count(F.lit(1)).alias("n"))


@query("split_official", "SELECT conv_id, turn, CASE WHEN role = 'user' THEN 'test' ELSE 'train' END AS split FROM conversations")
def _(spark, d):
    return S.official(load(spark, d, "conversations"), "role", ("user",)).select("conv_id", "turn", "split")


@query("dense_class_weights", "WITH c AS (SELECT quality, count(*) AS n FROM labels GROUP BY 1) SELECT quality, round(sum(n) OVER () / (count(*) OVER () * n), 6) AS weight FROM c")
def _(spark, d):
    return S.balanced_weights(load(spark, d, "labels"), "quality").groupBy("quality").agg(F.round(F.max("weight"), 6).alias("weight"))
