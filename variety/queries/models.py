"""Each family, fitted on planted labels and measured on held-out rows."""

from pyspark.sql import functions as F

from ..models.registry import DEFAULTS, fit
from ..operators import metrics as M
from ..plans import workloads as W
from .registry import query


def fitted(spark, d, family, target="y_lin", params=None, task="binary"):
    rows = W.dense(spark, d).withColumn("label", F.col(target).cast("double"))
    model = fit(family, rows.where("split = 'train'"), params, task)
    return model.transform(rows).select("vec_id", "split", "label", F.col("prediction").cast("double").alias("prediction"))


for _family in DEFAULTS:
    if _family in ("linear_regression", "majority"):
        continue

    @query(f"mod_{_family}")
    def _(spark, d, family=_family):
        return M.gap(fitted(spark, d, family)).withColumn("family", F.lit(family))


@query("mod_linear_regression")
def _(spark, d):
    rows = W.dense(spark, d).withColumn("label", F.get("features", F.lit(0)) * 2 - F.get("features", F.lit(1)))
    out = []
    for name, p in (("penalty", {"reg": 0.5, "l1_ratio": 0.0}), ("mixing", {"reg": 0.001, "l1_ratio": 0.5})):
        model = fit("linear_regression", rows.where("split = 'train'"), p)
        out.append(M.regression(model.transform(rows.where("split = 'test'"))).withColumn("reading", F.lit(name)))
    return out[0].unionByName(out[1])


@query("mod_lda_scores", "SELECT CAST(label % 2 AS INTEGER) AS label, round(count(*) / sum(count(*)) OVER (), 6) AS prior, round(avg(CAST(embedding[1] AS DOUBLE)), 6) AS mean_0 FROM embeddings GROUP BY 1")
def _(spark, d):
    model = fit("discriminant", W.dense(spark, d).withColumn("label", F.col("y_noise")))
    rows = [(i, float(p), float(m[0])) for i, (p, m) in enumerate(zip(model.facts["priors"], model.facts["means"], strict=True))]
    return spark.createDataFrame(rows, "label int, p double, m double").select("label", F.round("p", 6).alias("prior"), F.round("m", 6).alias("mean_0"))


@query("ens_stack")
def _(spark, d):
    from ..operators.ensemble import out_of_fold, stack

    names = ["logistic", "tree"]
    rows = W.dense(spark, d).withColumn("label", F.col("y_lin").cast("double"))
    train, test = rows.where("split = 'train'"), rows.where("split = 'test'")
    for f in names:
        whole = fit(f, train)
        train = out_of_fold(train, lambda part, f=f: fit(f, part), f)
        test = whole.transform(test).withColumnRenamed("prediction", f)
    scored = train.select("split", "label", *names).unionByName(test.select("split", "label", *names))
    model = stack(train, names, "label")
    return M.gap(model.transform(scored.withColumn("features", F.array(*(F.col(f).cast("double") for f in names)))))
