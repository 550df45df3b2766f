"""Accuracy, overfitting and collapse measures, and votes, on rule-based predictions."""

from pyspark.sql import functions as F

from ..functions.hashing import uniform_sql
from ..operators import ensemble as E
from ..operators import metrics as M
from ..plans import workloads as W
from ..sources.tables import load
from .registry import query

PRED = f"""p AS (SELECT d.doc_id, l.quality AS label, CAST((length(text) - length(regexp_replace(text, '[^A-Za-z0-9 \\n]', '', 'g'))) / greatest(length(text), 1) < 0.1 AS INTEGER) AS prediction,
    CASE WHEN {uniform_sql("split", "d.doc_id")} < 0.2 THEN 'test' ELSE 'train' END AS split FROM documents d JOIN labels l ON l.doc_id = d.doc_id)"""
CLASSES = """k AS (SELECT DISTINCT label AS c FROM p UNION SELECT DISTINCT prediction FROM p),
    f AS (SELECT c, (SELECT count(*) FROM p WHERE label = c) AS support, (SELECT count(*) FROM p WHERE prediction = c) AS predicted, (SELECT count(*) FROM p WHERE label = c AND prediction = c) AS hit FROM k)"""


@query("met_classification", f"WITH {PRED}, {CLASSES} SELECT CAST(sum(support) AS BIGINT) AS n, round(sum(hit) / sum(support), 6) AS accuracy, round(sum(2.0 * hit / (support + predicted) * support) / sum(support), 6) AS f1_weighted, round(avg(2.0 * hit / (support + predicted)), 6) AS f1_macro FROM f")
def _(spark, d):
    return M.classification(W.rule_predictions(spark, d))


@query("met_gap", f"WITH {PRED} SELECT round(avg(CASE WHEN split = 'train' THEN CAST(label = prediction AS INTEGER) END), 6) AS train_accuracy, round(avg(CASE WHEN split = 'test' THEN CAST(label = prediction AS INTEGER) END), 6) AS test_accuracy, round(avg(CASE WHEN split = 'train' THEN CAST(label = prediction AS INTEGER) END) - avg(CASE WHEN split = 'test' THEN CAST(label = prediction AS INTEGER) END), 6) AS gap FROM p")
def _(spark, d):
    return M.gap(W.rule_predictions(spark, d))


@query("met_confusion_norm", f"WITH {PRED}, c AS (SELECT label, prediction, count(*) AS n FROM p GROUP BY 1, 2) SELECT label, prediction, n, round(n / sum(n) OVER (PARTITION BY label), 6) AS share FROM c")
def _(spark, d):
    return M.confusion(W.rule_predictions(spark, d), normalized=True)


@query("met_collapse", f"WITH {PRED}, {CLASSES} SELECT round(max(predicted) / sum(predicted), 6) AS largest_prediction, round(max(support) / sum(support), 6) AS largest_label, count(*) FILTER (WHERE support > 0 AND hit = 0) AS lost_classes FROM f")
def _(spark, d):
    return M.collapse(W.rule_predictions(spark, d))


@query(
    "met_regression",
    """WITH m AS (SELECT o_orderpriority, avg(o_totalprice) AS p FROM orders GROUP BY 1), e AS (SELECT o_totalprice AS y, p - o_totalprice AS e FROM orders JOIN m ON m.o_orderpriority = orders.o_orderpriority)
    SELECT count(*) AS n, round(avg(abs(e)), 4) AS mae, round(sqrt(avg(e * e)), 4) AS rmse, round(1 - avg(e * e) / var_pop(y), 6) AS r2 FROM e""",
)
def _(spark, d):
    rows = load(spark, d, "orders")
    means = rows.groupBy("o_orderpriority").agg(F.avg("o_totalprice").alias("prediction"))
    got = M.regression(rows.join(F.broadcast(means), "o_orderpriority"), "o_totalprice")
    return got.select("n", F.round("mae", 4).alias("mae"), F.round("rmse", 4).alias("rmse"), "r2")


@query("met_scaling_slope", "SELECT round(regr_slope(ln(s), ln(n)), 6) AS power FROM (VALUES (100.0, 0.5), (200.0, 1.9), (400.0, 8.2), (800.0, 31.0)) t(n, s)")
def _(spark, d):
    return M.scaling_slope(spark.createDataFrame([(100.0, 0.5), (200.0, 1.9), (400.0, 8.2), (800.0, 31.0)], "n double, seconds double"))


@query("mod_majority", "SELECT quality AS value, count(*) AS n FROM labels GROUP BY quality ORDER BY n DESC, value LIMIT 1")
def _(spark, d):
    return load(spark, d, "labels").groupBy(F.col("quality").alias("value")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "value").limit(1)


MEMBERS = {"p1": 0.9, "p2": 0.8, "p3": 0.7}
RULES = "m AS (SELECT doc_id, CAST(doc_id % 2 AS INTEGER) AS p1, CAST(quality AS INTEGER) AS p2, CAST(doc_id % 3 = 0 AS INTEGER) AS p3 FROM labels)"


def _members(spark, d):
    return load(spark, d, "labels").select("doc_id", (F.col("doc_id") % 2).cast("int").alias("p1"), F.col("quality").cast("int").alias("p2"), (F.col("doc_id") % 3 == 0).cast("int").alias("p3"))


@query("ens_hard_vote", f"WITH {RULES} SELECT doc_id, CAST(p1 * 0.9 + p2 * 0.8 + p3 * 0.7 > (1 - p1) * 0.9 + (1 - p2) * 0.8 + (1 - p3) * 0.7 AS INTEGER) AS vote FROM m")
def _(spark, d):
    return _members(spark, d).select("doc_id", E.hard_vote(MEMBERS, 2).alias("vote"))


@query("ens_soft_vote", f"WITH {RULES} SELECT doc_id, CAST((0.3 + 0.3 * p1) * 0.9 + (0.2 + 0.5 * p2) * 0.8 + (0.4 + 0.3 * p3) * 0.7 > (0.7 - 0.3 * p1) * 0.9 + (0.8 - 0.5 * p2) * 0.8 + (0.6 - 0.3 * p3) * 0.7 AS INTEGER) AS vote FROM m")
def _(spark, d):
    rows = _members(spark, d)
    for m, (a, b) in {"p1": (0.3, 0.3), "p2": (0.2, 0.5), "p3": (0.4, 0.3)}.items():
        rows = rows.withColumn(m, F.array(F.lit(1 - a) - b * F.col(m), F.lit(a) + b * F.col(m)))
    return rows.select("doc_id", E.soft_vote(MEMBERS, 2).alias("vote"))


#: Four rules that tell whether a line is still open, each by one column.
TELLERS = {"by_date": "l_shipdate >= TIMESTAMP '1997-01-01 00:00:00'", "by_discount": "l_discount > 0.05", "by_flag": "l_returnflag = 'N'", "by_quantity": "l_quantity > 25"}
TOLD = "r AS (SELECT CAST(l_linestatus = 'O' AS INTEGER) AS y, " + ", ".join(f"CAST({rule} AS INTEGER) AS {m}" for m, rule in TELLERS.items()) + " FROM lineitem)"
HITS = ", ".join(f"avg(CAST({m} = y AS INTEGER)) AS {m}" for m in TELLERS)


def _told(spark, d):
    rows = load(spark, d, "lineitem")
    return rows.select((F.col("l_linestatus") == "O").cast("int").alias("y"), *(F.expr(rule.replace("TIMESTAMP '", "TIMESTAMP_NTZ '")).cast("int").alias(m) for m, rule in TELLERS.items()))


def _accuracies(rows, members):
    got = rows.agg(*(F.avg((F.col(m) == F.col("y")).cast("int")).alias(m) for m in members)).first()
    return {m: got[m] or 0.0 for m in members}


@query("ens_topk_weights", f"WITH {TOLD}, a AS (SELECT {HITS} FROM r), l AS (UNPIVOT a ON COLUMNS(*) INTO NAME model VALUE weight) SELECT model, round(weight, 6) AS weight FROM l ORDER BY weight DESC, model LIMIT 2")
def _(spark, d):
    scores = _accuracies(_told(spark, d), TELLERS)
    w = E.weights({m: scores[m] for m in E.top_k(scores, 2)})
    return spark.createDataFrame(list(w.items()), "model string, weight double").withColumn("weight", F.round("weight", 6))


@query("met_augmentation_balance", "WITH c AS (SELECT quality, count(*) / sum(count(*)) OVER () AS p FROM labels GROUP BY 1) SELECT quality, round(p, 6) AS share, round((SELECT -sum(p * ln(p)) FROM c), 6) AS entropy FROM c")
def _(spark, d):
    from pyspark.sql import Window

    counts = load(spark, d, "labels").groupBy("quality").agg(F.count(F.lit(1)).alias("n"))
    every = Window.partitionBy()
    rows = counts.withColumn("p", F.col("n") / F.sum("n").over(every))
    return rows.select("quality", F.round("p", 6).alias("share"), F.round(-F.sum(F.col("p") * F.log("p")).over(every), 6).alias("entropy"))


@query("ens_lift", f"WITH {TOLD} SELECT round(avg(CAST(CAST(by_date + by_discount + by_quantity >= 2 AS INTEGER) = y AS INTEGER)) - greatest(avg(CAST(by_date = y AS INTEGER)), avg(CAST(by_discount = y AS INTEGER)), avg(CAST(by_quantity = y AS INTEGER))), 6) AS lift FROM r")
def _(spark, d):
    members = ("by_date", "by_discount", "by_quantity")
    scores = _accuracies(_told(spark, d).withColumn("vote", E.hard_vote(dict.fromkeys(members, 1.0), 2)), (*members, "vote"))
    return spark.createDataFrame([(E.lift(scores.pop("vote"), scores),)], "lift double").withColumn("lift", F.round("lift", 6))


@query("met_sample_sufficiency")
def _(spark, d):
    from .workloads import _scores

    rows = _scores(spark, d, ("logistic",), "y_lin", 15).unionByName(_scores(spark, d, ("logistic",), "y_lin", 45))
    best = rows.agg(F.max(F.when(F.col("rho") == 45, F.col("test_accuracy"))).alias("full"))
    return rows.join(F.broadcast(best)).select("rho", F.round(F.col("test_accuracy") / F.col("full"), 4).alias("of_full"))
