"""Hyperparameter search: counts, operators and traces, on given tables where these have what they need, else on literals."""

import math

import pyarrow as pa

from pyspark.sql import functions as F

from ..functions.hashing import uniform_sql
from ..hpo import search as H
from ..hpo.space import SVM_GRID, Param, Space
from ..operators.metrics import summarize_trials
from ..operators.sampling import folds, nested_samples
from ..sources.tables import load
from .registry import query

VALUES = "c(c) AS (VALUES (0.01), (0.1), (1.0), (5.0), (10.0), (20.0)), g(g) AS (VALUES ('scale'), ('auto'), ('0.0001'), ('0.001'), ('0.01'), ('0.1')), d(d) AS (VALUES (2), (3), (4)), o(o) AS (VALUES (0.0), (0.1), (0.5))"


FOLD = f"CAST(floor({uniform_sql('fold', 'o_orderkey')} * 3) AS INTEGER)"
FOLDS_SQL = f"k AS (SELECT fold, CAST(sum(n) OVER () - n AS BIGINT) AS train_rows, n AS test_rows FROM (SELECT {FOLD} AS fold, count(*) AS n FROM orders GROUP BY 1))"


def _folds(spark, d):
    """Rows to learn from and to test on, of each fold of the orders."""
    n = folds(load(spark, d, "orders").select("o_orderkey"), "o_orderkey", 3).groupBy("fold").agg(F.count(F.lit(1)).alias("test_rows"))
    every = n.agg(F.sum("test_rows").alias("n"))
    return n.join(F.broadcast(every)).select("fold", (F.col("n") - F.col("test_rows")).alias("train_rows"), "test_rows")


@query(
    "hpo_grid_enumerate",
    f"""WITH {VALUES}, {FOLDS_SQL}, s AS (SELECT 'rbf' AS kernel, CAST(c AS DOUBLE) AS c, g AS gamma, CAST(NULL AS INTEGER) AS degree, CAST(NULL AS DOUBLE) AS coef0 FROM c CROSS JOIN g
    UNION ALL SELECT 'linear', CAST(c AS DOUBLE), NULL, NULL, NULL FROM c UNION ALL SELECT 'poly', CAST(c AS DOUBLE), g, d, CAST(o AS DOUBLE) FROM c CROSS JOIN g CROSS JOIN d CROSS JOIN o)
    SELECT kernel, c, gamma, degree, coef0, fold, train_rows, test_rows FROM s CROSS JOIN k""",
)
def _(spark, d):
    name = lambda g: g if g is None or isinstance(g, str) else f"{g:f}".rstrip("0")
    rows = [(t["kernel"], t["c"], name(t.get("gamma")), t.get("degree"), t.get("coef0")) for t in SVM_GRID.grid()]
    return spark.createDataFrame(rows, "kernel string, c double, gamma string, degree int, coef0 double").join(F.broadcast(_folds(spark, d)))


@query(
    "hpo_grid_counts",
    f"""WITH {FOLDS_SQL} SELECT kernel, CAST(configurations AS INTEGER) AS configurations, CAST(configurations * count(*) AS BIGINT) AS fits, CAST(configurations * sum(train_rows) AS BIGINT) AS trained_rows
    FROM (VALUES ('rbf', 36), ('linear', 6), ('poly', 324), ('all', 366)) t(kernel, configurations) CROSS JOIN k GROUP BY kernel, configurations""",
)
def _(spark, d):
    grid = SVM_GRID.grid()
    counts = {k: sum(t["kernel"] == k for t in grid) for k in ("rbf", "linear", "poly")} | {"all": len(grid)}
    rows = spark.createDataFrame(list(counts.items()), "kernel string, configurations int").join(F.broadcast(_folds(spark, d)))
    n = F.col("configurations")
    return rows.groupBy("kernel", n).agg((n * F.count(F.lit(1))).alias("fits"), (n * F.sum("train_rows")).alias("trained_rows"))


@query(
    "hpo_cv_select",
    f"""WITH s AS (SELECT o_custkey % 366 AS trial, {FOLD} AS fold, avg(CAST(o_orderstatus = 'F' AS INTEGER)) AS score FROM orders GROUP BY 1, 2), m AS (SELECT trial, avg(score) AS m, stddev_samp(score) AS sd, count(*) AS folds FROM s GROUP BY trial)
    SELECT trial, round(m, 6) AS mean_score, round(sd, 6) AS sd_score, folds, CAST(row_number() OVER (ORDER BY round(m, 9) DESC, trial) AS INTEGER) AS place FROM m""",
)
def _(spark, d):
    """Customers dealt to as many trials as the grid has; a trial's score on a fold is the share of its orders there that are filled."""
    rows = folds(load(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderstatus"), "o_orderkey", 3)
    ledger = rows.groupBy((F.col("o_custkey") % 366).alias("trial"), "fold").agg(F.avg((F.col("o_orderstatus") == "F").cast("int")).alias("score"))
    return summarize_trials(ledger)


FITNESS = [0.5, 0.9, 0.7, 0.9, 0.1, 0.6]


def _u(*parts):
    return "(('0x' || substr(md5(concat_ws('|', " + ", ".join(parts) + ")), 1, 8))::BIGINT / 4294967296.0)"


@query(
    "hpo_tournament",
    f"""WITH f(i, v) AS (VALUES {", ".join(f"({i}, {v})" for i, v in enumerate(FITNESS))}), t AS (SELECT unnest(range(0, 20)) AS t), k AS (SELECT unnest(range(0, 3)) AS k),
    drawn AS (SELECT t, CAST(floor({_u("42", "t", "k")} * 6) AS INTEGER) AS i FROM t CROSS JOIN k), ranked AS (SELECT t, f.i, row_number() OVER (PARTITION BY t ORDER BY v DESC, f.i) AS r FROM drawn JOIN f ON f.i = drawn.i)
    SELECT CAST(t AS INTEGER) AS tournament, i AS winner FROM ranked WHERE r = 1""",
)
def _(spark, d):
    return spark.createDataFrame([(t, H.tournament(FITNESS, 3, 42, t)) for t in range(20)], "tournament int, winner int")


GENES = Space("toy", tuple(Param(n, "choice", values=(0, 1)) for n in "abcde"))
GENES_SQL = "g(i, name) AS (VALUES (0, 'a'), (1, 'b'), (2, 'c'), (3, 'd'), (4, 'e')), p AS (SELECT unnest(range(0, 10)) AS p)"


@query("hpo_uniform_crossover", f"WITH {GENES_SQL} SELECT CAST(p AS INTEGER) AS pair, name, CAST(CASE WHEN {_u('42', 'p', 'name')} < 0.6 THEN 1 ELSE 0 END AS INTEGER) AS gene FROM p CROSS JOIN g")
def _(spark, d):
    a, b = dict.fromkeys("abcde", 0), dict.fromkeys("abcde", 1)
    return spark.createDataFrame([(p, n, v) for p in range(10) for n, v in H.uniform_crossover(GENES, a, b, 0.6, 42, p).items()], "pair int, name string, gene int")


#: A customer's genes are the bits of its nation; those of its other parent are the bits of its balance.
BITS = "CAST((n >> i) & 1 AS INTEGER)"
CUSTOMERS_SQL = "g(i, name) AS (VALUES (0, 'a'), (1, 'b'), (2, 'c'), (3, 'd'), (4, 'e')), p AS (SELECT c_custkey AS p, CAST(c_nationkey AS BIGINT) AS n, CAST(floor(abs(c_acctbal)) AS BIGINT) % 32 AS m FROM customer)"


def _genes(n):
    return {q.name: None if n is None else n >> i & 1 for i, q in enumerate(GENES.params)}


def _bred(spark, d, key, make):
    """A row for each customer and gene of the child that ``make(p, n, m)`` gives, made in the tasks."""
    rows = load(spark, d, "customer").select(F.col("c_custkey").alias("p"), F.col("c_nationkey").cast("bigint").alias("n"), (F.floor(F.abs("c_acctbal")).cast("bigint") % 32).alias("m"))

    def run(batches):
        for batch in batches:
            out = [(p, name, v) for p, n, m in zip(*(c.to_pylist() for c in batch.columns), strict=True) for name, v in make(p, n, m).items()]
            if out:
                p, names, genes = zip(*out, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(p, pa.int64()), pa.array(names, pa.string()), pa.array(genes, pa.int32())], [key, "name", "gene"])

    return rows.mapInArrow(run, f"{key} bigint, name string, gene int")


@query("hpo_one_point_crossover", f"WITH {CUSTOMERS_SQL} SELECT p AS pair, name, CASE WHEN i < 1 + floor({_u('42', 'p', chr(39) + 'cut' + chr(39))} * 4) THEN {BITS} ELSE {BITS.replace('n', 'm', 1)} END AS gene FROM p CROSS JOIN g")
def _(spark, d):
    return _bred(spark, d, "pair", lambda p, n, m: H.one_point_crossover(GENES, _genes(n), _genes(m), 42, p))


for _name, _k in (("reset", 1), ("multi", 3)):

    @query(
        f"hpo_mutation_{_name}",
        f"""WITH {CUSTOMERS_SQL}, r AS (SELECT p, n, i, name, row_number() OVER (PARTITION BY p ORDER BY {_u("42", "p", "'pick'", "name")}) AS k, {_u("42", "p", "'new'", "name")} AS u FROM p CROSS JOIN g)
        SELECT p AS child, name, CASE WHEN k <= {_k} THEN CAST(floor(u * 2) AS INTEGER) ELSE {BITS} END AS gene FROM r""",
    )
    def _(spark, d, k=_k):
        from ..hpo.space import u

        def make(p, n, m):
            ranked = sorted(GENES.params, key=lambda q: u(42, p, "pick", q.name))
            return H.reset_genes(GENES, _genes(n), ranked[:k], 42, p)

        return _bred(spark, d, "child", make)


@query(
    "hpo_aga_weights",
    """WITH RECURSIVE e AS (SELECT CAST(ts AS DATE) AS day, count(*) FILTER (WHERE event_type = 'click') AS a, count(*) FILTER (WHERE event_type = 'purchase') AS b, count(*) AS n FROM events WHERE ts IS NOT NULL GROUP BY 1),
    s AS (SELECT row_number() OVER (ORDER BY day) AS step, a, b, n FROM e),
    w(step, a, b) AS (SELECT 0::BIGINT, 0.5::DOUBLE, 0.5::DOUBLE UNION ALL SELECT s.step, (0.9 * w.a + 0.1 * s.a / s.n) / (0.9 * w.a + 0.1 * s.a / s.n + 0.9 * w.b + 0.1 * s.b / s.n), (0.9 * w.b + 0.1 * s.b / s.n) / (0.9 * w.a + 0.1 * s.a / s.n + 0.9 * w.b + 0.1 * s.b / s.n) FROM w JOIN s ON s.step = w.step + 1)
    SELECT CAST(step AS INTEGER) AS step, round(a, 6) AS uniform_weight, round(b, 6) AS one_point_weight FROM w""",
)
def _(spark, d):
    """Two operators whose successes are a day's clicks and purchases; the driver has a row a day."""
    kind = lambda t: F.count_if(F.col("event_type") == t)
    days = load(spark, d, "events").where("ts IS NOT NULL").groupBy(F.col("ts").cast("date").alias("day")).agg(kind("click").alias("a"), kind("purchase").alias("b"), F.count(F.lit(1)).alias("n"))
    rows, w = [(0, 0.5, 0.5)], [0.5, 0.5]
    for i, r in enumerate(days.orderBy("day").collect(), 1):
        w = H.update_weights(w, [r["a"], r["b"]], r["n"], 0.1, 0.0)
        rows.append((i, round(w[0], 6), round(w[1], 6)))
    return spark.createDataFrame(rows, "step int, uniform_weight double, one_point_weight double")


@query("hpo_elitism", "SELECT o_orderkey AS trial, o_totalprice AS score FROM orders ORDER BY score DESC NULLS LAST, trial LIMIT 2")
def _(spark, d):
    """Orders as trials, their price as the score."""
    rows = load(spark, d, "orders").select(F.col("o_orderkey").alias("trial"), F.col("o_totalprice").alias("score"))
    return rows.orderBy(F.desc("score"), "trial").limit(2)


@query(
    "hpo_sa_accept",
    """WITH k AS (SELECT unnest(range(0, 30)) AS k), t AS (SELECT k, 'geometric' AS cooling, 0.9 ** k AS t FROM k UNION ALL SELECT k, 'linear', 1 - k / 30.0 FROM k UNION ALL SELECT k, 'logarithmic', 1 / ln(exp(1) + k) FROM k)
    SELECT CAST(k AS INTEGER) AS step, cooling, round(exp(-0.05 / t), 6) AS chance FROM t""",
)
def _(spark, d):
    rows = [(k, c, round(math.exp(-0.05 / H.temperature(c, 1.0, k)), 6)) for k in range(30) for c in ("geometric", "linear", "logarithmic")]
    return spark.createDataFrame(rows, "step int, cooling string, chance double")


BOWL = Space("bowl", (Param("x", "real", -3.0, 3.0), Param("y", "real", -3.0, 3.0)))


def bowl(thetas):
    """Two basins; the deeper one is at (1, -0.5)."""
    return [max(-((t["x"] - 1) ** 2 + (t["y"] + 0.5) ** 2), -0.5 - ((t["x"] + 2) ** 2 + (t["y"] - 2) ** 2)) for t in thetas]


@query("hpo_sa_trace")
def _(spark, d):
    r = H.annealing(BOWL, bowl)
    best, rows = -math.inf, []
    for row in r.ledger:
        best = max(best, row["score"])
        rows.append((row["trial"], round(row["score"], 6), round(best, 6)))
    return spark.createDataFrame(rows, "trial int, score double, best double")


@query("hpo_strategies_on_bowl")
def _(spark, d):
    runs = [H.random_search(BOWL, bowl, 300), H.genetic(BOWL, bowl), H.adaptive_genetic(BOWL, bowl), H.annealing(BOWL, bowl, 300), H.tpe(BOWL, bowl, 40), H.successive_halving(BOWL, lambda t, r: bowl(t))]
    return spark.createDataFrame([(r.strategy, round(r.score, 6), r.trainings, len(r.ledger)) for r in runs], "strategy string, best double, trainings int, trials int")


HISTORY = [(0.1, 0.3), (0.2, 0.2), (0.25, 0.1), (0.4, 0.4), (0.6, 0.6), (0.8, 0.9)]


@query("hpo_tpe_ratio")
def _(spark, d):
    p = Param("x", "real", 0.0, 1.0)
    order = sorted(HISTORY, key=lambda r: r[1])
    good, bad = [x for x, _ in order[:2]], [x for x, _ in order[2:]]
    rows = [(i, round(math.log(H.density(p, good, i / 10)) - math.log(H.density(p, bad, i / 10)), 6)) for i in range(11)]
    return spark.createDataFrame(rows, "candidate int, log_ratio double")


@query(
    "hpo_halving_rungs",
    f"""WITH r AS (SELECT {uniform_sql("sample", "c_custkey")} AS u FROM customer) SELECT rho, trials, (SELECT count(*) FROM r WHERE CASE WHEN u < 0.02 THEN 2 WHEN u < 0.08 THEN 8 WHEN u < 0.15 THEN 15 WHEN u < 0.3 THEN 30 WHEN u < 0.45 THEN 45 ELSE 100 END <= rho) AS sample_rows
    FROM (VALUES (2, 27), (8, 9), (15, 3), (30, 1)) t(rho, trials)""",
)
def _(spark, d):
    """Points judged by their distance from the mean customer of ever larger samples; one scan sums all samples."""
    rows = nested_samples(load(spark, d, "customer"), "c_custkey").groupBy("rho_bucket")
    sums = rows.agg(F.count(F.lit(1)).alias("n"), F.sum("c_nationkey").alias("x"), F.sum(F.col("c_acctbal") / 5000).alias("y")).collect()

    def at(thetas, rho):
        n, x, y = (sum(r[c] or 0 for r in sums if r["rho_bucket"] <= rho) for c in "nxy")
        return [-((t["x"] - x / max(n, 1) / 12) ** 2) - (t["y"] - y / max(n, 1)) ** 2 for t in thetas]

    ledger = H.successive_halving(BOWL, at).ledger
    rungs = spark.createDataFrame([(x["rho"],) for x in ledger], "rho int").groupBy("rho").agg(F.count(F.lit(1)).cast("int").alias("trials"))
    seen = F.udf(lambda rho: sum(r["n"] for r in sums if r["rho_bucket"] <= rho), "bigint")
    return rungs.withColumn("sample_rows", seen("rho"))


@query(
    "hpo_ledger_cost",
    "SELECT strategy, trials, trials * folds AS fits, trials * learns * (SELECT count(*) FROM orders) AS trained_rows FROM (VALUES ('grid', 366, 3, 2), ('adaptive_genetic', 300, 2, 1), ('tpe', 15, 1, 1)) t(strategy, trials, folds, learns)",
)
def _(spark, d):
    """Trials, fits and rows that fits learn from, folds less the one kept; the toy score is the distance from the share of orders that are filled."""
    n, share = load(spark, d, "orders").agg(F.count(F.lit(1)), F.avg((F.col("o_orderstatus") == "F").cast("int"))).first()
    toy, score = Space("toy", (Param("x", "real"),)), lambda ts: [-abs(t["x"] - (share or 0.0)) for t in ts]
    trials = {"grid": (len(SVM_GRID.grid()), 3), "adaptive_genetic": (len(H.adaptive_genetic(toy, score).ledger), 2), "tpe": (len(H.tpe(toy, score).ledger), 1)}
    return spark.createDataFrame([(k, t, t * f, t * max(f - 1, 1) * n) for k, (t, f) in trials.items()], "strategy string, trials int, fits int, trained_rows bigint")
