"""Hybrid rows: audits, encodings, reputation."""

from pyspark.sql import functions as F

from ..functions.hashing import uniform_sql
from ..operators import tabular as T
from ..operators.sampling import folds
from ..plans import workloads as W
from ..sources.tables import load
from .registry import query

LAM = "(1 / (1 + exp(-({n} - 20.0) / 10.0)))"


def _blend(n, mean, overall):
    lam = LAM.format(n=n)
    return f"CASE WHEN {n} > 0 THEN {lam} * {mean} + (1 - {lam}) * {overall} ELSE {overall} END"


@query(
    "tab_target_enc_train",
    f"""WITH s AS (SELECT o_custkey, count(*) AS n, avg(o_totalprice) AS m FROM orders GROUP BY 1), g AS (SELECT avg(o_totalprice) AS g FROM orders)
    SELECT o_orderkey, round({_blend("n", "m", "g")}, 4) AS encoded FROM orders JOIN s ON s.o_custkey = orders.o_custkey CROSS JOIN g""",
)
def _(spark, d):
    rows = load(spark, d, "orders").select("o_orderkey", "o_custkey", "o_totalprice")
    return T.target_encode(rows, "o_custkey", "o_totalprice").select("o_orderkey", F.round("encoded", 4).alias("encoded"))


@query(
    "tab_target_enc_loo",
    f"""WITH s AS (SELECT o_custkey, count(*) AS n, sum(o_totalprice) AS s FROM orders GROUP BY 1), g AS (SELECT count(*) AS gn, sum(o_totalprice) AS gs FROM orders),
    r AS (SELECT o_orderkey, n - 1 AS n, (s - o_totalprice) / nullif(n - 1, 0) AS m, (gs - o_totalprice) / (gn - 1) AS g FROM orders JOIN s ON s.o_custkey = orders.o_custkey CROSS JOIN g)
    SELECT o_orderkey, round({_blend("n", "m", "g")}, 4) AS encoded FROM r""",
)
def _(spark, d):
    rows = load(spark, d, "orders").select("o_orderkey", "o_custkey", "o_totalprice")
    return T.target_encode(rows, "o_custkey", "o_totalprice", "leave_one_out").select("o_orderkey", F.round("encoded", 4).alias("encoded"))


FOLDED = f"f AS (SELECT o_orderkey, o_custkey, o_totalprice, CAST(floor({uniform_sql('fold', 'o_orderkey')} * 5) AS INTEGER) AS fold FROM orders)"


@query(
    "tab_target_enc_oof",
    f"""WITH {FOLDED}, r AS (SELECT a.o_orderkey, count(b.o_orderkey) AS n, avg(b.o_totalprice) AS m, any_value(g.g) AS g FROM f a
    JOIN (SELECT x.fold, (SELECT avg(o_totalprice) FROM f y WHERE y.fold <> x.fold) AS g FROM (SELECT DISTINCT fold FROM f) x) g ON g.fold = a.fold LEFT JOIN f b ON b.o_custkey = a.o_custkey AND b.fold <> a.fold GROUP BY a.o_orderkey)
    SELECT o_orderkey, round({_blend("n", "m", "g")}, 4) AS encoded FROM r""",
)
def _(spark, d):
    rows = folds(load(spark, d, "orders").select("o_orderkey", "o_custkey", "o_totalprice"), "o_orderkey", 5)
    return T.target_encode(rows, "o_custkey", "o_totalprice", "out_of_fold", "fold").select("o_orderkey", F.round("encoded", 4).alias("encoded"))


@query(
    "tab_target_enc_mest",
    """WITH s AS (SELECT o_custkey, count(*) AS n, sum(o_totalprice) AS s FROM orders GROUP BY 1), g AS (SELECT avg(o_totalprice) AS g FROM orders)
    SELECT o_orderkey, round((s + 10.0 * g) / (n + 10.0), 4) AS encoded FROM orders JOIN s ON s.o_custkey = orders.o_custkey CROSS JOIN g""",
)
def _(spark, d):
    rows = load(spark, d, "orders").select("o_orderkey", "o_custkey", "o_totalprice")
    return T.target_encode(rows, "o_custkey", "o_totalprice", m=10.0).select("o_orderkey", F.round("encoded", 4).alias("encoded"))


@query("tab_prune_columns", "SELECT o_custkey, o_orderpriority, count(*) AS n FROM orders GROUP BY 1, 2")
def _(spark, d):
    rows = T.prune(load(spark, d, "orders"), {"o_orderkey": "identifier", "o_orderdate": "date", "o_totalprice": "money", "o_orderstatus": "known after the sale"})
    return rows.groupBy("o_custkey", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query(
    "tab_identifier_audit",
    """SELECT 'o_orderkey' AS column_name, count(DISTINCT o_orderkey) AS distinct_values, round(count(DISTINCT o_orderkey) / count(*), 6) AS share, count(DISTINCT o_orderkey) / count(*) >= 0.95 AS identifier FROM orders
    UNION ALL SELECT 'o_custkey', count(DISTINCT o_custkey), round(count(DISTINCT o_custkey) / count(*), 6), count(DISTINCT o_custkey) / count(*) >= 0.95 FROM orders
    UNION ALL SELECT 'o_orderpriority', count(DISTINCT o_orderpriority), round(count(DISTINCT o_orderpriority) / count(*), 6), count(DISTINCT o_orderpriority) / count(*) >= 0.95 FROM orders""",
)
def _(spark, d):
    return T.identifier_audit(load(spark, d, "orders"), ["o_orderkey", "o_custkey", "o_orderpriority"])


REV = "l AS (SELECT l_orderkey, sum(l_extendedprice * (1 - l_discount)) AS revenue, count(*) AS n_lines, sum(l_quantity) AS quantity FROM lineitem GROUP BY 1)"


@query("tab_leak_audit", f"WITH {REV} SELECT round(corr(revenue, n_lines), 6) AS lines_corr, round(corr(revenue, quantity), 6) AS quantity_corr, round(corr(revenue, o_totalprice), 6) AS price_corr FROM l JOIN orders ON l_orderkey = o_orderkey")
def _(spark, d):
    per = load(spark, d, "lineitem").groupBy("l_orderkey").agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"), F.count(F.lit(1)).alias("n_lines"), F.sum("l_quantity").alias("quantity"))
    rows = per.join(load(spark, d, "orders").select("o_orderkey", "o_totalprice"), F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.agg(F.round(F.corr("revenue", "n_lines"), 6).alias("lines_corr"), F.round(F.corr("revenue", "quantity"), 6).alias("quantity_corr"), F.round(F.corr("revenue", "o_totalprice"), 6).alias("price_corr"))


@query(
    "tab_log_skew",
    """WITH m AS (SELECT avg(value) AS a, stddev_pop(value) AS s, avg(ln(1 + value)) AS b, stddev_pop(ln(1 + value)) AS t FROM events)
    SELECT 'value' AS column_name, round(avg(value), 4) AS mean_value, round(max(value), 4) AS max_value, round(avg(((value - a) / s) ** 3), 4) AS skew_before, round(avg(((ln(1 + value) - b) / t) ** 3), 4) AS skew_after FROM events CROSS JOIN m""",
)
def _(spark, d):
    return T.skew_report(load(spark, d, "events"), ["value"]).select("column_name", *(F.round(c, 4).alias(c) for c in ("mean_value", "max_value", "skew_before", "skew_after")))


BRANDS = "b AS (SELECT DISTINCT l_orderkey, p_brand FROM lineitem JOIN part ON p_partkey = l_partkey)"


@query("tab_multihot_brand", f"WITH {BRANDS}, v AS (SELECT p_brand, row_number() OVER (ORDER BY p_brand) - 1 AS i FROM (SELECT DISTINCT p_brand FROM part)) SELECT CAST(i AS INTEGER) AS slot, v.p_brand AS brand, count(*) AS orders FROM b JOIN v ON v.p_brand = b.p_brand GROUP BY 1, 2")
def _(spark, d):
    vocabulary = sorted(r[0] for r in load(spark, d, "part").select("p_brand").distinct().collect())
    rows = W.order_rows(spark, d).select(T.multi_hot("brands", vocabulary).alias("hot"))
    long = rows.select(F.posexplode("hot").alias("slot", "on")).groupBy("slot").agg(F.sum("on").alias("orders"))
    return long.where("orders > 0").select("slot", F.get(F.array(*map(F.lit, vocabulary)), F.col("slot")).alias("brand"), "orders")


@query("tab_onehot_string", f"WITH {BRANDS}, s AS (SELECT l_orderkey, string_agg(p_brand, ',' ORDER BY p_brand) AS s FROM b GROUP BY 1) SELECT count(DISTINCT s) AS whole_strings, (SELECT count(DISTINCT p_brand) FROM b) AS multi_hot_columns FROM s")
def _(spark, d):
    rows = W.order_rows(spark, d).where(F.size("brands") > 0).select(F.array_join("brands", ",").alias("s"), "brands")
    return rows.agg(F.count_distinct("s").alias("whole_strings")).join(F.broadcast(rows.select(F.explode("brands").alias("b")).agg(F.count_distinct("b").alias("multi_hot_columns"))))


@query("tab_encoding_width", "SELECT count(DISTINCT o_custkey) + count(DISTINCT o_orderpriority) AS one_hot_columns, 2 AS encoded_columns FROM orders")
def _(spark, d):
    return load(spark, d, "orders").agg((F.count_distinct("o_custkey") + F.count_distinct("o_orderpriority")).alias("one_hot_columns"), F.lit(2).alias("encoded_columns"))


@query(
    "tab_leak_probe",
    """WITH s AS (SELECT o_custkey, count(*) AS n, sum(o_totalprice) AS s FROM orders GROUP BY 1)
    SELECT round(corr(o_totalprice, s / n), 5) AS in_sample, round(corr(o_totalprice, (s - o_totalprice) / (n - 1)), 5) AS left_out FROM orders JOIN s ON s.o_custkey = orders.o_custkey WHERE n > 1""",
)
def _(spark, d):
    rows = load(spark, d, "orders").select("o_custkey", "o_totalprice")
    stats = rows.groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"), F.sum("o_totalprice").alias("s"))
    both = rows.join(stats, "o_custkey").where("n > 1")
    y = F.col("o_totalprice")
    return both.agg(F.round(F.corr(y, F.col("s") / F.col("n")), 5).alias("in_sample"), F.round(F.corr(y, (F.col("s") - y) / (F.col("n") - 1)), 5).alias("left_out"))


MEM = "m AS (SELECT DISTINCT l_orderkey AS o, l_suppkey AS p FROM lineitem), y AS (SELECT o_orderkey AS o, o_totalprice AS y, o_orderdate AS t, o_orderpriority AS pr FROM orders), k AS (SELECT y.o, y.y, y.t, m.p FROM y LEFT JOIN m ON m.o = y.o), g AS (SELECT avg(y) AS g FROM y)"


def _cast(spark, d):
    rows = W.order_rows(spark, d).select("o_orderkey", "y_noise", "suppliers", "o_orderdate", "fold")
    return rows


def _rounded(df):
    return df.select("o_orderkey", F.round("cast_reputation", 1).alias("reputation"), F.round("cast_experience", 4).alias("experience"))


@query(
    "tab_reputation_train",
    f"WITH {MEM}, s AS (SELECT p, count(*) AS n, avg(y) AS r FROM k WHERE p IS NOT NULL GROUP BY 1) SELECT k.o AS o_orderkey, round(avg(coalesce(s.r, g)), 1) AS reputation, round(avg(coalesce(s.n, 0)), 4) AS experience FROM k LEFT JOIN s ON s.p = k.p CROSS JOIN g GROUP BY 1",
)
def _(spark, d):
    return _rounded(T.reputation(_cast(spark, d), "o_orderkey", "suppliers", "y_noise"))


@query(
    "tab_reputation_loo",
    f"WITH {MEM}, s AS (SELECT p, count(*) AS n, sum(y) AS s FROM k WHERE p IS NOT NULL GROUP BY 1) SELECT k.o AS o_orderkey, round(avg(coalesce((s.s - k.y) / nullif(s.n - 1, 0), g)), 1) AS reputation, round(avg(coalesce(s.n - 1, 0)), 4) AS experience FROM k LEFT JOIN s ON s.p = k.p CROSS JOIN g GROUP BY 1",
)
def _(spark, d):
    return _rounded(T.reputation(_cast(spark, d), "o_orderkey", "suppliers", "y_noise", "leave_one_out"))


@query(
    "tab_reputation_asof",
    f"""WITH {MEM}, q AS (SELECT p, t, count(*) AS n, sum(y) AS s FROM k WHERE p IS NOT NULL GROUP BY 1, 2), w AS (SELECT p, t, sum(n) OVER (PARTITION BY p ORDER BY t ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS n, sum(s) OVER (PARTITION BY p ORDER BY t ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS s FROM q)
    SELECT k.o AS o_orderkey, round(avg(coalesce(w.s / w.n, g)), 1) AS reputation, round(avg(coalesce(w.n, 0)), 4) AS experience FROM k LEFT JOIN w ON w.p = k.p AND w.t = k.t CROSS JOIN g GROUP BY 1""",
)
def _(spark, d):
    return _rounded(T.reputation(_cast(spark, d), "o_orderkey", "suppliers", "y_noise", "as_of", day="o_orderdate"))


@query("tab_reputation_oof")
def _(spark, d):
    return _rounded(T.reputation(_cast(spark, d), "o_orderkey", "suppliers", "y_noise", "out_of_fold", fold="fold"))


@query("tab_experience", f"WITH {MEM}, s AS (SELECT p, count(*) AS n FROM k WHERE p IS NOT NULL GROUP BY 1) SELECT round(avg(n), 4) AS mean_experience, max(n) AS most, count(*) AS people FROM s")
def _(spark, d):
    rows = _cast(spark, d).select(F.explode("suppliers").alias("p")).groupBy("p").agg(F.count(F.lit(1)).alias("n"))
    return rows.agg(F.round(F.avg("n"), 4).alias("mean_experience"), F.max("n").alias("most"), F.count(F.lit(1)).alias("people"))


@query("tab_assemble")
def _(spark, d):
    vocabulary = sorted(r[0] for r in load(spark, d, "part").select("p_brand").distinct().collect())
    rows = T.target_encode(W.order_rows(spark, d), "o_custkey", "y_rev", "leave_one_out").withColumn("hot", T.multi_hot("brands", vocabulary))
    out, spans = T.assemble(rows, {"numeric": ["n_lines"], "brands": ["hot"], "customer": ["encoded"]})
    return out.agg(F.max(F.size("features")).alias("width"), F.count(F.lit(1)).alias("n")).withColumn("blocks", F.lit(str(spans)))


STATUS = ("F", "O", "P")


@query(
    "tab_target_enc_classes",
    f"""WITH s AS (SELECT o_custkey, o_orderstatus AS c, count(*) AS k FROM orders GROUP BY 1, 2), t AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1),
    g AS (SELECT c, count(o_orderkey) / (SELECT count(*) FROM orders) AS g FROM (VALUES ('F'), ('O'), ('P')) v(c) LEFT JOIN orders ON o_orderstatus = c GROUP BY 1),
    e AS (SELECT t.o_custkey, g.c, {_blend("t.n", "(coalesce(s.k, 0) / t.n)", "g.g")} AS e FROM t CROSS JOIN g LEFT JOIN s ON s.o_custkey = t.o_custkey AND s.c = g.c)
    SELECT o_orderkey, round(f.e, 6) AS share_f, round(o.e, 6) AS share_o, round(p.e, 6) AS share_p FROM orders JOIN e f ON f.o_custkey = orders.o_custkey AND f.c = 'F'
    JOIN e o ON o.o_custkey = orders.o_custkey AND o.c = 'O' JOIN e p ON p.o_custkey = orders.o_custkey AND p.c = 'P'""",
)
def _(spark, d):
    rows = load(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderstatus")
    rows = T.target_encode_classes(rows, "o_custkey", "o_orderstatus", list(STATUS))
    return rows.select("o_orderkey", *(F.round(F.get("encoded", F.lit(i)), 6).alias(f"share_{c.lower()}") for i, c in enumerate(STATUS)))
