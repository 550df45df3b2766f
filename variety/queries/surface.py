"""The relational surface that the methods stand on."""

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.sql import register
from ..sources.tables import SCHEMAS, load
from .registry import query

for _t in ("region", "nation", "supplier", "events"):
    _cols = [c.split()[0] for c in SCHEMAS[_t].split(",")]

    @query(f"op_scan_{_t}", f"SELECT {', '.join(_cols)} FROM {_t}")
    def _(spark, d, t=_t):
        return spark.read.schema(SCHEMAS[t]).parquet(f"{d}/{t}.parquet")


def _shared(spark, name):
    import uuid

    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir") or "/tmp/variety-surface"
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


@query("op_scan_libsvm", "SELECT CAST(label % 2 AS DOUBLE) AS label, count(*) AS n, round(sum(CAST(embedding[1] AS DOUBLE)), 4) AS first_column FROM embeddings GROUP BY 1")
def _(spark, d):
    from ..sources.tables import read_sparse_text, write_sparse_text

    path = _shared(spark, "libsvm")
    rows = load(spark, d, "embeddings")
    write_sparse_text(rows.select((F.col("label") % 2).alias("label"), F.col("embedding").cast("array<double>").alias("features")), path)
    return read_sparse_text(spark, path, 64).groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(F.get("features", F.lit(0))), 4).alias("first_column"))


@query("op_scan_text", "SELECT sum(len(string_split(text, chr(10)))) AS lines FROM benchmark")
def _(spark, d):
    path = _shared(spark, "text")
    load(spark, d, "benchmark").select(F.col("text").alias("value")).write.text(path)
    return spark.read.text(path).agg(F.count(F.lit(1)).alias("lines"))


@query("op_project", "SELECT o_orderkey, o_totalprice * 2 AS doubled, upper(o_orderpriority) AS priority FROM orders")
def _(spark, d):
    return load(spark, d, "orders").select("o_orderkey", (F.col("o_totalprice") * 2).alias("doubled"), F.upper("o_orderpriority").alias("priority"))


@query("op_filter", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 12 AND l_returnflag IN ('A', 'R') AND l_discount IS NOT NULL")
def _(spark, d):
    return load(spark, d, "lineitem").where(F.col("l_quantity").between(10, 12) & F.col("l_returnflag").isin("A", "R") & F.col("l_discount").isNotNull()).select("l_orderkey", "l_linenumber", "l_quantity")


for _how, _sql in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("full", "FULL JOIN")):

    @query(f"op_join_{_how}", f"SELECT c_custkey, count(o_orderkey) AS n FROM customer {_sql} orders ON c_custkey = o_custkey GROUP BY 1")
    def _(spark, d, how=_how):
        return load(spark, d, "customer").join(load(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), how).groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("op_join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def _(spark, d):
    return load(spark, d, "customer").join(load(spark, d, "orders").where("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("op_join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def _(spark, d):
    return load(spark, d, "customer").join(load(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("op_join_range", "SELECT r.band, count(*) AS n FROM orders JOIN (VALUES (0, 0, 100000), (1, 100000, 300000), (2, 300000, 10000000)) r(band, lo, hi) ON o_totalprice >= lo AND o_totalprice < hi GROUP BY 1")
def _(spark, d):
    bands = spark.createDataFrame([(0, 0, 100000), (1, 100000, 300000), (2, 300000, 10000000)], "band int, lo int, hi int")
    return load(spark, d, "orders").join(F.broadcast(bands), (F.col("o_totalprice") >= F.col("lo")) & (F.col("o_totalprice") < F.col("hi"))).groupBy("band").agg(F.count(F.lit(1)).alias("n"))


@query("op_join_salted", "SELECT s_nationkey, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN supplier ON s_suppkey = l_suppkey GROUP BY 1")
def _(spark, d):
    salts = 8
    left = load(spark, d, "lineitem").select("l_suppkey", "l_quantity", F.pmod(F.xxhash64("l_orderkey"), F.lit(salts)).alias("salt"))
    right = load(spark, d, "supplier").select("s_suppkey", "s_nationkey", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))).alias("salt"))
    return left.join(right, (F.col("l_suppkey") == F.col("s_suppkey")) & (left["salt"] == right["salt"])).groupBy("s_nationkey").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query("op_join_asof", "SELECT event_id, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_click FROM events")
def _(spark, d):
    rows = load(spark, d, "events").withColumn("click", F.when(F.col("event_type") == "click", F.col("event_id")))
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return rows.select("event_id", F.last("click", True).over(before).alias("last_click"))


@query("op_lateral", "SELECT o_orderkey, top.l_linenumber AS line FROM orders, LATERAL (SELECT l_linenumber FROM lineitem WHERE l_orderkey = o_orderkey ORDER BY l_extendedprice DESC, l_linenumber LIMIT 1) top")
def _(spark, d):
    best = Window.partitionBy("l_orderkey").orderBy(F.desc("l_extendedprice"), "l_linenumber")
    top = load(spark, d, "lineitem").withColumn("k", F.row_number().over(best)).where("k = 1").select(F.col("l_orderkey").alias("o_orderkey"), F.col("l_linenumber").alias("line"))
    return load(spark, d, "orders").select("o_orderkey").join(top, "o_orderkey")


@query("op_agg", "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_discount), 6) AS discount, round(stddev_samp(l_tax), 6) AS tax, min(l_linenumber) AS low, max(l_linenumber) AS high FROM lineitem GROUP BY 1")
def _(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount"), F.round(F.stddev_samp("l_tax"), 6).alias("tax"), F.min("l_linenumber").alias("low"), F.max("l_linenumber").alias("high")
    )


@query("op_agg_filter", "SELECT event_type, count(*) FILTER (WHERE value > 50) AS high, round(sum(CASE WHEN value <= 50 THEN value ELSE 0 END), 4) AS low_total FROM events GROUP BY 1")
def _(spark, d):
    return load(spark, d, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"), F.round(F.sum(F.when(F.col("value") <= 50, F.col("value")).otherwise(0)), 4).alias("low_total"))


@query("op_distinct", "SELECT count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts FROM lineitem")
def _(spark, d):
    return load(spark, d, "lineitem").agg(F.count_distinct("l_suppkey").alias("suppliers"), F.count_distinct("l_partkey").alias("parts"))


@query("op_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def _(spark, d):
    return load(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


@query("op_rollup", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def _(spark, d):
    return load(spark, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("op_pivot", "SELECT lang, count(*) FILTER (WHERE source = 'src0') AS src0, count(*) FILTER (WHERE source = 'src1') AS src1 FROM documents WHERE source IN ('src0', 'src1') GROUP BY 1")
def _(spark, d):
    return load(spark, d, "documents").where("source in ('src0', 'src1')").groupBy("lang").pivot("source", ["src0", "src1"]).agg(F.count(F.lit(1))).na.fill(0)


@query("op_unpivot", "SELECT p_partkey, 'p_size' AS feature, CAST(p_size AS DOUBLE) AS amount FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part")
def _(spark, d):
    rows = load(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice")
    return rows.unpivot("p_partkey", ["p_size", "p_retailprice"], "feature", "amount")


@query("op_win_rank", "SELECT o_orderkey, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC) AS INTEGER) AS place FROM orders")
def _(spark, d):
    return load(spark, d, "orders").select("o_orderkey", F.rank().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"))).alias("place"))


@query("op_win_frames", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 2) AS running, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS before FROM orders")
def _(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return load(spark, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w.rowsBetween(Window.unboundedPreceding, 0)), 2).alias("running"), F.lag("o_orderkey").over(w).alias("before"))


@query("op_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def _(spark, d):
    return load(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("op_set", "SELECT n_nationkey AS k FROM nation UNION SELECT c_nationkey FROM customer EXCEPT SELECT s_nationkey FROM supplier")
def _(spark, d):
    a, b, c = (load(spark, d, t).select(F.col(k).alias("k")) for t, k in (("nation", "n_nationkey"), ("customer", "c_nationkey"), ("supplier", "s_nationkey")))
    return a.union(b).distinct().exceptAll(c.distinct())


@query("op_str", "SELECT p_partkey, lower(p_name) AS low, length(p_name) AS chars, replace(p_type, ' ', '_') AS kind, levenshtein(p_name, p_type) AS apart FROM part")
def _(spark, d):
    return load(spark, d, "part").select("p_partkey", F.lower("p_name").alias("low"), F.length("p_name").cast("long").alias("chars"), F.replace(F.col("p_type"), F.lit(" "), F.lit("_")).alias("kind"), F.levenshtein("p_name", "p_type").cast("long").alias("apart"))


@query("op_date", "SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q, count(*) AS n FROM orders GROUP BY 1, 2")
def _(spark, d):
    return load(spark, d, "orders").groupBy(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q")).agg(F.count(F.lit(1)).alias("n"))


@query("op_math", "SELECT event_id, round(ln(1 + value), 6) AS logged, round(sqrt(value), 6) AS root, greatest(value, 50) AS least_50 FROM events")
def _(spark, d):
    return load(spark, d, "events").select("event_id", F.round(F.log1p("value"), 6).alias("logged"), F.round(F.sqrt("value"), 6).alias("root"), F.greatest("value", F.lit(50.0)).alias("least_50"))


@query("op_array", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def _(spark, d):
    return load(spark, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))


@query("op_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k FROM events")
def _(spark, d):
    return load(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("op_subquery", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.9 FROM orders)")
def _(spark, d):
    load(spark, d, "orders").createOrReplaceTempView("v_orders")
    return spark.sql("SELECT o_orderkey FROM v_orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.9 FROM v_orders)")


@query("op_cte", "WITH RECURSIVE s(i, v) AS (SELECT 1, 1 UNION ALL SELECT i + 1, v * 2 FROM s WHERE i < 10) SELECT i, v FROM s")
def _(spark, d):
    return spark.sql("WITH RECURSIVE s(i, v) AS (SELECT 1, 1 UNION ALL SELECT i + 1, v * 2 FROM s WHERE i < 10) SELECT i, v FROM s")


@query("op_entropy", "WITH c AS (SELECT lang, count(*) / sum(count(*)) OVER () AS p FROM documents GROUP BY 1) SELECT round(-sum(p * ln(p)), 6) AS entropy, round(1 - sum(p * p), 6) AS gini FROM c")
def _(spark, d):
    c = load(spark, d, "documents").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))
    p = F.col("n") / F.sum("n").over(Window.partitionBy())
    return c.select(p.alias("p")).agg(F.round(-F.sum(F.col("p") * F.log("p")), 6).alias("entropy"), F.round(1 - F.sum(F.col("p") * F.col("p")), 6).alias("gini"))


@query("op_sql_functions", "SELECT o_custkey, round(CASE WHEN n > 0 THEN m / (1 + exp(-(n - 20.0) / 10.0)) + g * (1 - 1 / (1 + exp(-(n - 20.0) / 10.0))) ELSE g END, 4) AS encoded FROM (SELECT o_custkey, count(*) AS n, avg(o_totalprice) AS m FROM orders GROUP BY 1) s CROSS JOIN (SELECT avg(o_totalprice) AS g FROM orders) t")
def _(spark, d):
    register(spark)
    load(spark, d, "orders").createOrReplaceTempView("v_orders")
    stats = "SELECT o_custkey, count(*) AS n, avg(o_totalprice) AS m FROM v_orders GROUP BY o_custkey"
    rows = spark.sql(f"SELECT o_custkey, smooth_encode(n, m, g, 20D, 10D) AS e FROM ({stats}) CROSS JOIN (SELECT avg(o_totalprice) AS g FROM v_orders)")
    return rows.select("o_custkey", F.round("e", 4).alias("encoded"))


@query("op_join_interval", "SELECT count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey AND l_shipdate >= o_orderdate AND l_shipdate < o_orderdate + INTERVAL 30 DAY")
def _(spark, d):
    near = (F.col("l_shipdate") >= F.col("o_orderdate")) & (F.col("l_shipdate") < F.col("o_orderdate") + F.expr("INTERVAL 30 DAY"))
    return load(spark, d, "orders").join(load(spark, d, "lineitem"), (F.col("l_orderkey") == F.col("o_orderkey")) & near).agg(F.count(F.lit(1)).alias("n"))


@query("op_join_nullsafe", "SELECT count(*) AS n FROM (VALUES (1), (NULL), (2)) a(x) JOIN (VALUES (1), (NULL)) b(y) ON x IS NOT DISTINCT FROM y")
def _(spark, d):
    a, b = spark.createDataFrame([(1,), (None,), (2,)], "x int"), spark.createDataFrame([(1,), (None,)], "y int")
    return a.join(b, F.col("x").eqNullSafe(F.col("y"))).agg(F.count(F.lit(1)).alias("n"))


@query("op_quantile", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS mid, round(quantile_cont(value, 0.9), 6) AS high FROM events GROUP BY 1")
def _(spark, d):
    return load(spark, d, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("mid"), F.round(F.percentile("value", 0.9), 6).alias("high"))


@query("op_map", "SELECT n_regionkey, count(*) AS entries FROM nation GROUP BY 1")
def _(spark, d):
    m = load(spark, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m"))
    return m.select("n_regionkey", F.size(F.transform_values("m", lambda k, v: F.lower(v))).cast("long").alias("entries"))


@query("op_array_nested", "SELECT conv_id, count(*) AS turns, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY 1")
def _(spark, d):
    rows = load(spark, d, "conversations").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role"))).alias("t"))
    return rows.select("conv_id", F.size("t").cast("long").alias("turns"), F.array_join(F.transform("t", lambda x: x["role"]), ">").alias("roles"))


@query("op_variant", "SELECT CAST(json_extract(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    return load(spark, d, "events").groupBy(F.variant_get(F.parse_json("props"), "$.k", "int").alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("op_win_share", "SELECT o_orderkey, CAST(ntile(4) OVER (ORDER BY o_orderkey) AS INTEGER) AS quarter, round(percent_rank() OVER (PARTITION BY o_orderstatus ORDER BY o_orderkey), 6) AS place FROM orders WHERE o_orderkey < 500")
def _(spark, d):
    rows = load(spark, d, "orders").where("o_orderkey < 500")
    return rows.select("o_orderkey", F.ntile(4).over(Window.orderBy("o_orderkey")).alias("quarter"), F.round(F.percent_rank().over(Window.partitionBy("o_orderstatus").orderBy("o_orderkey")), 6).alias("place"))


@query("op_approx")
def _(spark, d):
    return load(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("mid"))


@query("op_udtf")
def _(spark, d):
    from pyspark.sql.functions import udtf

    @udtf(returnType="gram: string")
    class WordGrams:
        """Runs of n words of a text."""

        def eval(self, text: str, n: int):
            words = (text or "").split()
            for i in range(len(words) - n + 1):
                yield (" ".join(words[i : i + n]),)

    spark.udtf.register("word_grams", WordGrams)
    load(spark, d, "benchmark").createOrReplaceTempView("v_benchmark")
    return spark.sql("SELECT item_id, count(*) AS grams FROM v_benchmark, LATERAL word_grams(text, 3) GROUP BY item_id")


@query("op_sink_roundtrip", "SELECT l_returnflag, count(*) AS n, sum(l_linenumber)::BIGINT AS lines FROM lineitem GROUP BY 1")
def _(spark, d):
    import tempfile
    import uuid

    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir") or tempfile.gettempdir()
    path = f"{base.rstrip('/')}/sink-{uuid.uuid4().hex}"
    load(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_returnflag").write.partitionBy("l_returnflag").parquet(path)
    back = spark.read.schema("l_orderkey bigint, l_linenumber int, l_returnflag string").parquet(path)
    return back.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.sum("l_linenumber").alias("lines"))
