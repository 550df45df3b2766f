"""Worked examples, invariants and plan shapes."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from variety.operators import augment, dense, ensemble, metrics, sampling, tabular, text


def test_smoothing_limits(spark):
    row = spark.range(1).select(*(F.round(tabular.lam(F.lit(float(n))), 6).alias(f"n{n}") for n in (3, 20, 200))).first()
    assert row["n20"] == 0.5 and row["n3"] == 0.154465 and row["n200"] > 0.9999


def test_unseen_and_training_only(spark):
    rows = spark.createDataFrame([("a", 1.0, "train"), ("a", 3.0, "train"), ("b", 100.0, "test"), (None, 5.0, "train")], "k string, y double, split string")
    got = {r["k"]: r["encoded"] for r in tabular.target_encode(rows, "k", "y", train="split = 'train'").collect()}
    assert got["b"] == 3.0 and got["a"] < 3.0


def test_leave_one_out_of_single_rows(spark):
    rows = spark.createDataFrame([("a", 1.0), ("b", 3.0)], "k string, y double")
    got = {r["k"]: r["encoded"] for r in tabular.target_encode(rows, "k", "y", "leave_one_out").collect()}
    assert got == {"a": 3.0, "b": 1.0}


def test_reputation_example(spark):
    rows = spark.createDataFrame([(1, 6.0, ["a"]), (2, 8.0, ["a"]), (3, 4.0, ["b"]), (4, None, ["a", "b", "z"]), (5, None, []), (6, None, None)], "id int, y double, p array<string>")
    got = {r["id"]: r for r in tabular.reputation(rows, "id", "p", "y").collect()}
    assert round(got[4]["cast_reputation"], 6) == 5.666667 and got[4]["cast_experience"] == 1.0
    assert got[5]["cast_reputation"] == got[6]["cast_reputation"] == 6.0 and got[6]["cast_experience"] == 0.0


def test_reputation_as_of_sees_earlier_days_only(spark):
    rows = spark.createDataFrame([(1, 1.0, ["a"], 1), (2, 3.0, ["a"], 2), (3, 9.0, ["a"], 3), (4, 5.0, ["a"], 3)], "id int, y double, p array<string>, day int")
    got = {r["id"]: r["cast_reputation"] for r in tabular.reputation(rows, "id", "p", "y", "as_of", day="day").collect()}
    assert got == {1: 4.5, 2: 1.0, 3: 2.0, 4: 2.0}


def test_exact_quotas_nest_and_ignore_layout(spark):
    rows = spark.range(4000).select("id", (F.col("id") % 3).alias("label"))
    small = {r["id"] for r in sampling.stratified(rows, "id", "label", 0.08, "exact").collect()}
    large = {r["id"] for r in sampling.stratified(rows.repartition(7), "id", "label", 0.3, "exact").collect()}
    assert small < large
    for c in range(3):
        assert sum(i % 3 == c for i in small) == math.floor(0.08 * len(range(c, 4000, 3)) + 0.5)


def test_metrics_example(spark):
    rows = spark.createDataFrame([(0, 0), (0, 0), (0, 0), (1, 0)], "label int, prediction int")
    got = metrics.classification(rows).first()
    assert (got["accuracy"], got["f1_weighted"], got["f1_macro"]) == (0.75, 0.642857, 0.428571)
    assert metrics.collapse(rows).first()["lost_classes"] == 1
    reg = metrics.regression(spark.createDataFrame([(1.0, 1.0), (2.0, 2.0), (3.0, 5.0)], "label double, prediction double")).first()
    assert (reg["mae"], reg["rmse"], reg["r2"]) == (0.666667, 1.154701, -1.0) and reg["rmse"] >= reg["mae"]


def test_votes_and_ties(spark):
    rows = spark.createDataFrame([(0, 1, 1), (0, 1, 0)], "a int, b int, c int")
    assert [r[0] for r in rows.select(ensemble.hard_vote({"a": 0.9, "b": 0.8, "c": 0.7}, 2)).collect()] == [1, 0]
    assert rows.limit(1).select(ensemble.hard_vote({"a": 1.0, "b": 1.0}, 2)).first()[0] == 0


def test_protected_negation(spark):
    row = spark.createDataFrame([("no fue bueno",)], "t string").select(text.filter_stop(text.tokens(F.col("t"))).alias("a"), text.filter_stop(text.tokens(F.col("t")), protect=()).alias("b")).first()
    assert row["a"] == ["no", "bueno"] and row["b"] == ["bueno"]


def test_repair_twice_is_once():
    assert text.repair_text("estÃ¡ bien") == "está bien" == text.repair_text(text.repair_text("estÃ¡ bien"))


def test_augmentation_touches_small_training_classes_only(spark):
    rows = spark.createDataFrame([(i, "a b c", 0 if i < 40 else 1, "test" if i % 5 == 0 else "train") for i in range(50)], "doc_id int, text string, y int, split string")
    got = augment.superset(rows, "doc_id", "y", lambda g: g).where("origin = 'synthetic'").collect()
    assert got and all(r["y"] == 1 and r["split"] == "train" for r in got)


def test_frozen_map(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(300, 5)) @ rng.normal(size=(5, 5))
    rows = spark.createDataFrame([(v.tolist(),) for v in x], "v array<double>")
    pca = dense.fit_pca(rows, "v", k=3)
    values = np.linalg.eigvalsh(np.cov(x.T))[::-1]
    assert np.allclose(pca.explained, values[:3]) and pca.report()["off_orthonormal"] < 1e-10
    got = np.stack([r["projected"] for r in pca.transform(rows, "v").collect()])
    assert np.allclose(got, x @ pca.components)


def test_scan_reads_only_what_is_asked(spark, small):
    from variety.queries import QUERIES

    plan = QUERIES["tab_target_enc_train"](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "o_orderpriority" not in plan and "CartesianProduct" not in plan


def test_empty_tables(spark):
    rows = spark.createDataFrame([], "id int, label int, prediction int, y double, k string")
    assert metrics.classification(rows).count() == 1
    assert tabular.target_encode(rows, "k", "y").count() == 0
    assert sampling.stratified(rows, "id", "label", 0.5, "exact").count() == 0


def test_stream_results_equal_batch_results(spark):
    from pyspark.sql import functions as F

    from variety.models.registry import fit
    from variety.plans import workloads as W
    from variety.queries import QUERIES
    from variety.sources.tables import load
    from variety.streaming import windows as S

    d = "/root/testdata/sf0.001"
    rows = W.dense(spark, d).withColumn("label", F.col("y_lin").cast("double"))
    batch = fit("discriminant", rows.where("split = 'train'"), None, "binary").transform(rows).select("vec_id", "prediction")
    assert sorted(map(tuple, batch.collect())) == sorted(map(tuple, QUERIES["op_stream_scoring"](spark, d).collect()))
    pairs = S.followed_within(S.stamped(load(spark, d, "events")), "click", "purchase")
    assert sorted(map(tuple, pairs.collect())) == sorted(map(tuple, QUERIES["op_stream_followed"](spark, d).collect()))


def test_sparse_text_round_trip(spark, tmp_path):
    from variety.sources.tables import read_sparse_text, write_sparse_text

    rows = [(1.0, [0.0, 2.5, -1e-7]), (0.0, [0.0, 0.0, 0.0])]
    write_sparse_text(spark.createDataFrame(rows, "label double, features array<double>"), str(tmp_path / "x"))
    assert sorted((r[0], r[1]) for r in read_sparse_text(spark, str(tmp_path / "x"), 3).collect()) == sorted(rows)


def test_fitted_encoders_take_empty_texts(spark):
    from pyspark.sql import functions as F

    from variety.operators import text as X

    rows = spark.createDataFrame([("a b c a b",), ("",), (None,), ("b c d",)], "text string")
    toks = X.tokens(F.coalesce(F.col("text"), F.lit("")))
    for encoder in (X.fit_word2vec(rows, toks, 4, 1), X.fit_tfidf_pca(rows, toks, 2, 16)):
        got = {r["text"]: r["features"] for r in X.encode_fields(rows, ["text"], encoder).collect()}
        assert all(len(v) == encoder.d for v in got.values()) and got[""] == got[None] == [0.0] * encoder.d


def test_appended_stream_rows_are_in_files_and_none_is_late(spark, tmp_path):
    from variety.queries import QUERIES

    schema = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
    for at, day in enumerate(("2024-01-20", "2024-01-01", "2024-01-10")):  # a file a batch, the later ones days late
        rows = spark.range(at * 10, at * 10 + 12).selectExpr("id as event_id", f"timestamp_ntz'{day} 10:00:00' as ts", "1L as user_id", "'click' as event_type", "id * 1D as value", "'{}' as props")
        spark.createDataFrame(rows.collect(), schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
    before = {t.name for t in spark.catalog.listTables()}
    got = QUERIES["op_stream_dedup"](spark, str(tmp_path))
    assert got.first()["n"] == 32
    joined = QUERIES["op_stream_static_join"](spark, str(tmp_path))
    assert joined.first()["n"] == 36
    assert {t.name for t in spark.catalog.listTables()} == before  # no memory table holds the rows


@pytest.mark.parametrize("name, table", [("ens_lift", "lineitem"), ("ens_topk_weights", "lineitem"), ("hpo_aga_weights", "events"), ("hpo_cv_select", "orders"), ("hpo_elitism", "orders"), ("hpo_grid_counts", "orders"), ("hpo_grid_enumerate", "orders"), ("hpo_halving_rungs", "customer"), ("hpo_ledger_cost", "orders"), ("hpo_mutation_multi", "customer"), ("hpo_mutation_reset", "customer"), ("hpo_one_point_crossover", "customer")])
def test_a_given_table_decides_the_rows(spark, small, tmp_path, name, table):
    """On fewer rows of its table a query says something else."""
    from variety.queries import QUERIES

    key = {"lineitem": "l_orderkey", "events": "event_id", "orders": "o_orderkey", "customer": "c_custkey"}[table]
    spark.read.parquet(f"{small}/{table}.parquet").where(f"{key} % 3 = 1").write.parquet(str(tmp_path / f"{table}.parquet"))
    rows = lambda d: sorted(map(repr, QUERIES[name](spark, d).collect()))
    assert rows(small) != rows(str(tmp_path))


def test_steps_on_characters_share_a_worker(spark):
    texts = ["plain", "cafÃ© Ⅻ", "ok 👍️ ❤️", "ﬁne â€œ", "Ã", "x️y", ""]
    rows = spark.createDataFrame([(t,) for t in texts], "t string")
    one_by_one = rows.select(text.demojize(text.nfkc(text.repair(F.col("t")))).alias("t"))
    at_once = rows.select(text.ReviewPipeline(("mask", "idioms")).texts(F.col("t")).alias("t"))
    assert at_once.collect() == one_by_one.collect()
    assert at_once._jdf.queryExecution().executedPlan().toString().count("ArrowEvalPython") == 1
