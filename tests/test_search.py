"""Search strategies: counts, invariants, agreement of executors with brute force."""

import math

import numpy as np
import pytest

from variety.hpo import search as H
from variety.hpo.space import MLP_GENES, REPORTED_MLP, SVM_GRID, Param, Space
from variety.models import learners as L
from variety.models.boosting import fit_boost, fit_boost_numpy

BOWL = Space("bowl", (Param("x", "real", -3.0, 3.0), Param("y", "real", -3.0, 3.0)))


def bowl(thetas):
    return [-((t["x"] - 1) ** 2 + (t["y"] + 0.5) ** 2) for t in thetas]


def test_grid_counts():
    grid = SVM_GRID.grid()
    assert len(grid) == 366 and len({str(t) for t in grid}) == 366
    assert all("degree" not in t for t in grid if t["kernel"] == "rbf") and all("gamma" not in t for t in grid if t["kernel"] == "linear")
    assert sum(REPORTED_MLP["layers"]) == 1408


def test_weights_example():
    assert [round(w, 6) for w in H.update_weights([0.5, 0.5], [8, 2], 20, 0.1, 0.0)] == [0.515789, 0.484211]


def test_acceptance():
    assert H.accept(0.0, 1.0, 0.999) and H.accept(-1, 1.0, 0.999)
    assert H.accept(0.02, 0.01, math.exp(-2) - 1e-9) and not H.accept(0.02, 0.01, math.exp(-2) + 1e-9)


@pytest.mark.parametrize("strategy", [H.genetic, H.adaptive_genetic, H.annealing, H.tpe, H.random_search])
def test_same_run_twice(strategy):
    a, b = strategy(BOWL, bowl), strategy(BOWL, bowl)
    assert [r["theta"] for r in a.ledger] == [r["theta"] for r in b.ledger] and a.score == max(r["score"] for r in a.ledger)


def test_elites_never_get_worse():
    r = H.adaptive_genetic(BOWL, bowl)
    best = [max(x["score"] for x in r.ledger if x["step"] == g) for g in range(15)]
    assert best == sorted(best) and r.trainings <= 272


def test_repair_keeps_conditions():
    for i in range(50):
        t = SVM_GRID.draw("r", i)
        assert ("degree" in t) == (t["kernel"] == "poly") and ("gamma" in t) == (t["kernel"] != "linear")
    assert set(MLP_GENES.draw("m", 1)) == {"layers", "dropout", "lr", "activation", "batch"}


def test_random_features_agree_with_the_kernel():
    from variety.models.registry import fourier_map, polynomial_map

    x = np.random.default_rng(1).normal(size=(40, 6))
    z = fourier_map(6, 20_000, 0.1)(x)
    assert np.abs(z @ z.T - L.kernel(x, x, "rbf", 0.1)).max() < 0.06
    p = polynomial_map(6, 0.5, 3, 0.1)(x)
    assert np.allclose(p @ p.T, L.kernel(x, x, "poly", 0.5, 3, 0.1))


def test_boosting_over_partitions_is_boosting(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(400, 5))
    y = (x[:, 0] * x[:, 1] > 0).astype(float)
    rows = spark.createDataFrame([(v.tolist(), float(t)) for v, t in zip(x, y, strict=True)], "features array<double>, label double").repartition(3)
    model = fit_boost(rows, rounds=4, leaves=8, n_bins=32)
    one = fit_boost_numpy(x, y, rounds=4, lr=0.3, leaves=8, depth=6, n_bins=32)
    got = {tuple(r["features"]): r["prediction"] for r in model.transform(rows).collect()}
    same = np.mean([got[tuple(v)] == float(s > 0) for v, s in zip(x, one(x), strict=True)])
    assert same > 0.99


def test_early_stop():
    rng = np.random.default_rng(3)
    x, y = rng.normal(size=(200, 3)), rng.integers(0, 2, 200).astype(float)
    model = fit_boost_numpy(x[:100], y[:100], rounds=200, valid=(x[100:], y[100:]), patience=5)
    assert len(model.trees) < 200


def test_packed_trials(spark):
    from variety.hpo.executor import packed

    rng = np.random.default_rng(5)
    x = rng.normal(size=(120, 4))
    rows = spark.createDataFrame([(v.tolist(), float(v[0] > 0), i % 2) for i, v in enumerate(x)], "features array<double>, label double, fold int")
    scores = packed(rows, "logistic")([{"reg": 0.01}, {"reg": 0.001}])
    assert len(scores) == 2 and min(scores) > 0.85


def test_boosting_of_several_classes_and_many_tasks(spark, monkeypatch):
    from variety.models import boosting

    rng = np.random.default_rng(3)
    x = rng.normal(size=(240, 3))
    y = np.digitize(x[:, 0] + x[:, 1], [-0.7, 0.7]).astype(float)
    rows = spark.createDataFrame([(r.tolist(), float(t)) for r, t in zip(x, y, strict=True)], "features array<double>, label double").repartition(4)
    plain = boosting.fit_boost(rows, task="multiclass", classes=3, rounds=3, leaves=6, n_bins=16)
    monkeypatch.setattr(boosting, "MANY_TASKS", 1)
    summed = boosting.fit_boost(rows, task="multiclass", classes=3, rounds=3, leaves=6, n_bins=16)
    told = [[r["prediction"] for r in m.transform(rows).orderBy("features").collect()] for m in (plain, summed)]
    want = [r["label"] for r in rows.orderBy("features").collect()]
    assert told[0] == told[1] and np.mean(np.array(told[0]) == want) > 0.9


def test_plans_of_boosting_do_not_grow_by_the_round(spark, monkeypatch):
    from pyspark.sql.classic.dataframe import DataFrame

    lengths, plain = [], DataFrame.mapInPandas

    def seen(self, *args, **more):
        lengths.append(len(self._jdf.queryExecution().toString()))
        return plain(self, *args, **more)

    monkeypatch.setattr(DataFrame, "mapInPandas", seen)
    rows = spark.range(60).selectExpr("array(id * 1D, id % 7D) as features", "id % 2D as label")
    fit_boost(rows, rounds=8, leaves=2, n_bins=8)
    assert max(lengths[-3:]) < 1.5 * max(lengths[:3])


def test_many_histograms_are_summed_before_the_driver_has_them(spark, monkeypatch):
    from pyspark.sql.classic.dataframe import DataFrame

    from variety.models import boosting

    monkeypatch.setattr(boosting, "SENT_BYTES", 3 * 2 * 16 * 2 * 8, raising=False)
    most, plain = [], DataFrame.collect

    def seen(self):
        got = plain(self)
        if got and "h" in self.columns:
            most.append(sum(len(r["h"]) for r in got))
        return got

    monkeypatch.setattr(DataFrame, "collect", seen)
    rows = spark.range(400).selectExpr("array(id % 20D, id % 7D) as features", "(id % 20) * (id % 7) % 2D as label")
    fit_boost(rows, rounds=2, leaves=16, n_bins=16, batch=16)
    assert max(most) <= 8 * 2 * 16 * 2 * 8  # the new leaves of one level, once and not once a task


@pytest.mark.parametrize("family, params", [("adaboost", {"n": 12, "depth": 2}), ("tree", {"depth": 4}), ("forest", {"trees": 20, "depth": 5})])
def test_trees_of_trials_agree_with_distributed_ones(spark, family, params):
    from variety.models.registry import fit

    rng = np.random.default_rng(11)
    x = rng.normal(size=(600, 5))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.4)).astype(float)
    rows = spark.createDataFrame([(i, v.tolist(), float(t)) for i, (v, t) in enumerate(zip(x, y, strict=True))], "i int, features array<double>, label double")
    model = fit(family, rows.where("i < 400"), params)
    far = np.array([r["prediction"] for r in model.transform(rows.where("i >= 400")).orderBy("i").collect()])
    near = L.fit_predict(family, params, x[:400], y[:400], x[400:])
    assert np.mean(far == near) > 0.85 and abs(L.accuracy(y[400:], near) - L.accuracy(y[400:], far)) < 0.1


def test_boosted_trees_reweight():
    from variety.models.trees import fit_adaboost

    x = np.arange(10, dtype=float)[:, None]
    y = np.array([1, 1, 1, 0, 0, 0, 1, 1, 1, 0], float)
    model = fit_adaboost(x, y, 3)
    # the textbook case of ten points and stumps: errors 0.3, 3 / 14 and 2 / 11, says twice 0.4236, 0.6496, 0.7520
    assert np.allclose(model.says, [0.8473, 1.2993, 1.5041], atol=1e-3) and (model(x) == y).all()


def test_f1_is_of_class_one():
    assert L.f1(np.zeros(3), np.zeros(3)) == 0 and L.f1(np.ones(2), np.ones(2)) == 1


def test_larger_samples_are_fitted_over_the_cluster(spark, monkeypatch):
    from variety.hpo import executor

    monkeypatch.setattr(executor, "PACKED_BYTES", 1000)
    rng = np.random.default_rng(5)
    x = rng.normal(size=(120, 4))
    rows = spark.createDataFrame([(v.tolist(), float(v[0] > 0), i % 2) for i, v in enumerate(x)], "features array<double>, label double, fold int")
    assert min(executor.packed(rows, "logistic")([{"reg": 0.01}])) > 0.85
    assert min(executor.packed(rows, "svm", measure="f1")([{"kernel": "linear", "c": 1.0}])) > 0.85
    assert min(executor.packed(rows, "boost")([{"n": 4, "lr": 0.3, "leaves": 4, "depth": 3}])) > 0.8


def test_draws_follow_the_density():
    from variety.hpo.search import density, sampled
    from variety.hpo.space import Param

    p = Param("lr", "log", 1e-3, 1.0)
    seen = [0.01, 0.02, 0.3]
    rng = np.random.default_rng(1)
    draws = np.log([sampled(p, seen, a, b) for a, b in rng.random((4000, 2))])
    edges = np.linspace(np.log(1e-3), 0, 9)
    share = np.histogram(draws, edges)[0] / len(draws)
    grid = [np.linspace(a, b, 41) for a, b in zip(edges, edges[1:])]
    want = [np.trapezoid([density(p, seen, np.exp(v)) for v in g], g) for g in grid]
    assert abs(sum(want) - 1) < 0.01 and np.abs(share - want).max() < 0.03
    c = Param("kernel", "choice", values=("a", "b"))
    got = [sampled(c, ["a", "a"], w, 0.0) for w in rng.random(4000)]
    assert abs(got.count("a") / 4000 - density(c, ["a", "a"], "a")) < 0.03


def test_the_ablation_cleans_shared_texts_once(spark, small, monkeypatch):
    from variety.operators import text as X
    from variety.queries import QUERIES

    calls, plain = [], X.mask
    monkeypatch.setattr(X, "mask", lambda c: calls.append(1) or plain(c))
    rows = QUERIES["w_reviews_ablation"](spark, small)
    assert rows.count() == 6 and len(calls) == 4  # two fields, then those of the variant that joins them first


def machine_alone(k, y, c, w, passes=60):
    """Coordinate ascent, a row and a cost at a time."""
    s, k, top = 2 * y - 1, k + 1.0, c * w
    a, f = np.zeros(len(y)), np.zeros(len(y))
    for _ in range(passes):
        most = 0.0
        for i in range(len(y)):
            new = min(max(a[i] + (1 - s[i] * f[i]) / k[i, i], 0.0), top[i])
            f += (new - a[i]) * s[i] * k[:, i]
            most, a[i] = max(most, abs(new - a[i])), new
        if most < 1e-4:
            break
    return a * s


@pytest.mark.parametrize("params", [{"kernel": "rbf", "gamma": "scale"}, {"kernel": "poly", "gamma": 0.1, "degree": 3, "coef0": 0.5}])
def test_machines_side_by_side_are_those_alone(params):
    rng = np.random.default_rng(4)
    x, costs = rng.normal(size=(210, 5)), (0.01, 1.0, 20.0)
    y = (x[:, 0] * x[:, 1] + 0.3 * rng.normal(size=210) > 0).astype(float)
    k = L.kernel(x[:150], x[:150], params["kernel"], L.resolve_gamma(x[:150], params["gamma"]), params.get("degree", 3), params.get("coef0", 0.0))
    got = L.fit_kernel_svms(k, y[:150], costs, w=L.balanced(y[:150]))
    want = np.stack([machine_alone(k, y[:150], c, L.balanced(y[:150])) for c in costs], axis=1)
    assert np.abs(got - want).max() < 1e-8
    told = L.predict_svms(params, costs, x[:150], y[:150], x[150:])
    assert all((told[i] == L.fit_predict("svm", params | {"c": c}, x[:150], y[:150], x[150:])).all() for i, c in enumerate(costs))


def test_margin_machines_of_one_kernel_share_a_task(spark, monkeypatch):
    from variety.hpo import executor

    assert executor.fits_a_worker(8000, 64, "svm") and not executor.fits_a_worker(100_000, 64, "svm")
    rng = np.random.default_rng(5)
    x = rng.normal(size=(120, 4))
    rows = spark.createDataFrame([(v.tolist(), float(v[0] > 0), i % 3) for i, v in enumerate(x)], "features array<double>, label double, fold int")
    grid = [{"kernel": "rbf", "c": c, "gamma": g} for g in ("auto", 0.01) for c in (0.1, 1.0, 10.0)] + [{"kernel": "linear", "c": 1.0}]
    scores, folds = executor.packed(rows, "svm", 3)(grid), np.arange(120) % 3
    y = (x[:, 0] > 0).astype(float)
    for theta, score in zip(grid, scores, strict=True):
        alone = [L.accuracy(y[folds == k], L.fit_predict("svm", theta, x[folds != k], y[folds != k], x[folds == k])) for k in range(3)]
        assert score == pytest.approx(np.mean(alone))


def test_polynomials_of_many_monomials_are_sketched():
    from variety.models.registry import polynomial_map

    rng = np.random.default_rng(6)
    x = rng.normal(size=(60, 64)) / 8
    z = polynomial_map(64, 1.0, 4, 0.5)(x)
    assert z.shape == (60, 2048) and np.abs(z @ z.T - L.kernel(x, x, "poly", 1.0, 4, 0.5)).mean() < 0.1
    assert polynomial_map(64, 1.0, 3, 0.0)(x).shape == (60, 2048) and polynomial_map(64, 1.0, 2, 0.1)(x).shape == (60, 2145)


@pytest.mark.parametrize("family, theta", [("svm", {"kernel": "rbf", "c": 1.0, "gamma": "auto"}), ("boost", {"n": 30, "lr": 0.3, "leaves": 4, "depth": 3}), ("forest", {"trees": 9, "depth": 4}), ("mlp", {"layers": (8,), "epochs": 3})])
def test_scores_do_not_depend_on_how_a_sample_travels(spark, monkeypatch, family, theta):
    from variety.hpo import executor

    rng = np.random.default_rng(8)
    x = rng.normal(size=(300, 4))
    rows = spark.createDataFrame([(v.tolist(), float(v[0] * v[1] > 0.2), i % 2) for i, v in enumerate(x)], "features array<double>, label double, fold int").repartition(3).persist()
    sent = executor.packed(rows, family)([theta])
    monkeypatch.setattr(executor, "PACKED_BYTES", 1000)
    assert executor.packed(rows, family)([theta]) == sent


def test_trials_fitted_over_the_cluster(spark):
    from variety.hpo.executor import distributed

    x = np.random.default_rng(5).normal(size=(120, 4))
    rows = spark.createDataFrame([(v.tolist(), float(v[0] > 0), i % 2) for i, v in enumerate(x)], "features array<double>, label double, fold int").coalesce(1)
    assert min(distributed(rows, "logistic")([{"reg": 0.01}])) > 0.85


@pytest.mark.parametrize("kind, coef0", [("rbf", 0.0), ("poly", 0.5)])
def test_kernels_need_not_be_held(monkeypatch, kind, coef0):
    rng = np.random.default_rng(4)
    x, z, costs, args = rng.normal(size=(210, 5)), rng.normal(size=(90, 5)), (0.01, 1.0, 20.0), (kind, 0.2, 3, coef0)
    y = (x[:, 0] * x[:, 1] + 0.3 * rng.normal(size=210) > 0).astype(float)
    whole, parts = L.fit_kernel_svms(L.kernel(x, x, *args), y, costs), L.fit_kernel_svms(L.KernelRows(x, *args), y, costs)
    assert np.abs(whole - parts).max() < 1e-6
    theta = {"kernel": kind, "gamma": 0.2, "degree": 3, "coef0": coef0}
    told = L.predict_svms(theta, costs, x, y, z)
    monkeypatch.setattr(L, "KERNEL_BYTES", 1000)
    assert (L.predict_svms(theta, costs, x, y, z) == told).all()


def test_leaves_are_weighed_once(monkeypatch):
    from variety.models import boosting, trees

    asked, weigh, seen, added = [], boosting.best_split, [], trees.class_sums
    monkeypatch.setattr(boosting, "best_split", lambda *a: asked.append(1) or weigh(*a))
    monkeypatch.setattr(trees, "class_sums", lambda bins, *a: seen.append(bins.shape[1]) or added(bins, *a))
    rng = np.random.default_rng(3)
    x = rng.normal(size=(400, 9))
    y = (x[:, 0] * x[:, 1] > 0).astype(float)
    fit_boost_numpy(x, y, rounds=1, leaves=24, depth=12)
    assert 1 < len(asked) <= 2 * 24
    trees.fit_forest(x, y, 3, 4)
    assert set(seen) == {3}  # only the columns that a split may use


def test_searches_run_beside_each_other(spark, monkeypatch):
    from threading import Barrier

    from variety.queries import workloads

    both, order = Barrier(2), []
    run = lambda f: lambda: order.append(f) or (f == "svm" or both.wait(20) is not None) and f
    monkeypatch.setattr(workloads, "searches", lambda spark, d: {f: run(f) for f in ("svm", "tree", "boost")})
    assert list(workloads.found_by(spark, "", ("svm", "tree", "boost")).values()) == ["svm", "tree", "boost"]
    assert order[-1] == "svm"
