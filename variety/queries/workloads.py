"""The experiments, end to end. Searches train on packed samples; winners are fitted on all training rows."""

from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..hpo import search as H
from ..hpo import space as P
from ..hpo.executor import ledger_frame, packed
from ..models.registry import fit
from ..operators import augment as A
from ..operators import ensemble as E
from ..operators import metrics as M
from ..operators import tabular as T
from ..operators import text as X
from ..plans import workloads as W
from ..sources.tables import drop_written, load, written
from .registry import query


def sample(spark, d, target="y_lin", rho=45, folds=2):
    rows = W.dense(spark, d).where(f"split = 'train' and rho_bucket <= {rho}")
    return rows.select("features", F.col(target).cast("double").alias("label"), (F.col("fold") % folds).alias("fold"))


#: The share of training rows that each experiment samples, in percent.
RHO = {"svm": 8, "logistic": 15, "mlp": 45, "boost": 30, "adaboost": 2, "tree": 2, "forest": 2}
#: Epochs of a network's trial; the winner is trained for longer.
TRIAL_EPOCHS = 5


def searches(spark, d, target="y_lin", grid=P.SVM_GRID, generations=15, population=20, genes=(8, 4), trials=15, steps=15, chains=2):
    """Each family's search by name, with the published spaces and budgets; smaller ones are arguments. ``genes`` are population and generations of the networks."""
    rows = lambda f, folds=2: sample(spark, d, target, RHO[f], folds)
    cooled = lambda f, space: H.annealing(space, packed(rows(f), f), steps=steps, chains=chains)
    return {
        "svm": lambda: H.grid(grid, packed(rows("svm", 3), "svm", 3)),
        "logistic": lambda: H.adaptive_genetic(P.LOGISTIC, packed(rows("logistic"), "logistic", measure="f1"), population=population, generations=generations),
        "mlp": lambda: H.genetic(P.MLP_GENES, packed(rows("mlp"), "mlp", extra={"epochs": TRIAL_EPOCHS}), population=genes[0], generations=genes[1]),
        "boost": lambda: H.tpe(P.LEAFWISE, packed(rows("boost"), "boost"), trials=trials, batch=5),
        "adaboost": lambda: cooled("adaboost", P.ADABOOST),
        "tree": lambda: cooled("tree", P.TREE),
        "forest": lambda: cooled("forest", P.FOREST),
    }


def found_by(spark, d, families):
    """The results of searches by family. Those that go step by step run beside each other, as each has few trials a step; then the grid, which fills all cores alone."""
    runs = searches(spark, d)
    steps = [f for f in families if f != "svm"]
    with ThreadPoolExecutor(max(len(steps), 1)) as pool:
        out = dict(zip(steps, pool.map(inheritable_thread_target(spark)(lambda f: runs[f]()), steps), strict=True))
    return {f: out[f] if f in out else runs[f]() for f in families}


def _ledger(spark, d, family):
    return ledger_frame(spark, searches(spark, d)[family]()).withColumn("rho", F.lit(RHO[family]))


for _name, _family in (("w_dense_svm_grid", "svm"), ("w_dense_lr_aga", "logistic"), ("w_dense_mlp_ga", "mlp"), ("w_dense_boost_tpe", "boost"), ("w_dense_ada_sa", "adaboost"), ("w_dense_tree_sa", "tree"), ("w_dense_forest_sa", "forest")):

    @query(_name)
    def _(spark, d, family=_family):
        return _ledger(spark, d, family)


def _scores(spark, d, families, target, rho=100):
    rows = W.dense(spark, d).withColumn("label", F.col(target).cast("double"))
    out = []
    for f in families:
        model = fit(f, rows.where(f"split = 'train' and rho_bucket <= {rho}"))
        out.append(M.gap(model.transform(rows)).withColumns({"family": F.lit(f), "target": F.lit(target), "rho": F.lit(rho)}))
    got = out[0]
    for o in out[1:]:
        got = got.unionByName(o)
    return got


@query("w_dense_leaderboard")
def _(spark, d):
    families = ("logistic", "svm_linear", "mlp", "gbt", "forest")
    rows = _scores(spark, d, families, "y_lin")
    for target in ("y_xor", "y_noise"):
        rows = rows.unionByName(_scores(spark, d, families, target))
    return rows


@query("w_dense_learning_curve")
def _(spark, d):
    rows = _scores(spark, d, ("logistic", "tree"), "y_lin", 8)
    for rho in (2, 15, 30, 45):
        rows = rows.unionByName(_scores(spark, d, ("logistic", "tree"), "y_lin", rho))
    return rows


@query("w_dense_ensemble")
def _(spark, d):
    """The three families that are best on a fold kept from training, weighted by their accuracy there, fitted on all training rows and voted on the test rows."""
    rows = W.dense(spark, d).withColumn("label", F.col("y_lin").cast("double"))
    train, test = rows.where("split = 'train'"), rows.where("split = 'test'")
    accuracy = {f: M.classification(fit(f, train.where("fold <> 0")).transform(train.where("fold = 0"))).first()["accuracy"] for f in ("logistic", "svm_linear", "tree", "mlp")}
    members = E.top_k(accuracy, 3)
    for f in members:
        test = fit(f, train).transform(test).withColumnRenamed("prediction", f)
    voted = test.withColumn("prediction", E.hard_vote(E.weights({f: accuracy[f] for f in members}), 2).cast("double"))
    return M.confusion(voted, normalized=True)


FIELDS = ["title", "body"]


def _cut_or_extended(rows):
    """Synthetic words: long bodies lose some of their end, all others gain a phrase, drawn by row and copy; half of the rows are also translated there and back."""
    u = uniform("aug", "doc_id", F.col("copy"))
    phrase = X.tokens(A.suffix(F.lit(""), u))
    body = F.when(F.size("body") >= 30, A.truncate(F.col("body"), u)).otherwise(F.concat("body", phrase))
    return rows.withColumn("body", F.when(uniform("trip", "doc_id", F.col("copy")) < 0.5, A.back_translate(body, F.xxhash64("doc_id", "copy"))).otherwise(body))


#: The steps on texts that all variants of the ablation share; what follows them differs.
SHARED_STEPS = X.ReviewPipeline.TEXT_STEPS[:-1]


def _rated(spark, d, label):
    return W.reviews(spark, d).withColumn("label", label).where("label is not null")


def _reviews(spark, d, label, pipeline=None, augment=True, joined=False, width=64, rows=None):
    """Reviews through the ordered pipeline: clean words of each field, synthetic rows for the small classes of training, lemmas, encodings. ``rows`` may be given with their label."""
    pipeline = pipeline or X.ReviewPipeline()
    rows = rows or _rated(spark, d, label)
    if joined:
        rows = rows.withColumns({"title": F.concat_ws(" ", "title", "body"), "body": F.lit("")})
    rows = pipeline.fields(rows, FIELDS)
    if augment:
        rows = written(rows.select("doc_id", "split", "label", *FIELDS), "fields")  # the rows and their children read it
        rows = A.superset(rows, "doc_id", "label", _cut_or_extended)
    return pipeline.encode(rows, FIELDS, X.HashedProjectionEncoder(width))


def _index(column, values):
    return F.create_map(*(F.lit(x) for i, v in enumerate(values) for x in (v, float(i))))[F.col(column)]


TYPES, STARS = ("en", "fr", "de", "es"), (1, 2, 3, 4, 5)


def _kept(spark, frames):
    """The few rows of measures, computed now, so that what was held in memory for them can go."""
    out = [r for f in frames for r in f.collect()]
    return spark.createDataFrame(out, frames[0].schema)


def _two(spark, rows, classes):
    """The two tree ensembles with untuned parameters."""
    rows, out = written(rows.select("split", "label", "features"), "reviews"), []
    for f in ("second_order_boost", "forest"):
        scored = written(fit(f, rows.where("split = 'train'"), None, "multiclass", classes).transform(rows).select("split", "label", "prediction"), "scored")
        test = scored.where("split = 'test'")
        got = M.classification(test).join(M.collapse(test)).join(M.gap(scored)).withColumn("family", F.lit(f))
        out.append(_kept(spark, [got]))
        drop_written(scored)
    drop_written(rows)
    return out[0].unionByName(out[1])


@query("w_reviews_type")
def _(spark, d):
    return _two(spark, _reviews(spark, d, _index("type", TYPES)), len(TYPES))


@query("w_reviews_polarity")
def _(spark, d):
    return _two(spark, _reviews(spark, d, _index("stars", STARS)), len(STARS))


@query("w_reviews_ablation")
def _(spark, d):
    """Five classes: the whole pipeline, then without one part of it, each measured on the same test rows."""
    variants = {
        "whole": {},
        "joined_fields": {"joined": True},
        "not_augmented": {"augment": False},
        "stop_words_kept": {"pipeline": X.ReviewPipeline(("stop",))},
        "negations_removed": {"pipeline": X.ReviewPipeline(protect=())},
        "words_as_they_are": {"pipeline": X.ReviewPipeline(("lemmas", "idioms"))},
    }
    out, label = [], _index("stars", STARS)
    shared = _rated(spark, d, label).select("doc_id", "split", "label", *(X.ReviewPipeline().texts(F.col(f), SHARED_STEPS).alias(f) for f in FIELDS))
    shared = written(shared, "shared")
    for name, change in variants.items():
        if "joined" not in change:  # whose fields are joined before these steps
            before = change.get("pipeline") or X.ReviewPipeline()
            change = change | {"rows": shared, "pipeline": before.leaving(SHARED_STEPS)}
        rows = written(_reviews(spark, d, label, **change).select("split", "label", "features"), "reviews")
        scored = fit("logistic", rows.where("split = 'train'"), None, "multiclass", len(STARS)).transform(rows).select("split", "label", "prediction")
        measures = M.gap(scored).join(M.collapse(scored.where("split = 'test'"))).withColumn("variant", F.lit(name))
        out.append(_kept(spark, [measures]))
        drop_written(rows)
    drop_written(shared)
    got = out[0]
    for o in out[1:]:
        got = got.unionByName(o)
    return got


#: An order's people: the suppliers of its lines, that of its first line, and its parts, in the places of a cast, a director and writers.
PEOPLE = {"cast": "suppliers", "lead": "leads", "crew": "parts"}
BLOCKS = ("numeric", "brands", "categories", "cast", "lead", "crew", "title", "description")


def orders_of(spark, d):
    """The rows that all hybrid features are made of, with the lists of people; made once and written to the shared folder."""
    rows = W.order_rows(spark, d).where("y_rev is not null")
    return written(rows.withColumns({"leads": F.array_compact(F.array("lead_supplier")), "few": F.log1p("n_lines")}), "orders")


def hybrid_features(base, target="y_rev", mode="leave_one_out", blocks=BLOCKS, width=32):
    """Numbers, smoothed categories, reputations of three lists of people, and two texts, side by side in ``features``; only the blocks that are asked for are made.

    Each encoding is made of a few columns of ``base`` and joined by key, so that the plan grows by the block and not by the product of blocks.
    """
    rows, seen, key = base, "split = 'train'", "o_orderkey"
    every = {"numeric": ["few"], "brands": ["hot"], "categories": ["by_customer", "by_nation"], "title": ["e_title"], "description": ["e_description"]}
    if "brands" in blocks:
        vocabulary = sorted(r[0] for r in base.select(F.explode("brands")).distinct().collect())
        rows = rows.withColumn("hot", T.multi_hot("brands", vocabulary))
    if "categories" in blocks:
        for category, name in (("o_custkey", "by_customer"), ("nation", "by_nation")):
            told = T.target_encode(base.select(key, category, target, "split"), category, target, mode, train=seen)
            rows = rows.join(told.select(key, F.col("encoded").alias(name)), key)
    for name, people in PEOPLE.items():
        if name in blocks:
            told = base.select(key, people, F.when(F.expr(seen), F.col(target)).alias("_y"))
            rows = rows.join(T.reputation(told, key, people, "_y", mode, name=name), key)
            every[name] = [f"{name}_reputation", f"{name}_experience"]
    encoder = X.HashedProjectionEncoder(width)
    texts = {"title": F.col("title"), "description": F.concat_ws(" ", "o_orderpriority", "nation", F.array_join("brands", " "))}
    for name, text in texts.items():
        if name in blocks:
            rows = rows.withColumn(f"e_{name}", encoder.encode(X.tokens(F.coalesce(text, F.lit("")))))
    columns = [c for b in blocks for c in every[b]]
    out, _ = T.assemble(rows.select(key, "split", F.col(target).alias("label"), *columns), {b: every[b] for b in blocks})
    return out.select(key, "split", "features", "label")


def _regress(spark, rows, families, name):
    rows, out = written(rows, "hybrid"), []
    for f in families:
        model = fit(f, rows.where("split = 'train'"), {"reg": 0.001} if f == "linear_regression" else None, "regression")
        out.append(M.regression(model.transform(rows), by=("split",)).withColumns({"family": F.lit(f), "variant": F.lit(name)}))
    got = _kept(spark, out)
    drop_written(rows)
    return got


@query("w_hybrid_regress")
def _(spark, d):
    families, base = ("linear_regression", "forest", "second_order_boost"), orders_of(spark, d)
    out = _regress(spark, hybrid_features(base), families, "revenue").unionByName(_regress(spark, hybrid_features(base, "y_noise"), families, "noise"))
    drop_written(base)
    return out


@query("w_hybrid_ablation")
def _(spark, d):
    one, base = ("linear_regression",), orders_of(spark, d)
    rows = _regress(spark, hybrid_features(base), one, "all")
    parts = {"brands": ("brands",), "encodings": ("categories", "cast", "lead", "crew"), "texts": ("title", "description"), "without_texts": BLOCKS[:-2]}
    for name, blocks in parts.items():
        rows = rows.unionByName(_regress(spark, hybrid_features(base, blocks=blocks), one, name))
    rows = rows.unionByName(_regress(spark, hybrid_features(base, "y_noise", "train_mean", ("categories",)), one, "noise_in_sample"))
    drop_written(base)
    return rows


@query("w_cross_domain")
def _(spark, d):
    """The families' places on dense vectors, reviews and hybrid rows; these ask whether an order earns more than the median."""
    families, out = ("logistic", "tree", "forest"), None
    dense = W.dense(spark, d).withColumn("label", F.col("y_lin").cast("double"))
    orders = hybrid_features(orders_of(spark, d))
    middle = orders.where("split = 'train'").agg(F.percentile_approx("label", 0.5)).first()[0]
    orders = orders.withColumn("label", (F.col("label") > middle).cast("double"))
    domains = {"dense": dense, "reviews": _reviews(spark, d, (F.col("type") == "en").cast("double")), "hybrid": orders}
    for name, rows in domains.items():
        rows = written(rows.select("split", "features", "label"), "domain")
        got = _kept(spark, [M.gap(fit(f, rows.where("split = 'train'")).transform(rows)).select(F.lit(name).alias("domain"), F.lit(f).alias("family"), F.col("test_accuracy").alias("score")) for f in families])
        drop_written(rows)
        out = got if out is None else out.unionByName(got)
    return out.withColumn("place", F.rank().over(Window.partitionBy("domain").orderBy(F.desc("score"))))


@query("w_hpo_cost")
def _(spark, d):
    rows = []
    for name, r in found_by(spark, d, RHO).items():
        rows.append((name, r.strategy, RHO[name], len(r.ledger), r.trainings, round(r.score, 4)))
    return spark.createDataFrame(rows, "family string, strategy string, rho int, trials int, trainings int, best double")


@query("w_dense_refit")
def _(spark, d):
    """Each search's best setting, fitted on all training rows and measured on the test rows."""
    rows = W.dense(spark, d).where("split in ('train', 'test')")
    rows = rows.select("features", F.col("y_lin").cast("double").alias("label"), (F.col("split") == "train").cast("int").alias("fold"))
    best = {f: found.best for f, found in found_by(spark, d, ("svm", "logistic", "boost", "adaboost")).items()}
    with ThreadPoolExecutor(len(best)) as pool:
        scores = pool.map(inheritable_thread_target(spark)(lambda f: packed(rows, f, folds=1)([best[f]])[0]), best)
        out = [(f, RHO[f], P.key_of(best[f]), score) for f, score in zip(best, scores, strict=True)]
    return spark.createDataFrame(out, "family string, rho int, theta string, test_accuracy double")
