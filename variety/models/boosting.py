"""Histogram boosting, leaf-wise: bins once, then histograms of gradients for each split.

Rows stay where they are. Each round's tree grows by the best leaves, a few at a time; one job
sums histograms over all partitions for the new leaves, and the sibling's is the parent's less the child's.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.dense import matrix
from ..sources.tables import drop_written, written


def soft(g, a):
    return np.sign(g) * np.maximum(np.abs(g) - a, 0.0)


def leaf_value(g, h, l1, l2):
    return -soft(g, l1) / (h + l2)


def best_split(hist: np.ndarray, l1: float, l2: float) -> tuple[float, int, int]:
    """(gain, feature, bin) of the best cut of a d by bins by 2 histogram; rows with a bin at or below go left."""
    left = np.cumsum(hist, axis=1)
    total = left[:, -1:, :]
    right = total - left
    score = lambda s: soft(s[..., 0], l1) ** 2 / (s[..., 1] + l2)
    gain = 0.5 * (score(left) + score(right) - score(total))
    gain[(left[..., 1] < 1e-6) | (right[..., 1] < 1e-6)] = -np.inf
    gain[:, -1] = -np.inf
    j, b = np.unravel_index(int(gain.argmax()), gain.shape)
    return float(gain[j, b]), int(j), int(b)


@dataclass
class Tree:
    """Nodes as (feature, bin, left, right); a leaf has feature -1 and its value in the place of the bin."""

    nodes: list = field(default_factory=lambda: [(-1, 0.0, -1, -1)])

    def leaves_of(self, bins: np.ndarray) -> np.ndarray:
        at = np.zeros(len(bins), np.int64)
        feature = np.array([n[0] for n in self.nodes])
        cut = np.array([n[1] for n in self.nodes], float)
        left, right = np.array([n[2] for n in self.nodes]), np.array([n[3] for n in self.nodes])
        while True:
            inner = np.flatnonzero(feature[at] >= 0)
            if not len(inner):
                return at
            node = at[inner]
            at[inner] = np.where(bins[inner, feature[node]] <= cut[node], left[node], right[node])

    def values(self, bins: np.ndarray) -> np.ndarray:
        return np.array([n[1] if n[0] < 0 else 0.0 for n in self.nodes])[self.leaves_of(bins)]


def grow(histogram, leaves: int, depth: int, l1: float, l2: float, lr: float, batch: int = 4) -> Tree:
    """A tree of at most ``leaves`` leaves. ``histogram(tree, nodes)`` sums over all rows for the given leaves."""
    tree = Tree()
    hists = {0: histogram(tree, [0])[0]}
    levels, ends, cuts = {0: 0}, 1, {}
    while ends < leaves:
        cuts = {n: cuts.get(n) or best_split(h, l1, l2) for n, h in hists.items() if levels[n] < depth}
        options = sorted(((*cut, n) for n, cut in cuts.items()), reverse=True)
        options = [o for o in options if o[0] > 1e-9][: min(batch, leaves - ends)]
        if not options:
            break
        small = []
        for _, j, b, n in options:
            tree.nodes[n] = (j, b, len(tree.nodes), len(tree.nodes) + 1)
            tree.nodes += [(-1, 0.0, -1, -1)] * 2
            levels[tree.nodes[n][2]] = levels[tree.nodes[n][3]] = levels[n] + 1
            small.append(tree.nodes[n][2])
            ends += 1
        for (_, _, _, n), left, h in zip(options, small, histogram(tree, small), strict=True):
            hists[left], hists[left + 1] = h, hists.pop(n) - h
    for n, h in hists.items():
        g, s = h[0].sum(axis=0)
        tree.nodes[n] = (-1, float(lr * leaf_value(g, s, l1, l2)), -1, -1)
    return tree


def sums(bins: np.ndarray, grad: np.ndarray, hess: np.ndarray, n_bins: int) -> np.ndarray:
    d = bins.shape[1]
    flat = (bins + np.arange(d) * n_bins).ravel()
    out = np.empty((d * n_bins, 2))
    out[:, 0] = np.bincount(flat, np.repeat(grad, d), d * n_bins)
    out[:, 1] = np.bincount(flat, np.repeat(hess, d), d * n_bins)
    return out.reshape(d, n_bins, 2)


def gradients(loss: str, y, score):
    if loss == "squared":
        return score - y, np.ones_like(score)
    p = 1 / (1 + np.exp(-np.clip(score, -35, 35)))
    return p - y, np.maximum(p * (1 - p), 1e-9)


def quantile_cuts(x: np.ndarray, n_bins: int) -> list[np.ndarray]:
    return [np.unique(np.quantile(x[:, j], np.linspace(0, 1, n_bins + 1)[1:-1])) for j in range(x.shape[1])]


def to_bins(x: np.ndarray, cuts: list[np.ndarray]) -> np.ndarray:
    return np.stack([np.searchsorted(c, x[:, j], "left") for j, c in enumerate(cuts)], axis=1) if len(x) else np.zeros((0, len(cuts)), np.int64)


def fit_boost_numpy(x, y, rounds=50, lr=0.1, leaves=31, depth=6, l1=0.0, l2=1.0, n_bins=64, loss="logistic", valid=None, patience=20):
    """The same core on arrays; the reference for the distributed one. Returns a scoring function."""
    cuts = quantile_cuts(x, n_bins)
    bins, trees = to_bins(x, cuts), []
    base = float(y.mean()) if loss == "squared" else 0.0
    score = np.full(len(y), base)
    best, stale, kept, held = np.inf, 0, 0, None if valid is None else (to_bins(valid[0], cuts), valid[1], np.full(len(valid[1]), base))
    for _ in range(rounds):
        g, h = gradients(loss, y, score)
        rows = {0: np.arange(len(y))}  # of each leaf

        def histogram(tree, nodes, g=g, h=h, rows=rows):
            for n in [n for n in rows if tree.nodes[n][0] >= 0]:
                j, b, left, right = tree.nodes[n]
                here = rows.pop(n)
                low = bins[here, j] <= b
                rows[left], rows[right] = here[low], here[~low]
            return [sums(bins[rows[n]], g[rows[n]], h[rows[n]], n_bins) for n in nodes]

        tree = grow(histogram, leaves, depth, l1, l2, lr)
        trees.append(tree)
        for n, here in rows.items():
            score[here] += tree.nodes[n][1]
        if held:
            held[2][...] += tree.values(held[0])
            error = float(((held[2] > 0) != (held[1] > 0.5)).mean())
            if error < best:
                best, stale, kept = error, 0, len(trees)
            else:
                stale += 1
            if stale >= patience:
                break
    trees = trees[:kept] if held else trees

    def predict(z):
        b = to_bins(np.asarray(z, float), cuts)
        return base + sum((t.values(b) for t in trees), np.zeros(len(b)))

    predict.trees = trees
    return predict


@dataclass
class BoostModel:
    cuts: list[np.ndarray]
    trees: list[list[Tree]]  # one list a class; one alone for two classes and for regression
    base: list[float]
    loss: str
    errors: list[float] = field(default_factory=list)

    def transform(self, df: DataFrame, features: str = "features", to: str = "prediction") -> DataFrame:
        cuts, trees, base, loss = self.cuts, self.trees, self.base, self.loss

        def score(frames):
            for x in frames:
                if not len(x):
                    yield pd.Series([], dtype=float)
                    continue
                bins = to_bins(matrix(x), cuts)
                s = np.stack([b + sum((t.values(bins) for t in ts), np.zeros(len(bins))) for b, ts in zip(base, trees, strict=True)], axis=1)
                yield pd.Series(s[:, 0] if loss == "squared" else s.argmax(axis=1).astype(float) if s.shape[1] > 1 else (s[:, 0] > 0).astype(float))

        from collections.abc import Iterator

        score.__annotations__ = {"frames": Iterator[pd.Series], "return": Iterator[pd.Series]}
        return df.withColumn(to, F.pandas_udf(score, "double")(F.col(features)))


def softmax(scores: np.ndarray) -> np.ndarray:
    e = np.exp(scores - scores.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def class_gradients(loss: str, y: np.ndarray, scores: np.ndarray, c: int):
    """Of one column of scores: of all classes at once under softmax, of the only one otherwise."""
    if scores.shape[1] == 1:
        return gradients(loss, y, scores[:, 0])
    p = softmax(scores)[:, c]
    return p - (y == c), np.maximum(2 * p * (1 - p), 1e-9)


#: Beyond this many tasks, or this many bytes of all tasks' histograms, they are summed in the cluster before the driver has them.
MANY_TASKS, SENT_BYTES = 64, 4 << 20
#: Classes whose jobs run beside each other, so that the driver has the histograms of no more at once.
SIDE_BY_SIDE = 2
#: A group that sums histograms there has at most about so many bytes of them.
GROUP_BYTES = 16 << 20


def fit_boost(df: DataFrame, features: str = "features", label: str = "label", task: str = "binary", rounds: int = 20, lr: float = 0.3, leaves: int = 31, depth: int = 6, l1: float = 0.0, l2: float = 1.0, n_bins: int = 64, classes: int = 2, patience: int = 20, valid: str | None = None, sample: int = 20_000, batch: int = 4) -> BoostModel:
    """Boosting over a DataFrame of array features; several classes share a softmax, one tree a class and round.

    Cuts come from at most ``sample`` rows. Rows are binned once, to bytes, and written to the shared folder beside their scores; a
    round adds its trees' values to the scores of the round before and writes them anew, so that no plan holds another round's. Up to ``batch`` leaves are split by a job; as many as
    ``leaves`` grow a tree level by level. Each job sums one d by bins histogram a leaf. With a ``valid`` column
    (boolean) training stops after ``patience`` rounds without a lower error there.
    """
    rows = df.select(features, F.col(label).cast("double").alias("y"), (F.col(valid) if valid else F.lit(False)).alias("v"))
    head = rows.orderBy(F.xxhash64(features)).limit(sample).select(features).toArrow().column(0).combine_chunks()
    cuts = quantile_cuts(head.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(head), -1), n_bins) if len(head) else []
    del head  # else the driver holds it in every round
    d = len(cuts)
    loss = "squared" if task == "regression" else "logistic"
    k = classes if task == "multiclass" else 1
    base = [float(rows.where("not v").agg(F.avg("y")).first()[0] or 0.0)] if loss == "squared" else [0.0] * k
    model = BoostModel(cuts, [[] for _ in range(k)], base, loss)
    best, stale, kept = np.inf, 0, 0
    stored = "b binary, y double, v boolean, s binary"

    def binned(frames):
        for f in frames:
            if len(f):
                start = np.array(base).tobytes()
                yield pd.DataFrame({"b": [r.tobytes() for r in to_bins(matrix(f[features]), cuts).astype(np.uint8)], "y": f["y"], "v": f["v"], "s": [start] * len(f)})

    def unpack(f):
        return np.frombuffer(b"".join(f["b"]), np.uint8).reshape(len(f), d).astype(np.int64), np.frombuffer(b"".join(f["s"])).reshape(len(f), k)

    data = written(rows.mapInPandas(binned, stored), "binned")
    tasks = data.rdd.getNumPartitions()

    def add(f):
        return f[:1].assign(h=[sum(np.frombuffer(h) for h in f["h"]).tobytes()])

    for _ in range(rounds):

        def of_class(c, data=data):
            def histogram(tree, nodes):
                size = d * n_bins * 2
                blocks = max(1, min(d, -(-tasks * size * 8 // GROUP_BYTES)))

                def partial(frames):
                    out = {n: np.zeros((d, n_bins, 2)) for n in nodes}
                    for f in frames:
                        if not len(f):
                            continue
                        b, s = unpack(f)
                        g, h = class_gradients(loss, f["y"].to_numpy(), s, c)
                        at = tree.leaves_of(b)
                        for n in nodes:
                            here = at == n
                            out[n] += sums(b[here], g[here], h[here], n_bins)
                    for n, v in out.items():
                        yield pd.DataFrame({"node": n, "j": range(blocks), "h": [x.tobytes() for x in np.array_split(v.ravel(), blocks)]})

                parts = data.where("not v").mapInPandas(partial, "node int, j int, h binary")
                if tasks > MANY_TASKS or tasks * len(nodes) * size * 8 > SENT_BYTES:
                    parts = parts.groupBy("node", "j").applyInPandas(add, "node int, j int, h binary")
                total = {n: np.zeros(size) for n in nodes}
                for got in parts.collect():
                    np.array_split(total[got["node"]], blocks)[got["j"]][...] += np.frombuffer(got["h"])
                return [total[n].reshape(d, n_bins, 2) for n in nodes]

            return grow(histogram, leaves, depth, l1, l2, lr, batch)

        with ThreadPoolExecutor(min(k, SIDE_BY_SIDE)) as pool:
            made = list(pool.map(of_class, range(k)))
        for c, tree in enumerate(made):
            model.trees[c].append(tree)

        def rescored(frames, made=made):
            for f in frames:
                if len(f):
                    b, s = unpack(f)
                    s = s + np.stack([t.values(b) for t in made], axis=1)
                    yield f.assign(s=[r.tobytes() for r in s])

        before, data = data, written(data.mapInPandas(rescored, stored), "scored")
        drop_written(before)
        if valid:

            def errors(frames):
                bad = n = 0
                for f in frames:
                    if len(f):
                        _, s = unpack(f)
                        p = s.argmax(axis=1) if k > 1 else s[:, 0] > 0
                        bad, n = bad + int((p != f["y"].to_numpy()).sum()), n + len(f)
                yield pd.DataFrame({"bad": [bad], "n": [n]})

            e = data.where("v").mapInPandas(errors, "bad long, n long").agg(F.sum("bad"), F.sum("n")).first()
            model.errors.append(e[0] / max(e[1] or 0, 1))
            if model.errors[-1] < best:
                best, stale, kept = model.errors[-1], 0, len(model.errors)
            else:
                stale += 1
        if valid and stale >= patience:
            break
    if valid:
        model.trees = [t[:kept] for t in model.trees]
    drop_written(data)
    return model
