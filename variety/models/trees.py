"""Classification trees over binned columns, and what reweights or averages them: for samples that fit one worker."""

from __future__ import annotations

import numpy as np

from .boosting import Tree, quantile_cuts, to_bins

N_BINS = 32


def purity(sums: np.ndarray) -> np.ndarray:
    """Squared class weights over their total; the total less this is the weighted Gini impurity."""
    return (sums * sums).sum(axis=-1) / np.maximum(sums.sum(axis=-1), 1e-300)


def class_sums(bins: np.ndarray, codes: np.ndarray, w: np.ndarray, k: int) -> np.ndarray:
    """Weights by column, bin and class."""
    d = bins.shape[1]
    flat = (bins + np.arange(d) * N_BINS) * k + codes[:, None]
    return np.bincount(flat.ravel(), np.repeat(w, d), d * N_BINS * k).reshape(d, N_BINS, k)


def grow_tree(bins: np.ndarray, codes: np.ndarray, w: np.ndarray, k: int, depth: int, min_split: int = 2, min_gain: float = 0.0, columns=None) -> Tree:
    """A tree of Gini splits; a leaf's value is the number of its heaviest class. ``columns()`` names the columns that one split may use."""
    tree, todo = Tree(), [(0, np.flatnonzero(w > 0), 0)]
    while todo:
        node, rows, level = todo.pop()
        total = np.bincount(codes[rows], w[rows], k)
        tree.nodes[node] = (-1, float(total.argmax()), -1, -1)
        if level >= depth or len(rows) < min_split or np.count_nonzero(total) < 2:
            continue
        some = np.sort(columns()) if columns else np.arange(bins.shape[1])
        left = np.cumsum(class_sums(bins[np.ix_(rows, some)] if columns else bins[rows], codes[rows], w[rows], k), axis=1)
        right = np.maximum(total - left, 0.0)
        gain = (purity(left) + purity(right) - purity(total)) / total.sum()
        least = 1e-12 * total.sum()
        gain[(left.sum(axis=-1) <= least) | (right.sum(axis=-1) <= least)] = -np.inf
        i, b = np.unravel_index(int(gain.argmax()), gain.shape)
        if not gain[i, b] > max(min_gain, 1e-12):
            continue
        j = some[i]
        goes = bins[rows, j] <= b
        at = len(tree.nodes)
        tree.nodes[node] = (int(j), int(b), at, at + 1)
        tree.nodes += [(-1, 0.0, -1, -1)] * 2
        todo += [(at, rows[goes], level + 1), (at + 1, rows[~goes], level + 1)]
    return tree


def voted(trees: list[Tree], says: list[float], cuts: list[np.ndarray], classes: np.ndarray):
    """A function that gives the class with the largest summed say; ties go to the smaller class."""

    def predict(z):
        bins = to_bins(np.asarray(z, float), cuts)
        votes = np.zeros((len(bins), len(classes)))
        for tree, say in zip(trees, says, strict=True):
            votes[np.arange(len(bins)), tree.values(bins).astype(int)] += say
        return classes[votes.argmax(axis=1)]

    predict.trees, predict.says = trees, says
    return predict


def _prepared(x, y):
    classes, codes = np.unique(y, return_inverse=True)
    cuts = quantile_cuts(x, N_BINS)
    return classes, codes, cuts, to_bins(x, cuts)


def fit_cart(x, y, depth=5, min_split=2, min_gain=0.0):
    classes, codes, cuts, bins = _prepared(x, y)
    return voted([grow_tree(bins, codes, np.ones(len(y)), len(classes), depth, min_split, min_gain)], [1.0], cuts, classes)


def fit_forest(x, y, trees=20, depth=5, seed=42):
    """Trees on bootstrap weights; each split sees the square root of the columns, rounded up."""
    classes, codes, cuts, bins = _prepared(x, y)
    rng, (n, d) = np.random.default_rng(seed), x.shape
    some = int(np.ceil(np.sqrt(d)))
    grown = [grow_tree(bins, codes, np.bincount(rng.integers(0, n, n), minlength=n).astype(float), len(classes), depth, columns=lambda: rng.choice(d, some, replace=False)) for _ in range(trees)]
    return voted(grown, [1.0] * trees, cuts, classes)


def fit_adaboost(x, y, n=10, lr=1.0, depth=1):
    """Multi-class weight form, as the distributed one: rows that a round misses weigh more in the next."""
    classes, codes, cuts, bins = _prepared(x, y)
    k = len(classes)
    w, trees, says = np.full(len(y), 1.0 / len(y)), [], []
    for _ in range(n):
        tree = grow_tree(bins, codes, w, k, depth)
        miss = tree.values(bins).astype(int) != codes
        error = float(w[miss].sum() / w.sum())
        if error >= 1 - 1 / k:
            break
        error = max(error, 1e-10)
        trees.append(tree)
        says.append(lr * (np.log((1 - error) / error) + np.log(k - 1)))
        if not miss.any():
            break
        w = w * np.exp(says[-1] * miss)
        w /= w.sum()
    return voted(trees, says, cuts, classes)
