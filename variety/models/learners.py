"""Small-sample learners in numpy, for trials that fit one worker and as references for the distributed ones."""

from __future__ import annotations

import numpy as np

from .boosting import fit_boost_numpy
from .trees import fit_adaboost, fit_cart, fit_forest

#: Rounds without a lower error after which boosting in a trial stops.
PATIENCE = 20
#: Rows of a kernel that are handled at once.
BLOCK = 64
#: A larger kernel matrix isn't held: its rows are made when they are asked for.
KERNEL_BYTES = 768 << 20


def sigmoid(v):
    return 1.0 / (1.0 + np.exp(-np.clip(v, -35, 35)))


def soft(v, a):
    return np.sign(v) * np.maximum(np.abs(v) - a, 0.0)


def fit_logistic(x, y, reg=0.01, l1_ratio=0.0, iterations=100, w=None):
    """Weights and intercept by proximal gradient steps."""
    n, d = x.shape
    w8 = np.ones(n) if w is None else w
    step = 1.0 / (0.25 * np.linalg.norm(x, 2) ** 2 / n * w8.max() + reg + 1e-9)
    beta, bias = np.zeros(d), 0.0
    for _ in range(int(iterations)):
        g = w8 * (sigmoid(x @ beta + bias) - y) / n
        beta = soft(beta - step * (x.T @ g + reg * (1 - l1_ratio) * beta), step * reg * l1_ratio)
        bias -= step * 4 * g.sum()
    return beta, bias


def fit_hinge(x, y, c=1.0, iterations=300, w=None):
    """A linear margin classifier: squared hinge loss by accelerated gradient steps; labels 0 and 1."""
    n, d = x.shape
    s = 2.0 * y - 1
    w8 = np.ones(n) if w is None else w
    lip = 2 * c * w8.max() * np.linalg.norm(np.c_[x, np.ones(n)], 2) ** 2 + 1
    beta = np.zeros(d + 1)
    ahead, t = beta.copy(), 1.0
    xx = np.c_[x, np.ones(n)]
    for _ in range(iterations):
        slack = np.maximum(0, 1 - s * (xx @ ahead))
        grad = np.append(ahead[:-1], 0.0) - 2 * c * xx.T @ (w8 * s * slack)
        nxt = ahead - grad / lip
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        beta, ahead, t = nxt, nxt + (t - 1) / t2 * (nxt - beta), t2
    return beta[:-1], beta[-1]


def balanced(y):
    classes, n = np.unique(y, return_counts=True)
    return (len(y) / (len(classes) * n))[np.searchsorted(classes, y)]


def kernel(x, z, kind, gamma=1.0, degree=3, coef0=0.0):
    """Products of all pairs, in one array of that size and a block of its rows."""
    out = x @ z.T
    if kind == "linear":
        return out
    own, other = (x * x).sum(1), (z * z).sum(1)
    for at in range(0, len(out), BLOCK):
        part = out[at : at + BLOCK]
        if kind == "poly":
            part *= gamma
            part += coef0
            once = part.copy()
            for _ in range(int(degree) - 1):
                part *= once
        else:
            part *= -2
            part += own[at : at + BLOCK, None] + other
            np.maximum(part, 0, out=part)
            part *= -gamma
            np.exp(part, out=part)
    return out


class KernelRows:
    """A kernel matrix whose parts are made when they are asked for."""

    def __init__(self, x, *args):
        self.x, self.args = x, args

    def __getitem__(self, at):
        rows, columns = at if isinstance(at, tuple) else (at, slice(None))
        return kernel(self.x[rows], self.x[columns], *self.args)


def fit_kernel_svms(k, y, costs, passes=60, w=None):
    """Dual coefficients of kernel machines on one kernel, a column for each cost, by coordinate ascent; the reference for feature maps.

    ``k`` is a matrix or its ``KernelRows``, of which only the rows that moved are made. The machines go over the rows side by side and each stops by itself, with the steps that it takes alone. A step
    is felt in its block of rows at once, and by the other rows when the block is done.
    """
    s = 2.0 * y - 1
    n, left = len(y), np.arange(len(costs))  # machines that still move
    out = np.zeros((n, len(costs)))
    a, f = np.zeros((n, len(costs))), np.zeros((n, len(costs)))
    top = np.outer(np.ones(n) if w is None else w, costs)
    for _ in range(passes):
        most, new, step = np.zeros(len(left)), np.zeros(len(left)), np.zeros(len(left))
        for at in range(0, n, BLOCK):
            here = slice(at, min(at + BLOCK, n))
            own = k[here, here] + 1.0  # the intercept, regularised
            own *= np.outer(s[here], s[here])
            scale = 1 / own.diagonal()
            near, now, most_of = 1 - s[here, None] * f[here], a[here].copy(), top[here]
            near *= scale[:, None]  # the steps that rows ask for
            moving = (np.minimum(np.maximum(now + near, 0.0), most_of) != now).any(axis=1)
            if not moving.any():
                continue
            own *= scale[:, None]
            was, columns, asked, values, tops = now.copy(), list(own.T[:, :, None]), list(near), list(now), list(most_of)
            for i in range(int(moving.argmax()), len(now)):
                value = values[i]
                np.add(value, asked[i], out=new)
                np.maximum(new, 0.0, out=new)
                np.minimum(new, tops[i], out=new)
                np.subtract(new, value, out=step)
                if np.count_nonzero(step):
                    near -= columns[i] * step
                    value[:] = new
            a[here] = now
            now -= was
            most = np.maximum(most, np.abs(now).max(axis=0))
            now *= s[here, None]
            felt = np.flatnonzero(now.any(axis=1))
            few = not isinstance(k, np.ndarray) or len(felt) * 3 < len(now)
            f += (now[felt].T @ k[at + felt] if few else now.T @ k[here]).T
            f += now.sum(axis=0)
        out[:, left] = a
        go = most >= 1e-4
        if not go.any():
            break
        if not go.all():
            left, a, f, top = left[go], a[:, go], f[:, go], top[:, go]
    return out * s[:, None]


def fit_kernel_svm(k, y, c=1.0, passes=60, w=None):
    return fit_kernel_svms(k, y, [c], passes, w)[:, 0]


def predict_svms(params, costs, x, y, z):
    """Predicted classes of ``z``, a row for each cost, by margin machines that share all other parameters and the kernel."""
    kind, w8 = params.get("kernel", "linear"), balanced(y)
    if kind == "linear":
        models = [fit_hinge(x, y, c, w=w8) for c in costs]
        return np.stack([z @ w + b > 0 for w, b in models]).astype(float)
    args = (kind, resolve_gamma(x, params.get("gamma", "scale")), int(params.get("degree", 3)), params.get("coef0", 0.0))
    held = len(x) ** 2 * 8 <= KERNEL_BYTES
    a = fit_kernel_svms(kernel(x, x, *args) if held else KernelRows(x, *args), y, costs, w=w8)
    scores = [kernel(z[i : i + BLOCK], x, *args) @ a + a.sum(axis=0) for i in range(0, len(z), BLOCK)]
    return (np.concatenate(scores) > 0).T.astype(float)


def resolve_gamma(x, rule):
    """``scale`` is 1 / (d * variance of all entries), ``auto`` is 1 / d; a number is itself."""
    return 1.0 / (x.shape[1] * x.var()) if rule == "scale" else 1.0 / x.shape[1] if rule == "auto" else float(rule)


def fit_discriminant(x, y, shrinkage=0.0):
    """(weights d by K, intercepts, classes) from class means and a shrunk pooled covariance."""
    classes = np.unique(y)
    means = np.stack([x[y == c].mean(axis=0) for c in classes])
    centred = x - means[np.searchsorted(classes, y)]
    cov = centred.T @ centred / max(len(x) - len(classes), 1)
    return discriminant(means, np.array([(y == c).mean() for c in classes]), cov, shrinkage) + (classes,)


def discriminant(means, priors, cov, shrinkage):
    d = len(cov)
    cov = (1 - shrinkage) * cov + shrinkage * np.trace(cov) / d * np.eye(d) + 1e-10 * np.eye(d)
    w = np.linalg.solve(cov, means.T)
    return w, np.log(priors) - 0.5 * (means.T * w).sum(axis=0)


ACTIVATIONS = {
    "relu": (lambda v: np.maximum(v, 0), lambda v, a: (v > 0).astype(float)),
    "tanh": (np.tanh, lambda v, a: 1 - a * a),
    "elu": (lambda v: np.where(v > 0, v, np.expm1(np.minimum(v, 0))), lambda v, a: np.where(v > 0, 1.0, a + 1)),
}


def init_mlp(sizes, activation, seed=42):
    rng = np.random.default_rng(seed)
    gain = 2.0 if activation in ("relu", "elu") else 1.0
    return [(rng.normal(size=(a, b)) * np.sqrt(gain / a), np.zeros(b)) for a, b in zip(sizes[:-1], sizes[1:], strict=True)]


def mlp_scores(net, x, activation):
    for w, b in net[:-1]:
        x = ACTIVATIONS[activation][0](x @ w + b)
    return x @ net[-1][0] + net[-1][1]


def mlp_epoch(net, state, x, y, activation, dropout, lr, batch, rng):
    """One epoch of Adam on mini-batches, with inverted dropout; ``state`` holds the moments and the step."""
    act, slope = ACTIVATIONS[activation]
    order = rng.permutation(len(x))
    k = net[-1][1].size
    for at in range(0, len(x), batch):
        i = order[at : at + batch]
        inputs, sums, masks, a = [], [], [], x[i]
        for w, b in net[:-1]:
            inputs.append(a)
            v = a @ w + b
            a = act(v)
            m = (rng.random(a.shape) >= dropout) / max(1 - dropout, 1e-9) if dropout else 1.0
            sums.append((v, a))
            masks.append(m)
            a = a * m
        inputs.append(a)
        z = a @ net[-1][0] + net[-1][1]
        z = np.exp(z - z.max(axis=1, keepdims=True))
        g = z / z.sum(axis=1, keepdims=True)
        g[np.arange(len(i)), y[i].astype(int)] -= 1
        g /= len(i)
        grads = [None] * len(net)
        for layer in range(len(net) - 1, -1, -1):
            grads[layer] = (inputs[layer].T @ g, g.sum(axis=0))
            if layer:
                g = (g @ net[layer][0].T) * masks[layer - 1] * slope(*sums[layer - 1])
        state["t"] += 1
        for layer, pair in enumerate(grads):
            for part in (0, 1):
                m, s = state["m"][layer][part], state["s"][layer][part]
                m += 0.1 * (pair[part] - m)
                s += 0.001 * (pair[part] ** 2 - s)
                net[layer][part][...] -= lr * (m / (1 - 0.9 ** state["t"])) / (np.sqrt(s / (1 - 0.999 ** state["t"])) + 1e-8)
    assert k
    return net


def new_state(net):
    zero = [tuple(np.zeros_like(p) for p in layer) for layer in net]
    return {"t": 0, "m": zero, "s": [tuple(np.zeros_like(p) for p in layer) for layer in net]}


def fit_mlp(x, y, layers=(32,), activation="relu", dropout=0.0, lr=1e-3, batch=64, epochs=30, seed=42):
    net = init_mlp([x.shape[1], *layers, int(y.max()) + 1 if len(y) else 2], activation, seed)
    state, rng = new_state(net), np.random.default_rng(seed)
    for _ in range(int(epochs)):
        mlp_epoch(net, state, x, y, activation, dropout, lr, int(batch), rng)
    return net


def accuracy(y, p):
    return float((y == p).mean()) if len(y) else 0.0


def f1(y, p, average="binary"):
    """``binary`` is the score of class 1, be it there or not."""
    scores, support = [], []
    for c in [1] if average == "binary" else np.unique(np.append(y, p)):
        hit, a, b = ((y == c) & (p == c)).sum(), (y == c).sum(), (p == c).sum()
        scores.append(2 * hit / (a + b) if a + b else 0.0)
        support.append(a)
    if not len(y):
        return 0.0
    return float(scores[0]) if average == "binary" else float(np.average(scores, weights=support if average == "weighted" else None))


def fit_predict(family, params, x, y, z):
    """Predicted classes of ``z`` by a learner fitted on x and y."""
    p = params
    if family == "logistic":
        w, b = fit_logistic(x, y, p.get("reg", 0.01), p.get("l1_ratio", 0.0), p.get("iterations", 100))
        return (z @ w + b > 0).astype(float)
    if family == "svm":
        return predict_svms(p, [p.get("c", 1.0)], x, y, z)[0]
    if family == "discriminant":
        w, b, classes = fit_discriminant(x, y, p.get("shrinkage", 0.0))
        return classes[(z @ w + b).argmax(axis=1)]
    if family == "mlp":
        net = fit_mlp(x, y, p.get("layers", (32,)), p.get("activation", "relu"), p.get("dropout", 0.0), p.get("lr", 1e-3), p.get("batch", 64), p.get("epochs", 5))
        return mlp_scores(net, z, p.get("activation", "relu")).argmax(axis=1).astype(float)
    if family == "tree":
        return fit_cart(x, y, int(p.get("depth", 5)), int(p.get("min_split", 2)), p.get("min_gain", 0.0))(z)
    if family == "forest":
        return fit_forest(x, y, int(p.get("trees", 20)), int(p.get("depth", 5)))(z)
    if family == "adaboost":
        return fit_adaboost(x, y, int(p.get("n", 10)), p.get("lr", 1.0), int(p.get("depth", 1)))(z)
    if family == "boost":
        held = np.arange(len(x)) % 5 == 4 if len(x) >= 50 else np.zeros(len(x), bool)  # rows that say when to stop
        depth = int(p.get("depth", 6))
        model = fit_boost_numpy(x[~held], y[~held], int(p.get("n", 50)), p.get("lr", 0.3), int(p.get("leaves", 1 << min(depth, 6))), depth, p.get("l1", 0.0), p.get("l2", 1.0), valid=(x[held], y[held]) if held.any() else None, patience=PATIENCE)
        return (model(z) > 0).astype(float)
    raise ValueError(f"unknown family {family}")
