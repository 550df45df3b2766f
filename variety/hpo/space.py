"""Search spaces with mixed and conditional parameters, and draws that depend on hashes alone."""

from __future__ import annotations

import hashlib
import itertools
import json
import math
from dataclasses import dataclass
from typing import Any


def u(*parts) -> float:
    """A number in [0, 1) from an MD5 of the parts, as in functions.hashing."""
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:8], 16) / 2**32


@dataclass(frozen=True)
class Param:
    """kind: choice, int, real, log or layers (a list of one to ``high`` sizes from ``values``). ``when`` names values of other parameters that make it active."""

    name: str
    kind: str
    low: float = 0.0
    high: float = 1.0
    values: tuple = ()
    when: tuple[str, tuple] | None = None

    def at(self, r: float) -> Any:
        if self.kind == "choice":
            return self.values[min(int(r * len(self.values)), len(self.values) - 1)]
        if self.kind == "int":
            return int(min(self.low + math.floor(r * (self.high - self.low + 1)), self.high))
        if self.kind == "log":
            return math.exp(math.log(self.low) + r * (math.log(self.high) - math.log(self.low)))
        if self.kind == "layers":
            n = 1 + min(int(r * self.high), int(self.high) - 1)
            return tuple(self.values[int(u("layers", r, i) * len(self.values))] for i in range(n))
        return self.low + r * (self.high - self.low)

    def step(self, value: Any, r: float, size: float) -> Any:
        """A neighbour of ``value``; bounds reflect."""
        if self.kind in ("choice", "layers"):
            return self.at(r)
        shift = 2 * r - 1
        if self.kind == "log":
            lo, hi, x = math.log(self.low), math.log(self.high), math.log(value)
        else:
            lo, hi, x = self.low, self.high, float(value)
        x += shift * size * (hi - lo)
        x = 2 * lo - x if x < lo else 2 * hi - x if x > hi else x
        x = min(max(x, lo), hi)
        return math.exp(x) if self.kind == "log" else int(round(x)) if self.kind == "int" else x


@dataclass(frozen=True)
class Space:
    family: str
    params: tuple[Param, ...]

    def repair(self, theta: dict) -> dict:
        """Without parameters that the others make inactive, and with those that they make active."""
        out: dict[str, Any] = {}
        for p in self.params:
            if p.when is None or out.get(p.when[0]) in p.when[1]:
                out[p.name] = theta[p.name] if p.name in theta else p.at(u("repair", p.name, key_of(theta)))
        return out

    def draw(self, *parts) -> dict:
        return self.repair({p.name: p.at(u(*parts, p.name)) for p in self.params})

    def grid(self) -> list[dict]:
        """All combinations of choices; a parameter counts only where it is active."""
        rows: list[dict] = [{}]
        for p in self.params:
            rows = [r | e for r in rows for e in ([{p.name: v} for v in p.values] if p.when is None or r.get(p.when[0]) in p.when[1] else [{}])]
        return rows


def key_of(theta: dict) -> str:
    return json.dumps({k: list(v) if isinstance(v, tuple) else v for k, v in sorted(theta.items())})


SVM_GRID = Space(
    "svm",
    (
        Param("kernel", "choice", values=("rbf", "linear", "poly")),
        Param("c", "choice", values=(0.01, 0.1, 1.0, 5.0, 10.0, 20.0)),
        Param("gamma", "choice", values=("scale", "auto", 1e-4, 1e-3, 1e-2, 1e-1), when=("kernel", ("rbf", "poly"))),
        Param("degree", "choice", values=(2, 3, 4), when=("kernel", ("poly",))),
        Param("coef0", "choice", values=(0.0, 0.1, 0.5), when=("kernel", ("poly",))),
    ),
)
MLP_GENES = Space(
    "mlp",
    (
        Param("layers", "layers", high=3, values=(16, 32, 64, 128, 256, 512, 1024)),
        Param("dropout", "real", 0.0, 0.7),
        Param("lr", "log", 1e-5, 1e-1),
        Param("activation", "choice", values=("relu", "tanh", "elu")),
        Param("batch", "int", 16, 512),
    ),
)
LOGISTIC = Space("logistic", (Param("reg", "log", 1e-6, 1.0), Param("l1_ratio", "real", 0.0, 1.0), Param("iterations", "int", 20, 200)))
DISCRIMINANT = Space("discriminant", (Param("shrinkage", "real", 0.0, 1.0),))
TREE = Space("tree", (Param("depth", "int", 1, 12), Param("min_split", "int", 2, 20), Param("min_gain", "log", 1e-6, 1e-1)))
FOREST = Space("forest", (Param("trees", "int", 10, 100), Param("depth", "int", 1, 12)))
ADABOOST = Space("adaboost", (Param("n", "int", 5, 60), Param("lr", "log", 1e-2, 1.0), Param("depth", "int", 1, 3)))
LEAFWISE = Space(
    "boost",
    (
        Param("lr", "log", 1e-5, 0.5),
        Param("n", "int", 50, 1000),
        Param("leaves", "int", 15, 255),
        Param("depth", "int", 3, 12),
        Param("l1", "log", 1e-8, 10.0),
        Param("l2", "log", 1e-8, 10.0),
    ),
)
#: The winners that the published experiments report, as regression fixtures.
REPORTED_SVM = {"kernel": "rbf", "c": 1.0, "gamma": 1e-4}
REPORTED_MLP = {"layers": (1024, 256, 128), "activation": "relu", "lr": 1e-5, "dropout": 0.6132, "batch": 407}
