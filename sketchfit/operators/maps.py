"""Feature maps: what a mean sketch averages. Each knows its batch form (numpy) and, where it is closed, its column form."""

from __future__ import annotations

import hashlib
import json
import math
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..functions.features import bounded_rows
from ..functions.keyed_random import fast_normals, normals

ACTIVATIONS: dict[str, Callable[[np.ndarray], np.ndarray]] = {
    "identity": lambda x: x,
    "cos": np.cos,
    "sin": np.sin,
    "tanh": np.tanh,
    "relu": lambda x: np.maximum(x, 0),
    "sigmoid": lambda x: 1 / (1 + np.exp(-x)),
    "gelu": lambda x: 0.5 * x * (1 + np.tanh(math.sqrt(2 / math.pi) * (x + 0.044715 * x**3))),
    "cos_sin": lambda x: np.concatenate([np.cos(x), np.sin(x)], axis=-1),
}


def act_gradient(name: str, x: np.ndarray) -> np.ndarray:
    if name == "identity":
        return np.ones_like(x)
    if name == "cos":
        return -np.sin(x)
    if name == "sin":
        return np.cos(x)
    if name == "tanh":
        return 1 - np.tanh(x) ** 2
    if name == "relu":
        return (x > 0).astype(float)
    if name == "sigmoid":
        s = 1 / (1 + np.exp(-x))
        return s * (1 - s)
    if name == "gelu":
        c = math.sqrt(2 / math.pi)
        t = np.tanh(c * (x + 0.044715 * x**3))
        return 0.5 * (1 + t) + 0.5 * x * (1 - t * t) * c * (1 + 3 * 0.044715 * x * x)
    raise ValueError(name)


@dataclass(frozen=True)
class FeatureMap:
    """kind, input width d, output width m, and the arrays that fix it. `map_id` is a content hash: only equal maps' sketches combine."""

    kind: str
    d: int
    m: int
    params: tuple[tuple[str, object], ...] = ()
    arrays: dict[str, np.ndarray] = field(default_factory=dict, compare=False, hash=False)
    extra_numbers: int = 0  # numbers that belong to the sketch's size besides m (landmarks)

    @property
    def map_id(self) -> str:
        h = hashlib.md5(json.dumps([self.kind, self.d, self.m, [list(p) for p in self.params]], default=str).encode())
        for name in sorted(self.arrays):
            h.update(name.encode() + np.ascontiguousarray(self.arrays[name]).tobytes())
        return h.hexdigest()

    @property
    def numbers(self) -> int:
        return self.m + self.extra_numbers

    @property
    def bound(self) -> float | None:
        """The largest norm of a feature vector, where it is known."""
        return {"fourier": math.sqrt(self.m / 2), "nystrom": 1.0}.get(self.kind)

    def batch(self, x: np.ndarray) -> np.ndarray:
        x = np.asarray(x, dtype=float)
        if self.kind == "identity":
            return x
        if self.kind == "outer_lt":
            a, b = np.tril_indices(self.d)
            return x[:, a] * x[:, b]
        if self.kind == "rank_one":
            return (x @ self.arrays["omega"].T) ** 2
        if self.kind == "outer_linear":
            a, b = np.tril_indices(self.d)
            return (x[:, a] * x[:, b]) @ self.arrays["w"].T + self.arrays["b"]
        if self.kind == "fourier":
            y = x @ self.arrays["omega"].T
            return np.concatenate([np.cos(y), np.sin(y)], axis=1)
        if self.kind == "linear_act":
            return ACTIVATIONS[dict(self.params)["act"]](x @ self.arrays["w"].T)
        if self.kind == "nystrom":
            return gaussian_kernel(x, self.arrays["landmarks"], dict(self.params)["gamma"]) @ self.arrays["root"]
        if self.kind == "network":
            return dict(self.params)["net"].forward(x)
        if self.kind == "concat":
            return np.concatenate([f.batch(x) for f in dict(self.params)["maps"]], axis=1)
        raise ValueError(self.kind)

    def columns(self, v: Column) -> list[Column]:
        """One expression for each feature; for closed maps of few features."""
        if self.kind == "identity":
            return [F.get(v, F.lit(j)) for j in range(self.d)]
        if self.kind == "outer_lt":
            return [F.get(v, F.lit(a)) * F.get(v, F.lit(b)) for a in range(self.d) for b in range(a + 1)]
        if self.kind == "rank_one":
            return [V.dot_literal(v, w) * V.dot_literal(v, w) for w in self.arrays["omega"]]
        if self.kind == "fourier":
            y = [V.dot_literal(v, w) for w in self.arrays["omega"]]
            return [F.cos(c) for c in y] + [F.sin(c) for c in y]
        if self.kind == "linear_act":
            act = {"cos": F.cos, "sin": F.sin, "tanh": F.tanh, "identity": lambda c: c, "relu": lambda c: F.greatest(c, F.lit(0.0)), "sigmoid": lambda c: 1 / (1 + F.exp(-c))}[dict(self.params)["act"]]
            return [act(V.dot_literal(v, w)) for w in self.arrays["w"]]
        raise ValueError(f"{self.kind} has no column form")

    @property
    def has_columns(self) -> bool:
        return self.kind in ("identity", "outer_lt", "rank_one", "fourier") or self.kind == "linear_act" and dict(self.params)["act"] not in ("gelu", "cos_sin")


def identity_map(d: int) -> FeatureMap:
    return FeatureMap("identity", d, d)


def outer_lt_map(d: int) -> FeatureMap:
    return FeatureMap("outer_lt", d, d * (d + 1) // 2)


def rank_one_map(omega: np.ndarray) -> FeatureMap:
    return FeatureMap("rank_one", omega.shape[1], omega.shape[0], arrays={"omega": omega})


def outer_linear_map(w: np.ndarray, b: np.ndarray, d: int) -> FeatureMap:
    return FeatureMap("outer_linear", d, len(b), arrays={"w": w, "b": b})


def linear_act_map(w: np.ndarray, act: str) -> FeatureMap:
    return FeatureMap("linear_act", w.shape[1], w.shape[0] * (2 if act == "cos_sin" else 1), (("act", act),), {"w": w})


def network_map(net, d: int, m: int) -> FeatureMap:
    return FeatureMap("network", d, m, (("net", net),), net.arrays())


def concat_maps(*maps: FeatureMap) -> FeatureMap:
    """Several maps in one scan; prefixes of one random matrix serve every smaller size as well."""
    return FeatureMap("concat", maps[0].d, sum(f.m for f in maps), (("maps", maps),), {f"{i}.{k}": a for i, f in enumerate(maps) for k, a in f.arrays.items()}, sum(f.extra_numbers for f in maps))


def directions(d: int, m: int, law: str, seed: int | str) -> np.ndarray:
    """m random directions; `chi`: Gaussian vectors, so the radius is chi(d); `unit`: radius one. A string seed uses md5 keys, which SQL can repeat."""
    g = normals(str(seed), m, d) if isinstance(seed, str) else fast_normals(seed, m, d)
    if law == "chi":
        return g
    if law == "unit":
        return g / np.linalg.norm(g, axis=1, keepdims=True)
    raise ValueError(law)


def random_projection(d: int, m: int, structure: str = "rank_one", law: str = "chi", layout: str = "lt", seed: int = 0) -> np.ndarray:
    """The m x D matrix A of a moment sketch. rank_one rows are those of the features (w'x)^2."""
    a, b = np.tril_indices(d)
    if structure == "rank_one":
        w = directions(d, m, law, seed)
        rows = w[:, :, None] * w[:, None, :]
        if layout == "full":
            return rows.reshape(m, d * d)
        off = np.where(a == b, 1.0, 2.0 if layout == "lt" else math.sqrt(2))
        return rows[:, a, b] * off
    size = d * d if layout == "full" else len(a)
    g = fast_normals(seed, m, size)
    return g / np.linalg.norm(g, axis=1, keepdims=True) if law == "unit" else g


def radius_grid(n: int = 10_000, top: float = 8.0) -> tuple[np.ndarray, np.ndarray]:
    r = np.linspace(0, top, n)
    density = np.sqrt(r**2 + r**4 / 4) * np.exp(-(r**2) / 2)
    c = np.cumsum(density)
    return r, c / c[-1]


def fourier_map(d: int, m: int, sigma: float = 1.0, radius: str = "gaussian", seed: int | str = 0) -> FeatureMap:
    """m real features: cosines then sines of m / 2 frequencies."""
    n = m // 2
    g = normals(str(seed), n, d) if isinstance(seed, str) else fast_normals(seed, n, d)
    if radius == "adapted":
        r, c = radius_grid()
        u = np.random.Generator(np.random.Philox(1 + (seed if isinstance(seed, int) else 0))).random(n)
        g = g / np.linalg.norm(g, axis=1, keepdims=True) * np.interp(u, c, r)[:, None] * math.sqrt(d) / 1.5
    return FeatureMap("fourier", d, 2 * n, (("radius", radius),), {"omega": g / sigma})


def pilot_scale(df: DataFrame, rows: int = 256, by: str = "dataset_id") -> dict[str, float]:
    """A kernel width for every dataset: the median distance between the rows of a pilot, at most `rows` of least key hash. A dataset of one row, or of equal rows, gets 1."""
    out = {}
    for name, x in bounded_rows(df, rows, by).items():
        a, b = np.triu_indices(len(x), 1)
        width = float(np.median(np.sqrt(((x[a] - x[b]) ** 2).sum(1)))) if len(a) else 0.0
        out[name] = width or 1.0
    return out


def gaussian_kernel(x: np.ndarray, y: np.ndarray, gamma: float) -> np.ndarray:
    sq = (x**2).sum(1)[:, None] + (y**2).sum(1)[None] - 2 * x @ y.T
    return np.exp(-gamma * np.maximum(sq, 0))


def nystrom_map(landmarks: np.ndarray, gamma: float) -> FeatureMap:
    """Features K^{-1/2} k(x) on landmarks; their coordinates count in the sketch's size."""
    w, u = np.linalg.eigh(gaussian_kernel(landmarks, landmarks, gamma))
    keep = w > 1e-10
    root = (u[:, keep] / np.sqrt(w[keep])) @ u[:, keep].T
    return FeatureMap("nystrom", landmarks.shape[1], len(landmarks), (("gamma", gamma),), {"landmarks": landmarks, "root": root}, landmarks.size)
