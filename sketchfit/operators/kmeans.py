"""Centroids from a sketch: unrolled descent, greedy matching pursuit, message passing; and the exact and mixture counterparts."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V
from .maps import ACTIVATIONS, FeatureMap, act_gradient


def jacobian_product(fm: FeatureMap, theta: np.ndarray, g: np.ndarray) -> np.ndarray:
    """For each row t of theta, the gradient with respect to t of <f(t), g_t>; g is one vector or one for each row."""
    g = np.broadcast_to(g, (len(theta), fm.m))
    if fm.kind == "fourier":
        w = fm.arrays["omega"]
        y = theta @ w.T
        n = len(w)
        return (-np.sin(y) * g[:, :n] + np.cos(y) * g[:, n:]) @ w
    if fm.kind == "linear_act":
        w, act = fm.arrays["w"], dict(fm.params)["act"]
        y = theta @ w.T
        if act == "cos_sin":
            n = len(w)
            return (-np.sin(y) * g[:, :n] + np.cos(y) * g[:, n:]) @ w
        return (act_gradient(act, y) * g) @ w
    if fm.kind == "nystrom":
        from .maps import gaussian_kernel

        gamma, marks = dict(fm.params)["gamma"], fm.arrays["landmarks"]
        k = gaussian_kernel(theta, marks, gamma)
        h = (g @ fm.arrays["root"].T) * k
        return 2 * gamma * (h @ marks - h.sum(1, keepdims=True) * theta)
    if fm.kind == "identity":
        return g
    eps, out = 1e-5, np.zeros_like(theta)
    for j in range(theta.shape[1]):
        up, down = theta.copy(), theta.copy()
        up[:, j] += eps
        down[:, j] -= eps
        out[:, j] = ((fm.batch(up) - fm.batch(down)) / (2 * eps) * g).sum(1)
    return out


def sketch_of_centroids(theta: np.ndarray, fm: FeatureMap, weights: np.ndarray | None = None) -> np.ndarray:
    a = np.full(len(theta), 1 / len(theta)) if weights is None else weights
    return a @ fm.batch(theta)


@dataclass(frozen=True)
class Centroids:
    theta: np.ndarray
    weights: np.ndarray
    loss: float
    steps: int
    failed: bool = False


def nnls(a: np.ndarray, b: np.ndarray, steps: int = 0) -> np.ndarray:
    """Least squares with non-negative unknowns, by an active set."""
    n = a.shape[1]
    x, free = np.zeros(n), np.zeros(n, dtype=bool)
    g, h = a.T @ a, a.T @ b
    for _ in range(steps or 3 * n + 10):
        w = h - g @ x
        w[free] = -np.inf
        j = int(np.argmax(w))
        if w[j] <= 1e-12:
            break
        free[j] = True
        while True:
            s = np.zeros(n)
            s[free] = np.linalg.lstsq(g[np.ix_(free, free)], h[free], rcond=None)[0]
            if (s[free] > 0).all():
                x = s
                break
            bad = free & (s <= 0)
            t = np.min(x[bad] / np.maximum(x[bad] - s[bad], 1e-300))
            x = x + t * (s - x)
            free &= x > 1e-14
            if not free.any():
                break
    return x


def inner_update(kind: str, alpha: float) -> Callable[[np.ndarray, np.ndarray, int, dict], np.ndarray]:
    def step(x: np.ndarray, g: np.ndarray, t: int, state: dict) -> np.ndarray:
        if kind == "sgd":
            return x - alpha * g
        if kind == "momentum":
            state["v"] = 0.9 * state.get("v", 0.0) + g
            return x - alpha * state["v"]
        state["m"] = 0.9 * state.get("m", 0.0) + 0.1 * g
        state["s"] = 0.999 * state.get("s", 0.0) + 0.001 * g * g
        return x - alpha * (state["m"] / (1 - 0.9**t)) / (np.sqrt(state["s"] / (1 - 0.999**t)) + 1e-8)

    return step


def decode_unrolled(z: np.ndarray, fm: FeatureMap, k: int, steps: int = 200, alpha: float = 0.02, inner: str = "adam", init_var: float = 0.08, seed: int = 0, starts: int = 3, weighting: str = "uniform", box: tuple[float, float] | None = (0.0, 1.0), trace: list | None = None, tol: float = 0.0) -> Centroids:
    """`steps` steps of an inner optimiser on the distance between the sketch of the centroids and z, from random starts; the start with the least sketch loss stays.

    weighting: uniform, softmax (weights follow alongside), or nnls (a last non-negative fit). box: centroids are kept in it.
    """
    best: Centroids | None = None
    for s in range(starts):
        rng = np.random.Generator(np.random.Philox([seed, s]))
        theta = 0.5 + math.sqrt(init_var) * rng.standard_normal((k, fm.d))
        if box:
            theta = np.clip(theta, *box)
        logits = np.zeros(k)
        state: dict = {}
        state_w: dict = {}
        step, step_w = inner_update(inner, alpha), inner_update("adam", 0.05)
        loss, t = np.inf, 0
        for t in range(1, steps + 1):
            a = np.exp(logits - logits.max())
            a /= a.sum()
            f = fm.batch(theta)
            e = a @ f - z
            new = float(e @ e)
            if trace is not None and s == 0:
                trace.append(new)
            if tol and abs(loss - new) <= tol * max(loss, 1e-300):
                break
            loss = new
            theta = step(theta, 2 * a[:, None] * jacobian_product(fm, theta, e), t, state)
            if box:
                theta = np.clip(theta, *box)
            if weighting == "softmax":
                q = 2 * f @ e
                logits = step_w(logits, a * (q - a @ q), t, state_w)
        a = np.exp(logits - logits.max())
        a /= a.sum()
        if weighting == "nnls":
            a = nnls(fm.batch(theta).T, z)
            a = a / a.sum() if a.sum() > 0 else np.full(k, 1 / k)
        e = a @ fm.batch(theta) - z
        got = Centroids(theta, a, float(e @ e), t)
        if best is None or got.loss < best.loss:
            best = got
    return best


def as_recurrence(z: np.ndarray, fm: FeatureMap, theta: np.ndarray, steps: int, alpha: float) -> np.ndarray:
    """The same steps as a recurrent cell applied over and over: the state is theta, the weights are those of the map, shared by all steps."""

    def cell(state: np.ndarray) -> np.ndarray:
        e = sketch_of_centroids(state, fm) - z
        return state - alpha * 2 / len(state) * jacobian_product(fm, state, e)

    for _ in range(steps):
        theta = cell(theta)
    return theta


def decode_greedy(z: np.ndarray, fm: FeatureMap, k: int, box: tuple[float, float] = (0.0, 1.0), replace: bool = True, restarts: int = 4, ascent: int = 80, polish: int = 120, seed: int = 0) -> Centroids:
    """Matching pursuit over continuous atoms. With replacement 2k rounds run, each keeping the k atoms of largest weight."""
    rng = np.random.Generator(np.random.Philox(seed))
    theta, a = np.zeros((0, fm.d)), np.zeros(0)
    residual = z.copy()
    rounds = 2 * k if replace else k
    for _ in range(rounds):
        start = box[0] + (box[1] - box[0]) * rng.random((restarts, fm.d))
        state: dict = {}
        step = inner_update("adam", 0.05 * (box[1] - box[0]))
        for t in range(1, ascent + 1):
            f = fm.batch(start)
            n = np.maximum(np.linalg.norm(f, axis=1, keepdims=True), 1e-12)
            corr = f @ residual
            g = residual[None] / n - (corr[:, None] / n**3) * f
            start = np.clip(step(start, -jacobian_product(fm, start, g), t, state), *box)
        f = fm.batch(start)
        score = (f @ residual) / np.maximum(np.linalg.norm(f, axis=1), 1e-12)
        theta = np.vstack([theta, start[np.argmax(score)]])
        if len(theta) > k:
            f = fm.batch(theta)
            n = np.linalg.norm(f, axis=1)
            b = nnls((f / n[:, None]).T, z)
            theta = theta[np.sort(np.argsort(-b, kind="stable")[:k])]
        a = nnls(fm.batch(theta).T, z)
        theta, a = _polish(z, fm, theta, a, box, polish)
        residual = z - a @ fm.batch(theta)
    e = float(residual @ residual)
    return Centroids(theta, a / a.sum() if a.sum() > 0 else np.full(len(theta), 1 / len(theta)), e, rounds)


def _polish(z, fm, theta, a, box, steps):
    state, state_a = {}, {}
    move, move_a = inner_update("adam", 0.01 * (box[1] - box[0])), inner_update("adam", 0.01)
    best, best_e = (theta, a), np.inf
    for t in range(1, steps + 1):
        f = fm.batch(theta)
        e = a @ f - z
        size = float(e @ e)
        if size < best_e:
            best, best_e = (theta, a), size
        g, ga = 2 * a[:, None] * jacobian_product(fm, theta, e), 2 * f @ e
        theta, a = np.clip(move(theta, g, t, state), *box), np.maximum(move_a(a, ga, t, state_a), 0)
    return best


def decode_message_passing(z: np.ndarray, fm: FeatureMap, k: int, steps: int = 60, damping: float = 0.7, grid: int = 33, seed: int = 0, prior: tuple[float, float] = (0.5, 0.1)) -> Centroids:
    """Approximate message passing for Fourier sketches. Unstable by nature: `failed` says when it diverged or got stuck at a loss above that of a single point."""
    omega = fm.arrays["omega"]
    n, d = omega.shape
    g = np.maximum(np.linalg.norm(omega, axis=1), 1e-9)
    u = omega / g[:, None]
    target = z[:n] + 1j * z[n:]
    rng = np.random.Generator(np.random.Philox(seed))
    theta = prior[0] + math.sqrt(prior[1]) * rng.standard_normal((k, d))
    var = np.full((k, d), prior[1])
    a = np.full(k, 1 / k)
    s = np.zeros((n, k))
    failed, t = False, 0
    for t in range(1, steps + 1):
        p_var = np.maximum((u**2) @ var.T, 1e-9)
        p = u @ theta.T - p_var * s
        # output step: the posterior of each projection on a grid, others at their mean
        wave = a[None] * np.exp(1j * g[:, None] * p) * np.exp(-0.5 * g[:, None] ** 2 * p_var)
        rest = target[:, None] - (wave.sum(1, keepdims=True) - wave)
        nodes = np.linspace(-3, 3, grid)
        x = p[..., None] + np.sqrt(p_var)[..., None] * nodes
        noise = np.maximum(np.mean(np.abs(target - wave.sum(1)) ** 2), 1e-6)
        fit = -np.abs(rest[..., None] - a[None, :, None] * np.exp(1j * g[:, None, None] * x)) ** 2 / noise - nodes**2 / 2
        w = np.exp(fit - fit.max(-1, keepdims=True))
        w /= w.sum(-1, keepdims=True)
        mean = (w * x).sum(-1)
        spread = np.maximum((w * (x - mean[..., None]) ** 2).sum(-1), 1e-12)
        s_new = (mean - p) / p_var
        tau = np.maximum((1 - spread / p_var) / p_var, 1e-9)
        s = damping * s + (1 - damping) * s_new
        # input step: Gaussian prior
        r_var = 1 / np.maximum(tau.T @ (u**2), 1e-9)
        r = theta + r_var * (s.T @ u)
        new = (r / r_var + prior[0] / prior[1]) / (1 / r_var + 1 / prior[1])
        var = 1 / (1 / r_var + 1 / prior[1])
        new = damping * theta + (1 - damping) * new
        if not np.isfinite(new).all() or np.abs(new).max() > 1e3:
            failed = True
            break
        moved = np.abs(new - theta).max()
        theta = new
        f = fm.batch(theta)
        fitted = nnls(f.T, z)
        a = fitted / fitted.sum() if fitted.sum() > 0 else np.full(k, 1 / k)
        if moved < 1e-7:
            break
    e = a @ fm.batch(theta) - z
    single = fm.batch(np.full((1, d), prior[0]))[0] - z
    return Centroids(theta, a, float(e @ e), t, failed or float(e @ e) > float(single @ single))


@dataclass(frozen=True)
class Mixture:
    weights: np.ndarray
    means: np.ndarray
    variances: np.ndarray
    loss: float


def gmm_from_sketch(z: np.ndarray, fm: FeatureMap, k: int, steps: int = 600, seed: int = 0, box: tuple[float, float] = (0.0, 1.0)) -> Mixture:
    """Diagonal Gaussians from a Fourier sketch: centroids by greedy pursuit, then descent on means, log variances and weights of the characteristic functions."""
    omega = fm.arrays["omega"]
    n = len(omega)
    first = decode_greedy(z, fm, k, box, seed=seed)
    mu, logv, a = first.theta.copy(), np.full((k, fm.d), math.log(0.005)), np.maximum(first.weights, 1e-3)
    a = a / a.sum()
    steps_of = [inner_update("adam", 0.01) for _ in range(3)]
    states: list[dict] = [{}, {}, {}]
    logits = np.log(a)
    best, best_e = None, np.inf
    for t in range(1, steps + 1):
        a = np.exp(logits - logits.max())
        a /= a.sum()
        fade = np.exp(-0.5 * np.exp(logv) @ (omega**2).T)
        y = mu @ omega.T
        f = np.concatenate([fade * np.cos(y), fade * np.sin(y)], axis=1)
        e = a @ f - z
        size = float(e @ e)
        if size < best_e:
            best, best_e = (a.copy(), mu.copy(), np.exp(logv)), size
        gc, gs = e[:n], e[n:]
        g_mu = 2 * a[:, None] * ((fade * (-np.sin(y) * gc + np.cos(y) * gs)) @ omega)
        g_v = -a[:, None] * ((fade * (np.cos(y) * gc + np.sin(y) * gs)) @ omega**2) * np.exp(logv)
        q = 2 * f @ e
        mu = np.clip(steps_of[0](mu, g_mu, t, states[0]), *box)
        logv = np.clip(steps_of[1](logv, g_v, t, states[1]), -12, 0)
        logits = steps_of[2](logits, a * (q - a @ q), t, states[2])
    return Mixture(*best, best_e)


def kmeans_mse_local(x: np.ndarray, theta: np.ndarray) -> float:
    d2 = (x**2).sum(1)[:, None] + (theta**2).sum(1)[None] - 2 * x @ theta.T
    return float(np.maximum(d2, 0).min(1).mean())


def lloyd_local(x: np.ndarray, k: int, steps: int = 20, seed: int = 0, starts: int = 1) -> np.ndarray:
    best, best_e = None, np.inf
    for s in range(starts):
        rng = np.random.Generator(np.random.Philox([seed, s]))
        theta = x[rng.integers(len(x))][None]
        for _ in range(1, k):
            d2 = ((x[:, None] - theta[None]) ** 2).sum(-1).min(1)
            total = d2.sum()
            theta = np.vstack([theta, x[rng.choice(len(x), p=d2 / total) if total > 0 else rng.integers(len(x))]])
        for _ in range(steps):
            c = ((x[:, None] - theta[None]) ** 2).sum(-1).argmin(1)
            theta = np.array([x[c == j].mean(0) if (c == j).any() else theta[j] for j in range(k)])
        e = kmeans_mse_local(x, theta)
        if e < best_e:
            best, best_e = theta, e
    return best


def lloyd_step(df: DataFrame, theta: np.ndarray) -> DataFrame:
    """One exact step over all rows: cid, n, and the mean of its rows; sums by coordinate combine on the map side."""
    from .tasks import assign

    d = theta.shape[1]
    x = V.as_doubles(F.col("features"))
    near = assign(df, theta).select("cid", *[F.get(x, F.lit(j)).alias(f"x{j}") for j in range(d)])
    out = near.groupBy("cid").agg(F.count("cid").alias("n"), *[F.sum(f"x{j}").alias(f"s{j}") for j in range(d)])
    return out.select("cid", "n", F.array(*[F.col(f"s{j}") / F.col("n") for j in range(d)]).alias("center"))


def kmeans_exact(df: DataFrame, d: int, k: int, steps: int = 20, seed: int = 0, pilot: int = 2000) -> np.ndarray:
    """Lloyd's algorithm over all rows; seeded by the spread-out start on a bounded pilot (rows of least key hash)."""
    if "row_key" in df.columns:
        rows = df.orderBy(F.md5(F.col("row_key").cast("string").cast("binary")), "row_key").limit(pilot)
    else:
        rows = df.orderBy(F.xxhash64("features"), "features").limit(pilot)
    x = np.array([r.features for r in rows.select("features").collect()], dtype=float)
    theta = lloyd_local(x, k, 0, seed, starts=1)
    for _ in range(steps):
        for r in lloyd_step(df, theta).collect():  # k rows
            theta[r.cid] = r.center
    return theta
