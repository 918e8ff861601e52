"""Meta-training: feature map and decoder fitted together over a collection of datasets, then frozen."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.keyed_random import uniform_col
from ..operators import privacy
from ..operators.kmeans import decode_unrolled, kmeans_mse_local, lloyd_local
from ..operators.maps import FeatureMap, linear_act_map, network_map, outer_lt_map
from ..operators.sketch import mean, mean_sketch, pack_lt, unpack_lt
from ..operators.tasks import matched_centroids
from .layers import Adam, Affine, Activation, Chain, Layer, residual_mlp
from .search import Space, derivative_free_search


def split_datasets(df: DataFrame, frac: float = 0.5, seed: int = 0, by: str = "dataset_id") -> DataFrame:
    """A column `split` of train or test by dataset, never by row."""
    return df.withColumn("split", F.when(uniform_col(f"split{seed}", F.col(by).cast("string")) < frac, "train").otherwise("test"))


def split_ids(ids: list[str], frac: float = 0.5, seed: int = 0) -> tuple[list[str], list[str]]:
    from ..functions.keyed_random import uniform

    train = [i for i in ids if uniform(f"split{seed}-{i}") < frac]
    return train, [i for i in ids if i not in set(train)]


# the moment pair ------------------------------------------------------------------------------------------------------


@dataclass
class MomentPair:
    """z = W v + b (v: the triangle of R, so W v is a mean sketch), triangle of R = scale * tanh(U z + c)."""

    d: int
    w: np.ndarray
    b: np.ndarray
    u: np.ndarray
    c: np.ndarray
    scale: float
    log: list[tuple[int, float, float]] = field(default_factory=list)

    @property
    def m(self) -> int:
        return len(self.b)

    def encode(self, v: np.ndarray) -> np.ndarray:
        return v / self.scale @ self.w.T + self.b

    def decode(self, z: np.ndarray) -> np.ndarray:
        return self.scale * np.tanh(z @ self.u.T + self.c)

    def moment(self, v: np.ndarray) -> np.ndarray:
        return unpack_lt(self.decode(self.encode(v)), self.d)


def bank_start(bank: np.ndarray, m: int, seed: int = 0, ridge: float = 1e-6) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Encoder rows: principal directions of the bank, then random ones beside them; decoder: least squares to the inverse tanh of the bank."""
    mean = bank.mean(0)
    _, s, vt = np.linalg.svd(bank - mean, full_matrices=False)
    k = min(m, int((s > 1e-9 * max(s[0], 1e-300)).sum()))
    rows = [vt[:k]]
    if m > k:
        g = np.random.Generator(np.random.Philox(seed)).standard_normal((m - k, bank.shape[1]))
        g -= (g @ vt[:k].T) @ vt[:k]
        q = np.linalg.qr(g.T)[0].T if m - k <= bank.shape[1] else g / np.linalg.norm(g, axis=1, keepdims=True)
        rows.append(q)
    w = np.vstack(rows)[:m]
    b = -w @ mean
    # around the bank mean the decoder is v = mean + w' z, whose inverse tanh has slope 1 / (1 - mean^2)
    mean = np.clip(mean, -0.999, 0.999)
    slope = 1 / (1 - mean**2)
    return w, b, slope[:, None] * w.T, np.arctanh(mean)


#: Datasets that are mixed with one another; a larger bank is dealt anew into groups of at most so many in each round.
MIXED = 256


def augment_bank(bank: np.ndarray, d: int, times: int, seed: int = 0) -> np.ndarray:
    """More training moments without a scan: count-weighted unions of datasets and small diagonal rescalings act on R alone. Every dataset takes part in every round."""
    rng = np.random.Generator(np.random.Philox(seed))
    out = [bank]
    a, b = np.tril_indices(d)
    for _ in range(times):
        groups = [bank] if len(bank) <= MIXED else [bank[g] for g in np.array_split(rng.permutation(len(bank)), -(-len(bank) // MIXED))]
        for group in groups:
            mixed = rng.dirichlet(np.full(len(group), 0.3), size=len(group)) @ group
            scale = np.exp(0.05 * rng.standard_normal((len(group), d)))
            out.append(mixed * scale[:, a] * scale[:, b])
    return np.vstack(out)


def bank_scale(bank: np.ndarray) -> float:
    return float(np.abs(bank).max()) * 1.0001 or 1.0


def train_moment_pair(bank: np.ndarray, d: int, m: int, steps: int = 300, rate: float = 3e-5, schedule: str = "plateau", batch: int = 64, seed: int = 0, augment: int = 8, held: np.ndarray | None = None, dp: tuple[float, float, float] | None = None, augmented: np.ndarray | None = None) -> MomentPair:
    """L1 distance of predicted and empirical triangles, by Adam. bank: G x d(d+1)/2 exact triangles of the training datasets.

    dp: (eps, delta, rows) puts the noise of a private release of that many rows, and the clamp, into every forward pass.
    augmented: what augment_bank made of bank / bank_scale(bank), where several sizes share it.
    A bank that steps x batch draws do not cover is gone through in shuffled order, in batches so large that all of it is seen.
    """
    scale = bank_scale(bank)
    own = bank / scale
    full = augment_bank(own, d, augment, seed) if augmented is None else augmented
    w, b, u, c = bank_start(full if augment else own, m, seed)
    pair = MomentPair(d, w, b, u, c, scale)
    rng = np.random.Generator(np.random.Philox([seed, 7]))
    opt = Adam(rate, schedule, steps)
    low, high = (full @ w.T + b).min(0), (full @ w.T + b).max(0)
    best, best_loss = None, math.inf
    every = max(1, steps // 20)
    order = rng.permutation(len(full)) if len(full) > steps * batch else None
    share = -(-len(full) // max(1, steps))
    for t in range(steps + 1):
        if t % every == 0:
            train = float(np.abs(np.tanh((own @ pair.w.T + pair.b) @ pair.u.T + pair.c) - own).sum(1).mean())
            test = float(np.abs(pair.decode(pair.encode(held)) - held).sum(1).mean() / scale) if held is not None else math.nan
            pair.log.append((t, train, test))
            opt.observe(train)
            if train < best_loss:
                best, best_loss = [x.copy() for x in (pair.w, pair.b, pair.u, pair.c)], train
        x = full[rng.integers(len(full), size=min(batch, len(full)))] if order is None else full[order.take(range(t * share, (t + 1) * share), mode="wrap")]
        z = x @ pair.w.T + pair.b
        if dp is not None:
            noise = privacy.gaussian_sigma(0.9 * dp[0], dp[1], float(np.linalg.norm(high - low)))
            z = np.clip(z + rng.normal(0, noise / dp[2], size=z.shape), low, high)
        y = np.tanh(z @ pair.u.T + pair.c)
        g = np.sign(y - x) * (1 - y * y) / len(x)
        gz = g @ pair.u
        opt.update({"w": pair.w, "b": pair.b, "u": pair.u, "c": pair.c}, {"w": gz.T @ x, "b": gz.sum(0), "u": g.T @ z, "c": g.sum(0)})
    pair.w, pair.b, pair.u, pair.c = best
    return pair


# a general learned pair -----------------------------------------------------------------------------------------------


@dataclass
class LearnedPair:
    """Any network as feature map, any network as decoder; the map is applied to rows and averaged."""

    encoder: Layer
    decoder: Layer

    def sketch(self, x: np.ndarray) -> np.ndarray:
        return self.encoder.forward(x).mean(0)

    def decode(self, z: np.ndarray) -> np.ndarray:
        return self.decoder.forward(np.atleast_2d(z))[0]


def train_pair(pair: LearnedPair, datasets: list[np.ndarray], loss, steps: int = 200, rate: float = 1e-3, seed: int = 0, rows: int = 128, two_batch: bool = False) -> list[float]:
    """Substitution of the prediction into the task's loss. loss(theta, rows) -> (value, gradient in theta).

    two_batch: the sketch comes from one batch of the dataset, the loss from another.
    """
    rng = np.random.Generator(np.random.Philox(seed))
    opt = Adam(rate)
    out = []
    for _ in range(steps):
        x = datasets[rng.integers(len(datasets))]
        order = rng.permutation(len(x))
        a, b = order[:rows], (order[rows : 2 * rows] if two_batch and len(x) > rows else order[:rows])
        h = pair.encoder.forward(x[a], True)
        theta = pair.decoder.forward(h.mean(0, keepdims=True), True)
        value, g = loss(theta[0], x[b])
        gz = pair.decoder.backward(g[None])
        pair.encoder.backward(np.repeat(gz / len(a), len(a), axis=0))
        opt.update({f"e{k}": v for k, v in pair.encoder.params().items()} | {f"d{k}": v for k, v in pair.decoder.params().items()}, {f"e{k}": v for k, v in pair.encoder.grads.items()} | {f"d{k}": v for k, v in pair.decoder.grads.items()})
        out.append(float(value))
    return out


def kmeans_meta_loss(kind: str, k: int, d: int, target: np.ndarray | None = None):
    """min: mean squared distance to the nearest predicted centroid. matched: squared distance to the target centroid paired with each."""

    def loss(theta: np.ndarray, x: np.ndarray) -> tuple[float, np.ndarray]:
        c = theta.reshape(k, d)
        if kind == "min":
            d2 = ((x[:, None] - c[None]) ** 2).sum(-1)
            near = d2.argmin(1)
            g = np.zeros_like(c)
            np.add.at(g, near, 2 * (c[near] - x) / len(x))
            return float(d2.min(1).mean()), g.ravel()
        want = target if target is not None else lloyd_local(x, k, 10)
        partner, value = matched_centroids(c, want)
        return value, 2 * (c - want[partner]).ravel()

    return loss


# the unrolled pair ----------------------------------------------------------------------------------------------------


@dataclass
class UnrolledPair:
    fm: FeatureMap
    steps: int
    alpha: float
    inner: str
    init_var: float
    weighting: str
    log: list[float] = field(default_factory=list)

    def decode(self, z: np.ndarray, k: int, seed: int = 0, starts: int = 3):
        return decode_unrolled(z, self.fm, k, self.steps, self.alpha, self.inner, self.init_var, seed, starts, self.weighting)


def unrolled_space(d: int, m: int, weightings: tuple[str, ...] = ("uniform",)) -> Space:
    return Space({"log_scale": 0.0, "log_alpha": math.log(0.02), "log_var": math.log(0.08)}, {"log_scale": 1.0, "log_alpha": 1.0, "log_var": 0.7}, {"act": ("cos_sin", "cos", "tanh", "relu"), "inner": ("adam", "sgd", "momentum"), "weighting": weightings}, 0)


def unrolled_from(point: dict, base: np.ndarray, steps: int) -> UnrolledPair:
    scale = math.exp(np.clip(point["log_scale"], -3, 4))
    shift = point["block"].reshape(-1)
    w = base * scale
    if len(shift):
        w = w + 0.1 * scale * shift[: w.size].reshape(w.shape)
    return UnrolledPair(linear_act_map(w, point["act"]), steps, math.exp(np.clip(point["log_alpha"], -9, 1)), point["inner"], math.exp(np.clip(point["log_var"], -6, 1)), point["weighting"])


def train_unrolled_pair(datasets: list[np.ndarray], k: int, m: int, budget: int = 60, steps: int = 80, seed: int = 0, strategy: str = "auto", weightings: tuple[str, ...] = ("uniform", "nnls"), dp: tuple[float, float] | None = None, tune_weights: bool = False, spark: SparkSession | None = None) -> UnrolledPair:
    """Searches scale (and, with tune_weights, entries) of W, the activation, inner optimiser, its rate, the spread of starts and the weighting together.

    datasets: bounded samples of the training datasets. With a session, candidates x datasets run as Spark tasks.
    dp: (eps, delta): every evaluation decodes a privately released sketch.
    """
    d = datasets[0].shape[1]
    base = np.random.Generator(np.random.Philox([seed, 3])).standard_normal((max(1, m // 2), d)) * 4
    space = unrolled_space(d, m, weightings)
    if tune_weights:
        space = Space(space.start, space.spread, space.choices, base.size)

    def one(point: dict, generation: int, x: np.ndarray, i: int) -> float:
        pair = unrolled_from(point, base, steps)
        f = pair.fm.batch(x)
        z = f.mean(0)
        if dp is not None:
            clip = float(np.linalg.norm(f, axis=1).max())
            z = privacy.privatize(f.sum(0), len(x), dp[0], dp[1], clip, f.min(0), f.max(0), seed=1000 * generation + i).clamped
        theta = pair.decode(z, k, seed=generation, starts=1).theta
        return kmeans_mse_local(x, theta)

    def objective(points: list[dict], generation: int) -> list[float]:
        if spark is None:
            return [float(np.mean([one(p, generation, x, i) for i, x in enumerate(datasets)])) for p in points]
        jobs = spark.createDataFrame([(c, i) for c in range(len(points)) for i in range(len(datasets))], "c int, i int").repartition(len(points) * len(datasets))
        held = spark.sparkContext.broadcast((points, datasets))  # bounded samples

        def work(pdfs):
            for pdf in pdfs:
                p, xs = held.value
                yield pdf.assign(loss=[one(p[c], generation, xs[i], i) for c, i in zip(pdf["c"], pdf["i"])])

        got = {r.c: r.loss for r in jobs.mapInPandas(work, "c int, i int, loss double").groupBy("c").agg(F.avg("loss").alias("loss")).collect()}
        held.unpersist()
        return [got[c] for c in range(len(points))]

    point, tool = derivative_free_search(space, objective, budget, strategy, seed, batched=True)
    pair = unrolled_from(point, base, steps)
    pair.log = tool.history
    return pair


def unrolled_gradient(x: np.ndarray, w: np.ndarray, theta: np.ndarray, steps: int, alpha: float) -> tuple[float, np.ndarray, float]:
    """(loss, its gradient in W, largest norm met on the way back) of `steps` plain steps on the sketch distance of cos-sin features, then the distance of rows to the centroids.

    Reverse mode through every inner step, second derivatives of the features included; the norm shows where the way back explodes.
    """
    k, n = len(theta), len(w)
    y = x @ w.T
    zc, zs = np.cos(y).mean(0), np.sin(y).mean(0)
    dzc, dzs = -(np.sin(y).T @ x) / len(x), (np.cos(y).T @ x) / len(x)
    states = []
    for _ in range(steps):
        u = theta @ w.T
        c, s = np.cos(u), np.sin(u)
        ec, es = c.mean(0) - zc, s.mean(0) - zs
        a = -s * ec + c * es
        states.append((theta, c, s, ec, es, a))
        theta = theta - alpha * (2 / k) * a @ w
    d2 = ((x[:, None] - theta[None]) ** 2).sum(-1)
    near = d2.argmin(1)
    v = np.zeros_like(theta)
    np.add.at(v, near, 2 * (theta[near] - x) / len(x))
    gw, top = np.zeros((n, x.shape[1])), float(np.linalg.norm(v))
    for theta_t, c, s, ec, es, a in reversed(states):
        p = (v @ w.T) * (2 / k)
        pull_c, pull_s = (-p * s).sum(0), (p * c).sum(0)
        gy = p * (-c * ec - s * es) - s / k * pull_c + c / k * pull_s
        gw -= alpha * (gy.T @ theta_t + (2 / k) * a.T @ v - pull_c[:, None] * dzc - pull_s[:, None] * dzs)
        v = v - alpha * gy @ w
        top = max(top, float(np.linalg.norm(v)))
    return float(d2.min(1).mean()), gw, top


def train_unrolled_backprop(datasets: list[np.ndarray], k: int, m: int, steps: int = 20, alpha: float = 0.02, rounds: int = 60, rate: float = 0.02, seed: int = 0) -> tuple[UnrolledPair, list[tuple[float, float]]]:
    """The gradient-trained alternative to the search: Adam on W. Returns the pair and (loss, largest norm on the way back) of every round."""
    rng = np.random.Generator(np.random.Philox([seed, 5]))
    d = datasets[0].shape[1]
    w = 4 * rng.standard_normal((max(1, m // 2), d))
    opt, log = Adam(rate), []
    for _ in range(rounds):
        x = datasets[rng.integers(len(datasets))]
        loss, g, top = unrolled_gradient(x, w, np.clip(0.5 + 0.28 * rng.standard_normal((k, d)), 0, 1), steps, alpha)
        log.append((loss, top))
        size = np.linalg.norm(g)
        opt.update({"w": w}, {"w": g if size < 10 else g * 10 / size})
    return UnrolledPair(linear_act_map(w, "cos_sin"), steps, alpha, "sgd", 0.08, "uniform", [x for x, _ in log]), log


# autoencoders ---------------------------------------------------------------------------------------------------------


def augment_permute_negate(x: np.ndarray, seed: int, step: int) -> np.ndarray:
    """The coordinates of the whole batch in one random order, some of them negated (0 and 1 change places)."""
    rng = np.random.Generator(np.random.Philox([seed, step]))
    flip = rng.random(x.shape[1]) < 0.5
    return np.where(flip, 1 - x, x)[:, rng.permutation(x.shape[1])]


class Autoencoder:
    """f and g with a bottleneck; the first layers' biases come from the dataset's sketch: W_x x + W_z z + b.

    mode: plain (no sketch), mean, sketch, mean_sketch, per_class (mean and sketch of the row's own class).
    dynamic: bias, or bias+scale (the sketch also scales the first layer's outputs).
    """

    def __init__(self, d: int, code: int = 50, hidden: int = 64, mode: str = "plain", sketch: int = 32, dynamic: str = "bias", blocks: int = 1, seed: int = 0):
        rng = np.random.Generator(np.random.Philox([seed, 11]))
        self.d, self.code, self.mode, self.dynamic = d, code, mode, dynamic
        self.zd = {"plain": 0, "mean": d, "sketch": sketch, "mean_sketch": d + sketch, "per_class": d + sketch}[mode]
        self.phi = Chain(Affine(d, hidden, rng), Activation("relu"), Affine(hidden, sketch, rng)) if "sketch" in mode or mode == "per_class" else None
        self.enc_in, self.dec_in = Affine(d, hidden, rng), Affine(code, hidden, rng)
        self.enc_z = Affine(self.zd, hidden, rng, 0.5) if self.zd else None
        self.dec_z = Affine(self.zd, hidden, rng, 0.5) if self.zd else None
        self.enc_s = Affine(self.zd, hidden, rng, 0.1) if self.zd and dynamic == "bias+scale" else None
        self.skip = Affine(self.zd, d, rng, 0.5) if self.zd else None
        self.enc = Chain(Activation("relu"), Affine(hidden, code, rng), Activation("tanh"))
        self.dec = Chain(Activation("relu"), Affine(hidden, d, rng))

    def nets(self) -> dict[str, Layer]:
        return {k: v for k, v in (("phi", self.phi), ("enc_in", self.enc_in), ("dec_in", self.dec_in), ("enc_z", self.enc_z), ("dec_z", self.dec_z), ("enc_s", self.enc_s), ("skip", self.skip), ("enc", self.enc), ("dec", self.dec)) if v is not None}

    def sketch_rows(self, x: np.ndarray) -> np.ndarray | None:
        """The feature map whose average is the conditioning vector; rows by features."""
        if self.mode == "plain":
            return None
        if self.mode == "mean":
            return x
        f = self.phi.forward(2 * x - 1)
        return f if self.mode == "sketch" else np.concatenate([x, f], axis=1)

    def biases(self, z: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Encoder and decoder first-layer biases of each dataset: all a scan has to ship."""
        return self.enc_z.forward(2 * z - 1), self.dec_z.forward(2 * z - 1)

    def logits(self, x: np.ndarray, z: np.ndarray | None) -> np.ndarray:
        h = self.enc_in.forward(2 * x - 1)
        if z is not None:
            zz = np.broadcast_to(2 * z - 1, (len(x), self.zd))
            if self.enc_s is not None:
                h = h * (1 + self.enc_s.forward(zz))
            h = h + self.enc_z.forward(zz)
        y = self.dec_in.forward(self.enc.forward(h))
        if z is None:
            return self.dec.forward(y)
        return self.dec.forward(y + self.dec_z.forward(zz)) + self.skip.forward(zz)

    def encode(self, x: np.ndarray, z: np.ndarray | None) -> np.ndarray:
        h = self.enc_in.forward(2 * x - 1)
        if z is not None:
            zz = np.broadcast_to(2 * z - 1, (len(x), self.zd))
            if self.enc_s is not None:
                h = h * (1 + self.enc_s.forward(zz))
            h = h + self.enc_z.forward(zz)
        return self.enc.forward(h)

    def reconstruct(self, x: np.ndarray, z: np.ndarray | None) -> np.ndarray:
        return (self.logits(x, z) > 0).astype(np.int8)

    def condition(self, x: np.ndarray, classes: np.ndarray | None = None) -> np.ndarray | None:
        """The conditioning vector of each row: its dataset's, or in per_class mode its class's."""
        f = self.sketch_rows(x)
        if f is None:
            return None
        if self.mode == "per_class" and classes is not None:
            out = np.empty_like(f)
            for c in np.unique(classes):
                out[classes == c] = f[classes == c].mean(0)
            return out
        return np.repeat(f.mean(0, keepdims=True), len(x), axis=0)


def train_autoencoder(ae: Autoencoder, sources: list[tuple[np.ndarray, np.ndarray | None]], steps: int = 300, rate: float = 2e-3, batch: int = 128, seed: int = 0, randomize: bool = False, two_batch: bool = True) -> list[float]:
    """sources: (bits, classes or None). The sketch comes from one half of a batch, the loss from the other; gradients reach the sketch network through the average."""
    rng = np.random.Generator(np.random.Philox([seed, 13]))
    opt = Adam(rate, "cosine", steps)
    losses = []
    for t in range(steps):
        x, cls = sources[rng.integers(len(sources))]
        pick = rng.integers(len(x), size=2 * batch)
        rows, own = x[pick].astype(float), (cls[pick] if cls is not None else None)
        if randomize:
            rows = augment_permute_negate(rows, seed, t)
        a, b = rows[:batch], rows[batch:] if two_batch else rows[:batch]
        z, spread = None, None
        if ae.mode != "plain":
            f = ae.phi.forward(2 * a - 1, True) if ae.phi is not None else None
            parts = [a] if ae.mode == "mean" else [f] if ae.mode == "sketch" else [a, f]
            feats = np.concatenate(parts, axis=1)
            if ae.mode == "per_class" and own is not None:
                ca, cb = own[:batch], own[batch:] if two_batch else own[:batch]
                spread = (cb[:, None] == ca[None]).astype(float)
                spread[spread.sum(1) == 0] = 1.0
                spread /= spread.sum(1, keepdims=True)
            else:
                spread = np.full((len(b), len(a)), 1 / len(a))
            z = spread @ feats
        y = ae.logits(b, z)
        p = 1 / (1 + np.exp(-np.clip(y, -30, 30)))
        losses.append(float(-(b * np.log(p + 1e-9) + (1 - b) * np.log(1 - p + 1e-9)).mean()))
        g = (p - b) / b.size * b.shape[1]
        grads: dict[str, np.ndarray] = {}
        gy = ae.dec.backward(g)
        gc = ae.dec_in.backward(gy)
        gh = ae.enc.backward(gc)
        if z is not None:
            gz = 2 * (ae.dec_z.backward(gy) + ae.skip.backward(g))
            if ae.enc_s is not None:
                pre = ae.enc_in.forward(2 * b - 1)
                gz += 2 * (ae.enc_z.backward(gh) + ae.enc_s.backward(gh * pre))
                gh = gh * (1 + (2 * z - 1) @ ae.enc_s.w + ae.enc_s.b)
            else:
                gz += 2 * ae.enc_z.backward(gh)
            if ae.phi is not None:
                gf = (spread.T @ gz)[:, -f.shape[1] :]
                ae.phi.backward(gf)
        ae.enc_in.backward(gh)
        params: dict[str, np.ndarray] = {}
        for name, net in ae.nets().items():
            params |= {f"{name}.{k}": v for k, v in net.params().items()}
            grads |= {f"{name}.{k}": v for k, v in net.grads.items()}
        opt.update(params, grads)
    return losses


def balanced_accuracy_local(truth: np.ndarray, pred: np.ndarray) -> float:
    """Mean of the true-positive and true-negative rates over all bits; a rate without cases is left out."""
    pos, neg = truth == 1, truth == 0
    rates = [float((pred[m] == v).mean()) for m, v in ((pos, 1), (neg, 0)) if m.any()]
    return float(np.mean(rates)) if rates else math.nan


def save_weights(spark: SparkSession, arrays: dict[str, np.ndarray], path: str) -> None:
    rows = [(i, k, int(np.atleast_2d(v).shape[0]), int(np.atleast_2d(v).shape[1]), [float(x) for x in np.ravel(v)]) for i, (k, v) in enumerate(sorted(arrays.items()))]
    spark.createDataFrame(rows, "layer int, kind string, n_rows int, n_cols int, data array<double>").coalesce(1).write.mode("overwrite").parquet(path)


def load_weights(spark: SparkSession, path: str) -> dict[str, np.ndarray]:
    return {r.kind: np.array(r.data).reshape(r.n_rows, r.n_cols) for r in spark.read.parquet(path).collect()}


def network_grid(d: int, m: int, styles=("bn_relu", "ln_gelu"), blocks=(1, 2), hidden=(16, 32), head: str = "none", seed: int = 0) -> list[tuple[str, int, int, Chain]]:
    return [(s, b, h, residual_mlp(d, m, s, b, h, head, seed)) for s in styles for b in blocks for h in hidden]


def training_log(spark: SparkSession, log: list) -> DataFrame:
    """step, train_loss, held_loss: entries of (step, train, held) as a moment pair keeps them, or bare training losses; what was not measured is null."""
    rows = [entry if isinstance(entry, tuple) else (i, entry, math.nan) for i, entry in enumerate(log)]
    known = lambda v: None if math.isnan(v) else float(v)
    return spark.createDataFrame([(int(i), known(a), known(b)) for i, a, b in rows], "step int, train_loss double, held_loss double")


FITTED = "dataset_id string, n long, i int, theta array<double>"


def fit_from_sketch(df: DataFrame, pair: MomentPair | UnrolledPair | LearnedPair, by: str | None = "dataset_id", k: int = 1, seed: int = 0) -> DataFrame:
    """Rows to parameters: one scan sketches every dataset of df, then each sketch alone is decoded, one row of FITTED for each row i of the parameters.

    A moment pair gives the rows of the estimated second moment, an unrolled pair k centroids, a learned pair one vector. Rows of `features`; an empty table gives no rows.
    """
    if isinstance(pair, MomentPair):
        fm, decode = outer_lt_map(pair.d), pair.moment  # the encoder is affine, so it commutes with the mean: sums of the triangle are its sketch
    elif isinstance(pair, UnrolledPair):
        fm = pair.fm

        def decode(z):
            return pair.decode(z, k, seed).theta
    else:
        first = df.select("features").first()
        if first is None:
            return df.sparkSession.createDataFrame([], FITTED)
        d = len(first.features)
        fm = network_map(pair.encoder, d, pair.encoder.forward(np.zeros((1, d))).shape[1])
        decode = pair.decode

    def each(pdfs):
        for pdf in pdfs:
            rows = [(name, n, i, row) for name, n, z in zip(pdf["dataset_id"], pdf["n"], pdf["z"]) for i, row in enumerate(np.atleast_2d(decode(np.asarray(z, dtype=float))))]
            yield pd.DataFrame(rows, columns=["dataset_id", "n", "i", "theta"])

    return mean(mean_sketch(df, fm, by)).select("dataset_id", "n", "z").mapInPandas(each, FITTED)


def bank_of(sk: dict[str, tuple[int, np.ndarray]], ids: list[str]) -> np.ndarray:
    return np.array([sk[i][1] for i in ids])


def moment_of(x: np.ndarray) -> np.ndarray:
    return pack_lt(x.T @ x / len(x))


