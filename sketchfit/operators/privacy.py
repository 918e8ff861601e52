"""Differentially private release of a sketch, and its parts: clip level, noise calibration, clamping, a ledger of releases."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V
from .maps import FeatureMap


def normal_cdf(x: float) -> float:
    return 0.5 * (1 + math.erf(x / math.sqrt(2)))


def gaussian_sigma(eps: float, delta: float, sensitivity: float, calibration: str = "analytic") -> float:
    """Noise of the Gaussian mechanism. classic holds for eps < 1 only; analytic is the least noise, by bisection."""
    if calibration == "classic":
        if eps >= 1:
            raise ValueError("the classic calibration needs eps < 1")
        return sensitivity * math.sqrt(2 * math.log(1.25 / delta)) / eps

    def leaks(sigma: float) -> float:
        a, b = sensitivity / (2 * sigma), eps * sigma / sensitivity
        tail = normal_cdf(-a - b)
        return normal_cdf(a - b) - (math.exp(min(eps, 700)) * tail if tail > 0 else 0.0)

    low, high = 1e-9 * sensitivity, sensitivity
    while leaks(high) > delta:
        high *= 2
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if leaks(mid) > delta else (low, mid)
    return high


@dataclass(frozen=True)
class Noise:
    sigma_sum: float
    scale_count: float


def calibrate(eps: float, delta: float, clip: float, split: float = 0.9, calibration: str = "analytic") -> Noise:
    """eps is split between the sum (Gaussian, sensitivity clip) and the count (Laplace, sensitivity 1)."""
    return Noise(gaussian_sigma(split * eps, delta, clip, calibration), 1 / ((1 - split) * eps))


def release(acc: np.ndarray, n: int, noise: Noise, rng: np.random.Generator) -> np.ndarray:
    """(sum + Gaussian) / (count + Laplace). acc must come from a scan with clipping. Call once for each release, on the driver, after the merge."""
    return (acc + rng.normal(0, noise.sigma_sum, size=len(acc))) / max(n + rng.laplace(0, noise.scale_count), 1.0)


def clamp(z: np.ndarray, low: np.ndarray | float, high: np.ndarray | float) -> np.ndarray:
    return np.minimum(np.maximum(z, low), high)


@dataclass(frozen=True)
class Release:
    z: np.ndarray
    clamped: np.ndarray
    eps: float
    delta: float
    clip: float
    noise: Noise


class Ledger:
    """Budget spent on each state version; a second release of the same version adds up, sketches of new rows start anew."""

    def __init__(self):
        self.rows: list[tuple[str, float, float]] = []

    def spend(self, version: str, eps: float, delta: float) -> None:
        self.rows.append((version, eps, delta))

    def spent(self, version: str) -> tuple[float, float]:
        own = [(e, d) for v, e, d in self.rows if v == version]
        return sum(e for e, _ in own), sum(d for _, d in own)


def privatize(acc: np.ndarray, n: int, eps: float, delta: float, clip: float, low=-np.inf, high=np.inf, split: float = 0.9, calibration: str = "analytic", seed: int | None = None, ledger: Ledger | None = None, version: str = "") -> Release:
    """A private mean sketch and its clamped form. seed is for tests; in production the generator is seeded by the system."""
    noise = calibrate(eps, delta, clip, split, calibration)
    z = release(acc, n, noise, np.random.default_rng(seed))
    if ledger is not None:
        ledger.spend(version, eps, delta)
    return Release(z, clamp(z, low, high), eps, delta, clip, noise)


def private_moment(r_sum: np.ndarray, n: int, eps: float, delta: float, clip: float, seed: int | None = None) -> np.ndarray:
    """The naive baseline: rows clipped to norm `clip`, so the sum of outer products has sensitivity clip^2; noise on every entry of the triangle (off-diagonals count twice)."""
    d = len(r_sum)
    noise = calibrate(eps, delta, clip * clip)
    rng = np.random.default_rng(seed)
    a, b = np.tril_indices(d)
    v = np.where(a == b, 1.0, math.sqrt(2)) * r_sum[a, b] + rng.normal(0, noise.sigma_sum, size=len(a))
    v = np.where(a == b, v, v / math.sqrt(2)) / max(n + rng.laplace(0, noise.scale_count), 1.0)
    out = np.zeros((d, d))
    out[a, b] = v
    out[b, a] = v
    return out


def feature_norm(v: Column, fm: FeatureMap) -> Column:
    return V.norm(F.array(*fm.columns(v)))


def max_feature_norm(df: DataFrame, fm: FeatureMap, by: Column | str | None = None) -> DataFrame:
    """dataset_id, max_norm: the clip level that meta-training rows give."""
    key = F.lit("all") if by is None else (F.col(by) if isinstance(by, str) else by)
    return df.groupBy(key.cast("string").alias("dataset_id")).agg(F.max(feature_norm(V.as_doubles(F.col("features")), fm)).alias("max_norm"))


def clip_fraction(df: DataFrame, fm: FeatureMap, clip: float, by: Column | str | None = None) -> DataFrame:
    key = F.lit("all") if by is None else (F.col(by) if isinstance(by, str) else by)
    over = (feature_norm(V.as_doubles(F.col("features")), fm) > clip).cast("double")
    return df.groupBy(key.cast("string").alias("dataset_id")).agg(F.avg(over).alias("fraction"))
