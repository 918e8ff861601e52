"""Principal components and ridge regression from second moments, and their errors, all without a scan."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V


def pca_from_moment(r: np.ndarray, k: int | None = None) -> np.ndarray:
    """Eigenvectors by falling eigenvalue, as columns; the entry of largest magnitude is positive."""
    w, v = np.linalg.eigh((r + r.T) / 2)
    v = v[:, np.argsort(-w, kind="stable")]
    v = v * np.sign(v[np.argmax(np.abs(v), axis=0), np.arange(v.shape[1])])
    return v if k is None else v[:, :k]


def pca_error(r: np.ndarray, v: np.ndarray) -> float:
    return float(np.trace(r) - np.trace(v.T @ r @ v))


def pca_error_profile(r: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Reconstruction error at ranks 1 to d of one orthonormal basis, from the moment alone."""
    return np.trace(r) - np.cumsum(np.einsum("ij,ik,kj->j", v, r, v))


def ridge_from_moment(r: np.ndarray, p: int, lam: float = 0.0, lambda_scale: str = "mean", n: int = 1, clip_psd: bool = False) -> np.ndarray:
    """Weights (p x q), targets first in the rows. `mean` adds lam to the mean moment; `sum` minimises the summed loss, so adds lam / n."""
    if clip_psd:
        from .moment_decoders import psd

        r = psd(r)
    q = len(r) - p
    add = lam if lambda_scale == "mean" else lam / n
    inner = r[p:, p:] + add * np.eye(q)
    if lam == 0:
        return np.linalg.lstsq(inner, r[p:, :p], rcond=None)[0].T
    return np.linalg.solve(inner, r[p:, :p]).T


def ridge_mse(r: np.ndarray, theta: np.ndarray, p: int) -> float:
    return float(np.trace(r[:p, :p]) - 2 * np.trace(theta @ r[p:, :p]) + np.trace(theta @ r[p:, p:] @ theta.T))


def pca_mean_errors(exact: np.ndarray, r: np.ndarray) -> np.ndarray:
    """The errors at ranks 1 to d - 1, averaged, of the bases of r (n x d x d) on the moments `exact`."""
    v = np.linalg.eigh((r + r.transpose(0, 2, 1)) / 2)[1][:, :, ::-1]
    kept = np.cumsum(np.einsum("nij,nij->nj", v, exact @ v), axis=1)
    return (np.trace(exact, axis1=1, axis2=2)[:, None] - kept)[:, :-1].mean(1)


def lre(err: float, ref: float, form: str = "ratio") -> float:
    """log10 of the error over that of the exact moment; `excess` takes the relative excess."""
    if form == "excess":
        return float(np.log10(max((err - ref) / ref, 1e-300)))
    return float(np.log10(err / ref))


def pca_transform(df: DataFrame, v: np.ndarray, column: str = "features") -> DataFrame:
    x = V.as_doubles(F.col(column))
    return df.withColumn("projected", F.array(*[V.dot_literal(x, v[:, j]) for j in range(v.shape[1])]))


def pca_reconstruct(df: DataFrame, v: np.ndarray, column: str = "projected") -> DataFrame:
    return df.withColumn("reconstructed", F.array(*[V.dot_literal(F.col(column), v[i]) for i in range(v.shape[0])]))


def ridge_predict(df: DataFrame, theta: np.ndarray, column: str = "features") -> DataFrame:
    """Prediction of the first target; features hold the targets first."""
    p, q = theta.shape
    x = F.slice(V.as_doubles(F.col(column)), p + 1, q)
    return df.withColumn("predicted", V.dot_literal(x, theta[0]))


def assign(df: DataFrame, theta: np.ndarray, column: str = "features") -> DataFrame:
    """cid (the nearest centroid, the first of equally near ones) and dist2 of every row, as one expression of k * d terms."""
    x = V.as_doubles(F.col(column))
    d2 = F.array(*[V.norm2(V.subtract(x, V.literal(c))) for c in theta])
    return df.withColumn("__d2", d2).withColumn("cid", V.argmin(F.col("__d2"))).withColumn("dist2", F.array_min("__d2")).drop("__d2")


def pca_loss(df: DataFrame, v: np.ndarray, by: Column | str | None = None) -> DataFrame:
    """Sum and mean of squared residuals over rows: the supervised loss, as a check of the moment form."""
    key = F.lit("all") if by is None else (F.col(by) if isinstance(by, str) else by)
    x = V.as_doubles(F.col("features"))
    kept = sum((V.dot_literal(x, v[:, j]) * V.dot_literal(x, v[:, j]) for j in range(1, v.shape[1])), V.dot_literal(x, v[:, 0]) * V.dot_literal(x, v[:, 0]))
    return df.groupBy(key.cast("string").alias("dataset_id")).agg(F.sum(V.norm2(x) - kept).alias("loss"), F.avg(V.norm2(x) - kept).alias("error"))


def ridge_loss(df: DataFrame, theta: np.ndarray, lam: float, by: Column | str | None = None) -> DataFrame:
    key = F.lit("all") if by is None else (F.col(by) if isinstance(by, str) else by)
    p, q = theta.shape
    x = V.as_doubles(F.col("features"))
    rest = F.slice(x, p + 1, q)
    e = sum((F.pow(F.get(x, F.lit(i)) - V.dot_literal(rest, theta[i]), 2) for i in range(p)), F.lit(0.0))
    return df.groupBy(key.cast("string").alias("dataset_id")).agg((F.sum(e) + F.lit(float(lam * (theta**2).sum()))).alias("loss"), F.avg(e).alias("mse"))


def kmeans_loss(df: DataFrame, theta: np.ndarray, by: Column | str | None = None) -> DataFrame:
    key = F.lit("all") if by is None else (F.col(by) if isinstance(by, str) else by)
    return assign(df, theta).groupBy(key.cast("string").alias("dataset_id")).agg(F.sum("dist2").alias("loss"), F.avg("dist2").alias("mse"))


class NoSurrogateLoss(Exception):
    """Autoencoders have no loss on the sketch alone."""


def moment_sketch_loss(r: np.ndarray, a: np.ndarray, z: np.ndarray) -> float:
    from .sketch import pack_lt

    return float(((a @ pack_lt(r) - z) ** 2).sum())


def moment_l1(r: np.ndarray, r_hat: np.ndarray) -> float:
    a, b = np.tril_indices(len(r))
    return float(np.abs(r[a, b] - r_hat[a, b]).sum())


def autoencoder_sketch_loss(*_args) -> float:
    raise NoSurrogateLoss("an autoencoder's loss cannot be stated on a sketch")


def kmeans_sketch_loss(theta: np.ndarray, z: np.ndarray, fm, weights: np.ndarray | None = None) -> float:
    f = fm.batch(theta)
    a = np.full(len(theta), 1 / len(theta)) if weights is None else weights
    return float(((a @ f - z) ** 2).sum())


def subspace_angle(v: np.ndarray, w: np.ndarray) -> float:
    s = np.clip(np.linalg.svd(v.T @ w, compute_uv=False), -1, 1)
    return float(np.arccos(s.min()))


def matched_centroids(theta: np.ndarray, other: np.ndarray) -> tuple[list[int], float]:
    """For each centroid its partner in `other`, at least total squared distance (assignment by shortest augmenting paths)."""
    cost = ((theta[:, None] - other[None]) ** 2).sum(-1)
    n = len(cost)
    u, v, match = np.zeros(n + 1), np.zeros(n + 1), np.zeros(n + 1, dtype=int)
    for i in range(1, n + 1):
        match[0] = i
        j0, least, way, done = 0, np.full(n + 1, np.inf), np.zeros(n + 1, dtype=int), np.zeros(n + 1, dtype=bool)
        while True:
            done[j0] = True
            i0 = match[j0]
            cur = cost[i0 - 1] - u[i0] - v[1:]
            better = ~done[1:] & (cur < least[1:])
            least[1:][better] = cur[better]
            way[1:][better] = j0
            free = np.flatnonzero(~done[1:]) + 1
            j1 = free[np.argmin(least[free])]
            delta = least[j1]
            u[match[done]] += delta
            v[done] -= delta
            least[~done] -= delta
            j0 = j1
            if match[j0] == 0:
                break
        while j0:
            match[j0] = match[way[j0]]
            j0 = way[j0]
    partner = [0] * n
    for j in range(1, n + 1):
        partner[match[j] - 1] = j - 1
    return partner, float(sum(cost[i, partner[i]] for i in range(n)))


def parameter_gap(kind: str, ref: np.ndarray, got: np.ndarray) -> float:
    if kind == "pca":
        return subspace_angle(ref, got)
    if kind == "ridge":
        return float(np.linalg.norm(ref - got))
    return matched_centroids(ref, got)[1] ** 0.5
