"""From a sketch of the second moment back to the moment: pseudo-inverse, gradient descent and three published decoders. Lower-triangle layout."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .maps import random_projection
from .sketch import pack_lt, unpack_lt


@dataclass(frozen=True)
class Decoded:
    r: np.ndarray
    steps: int
    residual: float


def psd(r: np.ndarray) -> np.ndarray:
    w, v = np.linalg.eigh(r)
    return (v * np.maximum(w, 0)) @ v.T


def _done(v: np.ndarray, a: np.ndarray, z: np.ndarray, d: int, steps: int, clip_psd: bool) -> Decoded:
    r = unpack_lt(v, d)
    if clip_psd:
        r = psd(r)
    return Decoded(r, steps, float(np.linalg.norm(a @ pack_lt(r) - z) / max(np.linalg.norm(z), 1e-300)))


def decode_pinv(z: np.ndarray, a: np.ndarray, d: int, clip_psd: bool = False) -> Decoded:
    """The minimum-norm solution; exact where A has full column rank."""
    return _done(np.linalg.lstsq(a, z, rcond=None)[0], a, z, d, 1, clip_psd)


def decode_gradient(z: np.ndarray, a: np.ndarray, d: int, steps: int = 2000, tol: float = 1e-10, clip_psd: bool = False) -> Decoded:
    step = 1 / np.linalg.norm(a, 2) ** 2
    v = np.zeros(a.shape[1])
    n = 0
    for n in range(1, steps + 1):
        g = a.T @ (a @ v - z)
        v = v - step * g
        if np.linalg.norm(g) <= tol * np.linalg.norm(a.T @ z):
            break
    return _done(v, a, z, d, n, clip_psd)


def decode_robust(z: np.ndarray, a: np.ndarray, d: int, rank: int, steps: int = 500, cut: float = 5.0, seed: int = 0) -> Decoded:
    """R = U U' with residuals above `cut` times their median left out in each step; spectral start."""
    w, v = np.linalg.eigh(unpack_lt(a.T @ z / len(z), d))
    top = np.argsort(-w)[:rank]
    u = v[:, top] * np.sqrt(np.maximum(w[top], 1e-6))
    ii, jj = np.tril_indices(d)
    scale = np.linalg.norm(a, 2) ** 2
    n, size = 0, max(np.linalg.norm(z), 1e-300)
    # start on the scale of the data
    fit = a @ pack_lt(u @ u.T)
    u = u * np.sqrt(max(fit @ z / max(fit @ fit, 1e-300), 1e-6))
    for n in range(1, steps + 1):
        e = a @ pack_lt(u @ u.T) - z
        e = np.where(np.abs(e) <= cut * np.median(np.abs(e)) + 1e-300, e, 0.0)
        g = np.zeros((d, d))
        g[ii, jj] = a.T @ e
        g = g + g.T
        u = u - g @ u / (2 * scale * max(np.linalg.norm(u, 2) ** 2, 1e-12))
        if np.linalg.norm(e) < 1e-9 * size:
            break
    return _done(pack_lt(u @ u.T), a, z, d, n, False)


def decode_accelerated(z: np.ndarray, a: np.ndarray, d: int, steps: int = 1000, sparsity: float = 0.0, clip_psd: bool = True) -> Decoded:
    """Momentum on the squared residual, then an entry-wise soft threshold and the cone of positive semi-definite matrices."""
    step = 1 / np.linalg.norm(a, 2) ** 2
    v = y = np.zeros(a.shape[1])
    t, n = 1.0, 0
    for n in range(1, steps + 1):
        x = y - step * (a.T @ (a @ y - z))
        x = np.sign(x) * np.maximum(np.abs(x) - step * sparsity, 0)
        if clip_psd:
            x = pack_lt(psd(unpack_lt(x, d)))
        nxt = (1 + np.sqrt(1 + 4 * t * t)) / 2
        y = x + (t - 1) / nxt * (x - v)
        if np.linalg.norm(x - v) <= 1e-10 * max(np.linalg.norm(x), 1e-300):
            v = x
            break
        v, t = x, nxt
    return _done(v, a, z, d, n, False)


def decode_expgrad(z: np.ndarray, a: np.ndarray, d: int, steps: int = 400, rate: float | None = None) -> Decoded:
    """Multiplicative updates through the matrix exponential: every iterate is positive definite."""
    trace = max(float(np.trace(decode_pinv(z, a, d).r)), 1e-6)
    log_r = np.eye(d) * np.log(trace / d)
    ii, jj = np.tril_indices(d)
    best, best_e, n = None, np.inf, 0
    eta = rate or 1.0
    for n in range(1, steps + 1):
        w, v = np.linalg.eigh(log_r)
        r = (v * np.exp(np.clip(w, -60, 60))) @ v.T
        e = a @ pack_lt(r) - z
        size = float(e @ e)
        if size < best_e:
            best, best_e = r, size
            eta = min(eta * 1.1, 1e3)
            kept = log_r
        else:
            eta /= 2
            log_r = kept
            if eta < 1e-12:
                break
            w, v = np.linalg.eigh(log_r)
            r = (v * np.exp(np.clip(w, -60, 60))) @ v.T
            e = a @ pack_lt(r) - z
        g = np.zeros((d, d))
        g[ii, jj] = a.T @ e
        g = (g + g.T) / 2
        log_r = log_r - eta * g / max(np.linalg.norm(g), 1e-300) * min(1.0, np.sqrt(best_e))
        if best_e < 1e-16 * max(float(z @ z), 1e-300):
            break
    return _done(pack_lt(best), a, z, d, n, False)


# the same decoders for many datasets of one map at once: z is n x m, the result n x d x d ---------------------------------


def unpack_all(v: np.ndarray, d: int) -> np.ndarray:
    r = np.zeros((len(v), d, d))
    a, b = np.tril_indices(d)
    r[:, a, b] = v
    r[:, b, a] = v
    return r


def pack_all(r: np.ndarray) -> np.ndarray:
    a, b = np.tril_indices(r.shape[1])
    return r[:, a, b]


def _lengths(x: np.ndarray) -> np.ndarray:
    return np.sqrt((x * x).reshape(len(x), -1).sum(1))


def _symmetric(g: np.ndarray, d: int) -> np.ndarray:
    """Half of G + G' where G has the gradient in its lower triangle."""
    r = np.zeros((len(g), d, d))
    a, b = np.tril_indices(d)
    r[:, a, b] = g
    return (r + r.transpose(0, 2, 1)) / 2


def psd_all(r: np.ndarray) -> np.ndarray:
    w, v = np.linalg.eigh(r)
    return (v * np.maximum(w, 0)[:, None, :]) @ v.transpose(0, 2, 1)


def gradient_all(z: np.ndarray, a: np.ndarray, d: int, steps: int = 2000, tol: float = 1e-10) -> np.ndarray:
    step = 1 / np.linalg.norm(a, 2) ** 2
    out, on = np.zeros((len(z), a.shape[1])), np.arange(len(z))  # those not yet done
    v, first = out.copy(), _lengths(z @ a)
    for _ in range(steps):
        g = (v @ a.T - z[on]) @ a
        v = v - step * g
        out[on] = v
        go = _lengths(g) > tol * first[on]
        on, v = on[go], v[go]
        if not len(on):
            break
    return unpack_all(out, d)


def robust_all(z: np.ndarray, a: np.ndarray, d: int, rank: int, steps: int = 500, cut: float = 5.0) -> np.ndarray:
    w, v = np.linalg.eigh(unpack_all(z @ a / z.shape[1], d))
    u = v[:, :, ::-1][:, :, :rank] * np.sqrt(np.maximum(w[:, ::-1][:, :rank], 1e-6))[:, None, :]
    scale, size = np.linalg.norm(a, 2) ** 2, np.maximum(_lengths(z), 1e-300)
    fit = pack_all(u @ u.transpose(0, 2, 1)) @ a.T
    u = u * np.sqrt(np.maximum((fit * z).sum(1) / np.maximum((fit * fit).sum(1), 1e-300), 1e-6))[:, None, None]
    out, on = u.copy(), np.arange(len(z))
    for _ in range(steps):
        e = pack_all(u @ u.transpose(0, 2, 1)) @ a.T - z[on]
        far = np.abs(e)
        e = np.where(far <= cut * np.median(far, axis=1, keepdims=True) + 1e-300, e, 0.0)
        top = np.linalg.eigvalsh(u.transpose(0, 2, 1) @ u)[:, -1]  # the square of the largest singular value
        u = u - _symmetric(e @ a, d) @ u / (scale * np.maximum(top, 1e-12))[:, None, None]
        out[on] = u
        go = _lengths(e) >= 1e-9 * size[on]
        on, u = on[go], u[go]
        if not len(on):
            break
    return out @ out.transpose(0, 2, 1)


def accelerated_all(z: np.ndarray, a: np.ndarray, d: int, steps: int = 1000) -> np.ndarray:
    step = 1 / np.linalg.norm(a, 2) ** 2
    out, on = np.zeros((len(z), a.shape[1])), np.arange(len(z))
    v = y = out.copy()
    t = 1.0
    for _ in range(steps):
        x = pack_all(psd_all(unpack_all(y - step * ((y @ a.T - z[on]) @ a), d)))
        nxt = (1 + np.sqrt(1 + 4 * t * t)) / 2
        y = x + (t - 1) / nxt * (x - v)
        out[on] = x
        go = _lengths(x - v) > 1e-10 * np.maximum(_lengths(x), 1e-300)
        on, v, y, t = on[go], x[go], y[go], nxt
        if not len(on):
            break
    return unpack_all(out, d)


def expgrad_all(z: np.ndarray, a: np.ndarray, d: int, steps: int = 400) -> np.ndarray:
    def state(log_r: np.ndarray, z: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        w, v = np.linalg.eigh(log_r)
        r = pack_all((v * np.exp(np.clip(w, -60, 60))[:, None, :]) @ v.transpose(0, 2, 1))
        return r, r @ a.T - z

    least = unpack_all(z @ np.linalg.pinv(a).T, d)
    trace = np.maximum(np.trace(least, axis1=1, axis2=2), 1e-6)
    log_r = np.eye(d) * np.log(trace / d)[:, None, None]
    out, on = np.zeros((len(z), a.shape[1])), np.arange(len(z))
    kept, kept_e, best = log_r.copy(), np.zeros_like(z), np.full(len(z), np.inf)
    eta = np.ones(len(z))
    for _ in range(steps):
        r, e = state(log_r, z[on])
        size = (e * e).sum(1)
        good = size < best
        out[on[good]] = r[good]
        best = np.where(good, size, best)
        kept, kept_e = np.where(good[:, None, None], log_r, kept), np.where(good[:, None], e, kept_e)
        eta = np.where(good, np.minimum(eta * 1.1, 1e3), eta / 2)
        go = good | (eta >= 1e-12)
        g = _symmetric(kept_e @ a, d)
        log_r = kept - (eta / np.maximum(_lengths(g), 1e-300) * np.minimum(1.0, np.sqrt(best)))[:, None, None] * g
        go &= best >= 1e-16 * np.maximum((z[on] ** 2).sum(1), 1e-300)
        on, log_r, kept, kept_e, best, eta = on[go], log_r[go], kept[go], kept_e[go], best[go], eta[go]
        if not len(on):
            break
    return unpack_all(out, d)


def full_size(d: int) -> int:
    return d * (d + 1) // 2


DECODERS = {"pinv": decode_pinv, "gradient": decode_gradient, "accelerated": decode_accelerated, "expgrad": decode_expgrad}


def random_pair(v: np.ndarray, d: int, m: int, law: str, seed: int = 0, structure: str = "rank_one") -> Decoded:
    """Random rank-one projections and the pseudo-inverse, from the exact moment's triangle v."""
    a = random_projection(d, m, structure, law, "lt", seed)
    return decode_pinv(a @ v, a, d)
