"""Variance identities, rank statistics and error bounds, with the simulations that check the surrogates."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np


def loss_variance(sigma: np.ndarray, m: np.ndarray) -> float:
    """Variance of the squared norm of a normal vector with mean ``m`` and covariance ``sigma``."""
    return float(2 * np.trace(sigma @ sigma) + 4 * m @ sigma @ m)


def centring(sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(A, C): diagonal of size shares, and the weighted centring matrix I - J A."""
    a = np.diag(sizes / sizes.sum())
    return a, np.eye(len(sizes)) - np.ones((len(sizes),) * 2) @ a


def scalar_covariance_variance(sizes, mu, var, printed: bool = False) -> dict[str, float]:
    """Variances of the stratified covariance estimate (``target``), of its known-mean surrogate, and the former by the
    relation between the two (``link``), for scalar normal strata.

    A quadratic form's variance carries twice the trace; ``printed`` drops that factor, to show the mismatch only.
    """
    sizes, mu, var = (np.asarray(x, dtype=float) for x in (sizes, mu, var))
    a, c = centring(sizes)
    s, g2 = np.diag(var), (sizes.sum() / (sizes.sum() - 1)) ** 2
    acs = a @ c @ s
    shift = 4 * mu @ acs @ a @ c @ mu
    target = g2 * ((1 if printed else 2) * np.trace(acs @ acs) + shift)
    surrogate = 2 * np.trace((a @ s) @ (a @ s)) + shift
    link = g2 * (surrogate + 2 * np.trace(a @ a @ s) ** 2 - 4 * np.trace(a @ a @ a @ s @ s))
    return {"target": float(target), "surrogate": float(surrogate), "link": float(link)}


def partitions(n: int, k: int) -> Iterator[tuple[int, ...]]:
    """All partitions of n rows into k blocks, as restricted-growth strings."""
    def grow(head: list[int], top: int):
        if len(head) == n:
            if top == k:
                yield tuple(head)
            return
        if n - len(head) < k - top:
            return
        for b in range(min(top + 1, k)):
            yield from grow([*head, b], max(top, b + 1))

    yield from grow([], 0)


def log_stirling(n: int, k: int) -> float:
    """Log of the number of partitions of n rows into k blocks."""
    if not 0 < k <= n:
        return 0.0 if n == k == 0 else -math.inf
    row = np.full(k + 1, -np.inf)
    row[0] = 0.0
    for _ in range(n):
        with np.errstate(divide="ignore"):
            row = np.concatenate(([-np.inf], np.logaddexp(row[1:] + np.log(np.arange(1, k + 1)), row[:-1])))
    return float(row[k])


def error_bounds(log_p: float, growth: float, rho: float) -> tuple[float, float]:
    """Logs of the worst-case bound and of the value under homogeneous displacements."""
    if rho >= 1:
        return -math.inf, -math.inf
    base = math.log(growth) if growth > 0 else -math.inf
    log_p2 = 2 * log_p + math.log1p(-math.exp(-2 * log_p)) if log_p > 0 else -math.inf
    both = log_p2 + math.log((1 - rho) / 6)
    return base + (both + log_p) / 2, base + both / 2


def ranks(x: np.ndarray) -> np.ndarray:
    """Average ranks from 1."""
    u, inv, n = np.unique(x, return_inverse=True, return_counts=True)
    return (np.cumsum(n) - (n - 1) / 2)[inv]


def spearman(x, y) -> float:
    a, b = ranks(np.asarray(x)), ranks(np.asarray(y))
    a, b = a - a.mean(), b - b.mean()
    return float((a @ b) / math.sqrt((a @ a) * (b @ b))) if len(a) > 1 and a.any() and b.any() else 1.0


def stratified_covariance(z: np.ndarray, blocks: np.ndarray) -> np.ndarray:
    """Covariance of the stratified mean: squared shares times population covariances within blocks."""
    out = np.zeros((z.shape[1],) * 2)
    for b in np.unique(blocks):
        x = z[blocks == b]
        x = x - x.mean(0)
        out += (len(x) / len(z)) ** 2 * (x.T @ x) / len(x)
    return out


def enumerate_partitions(z: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(blocks, f, g) over all partitions: f the loss variance at m = 1, g the variance of the mean."""
    if len(z) > 10:
        raise ValueError("all partitions of at most 10 rows can be listed")
    blocks = np.array(list(partitions(len(z), k)))
    sig = [stratified_covariance(z, b) for b in blocks]
    return blocks, np.array([loss_variance(s, np.ones(z.shape[1])) for s in sig]), np.array([np.trace(s) for s in sig])


def simulate_kernel_mean(d: int, trials: int = 1000, law: str = "wishart", seed: int = 0) -> float:
    """Rank correlation of loss variance and mean variance over random covariances of a law."""
    rng = np.random.default_rng([seed, d])
    f, g = [], []
    for _ in range(trials):
        if law == "wishart":
            x = rng.normal(size=(d, d))
            s = x @ x.T / d * rng.random()
        elif law == "scaled":  # one covariance shape at many scales
            x = np.random.default_rng([seed, d, 1]).normal(size=(d, 2 * d))
            s = x @ x.T / d * rng.random() + 0.01 * np.diag(rng.random(d))
        elif law == "isotropic":
            s = np.eye(d) * rng.random()
        else:
            raise ValueError(law)
        f.append(loss_variance(s, np.ones(d)))
        g.append(np.trace(s))
    return spearman(f, g)


def simulate_covariance(d: int, law: str = "normal", k: int = 8, trials: int = 60, batches: int = 2000, seed: int = 0) -> float:
    """Rank correlation of the variances of the covariance estimate and of its known-mean surrogate, sizes as 1..k."""
    rng = np.random.default_rng([seed, d, len(law)])
    n_h = np.arange(1, k + 1) * 10.0
    w, n = n_h / n_h.sum(), n_h.sum()
    f, g = [], []
    for _ in range(trials):
        mu, sd = rng.normal(size=(k, d)) * rng.random(), rng.random((k, d)) + 0.1
        z = mu + sd * rng.normal(size=(batches, k, d))
        if law == "lognormal":
            z, centre = np.exp(z), np.exp(mu + sd**2 / 2)
        else:
            centre = mu
        pop = w @ centre
        x = z - (w[:, None] * z).sum(1)[:, None]
        r = np.einsum("h,bhi,bhj->bij", w, x, x) * n / (n - 1)
        y = z - pop
        rp = np.einsum("h,bhi,bhj->bij", w, y, y)
        f.append(r.var(0).sum())
        g.append(rp.var(0).sum())
    return spearman(f, g)
