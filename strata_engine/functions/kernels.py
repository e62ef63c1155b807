"""Kernels as objects: a column expression, a block evaluator for Arrow tasks, a diagonal and, where there is one, a finite map."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column

from . import exprs as E


class Kernel:
    """Any positive-definite kernel: subclasses give ``block`` and, to stay in the JVM, ``expr``."""

    def expr(self, a, b) -> Column:
        raise NotImplementedError

    def block(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def diag(self, x: np.ndarray) -> np.ndarray:
        return np.array([self.block(r[None], r[None])[0, 0] for r in x])


@dataclass(frozen=True)
class Linear(Kernel):
    def expr(self, a, b):
        return E.dot(a, b)

    def block(self, x, y):
        return x @ y.T

    def diag(self, x):
        return np.einsum("ij,ij->i", x, x)

    def feature_map(self, x):
        return x


def _sq(x, y):
    return np.maximum((x * x).sum(1)[:, None] + (y * y).sum(1)[None] - 2 * x @ y.T, 0.0)


@dataclass(frozen=True)
class RBF(Kernel):
    """Sum of Gaussians: one bandwidth (the unit one by default) or a mixture."""

    gammas: tuple[float, ...] = (E.UNIT_GAMMA,)

    def expr(self, a, b):
        return E.rbf(a, b, self.gammas[0]) if len(self.gammas) == 1 else E.rbf_mix(a, b, self.gammas)

    def block(self, x, y):
        d = _sq(x, y)
        return sum(np.exp(-g * d) for g in self.gammas)

    def diag(self, x):
        return np.full(len(x), float(len(self.gammas)))


MIXTURE = RBF(E.GAMMAS)


@dataclass(frozen=True)
class Quadratic(Kernel):
    mu: tuple[float, ...] = field(default=())

    def expr(self, a, b):
        from pyspark.sql import functions as F

        m = F.array(*[F.lit(float(v)) for v in self.mu])
        return E.quadratic(a, b, m)

    def block(self, x, y):
        m = np.asarray(self.mu)
        return ((x - m) @ (y - m).T) ** 2

    def feature_map(self, x):
        x = x - np.asarray(self.mu)
        i, j = np.triu_indices(x.shape[1])
        return x[:, i] * x[:, j] * np.where(i == j, 1.0, 2**0.5)


class FourierMap:
    """Random Fourier features of a (mixture of) Gaussian kernel(s): its error falls with the root of the frequencies."""

    def __init__(self, kernel: RBF, d: int, freqs: int = 256, seed: int = 0):
        rng = np.random.default_rng(seed)
        self.freqs = freqs
        self.w = [rng.normal(0.0, (2 * g) ** 0.5, (d, freqs)) for g in kernel.gammas]

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return np.concatenate([f(x @ w) for w in self.w for f in (np.cos, np.sin)], axis=1) / self.freqs**0.5


class LandmarkMap:
    """Nystroem map on landmark rows; exact on the span of their images."""

    def __init__(self, kernel: Kernel, landmarks: np.ndarray, ridge: float = 1e-10):
        self.kernel, self.landmarks = kernel, landmarks
        val, vec = np.linalg.eigh(kernel.block(landmarks, landmarks))
        keep = val > ridge * max(val.max(), 1e-300)
        self.root = vec[:, keep] / np.sqrt(val[keep])

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return self.kernel.block(x, self.landmarks) @ self.root


def map_error(kernel: Kernel, fmap, x: np.ndarray) -> tuple[float, float]:
    """Greatest and mean absolute error of a map's inner products on rows ``x``."""
    f = fmap(x)
    e = np.abs(f @ f.T - kernel.block(x, x))
    return float(e.max()), float(e.mean())
