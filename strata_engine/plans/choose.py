"""Choice between exact and mapped plans, as a cost rule that can be printed."""

from __future__ import annotations

import math
from dataclasses import dataclass

from ..functions.kernels import Kernel, Linear, Quadratic
from ..operators.core import SMALL_ROWS


@dataclass(frozen=True)
class Plan:
    path: str
    buckets: int
    map_dims: int
    evaluations: float
    shuffled_bytes: float
    passes: int
    fit_fraction: float


def choose(n: int, d: int, k: int, kernel: Kernel, rounds: int = 5, trials: int = 100, freqs: int = 256, worker_mb: float = 128, fit_rows: int = 10_000_000) -> Plan:
    """Exact for at most ``SMALL_ROWS`` rows; else a finite map, fitted on a sample beyond ``fit_rows``.

    A bucket's features fit a worker, and has at least 50 k rows, below which greedy assignment loses quality.
    """
    if n <= SMALL_ROWS:
        return Plan("exact", 1, 0, float(n) ** 2, float(n) * k * 8, rounds, 1.0)
    m = d if isinstance(kernel, Linear) else d * (d + 1) // 2 if isinstance(kernel, Quadratic) else 2 * freqs * len(getattr(kernel, "gammas", (1,)))
    share = min(1.0, fit_rows / n)
    by_memory, by_quality = math.ceil(n * share * d * 8 / (worker_mb * 1e6)), max(1, int(n * share) // (50 * k))
    buckets = max(1, min(max(by_memory, 1), by_quality) if by_memory <= by_quality else by_memory)
    return Plan("mapped", buckets, m, n * share * k * m * rounds, buckets * k * (m + 2) * 8.0 * rounds, rounds + 1, share)


def explain_strata(n: int, d: int, k: int, kernel: Kernel, **options) -> str:
    p = choose(n, d, k, kernel, **options)
    return f"path={p.path} buckets={p.buckets} map_dims={p.map_dims} evaluations={p.evaluations:.3g} shuffled_bytes={p.shuffled_bytes:.3g} passes={p.passes} fit_fraction={p.fit_fraction:.3g}"
