"""Size-weighted assignment of rows to strata: numpy cores that run on a driver's small matrix or inside an Arrow task."""

from __future__ import annotations

import numpy as np


def assignment_cost(dist: np.ndarray, strata: np.ndarray) -> float:
    """Sum over strata of size times summed distance."""
    k = dist.shape[1]
    sizes = np.bincount(strata, minlength=k)
    return float((sizes * np.bincount(strata, weights=dist[np.arange(len(dist)), strata], minlength=k)).sum())


def nearest(dist: np.ndarray) -> np.ndarray:
    return dist.argmin(1)


class Pass:
    """One pass in a given order, fed piece by piece: only sizes and sums so far are kept, whatever the number of rows.

    Each row takes the stratum that is cheapest at the sizes so far; ``parallel`` rows share stale sizes.
    ``score='marginal'`` adds what the residents of a stratum pay for its growth. Ties go to the lowest stratum. A stretch
    of rows is guessed at once and guessed again with the sizes that the guess implies until nothing changes: then each
    row saw just what the rows before it left, so the picks are those of a row-by-row pass.
    """

    def __init__(self, parallel: int = 1, score: str = "printed"):
        self.parallel, self.marginal = parallel, score == "marginal"
        self.sizes = self.sums = np.zeros(0)
        self.stale, self.open, self.width = (self.sizes, self.sums), 0, parallel

    def take(self, dist: np.ndarray) -> np.ndarray:
        if not len(self.sizes):
            self.sizes = self.sums = np.zeros(dist.shape[1])
        dist = np.maximum(dist, 0.0)
        out, at = np.empty(len(dist), dtype=np.int64), 0
        while at < len(dist):
            if self.open:  # the rest of a group that began in an earlier piece
                d = dist[at : at + self.parallel - self.open]
                pick = self._cheapest(d, *self.stale)
            else:
                d = dist[at : at + self.width]
                self.stale, pick = (self.sizes, self.sums), self._settle(d)
                whole = len(d) // self.parallel * self.parallel
                if 0 < whole < len(d):  # a group that stays open begins a stretch of its own
                    d, pick = d[:whole], pick[:whole]
            self._add(d, pick)
            self.open = (self.open + len(d)) % self.parallel
            out[at : at + len(d)] = pick
            at += len(d)
        return out

    def cost(self) -> float:
        """Sum over strata of size times summed distance, added in their order."""
        return float(np.cumsum(self.sizes * self.sums)[-1]) if len(self.sizes) else 0.0

    def _cheapest(self, d: np.ndarray, sizes: np.ndarray, sums: np.ndarray) -> np.ndarray:
        cost = d * (sizes + 1.0)
        return (cost + sums if self.marginal else cost).argmin(1)

    def _settle(self, d: np.ndarray) -> np.ndarray:
        n, k = d.shape
        row, first = np.arange(n), np.arange(n) // self.parallel * self.parallel
        pick, rounds = self._cheapest(d, self.sizes, self.sums), 0
        while n > self.parallel:
            before = np.zeros((n + 1, k))
            before[0] = self.sizes
            before[row + 1, pick] = 1.0
            sizes, sums = np.cumsum(before, axis=0)[first], 0.0
            if self.marginal:
                before = np.zeros((n + 1, k))
                before[0] = self.sums
                before[row + 1, pick] = d[row, pick]
                sums = np.cumsum(before, axis=0)[first]
            now, rounds = self._cheapest(d, sizes, sums), rounds + 1
            if (now == pick).all():
                break
            pick = now
        if rounds <= 6 and self.width < 4096:
            self.width *= 2
        elif rounds > 12 and self.width > self.parallel:
            self.width //= 2
        return pick

    def _add(self, d: np.ndarray, pick: np.ndarray) -> None:
        self.sizes = self.sizes + np.bincount(pick, minlength=len(self.sizes))
        add = np.zeros((len(d) + 1, len(self.sums)))
        add[0] = self.sums
        add[np.arange(len(d)) + 1, pick] = d[np.arange(len(d)), pick]
        self.sums = np.cumsum(add, axis=0)[-1]


def greedy(dist: np.ndarray, order: np.ndarray | None = None, parallel: int = 1, score: str = "printed") -> np.ndarray:
    """One ``Pass`` over a matrix, in its order or another."""
    order = np.arange(len(dist)) if order is None else order
    out = np.empty(len(dist), dtype=np.int64)
    out[order] = Pass(parallel, score).take(dist[order])
    return out


def best_of(dist: np.ndarray, trials: int, parallel: int = 10, seed: int = 0, score: str = "printed", orders: list[np.ndarray] | None = None) -> tuple[np.ndarray, float, list[float]]:
    """The cheapest of ``trials`` passes over shuffled rows, all advanced together, and the cost of every one.

    Trials are nested: the first R of more trials are the same ones, so more can't be worse.
    """
    dist = np.maximum(dist, 0.0)
    n, k = dist.shape
    trials = len(orders) if orders is not None else trials
    best, best_cost, costs = None, np.inf, []
    for lo in range(0, trials, 256):
        some = range(lo, min(trials, lo + 256))
        perm = np.stack([orders[t] if orders is not None else np.random.default_rng([seed, t]).permutation(n) for t in some])
        r = len(perm)
        sizes, sums, picks = np.zeros((r, k)), np.zeros((r, k)), np.empty((r, n), dtype=np.int64)
        lane = np.arange(r)
        for at in range(0, n, parallel):
            rows = perm[:, at : at + parallel]
            d = dist[rows]
            cost = d * (sizes + 1.0)[:, None, :]
            if score == "marginal":
                cost = cost + sums[:, None, :]
            pick = cost.argmin(2)
            for c in range(pick.shape[1]):
                picks[lane, rows[:, c]] = pick[:, c]
                sizes[lane, pick[:, c]] += 1
                sums[lane, pick[:, c]] += d[lane, c, pick[:, c]]
        total = (sizes * sums).sum(1)
        costs += total.tolist()
        i = int(total.argmin())
        if total[i] < best_cost:
            best, best_cost = picks[i].copy(), float(total[i])
    return best, best_cost, costs


def polish(dist: np.ndarray, strata: np.ndarray, sweeps: int = 20) -> np.ndarray:
    """Single-row moves under the true cost until none helps."""
    dist, strata = np.maximum(dist, 0.0), strata.copy()
    k = dist.shape[1]
    sizes = np.bincount(strata, minlength=k).astype(float)
    sums = np.bincount(strata, weights=dist[np.arange(len(dist)), strata], minlength=k)
    for _ in range(sweeps):
        moved = False
        for i, row in enumerate(dist):
            a = strata[i]
            leave = sizes[a] * sums[a] - (sizes[a] - 1) * (sums[a] - row[a])
            enter = (sizes + 1) * (sums + row) - sizes * sums
            enter[a] = np.inf
            b = int(enter.argmin())
            if enter[b] < leave - 1e-12:
                sizes[a], sums[a] = sizes[a] - 1, sums[a] - row[a]
                sizes[b], sums[b] = sizes[b] + 1, sums[b] + row[b]
                strata[i], moved = b, True
        if not moved:
            break
    return strata


def _simplex(v: np.ndarray) -> np.ndarray:
    """Each row's projection onto the probability simplex."""
    u = -np.sort(-v, axis=1)
    c = (np.cumsum(u, axis=1) - 1) / np.arange(1, v.shape[1] + 1)
    rho = (u > c).sum(1)
    return np.maximum(v - c[np.arange(len(v)), rho - 1][:, None], 0)


def relaxed(dist: np.ndarray, iters: int = 400, seed: int = 0, limit: int = 1_000_000) -> tuple[np.ndarray, float, np.ndarray]:
    """A local optimum of the continuous programme, its value, and its rounding by greatest share.

    Barrier steps on the interior for small problems, projected gradient beyond. The cost is convex within a row's
    shares, so fractional optima below every integer cost exist and are reported as such. For a few hundred rows only.
    """
    n, k = dist.shape
    if n * k > limit:
        raise ValueError(f"the continuous programme is for small inputs; {n} x {k} is over {limit}")
    dist = np.maximum(dist, 0.0)
    rng = np.random.default_rng(seed)
    u = _simplex(np.full((n, k), 1 / k) + 0.01 * rng.random((n, k)))
    value = lambda u: float(((u * dist).sum(0) * u.sum(0)).sum())
    if n * k <= 2000:
        for t in 10.0 ** np.arange(0, 5):
            for _ in range(30):  # log-barrier, diagonal Newton steps on the simplex
                u = np.maximum(u, 1e-9)
                g = t * (dist * u.sum(0) + (u * dist).sum(0)) - 1 / u
                h = t * 2 * dist + 1 / u**2
                lam = (g / h).sum(1) / (1 / h).sum(1)
                step = -(g - lam[:, None]) / h
                a = np.where(step < 0, -u / np.where(step < 0, step, -1), np.inf).min(1).clip(max=1.0)
                u = u + 0.9 * a[:, None] * step
    rate, best = 1.0 / max(2 * dist.max() * n, 1e-12), value(u)
    for _ in range(iters):
        v = _simplex(u - rate * (dist * u.sum(0) + (u * dist).sum(0)))
        now = value(v)
        if now < best:
            u, best, rate = v, now, rate * 1.3
        else:
            rate *= 0.5
            if rate < 1e-14:
                break
    return u, best, u.argmax(1)
