"""Training with periodic re-stratification, random search, and grids whose cells are spread over Spark tasks."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.pandas.types import to_arrow_type

from ..functions.kernels import MIXTURE, RBF, FourierMap, Linear, Quadratic
from ..operators import greedy as G
from ..operators.cluster import mean_variance, seed_kpp, stratify, uniform_variance
from ..operators.diverse import EXACT_PAIRS, dpp_sample
from .model import Adam, Net

SAMPLERS = ("uniform", "seeding", "dpp", "kmeans_inputs", "kmeans_features", "swks")


class Sampler:
    """Minibatches of one domain: rows and weights. Strata are rebuilt when told to."""

    def __init__(self, name: str, k: int, loss: str, seed: int, trials: int = 100, parallel: int = 10):
        self.name, self.k, self.loss, self.trials, self.parallel = name, k, loss, trials, parallel
        self.rng, self.strata, self.seed, self.eig, self.objective = np.random.default_rng(seed), None, seed, None, None

    def rebuild(self, x: np.ndarray, z: np.ndarray) -> None:
        n, k = len(z), min(self.k, len(z))
        if self.name == "swks":
            kernel = Quadratic(tuple(z.mean(0))) if self.loss == "cad" else MIXTURE
            start = np.sort(self.rng.choice(n, k, replace=False)) if len(np.unique(z, axis=0)) < k else None
            self.strata = stratify(z, kernel, k, trials=self.trials, parallel=self.parallel, max_iter=5, seed=int(self.rng.integers(1 << 30)), start=start).strata
        elif self.name == "kmeans_features" or self.name == "kmeans_inputs" and self.strata is None:
            self.strata = stratify(z if self.name == "kmeans_features" else x, Linear(), k, weighted=False, max_iter=10, seed=self.seed, start=np.sort(self.rng.choice(n, k, replace=False))).strata
        elif self.name == "dpp":
            if n <= EXACT_PAIRS:
                self.eig = np.linalg.eigh(MIXTURE.block(z, z))
            else:  # the kernel's finite map: its second moments have the same eigenvalues
                f = FourierMap(MIXTURE, z.shape[1], 32)(z)
                val, vec = np.linalg.eigh(f.T @ f)
                keep = val > 1e-10 * val.max()
                self.eig = val[keep], f @ (vec[:, keep] / np.sqrt(val[keep]))
        self.z = z

    def draw(self) -> tuple[np.ndarray, np.ndarray]:
        n, k = len(self.z), min(self.k, len(self.z))
        if self.name == "uniform":
            return self.rng.integers(0, n, k), np.full(k, 1.0 / k)
        if self.name == "seeding":
            z = self.z
            near, got = np.full(len(z), np.inf), [int(self.rng.integers(len(z)))]
            for _ in range(k - 1):
                near = np.minimum(near, ((z - z[got[-1]]) ** 2).sum(1))
                s = near.sum()
                got.append(int(self.rng.choice(len(z), p=near / s)) if s > 0 else int(self.rng.integers(len(z))))
            return np.array(got), np.full(k, 1.0 / k)
        if self.name == "dpp":
            got = dpp_sample(*self.eig, min(k, len(self.eig[0])), self.rng)
            return got, np.full(len(got), 1.0 / len(got))
        order = np.argsort(self.strata, kind="stable")
        sizes = np.bincount(self.strata, minlength=k)
        first = np.cumsum(sizes) - sizes
        full = np.flatnonzero(sizes)
        pick = order[first[full] + (self.rng.random(len(full)) * sizes[full]).astype(int)]
        return pick, sizes[full] / n

    def variance(self, z: np.ndarray, kernel=MIXTURE) -> float:
        gram = kernel.block(z, z)
        return uniform_variance(gram, self.k) if self.strata is None else mean_variance(gram, self.strata, int(self.strata.max()) + 1)


@dataclass
class Config:
    method: str = "med"
    sampler: str = "swks"
    k: int = 32
    lr: float = 1e-2
    decay: float = 1e-4
    lam: float = 1.0
    steps: int = 200
    every: int = 100  # iterations between re-stratifications
    growth: float = 1.0  # of that interval, after each one
    staleness: float | None = None  # instead: rebuild when the variance has grown by this factor
    width: int = 8
    trials: int = 20
    parallel: int = 10
    task_weights: str = "stratum"
    seed: int = 0


def train(data: dict, c: Config, trace: list | None = None, traced: int = 10) -> Net:
    """``data``: xs, ys, es (environments), xt. Weights n_h/n go to the discrepancy and, by default, to the task loss.

    ``trace`` collects (step, discrepancy, variance of the kernel mean every ``traced`` steps).
    """
    xs, ys, xt = data["xs"], data["ys"], data["xt"]
    net = Net(c.method, xs.shape[1], c.width, data["classes"], c.seed, c.lam)
    opt = Adam(net.p, c.lr, c.decay)
    s, t = (Sampler(c.sampler, c.k, c.method, [c.seed, i][1] + 2 * c.seed, c.trials, c.parallel) for i in (0, 1))
    due, wait, then = 0, c.every, None
    for it in range(c.steps):
        if it >= due or c.staleness and it % 10 == 0 and s.strata is not None and then and s.variance(net.features(xs)) > c.staleness * then:
            s.rebuild(xs, net.features(xs))
            t.rebuild(xt, net.features(xt))
            due, wait = it + int(wait), wait * c.growth
            then = s.variance(net.features(xs)) if c.staleness and s.strata is not None else None
        i, w = s.draw()
        j, v = t.draw()
        env = data["es"][i] if c.method == "arm" else None
        task_w = w if c.task_weights == "stratum" else np.full(len(i), 1.0 / len(i))
        _, da, g = net.loss(xs[i], ys[i], task_w if c.method in ("erm", "arm") else w, xt[j], v, len(xs), len(xt), env)
        opt.step(net.p, g)
        if trace is not None:
            trace.append((it, float(da), s.variance(net.features(xs)) if it % traced == 0 else None))
    return net


def accuracy(net: Net, x, y, env=None) -> tuple[float, float]:
    """(accuracy, balanced accuracy)."""
    p = net.predict(x, env)
    per = [float((p[y == c] == c).mean()) for c in np.unique(y)]
    return float((p == y).mean()), float(np.mean(per)) if per else 0.0


def search(data: dict, method: str, sampler: str, configs: int = 10, seed: int = 0, **fixed) -> Config:
    """Random search, judged on source rows that are held out: learning rate, decay, k = 2^U(3,7), lambda = 10^U(-1,1)."""
    rng = np.random.default_rng([seed, 99])
    hold = rng.random(len(data["xs"])) < 0.2
    part = data | {"xs": data["xs"][~hold], "ys": data["ys"][~hold], "es": data["es"][~hold]}
    best, best_acc = None, -1.0
    for i in range(configs):
        c = Config(method, sampler, k=int(2 ** rng.uniform(3, 7)), lam=10 ** rng.uniform(-1, 1), lr=10 ** rng.uniform(-3, -1.5), decay=10 ** rng.uniform(-6, -2), seed=seed * 100 + i, **fixed)
        acc = accuracy(train(part, c), data["xs"][hold], data["ys"][hold], data["es"][hold])[0]
        if acc > best_acc:
            best, best_acc = c, acc
    return best


def split(x, y, env, target: str, classes: int, seed: int = 0) -> dict:
    """Source: all other environments; target: this one, part of it for adaptation (unlabelled) and the rest for scoring."""
    at = env == target
    hold = np.random.default_rng([seed, 5]).random(len(x)) < 0.5
    return {"xs": x[~at], "ys": y[~at], "es": env[~at], "xt": x[at & ~hold], "xe": x[at & hold], "ye": y[at & hold], "classes": classes}


def grid(spark: SparkSession, sets: dict[str, dict], cells: list[dict], configs: int = 2, **fixed) -> DataFrame:
    """One task a cell: accuracy, discrepancies of held-out features and seconds; the bounded data are broadcast once.

    A cell names its dataset, method, sampler and repeat, and may fix further settings of its own.
    """
    total = sum(a.nbytes for s in sets.values() for a in s.values() if isinstance(a, np.ndarray))
    if total > 256_000_000:
        raise ValueError("training sets for the grid are bounded at 256 MB; train on draws of one set instead")
    shared = spark.sparkContext.broadcast(sets)

    def run(c: dict) -> tuple:
        data, began = shared.value[c["dataset"]], time.perf_counter()
        own = fixed | {k: v for k, v in c.items() if k not in ("dataset", "method", "sampler", "repeat")}
        found = search(data, c["method"], c["sampler"], configs, c["repeat"], **own) if configs > 1 else Config(c["method"], c["sampler"], seed=c["repeat"], **own)
        net = train(data, found)
        seconds = time.perf_counter() - began
        return (c["dataset"], c["method"], c["sampler"], c["repeat"], *accuracy(net, data["xe"], data["ye"], np.zeros(len(data["xe"]))), *discrepancies(net, data), seconds)

    return over_tasks(spark, cells, run, "dataset string, method string, sampler string, repeat int, accuracy double, balanced double, med double, cad double, seconds double")


def discrepancies(net: Net, data: dict) -> tuple[float, float]:
    """(mean-embedding, covariance) discrepancy of source features and those of target rows that training didn't see."""
    a, b = net.features(data["xs"]), net.features(data["xe"])
    if min(len(a), len(b)) < 2:
        return float("nan"), float("nan")
    med = MIXTURE.block(a, a).mean() + MIXTURE.block(b, b).mean() - 2 * MIXTURE.block(a, b).mean()
    return float(max(med, 0.0)), float(((np.cov(a.T) - np.cov(b.T)) ** 2).sum())


def over_tasks(spark: SparkSession, cells: list, run: Callable, schema: str, most: int = 512) -> DataFrame:
    """The row, or rows, that ``run`` gives for each cell, spread over tasks; the cells are bounded and go with the tasks."""
    kinds = spark.createDataFrame([], schema).schema
    df = spark.createDataFrame([(i,) for i in range(len(cells))], "i long").repartitionByRange(max(1, min(len(cells), most)), "i")

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in b.column(0).to_pylist():
                out = run(cells[i])
                rows = out if isinstance(out, list) else [out]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, to_arrow_type(f.dataType)) for c, f in zip(zip(*rows, strict=True), kinds, strict=True)], names=kinds.names)

    return df.mapInArrow(work, kinds)


__all__ = ["SAMPLERS", "RBF", "Config", "Sampler", "accuracy", "discrepancies", "grid", "over_tasks", "search", "seed_kpp", "split", "train", "G"]
