"""Diverse minibatch samplers: squared-distance seeding and a fixed-size determinantal process."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.kernels import FourierMap, Kernel
from ..sources.io import staged
from .cluster import seed_kpp
from .core import Small, _rows


#: Up to so many rows a kernel's eigenpairs are computed; beyond, those of a finite map's second moments (equally exact for that map).
EXACT_PAIRS = 2_000


def symmetric_sums(lam: np.ndarray, k: int) -> np.ndarray:
    """Elementary symmetric sums: row j, column i is that of order j of the first i eigenvalues."""
    e = np.zeros((k + 1, len(lam) + 1))
    e[0] = 1
    for order in range(1, k + 1):
        e[order, 1:] = np.cumsum(lam * e[order - 1, :-1])
    return e


def pick_pairs(lam: np.ndarray, e: np.ndarray, rng: np.random.Generator) -> list[int]:
    """Which eigenpairs span the draw: as many as the sums' greatest order."""
    keep, left = [], len(e) - 1
    for j in range(len(lam), 0, -1):
        if not left:
            break
        if rng.random() < lam[j - 1] * e[left - 1, j - 1] / max(e[left, j], 1e-300):
            keep.append(j - 1)
            left -= 1
    return keep


def dpp_sample(eigval: np.ndarray, eigvec: np.ndarray, k: int, rng: np.random.Generator) -> np.ndarray:
    """k rows of a determinantal process of fixed size, from its kernel's eigenpairs; no more than its rank, one at least."""
    lam = np.maximum(eigval, 0)
    lam = lam / max(lam.max(), 1e-300)  # the size is fixed, so a common scale doesn't matter
    keep = pick_pairs(lam, symmetric_sums(lam, min(k, max(1, int((lam > 1e-10).sum())))), rng)
    v = eigvec[:, keep]
    left, c, out = (v * v).sum(1), np.zeros((len(keep), len(v))), []
    for t in range(len(keep)):  # what the picked rows leave of every row's length in the subspace
        i = int(rng.choice(len(left), p=left / left.sum()))
        out.append(i)
        c[t] = (v @ v[i] - c[:t].T @ c[:t, i]) / left[i] ** 0.5
        left = np.maximum(left - c[t] ** 2, 0)
        left[i] = 0
    return np.sort(np.array(out))


def draws(ff: DataFrame, kernel: Kernel, k: int, iters: int, how: str, seed: int = 42, freqs: int = 64) -> DataFrame:
    """(iter, id, weight = 1/k, or 1 by the draws of an iteration that has fewer) of iterations spread over tasks.

    ``how``: 'seeding' restarts the squared-distance race every iteration; 'dpp' draws from the rows' kernel. Neither
    is weighted, so the kernel mean of its draws is biased; measure that beside its variance. Beyond ``EXACT_PAIRS``
    rows, all rows take part through the kernel's finite map (``freqs`` random frequencies for Gaussian kernels).
    """
    spark = ff.sparkSession
    if ff.limit(EXACT_PAIRS + 1).count() > EXACT_PAIRS:
        fmap = kernel.feature_map if hasattr(kernel, "feature_map") else FourierMap(kernel, len(ff.select("z").first()["z"]), freqs)
        return draws_over_rows(ff, fmap, k, iters, how, seed)
    small = Small(ff, limit=EXACT_PAIRS)
    z, ids = small.z, small.ids
    eig = np.linalg.eigh(kernel.block(z, z)) if how == "dpp" else None

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            its, out, weights = [], [], []
            for it in b.column(0).to_pylist():
                at = seed_kpp(z, ids, kernel, k, f"{seed}:{it}") if how == "seeding" else dpp_sample(*eig, k, np.random.default_rng([seed, it]))
                its += [it] * len(at)
                out += ids[at].tolist()
                weights += [1.0 / len(at)] * len(at)
            yield pa.RecordBatch.from_arrays([pa.array(its, pa.int64()), pa.array(out, pa.int64()), pa.array(weights, pa.float64())], names=["iter", "id", "weight"])

    return spark.range(iters).mapInArrow(work, "iter long, id long, weight double")


def uniforms(ids: np.ndarray, *key: int) -> np.ndarray:
    """Uniforms in (0, 1), one a row, keyed by its id and integers."""
    x = ids.astype(np.uint64)
    with np.errstate(over="ignore"):
        for part in key:
            x = (x ^ np.uint64(part + 1)) * np.uint64(0x9E3779B97F4A7C15)
            x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
            x ^= x >> np.uint64(32)
    return ((x >> np.uint64(12)).astype(np.float64) + 0.5) / float(1 << 52)


def second_moments(ff: DataFrame, fmap) -> np.ndarray:
    """Sum over rows of the outer product of mapped rows: m x m numbers a task."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = 0.0
        for b in batches:
            if len(b):
                f = fmap(_rows(b))
                total = total + f.T @ f
        if not isinstance(total, float):
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(total.size)), pa.array(total.ravel())], names=["i", "v"])

    got = ff.select("z").mapInArrow(work, "i long, v double").groupBy("i").agg(F.sum("v").alias("v")).toArrow()
    m = int(round(len(got) ** 0.5))
    out = np.zeros(m * m)
    out[got["i"].to_numpy()] = got["v"].to_numpy()
    return out.reshape(m, m)


def draws_over_rows(ff: DataFrame, fmap, k: int, iters: int, how: str, seed: int = 42) -> DataFrame:
    """The same draws from all rows of any number, through a finite map: k passes for all iterations together.

    In a pass every row races, in every iteration, on its squared distance to what that iteration has picked, or on what
    is left of it in the subspace of eigenpairs that the iteration drew; the winners' mapped rows, iters x m numbers, come
    back. The eigenpairs are those of the map's second moments. Rows that can't win (copies of picked ones) don't race;
    an iteration that nothing is left for ends early.
    """
    spark = ff.sparkSession
    ff = staged(ff.select("id", "z"), "pool")
    picked: list[list[int]] = [[] for _ in range(iters)]
    if how == "dpp":
        val, vec = np.linalg.eigh(second_moments(ff, fmap))
        keep = val > 1e-10 * max(val.max(initial=0.0), 1e-300)
        lam, vec = val[keep] / val.max(initial=1.0), vec[:, keep] / np.sqrt(val[keep])
        sums = symmetric_sums(lam, min(k, len(lam)))
        spans = [vec[:, pick_pairs(lam, sums, np.random.default_rng([seed, it]))] for it in range(iters)]
    else:
        spans = [np.zeros((0, 0))] * iters  # what is picked, mapped

    def racing(spans: list[np.ndarray], step: int):
        def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            best: dict[int, tuple[float, int, np.ndarray]] = {}
            for b in batches:
                if not len(b):
                    continue
                f, ids = fmap(_rows(b)), b.column(0).to_numpy()
                norms = (f * f).sum(1)
                for it, s in enumerate(spans):
                    if how == "dpp":
                        p = ((f @ s) ** 2).sum(1) if s.shape[1] else np.zeros(len(f))
                    else:
                        p = np.maximum(norms[:, None] - 2 * f @ s.T + (s * s).sum(1), 0).min(1) if len(s) else np.ones(len(f))
                    race = np.full(len(f), np.inf)
                    at = p > 1e-12
                    race[at] = -np.log(uniforms(ids[at], seed, it, step)) / p[at]
                    i = int(np.lexsort((ids, race))[0])
                    if race[i] < np.inf and (it not in best or (race[i], ids[i]) < best[it][:2]):
                        best[it] = (float(race[i]), int(ids[i]), f[i])
            for it, (race, i, row) in best.items():
                yield pa.RecordBatch.from_arrays([pa.array([it]), pa.array([race]), pa.array([i]), pa.array([row.tolist()], pa.list_(pa.float64()))], names=["iter", "race", "id", "f"])

        return work

    for step in range(k):
        got = ff.mapInArrow(racing(spans, step), "iter long, race double, id long, f array<double>").groupBy("iter").agg(F.min_by(F.struct("id", "f"), F.struct("race", "id")).alias("w")).collect()
        spans = list(spans)
        for r in got:
            it, row = r["iter"], np.array(r["w"]["f"])
            picked[it].append(r["w"]["id"])
            if how == "dpp":
                y = row @ spans[it]
                q, _ = np.linalg.qr(np.column_stack((y, np.eye(len(y)))))
                spans[it] = spans[it] @ q[:, 1 : len(y)]  # what is orthogonal to the pick
            else:
                spans[it] = np.vstack((spans[it], row)) if len(spans[it]) else row[None]
    rows = [(it, i, 1.0 / len(p)) for it, p in enumerate(picked) for i in p]
    return spark.createDataFrame(rows, "iter long, id long, weight double")


def bias_variance(z: np.ndarray, kernel: Kernel, batches: list[tuple[np.ndarray, np.ndarray]]) -> tuple[float, float]:
    """(squared bias, variance) of the kernel mean over minibatches (rows, weights), around the population's mean."""
    gram = kernel.block(z, z)
    w = np.zeros((len(batches), len(z)))
    for i, (at, weight) in enumerate(batches):
        np.add.at(w[i], at, weight)
    mean = w.mean(0)
    off = mean - 1.0 / len(z)
    around = w - mean
    return float(off @ gram @ off), float(np.einsum("ij,jk,ik->i", around, gram, around).mean())
