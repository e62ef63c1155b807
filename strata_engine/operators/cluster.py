"""Kernel seeding and the alternating stratification, exact for bounded frames and mapped beyond.

The mapped path is Lloyd's loop over a finite feature map: centroids (k x m numbers) go to the tasks, every bucket of
rows is assigned greedily with its own sizes, and sums of features come back, one job a round. The best round is kept.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import exprs as E
from ..functions.kernels import Kernel, Linear
from ..sources import io
from . import greedy as G
from .core import Small, Spread, _rows, distances_of_sums

#: Rows up to which all pairs are kept at once, on the driver.
GRAM_ROWS = 4_000


def u01(*parts) -> float:
    """The portable uniform, on the driver."""
    import hashlib

    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:13], 16) / float(1 << 52)


def seed_kpp(z: np.ndarray, ids: np.ndarray, kernel: Kernel, k: int, seed: int | str = 42) -> np.ndarray:
    """Indexes of k seeds: the first by least uniform, each further one by an exponential race on squared image distances."""
    if len(np.unique(z, axis=0)) < k:
        raise ValueError(f"fewer distinct rows than {k} strata")
    first = int(np.argmin([u01(seed, "seed", 0, i) for i in ids]))
    picked, diag = [first], kernel.diag(z)
    near = np.full(len(z), np.inf)
    for r in range(1, k):
        c = z[picked[-1]][None]
        near = np.minimum(near, np.maximum(diag + kernel.diag(c)[0] - 2 * kernel.block(z, c)[:, 0], 0.0))
        with np.errstate(divide="ignore"):
            race = np.array([-np.log(1 - u01(seed, "seed", r, i)) for i in ids]) / near
        race[near <= 1e-12] = np.inf
        picked.append(int(race.argmin()))
    return np.array(picked)


def seed_rows(ff: DataFrame, kernel: Kernel, k: int, seed: int | str = 42) -> tuple[list[int], np.ndarray]:
    """The ids and vectors that ``seed_kpp`` picks, from a frame of any size: a pass a seed, which keeps the winner of the race."""
    first = ff.select("id", "z").orderBy(E.portable_u(seed, "seed", 0, F.col("id")), "id").limit(1).collect()
    ids, z = [r["id"] for r in first], [r["z"] for r in first]

    def racing(to: np.ndarray):
        def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if len(b):
                    x = _rows(b)
                    near = np.maximum(kernel.diag(x)[:, None] + kernel.diag(to) - 2 * kernel.block(x, to), 0.0).min(1)
                    at = np.flatnonzero(near > 1e-12)
                    race = -np.log(1 - b.column(2).to_numpy()[at]) / near[at]
                    i = at[np.lexsort((b.column(0).to_numpy()[at], race))[:1]]
                    yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(i)), b.column(1).take(pa.array(i)), pa.array(np.sort(race)[:1])], names=["id", "z", "race"])

        return work

    for r in range(1, k):
        dealt = ff.select("id", E.vec("z").alias("z"), E.portable_u(seed, "seed", r, F.col("id")).alias("u"))
        won = dealt.mapInArrow(racing(np.array(z, dtype=float)), "id long, z array<double>, race double").orderBy("race", "id").limit(1).collect() if ids else []
        if not won:
            raise ValueError(f"fewer distinct rows than {k} strata")
        ids, z = [*ids, won[0]["id"]], [*z, won[0]["z"]]
    return ids, np.array(z, dtype=float)


@dataclass
class Strata:
    strata: np.ndarray
    variance: float
    rounds: int
    history: list[float]
    reseeded: int


def image_distances(z: np.ndarray, strata: np.ndarray, kernel: Kernel, k: int, gram: np.ndarray | None = None) -> np.ndarray:
    gram = kernel.block(z, z) if gram is None else gram
    one = np.zeros((len(z), k))
    one[np.arange(len(z)), strata] = 1
    n = one.sum(0)
    s = gram @ one
    safe = np.maximum(n, 1)
    d = np.diag(gram)[:, None] - 2 * s / safe + np.einsum("ij,ij->j", one, s) / safe**2
    return np.where(n > 0, np.maximum(d, 0), np.inf)


def mean_variance(gram: np.ndarray, strata: np.ndarray, k: int) -> float:
    """Variance of the stratified kernel mean: sizes times scatters, over n squared."""
    out = 0.0
    for h in range(k):
        at = strata == h
        n = int(at.sum())
        if n:
            out += n * (np.diag(gram)[at].sum() - gram[np.ix_(at, at)].sum() / n)
    return max(out, 0.0) / len(strata) ** 2


def uniform_variance(gram: np.ndarray, k: int, replace: bool = True) -> float:
    n = len(gram)
    v = (np.diag(gram).mean() - gram.mean()) / k
    return float(v if replace else v * (n - k) / max(n - 1, 1))


def portable_orders(ids: np.ndarray, trials: int, seed: int, it: int, first: int = 0) -> list[np.ndarray]:
    """Shuffled orders of a round's trials, from number ``first`` on, by portable uniforms, which SQL can replay."""
    return [np.lexsort((ids, [u01(seed, "perm", it, t, i) for i in ids.tolist()])) for t in range(first, first + trials)]


def stratify(z: np.ndarray, kernel: Kernel, k: int, ids: np.ndarray | None = None, weighted: bool = True, trials: int = 100, parallel: int = 10, max_iter: int = 20, patience: int = 4, seed: int = 42, start: np.ndarray | None = None, polish: bool = False, portable: bool = False) -> Strata:
    """Alternate image distances and (size-weighted or nearest) assignment, keeping the best round.

    An empty stratum takes the row with the largest weighted distance. ``k`` of at least n gives singletons. ``portable``
    takes the trials' orders from portable uniforms keyed by id.
    """
    n = len(z)
    ids = np.arange(n) if ids is None else ids
    if k >= n:
        return Strata(np.arange(n), 0.0, 0, [0.0], 0)
    gram = kernel.block(z, z)
    picked = seed_kpp(z, ids, kernel, k, seed) if start is None else start
    d = np.maximum(np.diag(gram)[:, None] + np.diag(gram)[picked] - 2 * gram[:, picked], 0)
    best, best_v, history, bad, reseeded, now = None, np.inf, [], 0, 0, None
    for it in range(max_iter):
        orders = portable_orders(ids, trials, seed, it) if portable and weighted else None
        new = G.best_of(d, trials, parallel, seed + it, orders=orders)[0] if weighted and (trials > 1 or parallel > 1) else G.greedy(d) if weighted else G.nearest(d)
        counts = np.bincount(new, minlength=k)
        for h in np.flatnonzero(counts == 0):
            cost = d[np.arange(n), new] * counts[new]
            cost[counts[new] <= 1] = -1
            i = int(cost.argmax())
            counts[new[i]] -= 1
            new[i], counts[h] = h, 1
            reseeded += 1
        v = mean_variance(gram, new, k)
        history.append(v)
        if v < best_v - 1e-15:
            best, best_v, bad = new, v, 0
        else:
            bad += 1
        if now is not None and (new == now).all() or bad >= patience:
            break
        now = new
        d = image_distances(z, new, kernel, k, gram)
    if polish:
        moved = G.polish(image_distances(z, best, kernel, k, gram), best)
        v = mean_variance(gram, moved, k)
        if v < best_v:
            best, best_v = moved, v
    return Strata(best, best_v, len(history), history, reseeded)


def stratify_frame(ff: DataFrame, kernel: Kernel | Callable[[np.ndarray], Kernel], k: int, fmap=None, **options) -> DataFrame:
    """(domain, id, stratum), each domain by itself. Exact; with ``fmap`` the mapped path is taken. Beyond ``GRAM_ROWS``
    rows pairs are computed anew in the tasks in every round, and the trials of a round are dealt over tasks.

    ``kernel`` may also be a function that makes one of a domain's rows, such as the quadratic one about their mean.
    An empty frame gives no rows, a domain of up to k rows a stratum for each, a null vector an error.
    """
    spark = ff.sparkSession
    if fmap is not None:
        return stratify_mapped(ff, fmap, k, **options)
    if not {"weighted", "start", "polish"} & set(options) and ff.count() > GRAM_ROWS:
        return _stratify_spread(ff, kernel, k, **options)
    small = Small(ff, "domain")
    parts = []
    for dom in sorted(set(small.extra["domain"].tolist())):
        at = small.extra["domain"] == dom
        found = stratify(small.z[at], kernel if isinstance(kernel, Kernel) else kernel(small.z[at]), k, small.ids[at], **options)
        parts.append(pa.table({"domain": pa.array([dom] * int(at.sum())), "id": pa.array(small.ids[at]), "stratum": pa.array(found.strata, pa.int32())}))
    return spark.createDataFrame(pa.concat_tables(parts)) if parts else spark.createDataFrame([], "domain string, id long, stratum int")


def _stratify_spread(ff: DataFrame, kernel: Kernel | Callable[[np.ndarray], Kernel], k: int, trials: int = 100, parallel: int = 10, max_iter: int = 20, patience: int = 4, seed: int = 42, portable: bool = False) -> DataFrame:
    """``stratify`` of every domain by sums that come from the tasks; the driver keeps k numbers a row, never pairs."""
    spark, parts = ff.sparkSession, []
    for dom in sorted(r["domain"] for r in ff.select("domain").distinct().collect()):
        one = ff.filter(F.col("domain") == dom)
        spread = Spread(one)
        ids, n = spread.ids, len(spread)
        if n <= k:
            found = np.arange(n)
        else:
            if isinstance(kernel, Kernel):
                own = kernel
            else:  # made of the mean of the rows, by chunks
                own = kernel(sum(x.value.astype(float).sum(0) for x in spread.chunks)[None] / n)
            found = _alternate(spread, own, seed_rows(one, own, k, seed)[1], k, trials, parallel, max_iter, patience, seed, portable)
        spread.close()
        parts.append(pa.table({"domain": pa.array([dom] * n), "id": pa.array(ids), "stratum": pa.array(found, pa.int32())}))
    return spark.createDataFrame(pa.concat_tables(parts)) if parts else spark.createDataFrame([], "domain string, id long, stratum int")


def _alternate(spread: Spread, kernel: Kernel, centres: np.ndarray, k: int, trials: int, parallel: int, max_iter: int, patience: int, seed: int, portable: bool) -> np.ndarray:
    n, everyone = len(spread), [x.value.astype(float) for x in spread.chunks]
    diag = np.concatenate([kernel.diag(x) for x in everyone])
    d = np.concatenate([np.maximum(kernel.diag(x)[:, None] + kernel.diag(centres) - 2 * kernel.block(x, centres), 0) for x in everyone])
    del everyone
    best, best_v, bad, now = None, np.inf, 0, None
    for it in range(max_iter):
        new = _dealt_trials(spread, d, trials, parallel, seed, it, portable)
        counts = np.bincount(new, minlength=k)
        for h in np.flatnonzero(counts == 0):
            cost = d[np.arange(n), new] * counts[new]
            cost[counts[new] <= 1] = -1
            i = int(cost.argmax())
            counts[new[i]] -= 1
            new[i], counts[h] = h, 1
        s = spread.mapped_sums(kernel, new, k) if hasattr(kernel, "feature_map") else spread.sums(kernel, new, k)
        inner = np.bincount(new, weights=s[np.arange(n), new], minlength=k)
        v = max(float((counts * (np.bincount(new, weights=diag, minlength=k) - inner / counts)).sum()), 0.0) / n**2
        if v < best_v - 1e-15:
            best, best_v, bad = new, v, 0
        else:
            bad += 1
        if now is not None and (new == now).all() or bad >= patience:
            break
        now, d = new, distances_of_sums(s, new, counts, diag)
    return best


def _dealt_trials(spread: Spread, d: np.ndarray, trials: int, parallel: int, seed: int, it: int, portable: bool) -> np.ndarray:
    """The cheapest of a round's shuffled passes, the first of equals; every task takes some and returns its best."""
    spark = spread.spark
    shared = spark.sparkContext.broadcast((spread.ids, d))
    tasks = min(trials, 2 * spark.sparkContext.defaultParallelism)

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mine = [t for b in batches for t in b.column(0).to_pylist()]
        ids, dist = shared.value
        best = None
        for lo in range(0, len(mine), 8):
            some = mine[lo : lo + 8]
            orders = [portable_orders(ids, 1, seed, it, t)[0] if portable else np.random.default_rng([seed + it, t]).permutation(len(ids)) for t in some]
            picks, cost, costs = G.best_of(dist, 0, parallel, orders=orders)
            if best is None or cost < best[0]:
                best = (cost, some[costs.index(cost)], picks.astype(np.int32).tobytes())
        if best:
            yield pa.RecordBatch.from_pydict({"cost": [best[0]], "t": [best[1]], "picks": [best[2]]})

    got = spark.range(0, trials, 1, tasks).mapInArrow(work, "cost double, t long, picks binary").toArrow().sort_by([("cost", "ascending"), ("t", "ascending")])
    shared.destroy()
    return np.frombuffer(got.column("picks")[0].as_py(), dtype=np.int32).astype(np.int64)


def seed_parallel(ff: DataFrame, fmap, k: int, rounds: int = 5, oversample: int | None = None, seed: int = 42) -> tuple[np.ndarray, np.ndarray]:
    """Ids and mapped rows of k seeds of one domain, drawn from all its rows in ``rounds`` passes instead of k.

    A round takes the ``oversample`` (2 k by default) rows that win an exponential race on their squared image distance
    to what is picked; a last pass counts the rows nearest to each pick, and k picks win races weighted by those counts.
    The driver and the tasks hold at most ``rounds * oversample + 1`` rows, whatever the input. ``ff`` is read in every
    pass: store one that is dear to compute.
    """
    width = oversample or 2 * k
    first = ff.select("id", "z").orderBy(E.portable_u(seed, "seed", 0, F.col("id")), "id").limit(1).collect()
    ids, z = [r["id"] for r in first], [r["z"] for r in first]

    def squared(rows: np.ndarray, to: np.ndarray) -> np.ndarray:
        f = fmap(rows)
        return np.maximum((f * f).sum(1)[:, None] - 2 * f @ to.T + (to * to).sum(1), 0.0)

    def racing(to: np.ndarray):
        def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if len(b):
                    near = squared(_rows(b), to).min(1)
                    race = np.full(len(b), np.inf)
                    at = near > 1e-12
                    race[at] = -np.log(1 - b.column(2).to_numpy()[at]) / near[at]
                    yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(race)], names=["id", "z", "race"])

        return work

    def counting(to: np.ndarray):
        def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            n = np.zeros(len(to), dtype=np.int64)
            for b in batches:
                if len(b):
                    n += np.bincount(squared(_rows(b), to).argmin(1), minlength=len(to))
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(to))), pa.array(n)], names=["i", "n"])

        return work

    for r in range(1, rounds + 1):
        if not ids:
            break
        dealt = ff.select("id", F.col("z").cast("array<double>").alias("z"), E.portable_u(seed, "over", r, F.col("id")).alias("u"))
        won = dealt.mapInArrow(racing(fmap(np.array(z, dtype=float))), "id long, z array<double>, race double").filter("race < double('infinity')").orderBy("race", "id").limit(width).collect()
        ids += [x["id"] for x in won]
        z += [x["z"] for x in won]
    f = fmap(np.array(z, dtype=float)) if ids else np.zeros((0, 1))
    if len(np.unique(f, axis=0)) < k:
        raise ValueError(f"fewer distinct rows than {k} strata")
    n = np.zeros(len(ids))
    for x in ff.select("z").mapInArrow(counting(f), "i long, n long").groupBy("i").agg(F.sum("n").alias("n")).collect():
        n[x["i"]] = x["n"]
    near, picked = np.full(len(ids), np.inf), []
    for r in range(k):
        mass = np.maximum(n, 1e-9) * (near if picked else 1.0)
        with np.errstate(divide="ignore"):
            race = np.array([-np.log(1 - u01(seed, "pick", r, i)) for i in ids]) / mass
        race[near <= 1e-12] = np.inf
        picked.append(int(race.argmin()))
        near = np.minimum(near, ((f - f[picked[-1]]) ** 2).sum(1))
    return np.array(ids)[picked], f[picked]


def _sampled_seeds(dealt: DataFrame, fmap, k: int, seed: int, sample: int, total: int) -> dict[str, np.ndarray]:
    some = Small(dealt.filter(E.portable_u(seed, "sample", F.col("id")) < min(1.0, sample / max(total, 1))), "domain", limit=2 * sample)
    centres = {}
    for dom in sorted(set(some.extra["domain"].tolist())):
        at = some.extra["domain"] == dom
        f = fmap(some.z[at])
        centres[dom] = f[seed_kpp(f, some.ids[at], Linear(), k, seed)]
    return centres


def _cheapest(d: np.ndarray, trials: int, parallel: int, seed: int) -> np.ndarray:
    """The cheapest of shuffled passes, as many at once as keep their orders and picks within about 64 MB."""
    lanes, best, best_cost = max(1, (4 << 20) // max(len(d), 1)), None, np.inf
    for lo in range(0, trials, lanes):
        orders = [np.random.default_rng([seed, t]).permutation(len(d)) for t in range(lo, min(trials, lo + lanes))]
        found, cost, _ = G.best_of(d, 0, parallel, orders=orders)
        if best is None or cost < best_cost:
            best, best_cost = found, cost
    return best


def stratify_mapped(ff: DataFrame, fmap, k: int, rounds: int = 5, buckets: int | None = None, parallel: int = 10, seed: int = 42, sample: int = 20_000, weighted: bool = True, seeding: str = "sample", trials: int = 100) -> DataFrame:
    """Fit centroids over all rows of each domain, one job a round, and assign every row in the last, best round.

    Seeds come from a bounded sample (documented: ``sample`` rows of smallest uniforms), or from all rows with
    ``seeding="parallel"``. Rows are dealt into hash buckets; a bucket must fit a Python worker, so that by default there
    are as many as keep its vectors within about 64 MB, and 64 at least. They are written once, bucketed, so that rounds
    read and don't shuffle them. An empty frame gives no rows; a null vector raises.
    """
    spark = ff.sparkSession
    whole = ff.agg(F.count("*").alias("n"), F.max(F.size("z")).alias("d")).first()
    total = whole["n"]
    buckets = buckets or max(64, -(-total * (whole["d"] or 1) * 8 // (64 << 20)))
    b = F.pmod(E.hash_bits(seed, "bucket", F.col("id")), F.lit(buckets)).cast("int")
    files = min(buckets, 100_000)
    table, path = f"strata_dealt_{uuid.uuid4().hex}", io.new_path(spark, "dealt")
    io.write_bucketed(ff.select("id", "z", "domain", b.alias("b")).repartition(files, "b"), table, path, files, "b")
    try:
        dealt = spark.table(table)
        if seeding == "parallel":
            domains = sorted(r["domain"] for r in dealt.select("domain").distinct().collect())
            centres = {dom: seed_parallel(dealt.filter(F.col("domain") == dom), fmap, k, seed=seed)[1] for dom in domains}
        else:
            centres = _sampled_seeds(dealt, fmap, k, seed, sample, total)
        return _lloyd(dealt, fmap, k, rounds, parallel, seed, weighted, trials, centres)
    finally:
        spark.sql(f"DROP TABLE IF EXISTS {table}")
        io.remove(spark, path)


def _lloyd(dealt: DataFrame, fmap, k: int, rounds: int, parallel: int, seed: int, weighted: bool, trials: int, centres: dict[str, np.ndarray]) -> DataFrame:
    """The rounds over a table that is bucketed by ``b``: no round moves a vector."""

    def pick(t: pa.Table, centres, it: int):
        t = t.sort_by("id")
        f = fmap(_rows(t))
        c = centres[t["domain"][0].as_py()]
        d = np.maximum((f * f).sum(1)[:, None] - 2 * f @ c.T + (c * c).sum(1), 0)
        return t, f, d, _cheapest(d, trials, parallel, seed + it) if weighted else G.nearest(d)

    def summing(now, it: int):
        def sums(t: pa.Table) -> pa.Table:
            t, f, d, s = pick(t, now, it)
            out = np.zeros((k, f.shape[1] + 2))
            np.add.at(out, s, np.concatenate((np.ones((len(s), 1)), d[np.arange(len(s)), s][:, None], f), axis=1))
            return pa.table({"domain": pa.array([t["domain"][0].as_py()] * out.size), "i": pa.array(np.arange(out.size)), "v": pa.array(out.ravel())})

        return sums

    best, best_value = (centres, 0), np.inf
    for it in range(rounds):
        now = dict(centres)
        got = dealt.groupBy("domain", "b").applyInArrow(summing(now, it), "domain string, i long, v double").groupBy("domain", "i").agg(F.sum("v").alias("v")).collect()
        value, fresh = 0.0, {}
        for dom in centres:
            m = np.zeros(k * (centres[dom].shape[1] + 2))
            for r in got:
                if r["domain"] == dom:
                    m[r["i"]] = r["v"]
            m = m.reshape(k, -1)
            value += float((m[:, 0] * m[:, 1]).sum())
            fresh[dom] = np.where(m[:, :1] > 0, m[:, 2:] / np.maximum(m[:, :1], 1), centres[dom])
        if value < best_value:
            best, best_value = (now, it), value
        centres = fresh

    def final(t: pa.Table) -> pa.Table:
        t, _, _, s = pick(t, *best)
        return pa.table({"domain": t["domain"], "id": t["id"], "stratum": pa.array(s, pa.int32())})

    return io.staged(dealt.groupBy("domain", "b").applyInArrow(final, "domain string, id long, stratum int"), "strata")


def nearest_rounds(ff: DataFrame, centres: np.ndarray, rounds: int) -> DataFrame:
    """Lloyd rounds of linear k-means in SQL functions: (id, stratum); a round is one scan and k x d sums."""
    k, d = centres.shape
    for r in range(rounds):
        near = _nearest(ff, centres)
        if r == rounds - 1:
            return near.select("id", "stratum")
        got = {x["stratum"]: x for x in near.groupBy("stratum").agg(*[F.avg(F.col("z")[i]).alias(f"m{i}") for i in range(d)]).collect()}
        centres = np.array([[round(got[j][f"m{i}"], 9) for i in range(d)] if j in got else centres[j] for j in range(k)])
    raise ValueError("rounds must be positive")


def _nearest(ff: DataFrame, centres: np.ndarray) -> DataFrame:
    cells = F.array(*[F.round(E.sqdist("z", F.array(*[F.lit(float(v)) for v in c])), 9) for c in centres])
    return ff.withColumn("dist", cells).withColumn("stratum", (F.array_position("dist", F.array_min("dist")) - 1).cast("int"))
