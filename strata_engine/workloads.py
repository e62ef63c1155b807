"""The experiment workloads on the given tables. Their cells are spread over tasks; steps and rows are arguments."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import exprs as E
from .functions import frames, theory
from .functions.kernels import RBF, Linear, Quadratic
from .operators import cluster, core
from .operators import greedy as G
from .sources.io import load
from .train import loop

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def workload(f: Callable) -> Callable:
    QUERIES[f.__name__] = f
    return f


def _frame(spark, schema, data):
    return spark.createDataFrame(data, schema)


def _by_supplier(spark, d) -> DataFrame:
    """Line items with standardised features, by supplier: the populations whose variances are ranked."""
    return frames.standardised(load(spark, d, "lineitem", [*frames.LINE, "l_orderkey", "l_linenumber", "l_suppkey"]), frames.LINE)


def _ranked(found: DataFrame) -> list[tuple]:
    """(dims, law, populations, rho) from a pair of variances f and g for every population."""
    t, out = found.toArrow(), []
    dims, law, f, g = (t.column(c).to_numpy(zero_copy_only=False) for c in ("dims", "law", "f", "g"))
    for k, name in sorted(set(zip(dims.tolist(), law.tolist(), strict=True))):
        at = (dims == k) & (law == name)
        out.append((k, name, int(at.sum()), theory.spearman(f[at], g[at])))
    return out


@workload
def x1_surrogate_mean(spark, d, dims=(1, 2, 4)):
    """Rank correlation of loss variance and mean variance over the covariances of suppliers' line items, as they are and with equal variances of the same sum."""
    c = _by_supplier(spark, d).groupBy("l_suppkey").agg(*[F.covar_pop(F.col("z")[i], F.col("z")[j]).alias(f"c{i}{j}") for i in range(max(dims)) for j in range(i, max(dims))])
    cells = []
    for k in dims:
        twice = lambda p, k=k: sum((p(F.col(f"c{i}{j}")) * (1.0 if i == j else 2.0) for i in range(k) for j in range(i, k)), F.lit(0.0))
        trace = sum((F.col(f"c{i}{i}") for i in range(k)), F.lit(0.0))
        for law, f in (("measured", 2 * twice(lambda x: x * x) + 4 * twice(lambda x: x)), ("isotropic", 2 * trace * trace / k + 4 * trace)):
            cells.append(F.struct(F.lit(k).alias("dims"), F.lit(law).alias("law"), F.round(f, 12).alias("f"), F.round(trace, 12).alias("g")))
    return _frame(spark, "dims int, law string, populations long, rho double", _ranked(c.select(F.inline(F.array(*cells)))))


@workload
def x2_surrogate_covariance(spark, d, dims=(1, 2, 4), batches=1000, k=8):
    """Rank correlation of the variances of the covariance estimate and of its known-mean surrogate over suppliers: each draws
    ``batches`` minibatches, a line item from each of ``k`` strata of its own, of the features and of their exponentials."""

    def work(t: pa.Table) -> pa.Table:
        t = t.sort_by([("l_orderkey", "ascending"), ("l_linenumber", "ascending")])
        x, own, out = core._rows(t), np.arange(t.num_rows) % k, []
        n_h = np.bincount(own, minlength=k)
        n_h = n_h[n_h > 0]
        rng = np.random.default_rng([42, t.column("l_suppkey")[0].as_py()])
        pick = np.floor(rng.random((batches, len(n_h))) * n_h).astype(np.int64) * k + np.arange(len(n_h))
        w, n = n_h / n_h.sum(), max(int(n_h.sum()), 2)
        for law, z in (("measured", x), ("exponential", np.exp(x))):
            for m in dims:
                b = z[pick, :m]
                far, near = b - np.einsum("h,bhi->bi", w, b)[:, None], b - z[:, :m].mean(0)
                f, g = (np.einsum("h,bhi,bhj->bij", w, e, e) * s for e, s in ((far, n / (n - 1)), (near, 1.0)))
                out.append((m, law, float(f.var(0).sum()), float(g.var(0).sum())))
        return pa.table(dict(zip(("dims", "law", "f", "g"), (pa.array(c, v) for c, v in zip(zip(*out, strict=True), (pa.int32(), pa.string(), pa.float64(), pa.float64()), strict=True)), strict=True)))

    found = _by_supplier(spark, d).select("l_suppkey", "l_orderkey", "l_linenumber", "z").groupBy("l_suppkey").applyInArrow(work, "dims int, law string, f double, g double")
    return _frame(spark, "dims int, law string, populations long, rho double", _ranked(found))


def _problem(spark, d, n=100, k=16):
    """n embeddings, the size of the assignment experiment, and their Euclidean distances to k seeded rows."""
    small = core.Small(frames.embeddings(spark, d).orderBy("id").limit(n))
    at = cluster.seed_kpp(small.z, small.ids, Linear(), min(k, len(small.ids)))
    return np.sqrt(np.maximum(((small.z[:, None] - small.z[None, at]) ** 2).sum(2), 0))


@workload
def x3_assignment_quality(spark, d, trials=100_000):
    """Loss and seconds of every way to assign the small problem, a task each."""
    m = _problem(spark, d)
    ways = {
        "greedy": lambda: G.assignment_cost(m, G.best_of(m, trials, 10)[0]),
        "relaxed_rounded": lambda: G.assignment_cost(m, G.relaxed(m)[2]),
        "relaxed_value": lambda: G.relaxed(m)[1],
        "nearest": lambda: G.assignment_cost(m, G.nearest(m)),
        "greedy_polished": lambda: G.assignment_cost(m, G.polish(m, G.best_of(m, 100, 10)[0])),
    }

    def run(name):
        began = time.perf_counter()
        return name, ways[name](), time.perf_counter() - began

    return loop.over_tasks(spark, list(ways), run, "method string, loss double, seconds double")


@workload
def x4_loss_by_trials(spark, d, most=100_000, seeds=5):
    """Least loss of the first R trials, for R to a hundred thousand: trials are nested, a task a seed."""
    m = _problem(spark, d)

    def run(s):
        costs = np.minimum.accumulate(G.best_of(m, most, 10, s)[2])
        return [(r, s, float(costs[r - 1])) for r in (1, 10, 100, 1000, 10_000, 100_000) if r <= most]

    return loop.over_tasks(spark, list(range(seeds)), run, "trials int, seed int, loss double")


@workload
def x5_loss_by_parallel(spark, d, seeds=3, trials=100):
    m = _problem(spark, d)

    def run(p):
        costs = [G.best_of(m, trials, p, s)[2] for s in range(seeds)]
        return [(p, s, float(min(c)), float(np.mean(c))) for s, c in enumerate(costs)]

    return loop.over_tasks(spark, list(range(1, 21)), run, "parallel int, seed int, best_loss double, mean_loss double")


@workload
def x6_variance_by_k(spark, d, ks=(2, 8, 32, 128, 256), n=1000, trials=20):
    """Analytic variance of the kernel mean for uniform draws, linear, kernel and size-weighted strata, on n rows a table; a task a cell."""
    tables = {"embeddings": frames.embeddings(spark, d), "lineitem": frames.lineitem(spark, d, "null")}
    z = {name: core.Small(ff.orderBy("id").limit(n)).z for name, ff in tables.items()}
    ways = {"uniform": None, "linear": (Linear(), False), "kernel": (RBF(), False), "swks": (RBF(), True)}

    def run(cell):
        name, k, way = cell
        gram = RBF().block(z[name], z[name])
        u = v = cluster.uniform_variance(gram, k)
        if ways[way]:
            kernel, weighted = ways[way]
            v = cluster.mean_variance(gram, cluster.stratify(z[name], kernel, k, weighted=weighted, trials=trials, max_iter=8).strata, k)
        return name, k, way, float(v), float(u / v) if v > 0 else None

    return loop.over_tasks(spark, [(name, k, way) for k in sorted(ks, reverse=True) for name in z for way in ways if k < len(z[name])], run, "table string, k int, method string, variance double, gain double")


def _drawn(ff: DataFrame, n: int, seed: int = 42) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids, vectors and environments of n rows, as many of each environment, those of smallest uniforms: a bounded draw, as the paper's sets are of bounded size."""
    u = E.portable_u(seed, "pick", F.col("id"))
    each = max(1, n // max(1, ff.select("env").distinct().count()))
    place = F.row_number().over(Window.partitionBy("env").orderBy(u, "id"))
    got = ff.select("id", "z", "env", place.alias("place")).filter(F.col("place") <= each).orderBy("id").collect()
    return np.array([r["id"] for r in got]), np.array([r["z"] for r in got], dtype=float), np.array([r["env"] for r in got])


def _planted(drawn, classes: int, target: str, source: str | None = None) -> dict:
    """A split with planted classes: one environment, or all others, against the target."""
    ids, z, env = drawn
    at = np.ones(len(env), dtype=bool) if source is None else (env == source) | (env == target)
    x, y = frames.planted(ids[at], z[at], env[at], classes, target)
    return loop.split(x, y, env[at], target, classes)


def datasets(spark: SparkSession, sf_dir: str, n: int = 1000, every: bool = True) -> dict[str, dict]:
    """The splits of the four planted workloads, or the first of each: one target region, each language and each flag against
    the rest, and each ordered pair of languages. Every environment that the tables have is a target."""
    star, docs, line = _drawn(frames.star(spark, sf_dir), n), _drawn(frames.documents(spark, sf_dir), n), _drawn(frames.lineitem(spark, sf_dir, "null"), n)
    names = lambda drawn: sorted(set(drawn[2].tolist()))
    out = {
        "star_regions": {"ASIA" if "ASIA" in names(star) else names(star)[-1]: (star, 2, None)},
        "document_languages": {t: (docs, 2, None) for t in names(docs)},
        "line_flags": {t: (line, 4, None) for t in names(line)},
        "language_pairs": {f"{s}>{t}": (docs, 20, s) for s in names(docs) for t in names(docs) if s != t},
    }
    some = {w: dict(list(splits.items())[: None if every else 1]) for w, splits in out.items()}
    return {f"{w}/{t}": _planted(drawn, classes, t.split(">")[-1], source) for w, splits in some.items() for t, (drawn, classes, source) in splits.items()}


@workload
def splits(spark, d):
    """(dataset, target, n): the leave-one-out and pairwise splits of every workload; a pair's rows are those of both."""
    out = None
    docs = frames.documents(spark, d)
    for name, ff in (("star_regions", frames.star(spark, d)), ("document_languages", docs), ("line_flags", frames.lineitem(spark, d, "null"))):
        one = ff.groupBy("env").agg(F.count("*").alias("n")).select(F.lit(name).alias("dataset"), F.col("env").alias("target"), "n")
        out = one if out is None else out.unionByName(one)
    by = docs.groupBy("env").agg(F.count("*").alias("n"))
    pair = by.select(F.col("env").alias("a"), F.col("n").alias("na")).join(F.broadcast(by.select(F.col("env").alias("b"), F.col("n").alias("nb"))), F.col("a") != F.col("b"))  # a row a language
    return out.unionByName(pair.select(F.lit("language_pairs").alias("dataset"), F.concat_ws(">", "a", "b").alias("target"), (F.col("na") + F.col("nb")).alias("n")))


def _cells(names, methods, samplers, repeats, **own):
    return [{"dataset": s, "method": m, "sampler": p, "repeat": r} | own for p in samplers for m in methods for s in names for r in range(repeats)]


def summary(g: DataFrame) -> DataFrame:
    """Means and standard errors by workload, over its splits and repeats."""
    g = g.withColumn("workload", F.element_at(F.split("dataset", "/"), 1)).groupBy("workload", "method", "sampler")
    return g.agg(F.countDistinct("dataset").alias("splits"), F.count("*").alias("runs"), F.avg("accuracy").alias("mean_accuracy"), (F.stddev_samp("accuracy") / F.sqrt(F.count("*"))).alias("std_err"), F.avg("balanced").alias("balanced"), F.avg("seconds").alias("seconds"))


@workload
def x11_sampler_grid(spark, d, n=600, steps=100, every=50, repeats=5, methods=("erm", "cad", "med"), configs=1):
    """Accuracy by sampler and loss on all splits: mean and standard error over splits and repeats."""
    sets = datasets(spark, d, n)
    return summary(loop.grid(spark, sets, _cells(sets, methods, reversed(loop.SAMPLERS), repeats), configs, steps=steps, every=every, k=16, trials=10))


@workload
def x11_searched(spark, d, n=600, steps=100, every=50, repeats=3, configs=10):
    """The same for one split of every workload, two samplers and both losses, each after a random search of ten points."""
    sets = datasets(spark, d, n, every=False)
    return summary(loop.grid(spark, sets, _cells(sets, ("erm", "cad", "med"), ("swks", "uniform"), repeats), configs, steps=steps, every=every, trials=10))


@workload
def x12_method_grid(spark, d, n=600, steps=150, every=50, repeats=5, configs=1):
    """Accuracy of every adaptation method under uniform draws, and of both discrepancies under size-weighted strata, on all splits."""
    from .train.model import METHODS

    sets = datasets(spark, d, n)
    cells = _cells(sets, ("cad", "med"), ("swks",), repeats) + _cells(sets, METHODS, ("uniform",), repeats)
    return summary(loop.grid(spark, sets, cells, configs, steps=steps, every=every, k=16, trials=10))


@workload
def x13_wallclock(spark, d, n=600, steps=300, repeats=3):
    """Seconds of a training run by sampler on one split of every workload: mean and standard error over both discrepancies and repeats."""
    sets = datasets(spark, d, n, every=False)
    g = loop.grid(spark, sets, _cells(sets, ("cad", "med"), reversed(loop.SAMPLERS), repeats), 1, steps=steps, k=16, trials=10)
    return g.groupBy("dataset", "sampler").agg(F.count("*").alias("runs"), F.avg("seconds").alias("seconds"), (F.stddev_samp("seconds") / F.sqrt(F.count("*"))).alias("std_err"))


@workload
def x14_heldout_discrepancy(spark, d, n=600, steps=300, repeats=3):
    """Discrepancies of held-out features after training, by loss and sampler, beside source-only training, on one split of every workload."""
    sets = datasets(spark, d, n, every=False)
    g = loop.grid(spark, sets, _cells(sets, ("erm", "cad", "med"), reversed(loop.SAMPLERS), repeats), 1, steps=steps, k=16, trials=10)
    return g.groupBy("dataset", F.col("method").alias("loss"), "sampler").agg(F.count("*").alias("runs"), F.avg("med").alias("med"), F.avg("cad").alias("cad"))


@workload
def x15_interval(spark, d, n=600, steps=1500, intervals=(10, 50, 100, 500, 1000), repeats=3):
    """Variance along runs and accuracy, by re-stratification interval and loss; uniform draws and schedules that grow or wait beside."""
    data = spark.sparkContext.broadcast(datasets(spark, d, n, every=False)["document_languages/de"])
    kinds = {str(t): {"every": t} for t in intervals} | {"growing": {"every": 10, "growth": 1.5}, "stale_1.2": {"every": 10**9, "staleness": 1.2}, "uniform": {"sampler": "uniform"}}

    def run(cell):
        name, loss, seed = cell
        trace: list = []
        net = loop.train(data.value, loop.Config(**({"method": loss, "sampler": "swks", "k": 32, "steps": steps, "trials": 10, "seed": seed} | kinds[name])), trace, 25)
        v = [t[2] for t in trace if t[2] is not None]
        return (name, loss, seed, float(np.mean(v[: len(v) // 2])), float(np.mean(v[len(v) // 2 :])), *loop.accuracy(net, data.value["xe"], data.value["ye"]))

    g = loop.over_tasks(spark, [(name, loss, r) for name in kinds for loss in ("med", "cad") for r in range(repeats)], run, "every string, loss string, repeat int, variance_early double, variance_late double, accuracy double, balanced double")
    mean = [F.avg(c).alias(c) for c in ("variance_early", "variance_late", "accuracy", "balanced")]
    return g.groupBy("every", "loss").agg(F.count("*").alias("runs"), *mean, (F.stddev_samp("accuracy") / F.sqrt(F.count("*"))).alias("std_err"))


def _text_frame(spark, d, table, key, col):
    f = E.text_features(col)
    return load(spark, d, table, [key, col]).select(F.col(key).alias("id"), F.array(*f.values()).alias("z"), F.lit(table).alias("env"))


@workload
def x17_environment_distance(spark, d):
    """Discrepancy between text environments under the quadratic kernel's exact map, over all rows of each."""
    parts = [_text_frame(spark, d, t, k, c) for t, k, c in (("documents", "doc_id", "text"), ("benchmark", "item_id", "text"), ("conversations", "conv_id", "text"), ("pages", "page_id", "html"))]
    ff = parts[0]
    for p in parts[1:]:
        ff = ff.unionByName(p)
    m = core.mean_vectors(ff, Quadratic((0.0,) * 8).feature_map, "env")
    names = sorted(m)
    return _frame(spark, "a string, b string, med double", [(a, b, float(((m[a][0] - m[b][0]) ** 2).sum())) for i, a in enumerate(names) for b in names[i + 1 :]]).select("a", "b", E.r6("med").alias("med"))


@workload
def x18_account_covariance(spark, d):
    """Covariance discrepancy of customers' and suppliers' (balance, key share) by nation."""
    c, s = load(spark, d, "customer"), load(spark, d, "supplier")
    nc, ns = c.count(), s.count()
    a = c.select(F.col("c_nationkey").alias("nation"), (F.col("c_acctbal") / 1000).alias("x"), (F.col("c_custkey") / F.lit(float(nc))).alias("y"))
    b = s.select(F.col("s_nationkey").alias("nation"), (F.col("s_acctbal") / 1000).alias("x"), (F.col("s_suppkey") / F.lit(float(ns))).alias("y"))
    m = lambda df, t: df.groupBy("nation").agg(F.var_samp("x").alias(f"{t}xx"), F.covar_samp("x", "y").alias(f"{t}xy"), F.var_samp("y").alias(f"{t}yy"))
    sq = lambda k: F.pow(F.col("c" + k) - F.col("s" + k), F.lit(2.0))
    return m(a, "c").join(m(b, "s"), "nation").filter("sxx is not null and cxx is not null").select("nation", E.r6(sq("xx") + 2 * sq("xy") + sq("yy")).alias("cad"))
