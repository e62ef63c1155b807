"""Queries over the given tables, one for each method, variant, baseline, measure, workload and operator."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import sqlapi, workloads
from .functions import exprs as E
from .functions import frames, theory
from .functions.kernels import MIXTURE, RBF, FourierMap, LandmarkMap, Linear, Quadratic, map_error
from .operators import cluster, core, diverse
from .operators import greedy as G
from .operators import relational as R
from .oracles import SQL
from .sources import io
from .sources.io import TABLES, load
from .streaming import drift
from .train import loop

K = 8
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def query(f: Callable) -> Callable:
    QUERIES[f.__name__] = f
    return f


def rows(spark: SparkSession, schema: str, data: list[tuple]) -> DataFrame:
    return spark.createDataFrame(data, schema)


def _emb(spark, d):
    return frames.embeddings(spark, d)


def _first(ff: DataFrame, k: int = K) -> np.ndarray:
    """The k rows with the smallest ids, as centres and landmarks."""
    return np.array([r["z"] for r in ff.orderBy("id").select("z").limit(k).collect()], dtype=float)


def _dist(spark, d) -> DataFrame:
    ff = _emb(spark, d)
    return core.centre_distances(ff, _first(ff)).select("id", "domain", "dist")


def _strata(spark, d) -> DataFrame:
    return core.assign(_dist(spark, d))


def _domain_strata(spark, d) -> DataFrame:
    """Strata within each domain by id, as a fixed partition."""
    return _emb(spark, d).select("id", "domain", F.pmod("id", F.lit(K)).cast("int").alias("stratum"))


def _domain_draws(spark, d, iters=20, uniform=False) -> DataFrame:
    s, seeds = _domain_strata(spark, d), {"s": 42, "t": 43}
    out = core.draw_uniform(s, K, iters, seeds, ("domain",)) if uniform else core.draw_strata(s, iters, seeds, 1, ("domain",))
    return out.select("iter", "id", "weight", "domain")


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Size-weighted kernel strata of embeddings, k = 8: sizes and the objective of each stratum."""
    ff = _emb(spark, sf_dir).withColumn("domain", F.lit("s"))
    s = cluster.stratify_frame(ff, MIXTURE, K, trials=20, parallel=10, max_iter=5).select("id", "stratum")
    return core.scatter(ff, s, MIXTURE).select("stratum", "n_h", "scatter", (F.col("n_h") * F.col("scatter")).alias("weighted")).orderBy("stratum")


# ---- discrepancies -------------------------------------------------------------------------------------------------


@query
def med_exact(spark, d):
    ff = _emb(spark, d)
    n = {r["domain"]: r["count"] for r in ff.groupBy("domain").count().collect()}
    return rows(spark, "n_s long, n_t long, med double", [(n["s"], n["t"], core.med_exact(ff, MIXTURE))]).withColumn("med", E.r6("med"))


@query
def med_mapped(spark, d):
    """All line items through the quadratic kernel's exact finite map (ten components)."""
    ff = frames.lineitem(spark, d)
    q = Quadratic((0.0, 0.0, 0.0, 0.0))
    return rows(spark, "med double", [(core.med_mapped(ff, q.feature_map),)]).withColumn("med", E.r6("med"))


@query
def med_hat(spark, d):
    return core.med_hat(_domain_draws(spark, d), _emb(spark, d).drop("domain"), MIXTURE).select("iter", E.r6("value").alias("value"))


@query
def med_hat_uniform(spark, d):
    return core.med_hat(_domain_draws(spark, d, uniform=True), _emb(spark, d).drop("domain"), MIXTURE).select("iter", E.r6("value").alias("value"))


@query
def med_plugin_bias(spark, d):
    """Excess of the expected plug-in over the discrepancy: the variances of both stratified means."""
    ff, s = _emb(spark, d), _domain_strata(spark, d)
    out = None
    for dom in ("s", "t"):
        one = core.scatter(ff, s.filter(F.col("domain") == dom), MIXTURE).agg((F.sum(F.col("n_h") * F.col("scatter")) / F.pow(F.sum("n_h"), F.lit(2.0))).alias("v"))
        out = one if out is None else out.unionByName(one)
    return out.agg(E.r6(F.sum("v")).alias("bias"))


@query
def cad_exact(spark, d):
    return core.cad_exact(frames.lineitem(spark, d), 4).select("n_s", "n_t", E.r6("cad").alias("cad"))


def _line_draws(spark, d, iters=20):
    ff = io.staged(frames.lineitem(spark, d).select("id", "z", "domain"))
    s = ff.select("id", "domain", F.pmod("id", F.lit(K)).cast("int").alias("stratum"))
    return ff, core.draw_strata(s, iters, {"s": 42, "t": 43}, 1, ("domain",)).select("iter", "id", "weight", "domain")


def _line_cov(spark, d, known=False):
    ff, draws = _line_draws(spark, d)
    n = {r["domain"]: r["count"] for r in ff.groupBy("domain").count().collect()}
    mu = {r["domain"]: [r[f"m{i}"] for i in range(4)] for r in ff.groupBy("domain").agg(*[F.avg(F.col("z")[i]).alias(f"m{i}") for i in range(4)]).collect()} if known else None
    return core.cov_hat(draws, ff.drop("domain"), 4, n, mu)


@query
def cov_hat(spark, d):
    c = _line_cov(spark, d)
    return c.select("domain", "iter", *[E.r6(x).alias(x) for x in c.columns[2:]])


@query
def cov_known_mean(spark, d):
    c = _line_cov(spark, d, True)
    return c.select("domain", "iter", *[E.r6(x).alias(x) for x in c.columns[2:]])


@query
def cad_hat(spark, d):
    return core.cad_hat(_line_cov(spark, d), 4).select("iter", E.r6("value").alias("value"))


@query
def cad_wide(spark, d):
    """Covariance discrepancy of 64-dimensional embeddings, by partial Gram matrices."""
    c = core.gram_covariances(_emb(spark, d))
    return rows(spark, "n_s long, n_t long, cad double", [(c["s"][1], c["t"][1], float(((c["s"][0] - c["t"][0]) ** 2).sum()))]).withColumn("cad", E.r6(F.col("cad") * 1000))


@query
def combined_objective(spark, d):
    """Task loss (a fixed function of the features) plus twice the discrepancy of every minibatch."""
    ff, draws = _emb(spark, d), io.checkpointed(_domain_draws(spark, d))
    loss = ff.select("id", F.pow(F.col("z")[0] - F.col("z")[1], F.lit(2.0)).alias("loss"))
    return core.combined(draws, loss, "loss", core.med_hat(draws, ff.drop("domain"), MIXTURE), 2.0).select("iter", *[E.r6(c).alias(c) for c in ("task", "value", "objective")])


# ---- kernels: every row against the landmark rows --------------------------------------------------------------------


def _kernel(spark, d, kernel_of):
    ff = _emb(spark, d)
    c = _first(ff)
    kernel = kernel_of(ff)
    cells = F.array(*[F.struct(F.lit(j).alias("b"), kernel.expr("z", F.array(*[F.lit(float(v)) for v in x])).alias("k")) for j, x in enumerate(c)])
    return ff.select(F.col("id").alias("a"), F.explode(cells).alias("e")).select("a", "e.b", E.r6("e.k").alias("k"))


@query
def kernel_linear(spark, d):
    return _kernel(spark, d, lambda ff: Linear())


@query
def kernel_rbf(spark, d):
    return _kernel(spark, d, lambda ff: RBF())


@query
def kernel_rbf_mix(spark, d):
    return _kernel(spark, d, lambda ff: MIXTURE)


@query
def kernel_quad(spark, d):
    return _kernel(spark, d, lambda ff: Quadratic(tuple(r for r in ff.agg(*[F.avg(F.col("z")[i]) for i in range(64)]).first())))


@query
def rff_error(spark, d):
    """Errors of Fourier features over all pairs of rows, in tiles."""
    spread, freqs = core.Spread(_emb(spark, d)), (64, 256, 1024)
    dims = spread.chunks[0].value.shape[1]
    errors = spread.map_errors(MIXTURE, [FourierMap(MIXTURE, dims, f) for f in freqs])
    spread.close()
    return rows(spark, "freqs int, max_error double, mean_error double", [(f, *e) for f, e in zip(freqs, errors, strict=True)])


@query
def landmark_error(spark, d):
    """Errors of the landmark map for growing numbers of landmark rows, the last of which takes all."""
    small = core.Small(_emb(spark, d).orderBy("id").limit(500))
    return rows(spark, "landmarks int, max_error double, mean_error double", [(m, *map_error(RBF(), LandmarkMap(RBF(), small.z[:m]), small.z)) for m in (20, 100, len(small.ids))])


# ---- stratification --------------------------------------------------------------------------------------------------


@query
def seed_kpp(spark, d):
    """Seeds from all rows, a pass a seed."""
    return rows(spark, "r int, vec_id long", list(enumerate(cluster.seed_rows(_emb(spark, d), RBF(), K)[0])))


@query
def kernel_distances(spark, d):
    ff = _emb(spark, d)
    s = ff.select("id", F.pmod("id", F.lit(K)).cast("int").alias("stratum"))
    out = core.kernel_distances(ff, s, RBF(), K)
    return out.select(F.col("id").alias("vec_id"), F.posexplode("dist").alias("stratum", "dist")).select("vec_id", "stratum", E.r6("dist").alias("dist"))


def _named(df):
    return df.select(F.col("id").alias("vec_id"), "stratum")


@query
def assign_greedy(spark, d):
    return _named(_strata(spark, d))


@query
def assign_marginal(spark, d):
    return _named(core.assign(_dist(spark, d), score="marginal"))


@query
def assign_parallel(spark, d):
    return _named(core.assign(_dist(spark, d), parallel=10))


@query
def assign_bucketed(spark, d):
    return _named(core.assign(_dist(spark, d), buckets=4))


@query
def assign_by_domain(spark, d):
    """Each domain's rows assigned by themselves, with sizes of their own."""
    return core.assign(_dist(spark, d), by=("domain",)).select("domain", F.col("id").alias("vec_id"), "stratum")


@query
def assign_nearest(spark, d):
    return _named(core.assign(_dist(spark, d), "nearest"))


def _trial_dist(spark, d) -> DataFrame:
    """Distances of all rows for trials, or an error where a user has set a ceiling that they exceed."""
    dist = _dist(spark, d).select("id", "dist")
    if core.EXACT_ROWS < dist.count():
        raise ValueError(f"exact trials are for at most {core.EXACT_ROWS} rows; assign in buckets instead")
    return dist


def _cost6(c):
    """Six digits by scaling, as DuckDB rounds: costs of many rows have all their digits before these."""
    return F.floor(F.col(c) * 1e6 + 0.5) / 1e6


@query
def assign_trials(spark, d):
    """Four shuffled passes over all rows, a task each."""
    shuffled = _trial_dist(spark, d).select(F.explode(F.array(*[F.lit(t) for t in range(4)])).alias("trial"), "id", "dist").withColumn("u", E.portable_u(42, "perm", F.col("trial"), F.col("id")))
    costs = core.pass_costs(shuffled, "trial", "u", "id").collect()
    best = min(r["cost"] for r in costs)
    return rows(spark, "trial int, cost double, is_best boolean", [(r["trial"], r["cost"], r["cost"] == best) for r in costs]).withColumn("cost", _cost6("cost"))


@query
def assign_relaxed(spark, d):
    """Ways to assign all rows, a task each; every one holds the k distances of each row."""
    got = _trial_dist(spark, d).toArrow().sort_by("id")
    m = core._rows(got, "dist")
    best = lambda: cluster._cheapest(m, 100, 10, 0)
    ways = {"relaxed": lambda: (lambda u, value, rounded: [("relaxed", value), ("relaxed_rounded", G.assignment_cost(m, rounded))])(*G.relaxed(m, limit=max(1_000_000, m.size))), "greedy_best_of_100": lambda: (lambda s: [("greedy_best_of_100", G.assignment_cost(m, s)), ("polished", G.assignment_cost(m, G.polish(m, s)))])(best()), "nearest": lambda: [("nearest", G.assignment_cost(m, G.nearest(m)))]}
    return loop.over_tasks(spark, list(ways), lambda way: ways[way](), "method string, loss double")


@query
def stratify_med(spark, d):
    return cluster.stratify_frame(_emb(spark, d), MIXTURE, K, trials=100, parallel=10, max_iter=5, portable=True).select("domain", F.col("id").alias("vec_id"), "stratum")


@query
def stratify_cad_exact(spark, d):
    """Covariance strata of embeddings: the quadratic kernel about each domain's mean."""
    about_mean = lambda z: Quadratic(tuple(z.mean(0)))
    return cluster.stratify_frame(_emb(spark, d), about_mean, K, trials=100, parallel=10, max_iter=5, portable=True).select("domain", F.col("id").alias("vec_id"), "stratum")


@query
def stratify_cad(spark, d):
    """All line items, each domain: the quadratic kernel's exact map, bucketed assignment."""
    ff = frames.lineitem(spark, d)
    n = ff.count()
    return cluster.stratify_frame(ff, None, K, fmap=Quadratic((0.0,) * 4).feature_map, rounds=3, buckets=max(1, n // 20_000)).select("domain", "id", "stratum")


@query
def stratify_mapped(spark, d):
    """Embeddings by random Fourier features: the path at scale, on a frame where exact strata exist to compare."""
    ff = _emb(spark, d)
    return cluster.stratify_frame(ff, None, K, fmap=FourierMap(MIXTURE, 64, 64), rounds=3, buckets=2).select("domain", F.col("id").alias("vec_id"), "stratum")


@query
def seed_parallel(spark, d):
    """Seeds of all line items, drawn in five passes whatever their number."""
    ids, z = cluster.seed_parallel(frames.lineitem(spark, d, "null"), lambda x: x, K)
    return rows(spark, "pick int, id long, norm double", [(i, int(a), round(float(np.sqrt((v * v).sum())), 6)) for i, (a, v) in enumerate(zip(ids, z, strict=True))])


def _line_first(ff):
    return np.array([[round(v, 9) for v in r["z"]] for r in ff.orderBy("id").select("z").limit(K).collect()])


@query
def kmeans_features(spark, d):
    """Linear strata of all line items: two rounds from the rows of smallest ids."""
    ff = io.staged(frames.lineitem(spark, d, "null").select("id", "z"))
    return cluster.nearest_rounds(ff, _line_first(ff), 2)


@query
def kmeans_inputs(spark, d):
    """Strata on raw inputs (order price and customer balance), computed once."""
    o, c = load(spark, d, "orders", ["o_orderkey", "o_custkey", "o_totalprice"]), load(spark, d, "customer", ["c_custkey", "c_acctbal"])
    ff = frames.standardised(o.join(c, F.col("o_custkey") == F.col("c_custkey")), ("o_totalprice", "c_acctbal")).select(F.col("o_orderkey").alias("id"), "z")
    return cluster.nearest_rounds(ff, _line_first(ff), 2)


@query
def kernel_kmeans(spark, d):
    """Unweighted kernel k-means: one round of kernel distances from a fixed start, then the nearest mean."""
    ff = _emb(spark, d)
    s = ff.select("id", F.pmod("id", F.lit(K)).cast("int").alias("stratum"))
    dist = core.kernel_distances(ff, s, RBF(), K).withColumn("dist", F.transform("dist", lambda x: F.round(x, 9)))
    return _named(core.assign(dist, "nearest"))


@query
def strata_by_label(spark, d):
    ff = _emb(spark, d)
    return ff.select("id", "y").join(core.equal_count(ff, K), "id").select(F.col("id").alias("vec_id"), F.col("y").alias("stratum"), F.col("stratum").alias("equal_count"))


@query
def strata_sizes(spark, d):
    s = core.sizes(_strata(spark, d))
    w = Window.orderBy("n_h", "stratum")
    r = s.withColumn("r", F.row_number().over(w))  # one row a stratum
    return r.agg(F.count("*").alias("k"), F.min("n_h").alias("smallest"), F.max("n_h").alias("largest"), E.r6(F.sum((2 * F.col("r") - F.lit(K) - 1) * F.col("n_h")) / (F.lit(K) * F.sum("n_h"))).alias("gini"))


# ---- samplers --------------------------------------------------------------------------------------------------------


@query
def draw_uniform(spark, d):
    return core.draw_uniform(_emb(spark, d), K, 20).select("iter", F.col("id").alias("vec_id"), E.r6("weight").alias("weight"))


@query
def draw_strata(spark, d):
    return core.draw_strata(_strata(spark, d), 20).select("iter", "stratum", F.col("id").alias("vec_id"), E.r6("weight").alias("weight"))


@query
def draw_alloc(spark, d):
    return core.draw_allocated(_strata(spark, d), 32, 10).select("iter", "stratum", F.col("id").alias("vec_id"), E.r6("weight").alias("weight"))


@query
def draw_weighted(spark, d):
    ff = load(spark, d, "customer", ["c_custkey", "c_acctbal"]).select(F.col("c_custkey").alias("id"), F.greatest(F.col("c_acctbal"), F.lit(0.0)).alias("w"))
    return core.draw_weighted(ff, "w", 4, 5).select("iter", "c", F.col("id").alias("c_custkey"), E.r6("weight").alias("weight"))


@query
def draw_seeding(spark, d):
    return diverse.draws(_emb(spark, d), MIXTURE, K, 20, "seeding").select("iter", F.col("id").alias("vec_id"), "weight")


@query
def draw_dpp(spark, d):
    return diverse.draws(_emb(spark, d), MIXTURE, K, 20, "dpp")


def _every_line(spark, d, how):
    ff = frames.lineitem(spark, d, "null")
    return diverse.draws_over_rows(ff, Quadratic((0.0,) * 4).feature_map, K, 10, how).select("iter", "id", E.r6("weight").alias("weight"))


@query
def draw_seeding_lines(spark, d):
    """Squared-distance seeding anew in every minibatch, from all line items."""
    return _every_line(spark, d, "seeding")


@query
def draw_dpp_lines(spark, d):
    """Determinantal minibatches from all line items."""
    return _every_line(spark, d, "dpp")


@query
def draw_kmeans_features(spark, d):
    return core.draw_strata(kmeans_features(spark, d), 20).select("iter", "stratum", "id", E.r6("weight").alias("weight"))


@query
def draw_kmeans_inputs(spark, d):
    return core.draw_strata(kmeans_inputs(spark, d), 20).select("iter", "stratum", "id", E.r6("weight").alias("weight"))


@query
def draw_swks(spark, d):
    s = stratify_med(spark, d).filter("domain = 's'").select(F.col("vec_id").alias("id"), "stratum")
    return core.draw_strata(s, 20).select("iter", "stratum", F.col("id").alias("vec_id"), E.r6("weight").alias("weight"))


@query
def draw_distinct(spark, d):
    """Uniform minibatches without replacement."""
    return core.draw_distinct(_emb(spark, d), K, 20).select("iter", F.col("id").alias("vec_id"), "weight")


@query
def draw_alloc_deviation(spark, d):
    """Draws shared out by size times the deviation of a stratum's first component."""
    ff, s = _emb(spark, d), _strata(spark, d)
    sd = ff.select("id", F.col("z")[0].alias("x")).join(s, "id").groupBy("stratum").agg(F.round(F.stddev_pop("x"), 9).alias("sd"))
    return core.draw_allocated(s, 32, 10, deviation=sd).select("iter", "stratum", F.col("id").alias("vec_id"), E.r6("weight").alias("weight"))


# ---- measures --------------------------------------------------------------------------------------------------------


@query
def strata_objective(spark, d):
    s = core.scatter(_emb(spark, d), _strata(spark, d), RBF())
    return s.select("stratum", "n_h", E.r6("scatter").alias("scatter"), E.r6(F.col("n_h") * F.col("scatter")).alias("weighted"))


def _variances(spark, d):
    ff = _emb(spark, d)
    s = core.scatter(ff, _strata(spark, d), RBF()).agg((F.sum(F.col("n_h") * F.col("scatter")) / F.pow(F.sum("n_h"), F.lit(2.0))).alias("v")).first()["v"]
    pairs = core.pair_sums(ff, RBF()).values()
    of, n = sum(c for _, c in pairs), ff.count()
    uni = (1.0 - sum(v for v, _ in pairs) / of) / K
    return s, uni, uni * (n - K) / (n - 1)


@query
def mean_variance(spark, d):
    s = _variances(spark, d)[0]
    return rows(spark, "method string, variance double", [("swks_greedy", s)]).withColumn("variance", E.r6(F.col("variance") * 1000))


@query
def mean_variance_uniform(spark, d):
    _, u, w = _variances(spark, d)
    return rows(spark, "method string, variance double", [("replace", u), ("no_replace", w)]).withColumn("variance", E.r6(F.col("variance") * 1000))


@query
def variance_gain(spark, d):
    s, u, _ = _variances(spark, d)
    return rows(spark, "gain double", [(u / s,)]).withColumn("gain", E.r6("gain"))


@query
def mean_variance_mc(spark, d):
    """Mean squared distance of drawn to population means of all line items under the linear kernel."""
    ff = io.staged(frames.lineitem(spark, d, "null").select("id", "z"))
    s = ff.select("id", F.pmod("id", F.lit(K)).cast("int").alias("stratum"))
    mu = ff.agg(*[F.avg(F.col("z")[i]).alias(f"m{i}") for i in range(4)]).first()
    g = core.fetch(core.draw_strata(s, 50), ff).groupBy("iter").agg(*[F.sum(F.col("weight") * F.col("z")[i]).alias(f"x{i}") for i in range(4)])
    sq = sum((F.pow(F.col(f"x{i}") - F.lit(mu[f"m{i}"]), F.lit(2.0)) for i in range(4)), F.lit(0.0))
    return g.agg(F.count("*").alias("iters"), E.r6(F.avg(sq)).alias("variance"))


@query
def loss_variance_mc(spark, d):
    return core.med_hat(_domain_draws(spark, d), _emb(spark, d).drop("domain"), MIXTURE).agg(F.count("*").alias("iters"), E.r6(F.avg("value")).alias("mean_value"), E.r6(F.var_samp("value") * 1000).alias("variance_e3"))


@query
def mean_variance_enum(spark, d):
    """Regions' nations as strata: every tuple of one nation a region, 5^5 draws, against the analytic variance."""
    n = load(spark, d, "nation").select("n_nationkey", F.col("n_regionkey").alias("h"), F.col("n_nationkey").cast("double").alias("x"))
    tot = n.count()
    by = n.groupBy("h").agg(F.count("*").alias("n_h"), F.var_pop("x").alias("v"))
    analytic = by.agg(F.sum(F.pow(F.col("n_h") / tot, F.lit(2.0)) * F.col("v")).alias("a")).withColumn("k", F.lit(1))
    t = None
    for h in range(5):
        one = n.filter(F.col("h") == h).select((F.col("x") * (F.count("*").over(Window.partitionBy("h")) / tot)).alias(f"x{h}"))
        t = one if t is None else t.crossJoin(one)  # five members each, by the definition of all draw tuples
    m = sum((F.col(f"x{h}") for h in range(5)), F.lit(0.0))
    return t.select(m.alias("m")).agg(F.count("*").alias("tuples"), E.r6(F.var_pop("m")).alias("enumerated")).withColumn("k", F.lit(1)).join(analytic, "k").select("tuples", "enumerated", E.r6("a").alias("analytic"))


@query
def gchi2_variance(spark, d):
    """Loss variance under normal means: source and target covariances of stratified means of line items."""
    ff = frames.lineitem(spark, d)
    s = ff.withColumn("stratum", F.pmod("id", F.lit(K)))
    pairs = [(i, j) for i in range(4) for j in range(i, 4)]
    by = s.groupBy("domain", "stratum").agg(F.count("*").alias("n_h"), *[F.covar_pop(F.col("z")[i], F.col("z")[j]).alias(f"c{i}{j}") for i, j in pairs]).collect()
    mu = {r["domain"]: np.array([r[f"m{i}"] for i in range(4)]) for r in ff.groupBy("domain").agg(*[F.avg(F.col("z")[i]).alias(f"m{i}") for i in range(4)]).collect()}
    sig = np.zeros((4, 4))
    for dom in ("s", "t"):
        n = sum(r["n_h"] for r in by if r["domain"] == dom)
        for r in by:
            if r["domain"] == dom:
                for i, j in pairs:
                    v = (r["n_h"] / n) ** 2 * r[f"c{i}{j}"]
                    sig[i, j] += v
                    if i != j:
                        sig[j, i] += v
    return rows(spark, "variance double", [(theory.loss_variance(sig, mu["s"] - mu["t"]) * 1e3,)]).withColumn("variance", E.r6("variance"))


def _scalar_strata(spark, d):
    p = load(spark, d, "part", ["p_partkey", "p_size", "p_retailprice"]).filter("p_retailprice is not null")
    return p.groupBy(F.pmod("p_size", F.lit(K)).alias("h")).agg(F.count("*").alias("n_h"), F.avg(F.col("p_retailprice") / 1000).alias("mu"), F.var_pop(F.col("p_retailprice") / 1000).alias("v")).orderBy("h").collect()


@query
def cov_variance_scalar(spark, d):
    s = _scalar_strata(spark, d)
    v = theory.scalar_covariance_variance([r["n_h"] for r in s], [r["mu"] for r in s], [r["v"] for r in s])
    return rows(spark, "target double, surrogate double", [(v["target"] * 1e3, v["surrogate"] * 1e3)]).select(E.r6("target").alias("target"), E.r6("surrogate").alias("surrogate"))


@query
def cov_variance_link(spark, d):
    s = _scalar_strata(spark, d)
    v = theory.scalar_covariance_variance([r["n_h"] for r in s], [r["mu"] for r in s], [r["v"] for r in s])
    return rows(spark, "link double, gap double", [(v["link"] * 1e3, abs(v["link"] - v["target"]))]).select(E.r6("link").alias("link"), E.r6("gap").alias("gap"))


def _enumerated(spark, d):
    """All partitions of the regions (mean balance, price of their customers' orders) into three blocks."""
    o, c, n = load(spark, d, "orders"), load(spark, d, "customer"), load(spark, d, "nation")
    g = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_regionkey").agg(F.round(F.avg("c_acctbal") / 1000, 6).alias("a"), F.round(F.avg("o_totalprice") / 100000, 6).alias("b")).orderBy("n_regionkey").collect()
    return theory.enumerate_partitions(np.array([[r["a"], r["b"]] for r in g]), 3)


@query
def surrogate_spearman(spark, d):
    _, f, g = _enumerated(spark, d)
    f, g = np.round(f, 12), np.round(g, 12)
    rho = theory.spearman(f, g)
    return rows(spark, "p long, rho double", [(len(f), rho)]).withColumn("rho", E.r6("rho"))


@query
def rank_displacement(spark, d):
    _, f, g = _enumerated(spark, d)
    rf, rg = theory.ranks(np.round(f, 12)), theory.ranks(np.round(g, 12))
    return rows(spark, "p long, sum_sq double, rank_of_best double", [(len(f), float(((rf - rg) ** 2).sum()), float(rf[int(np.round(g, 12).argmin())]))])


@query
def error_bounds(spark, d):
    """Logs of both bounds for k = 8, rho = 0.99, growth 1, where n is the number of events of a user; null without partitions or with one."""
    users = load(spark, d, "events", ["user_id"]).groupBy("user_id").agg(F.count("*").alias("n")).groupBy("n").agg(F.count("*").alias("users"))

    def work(batches):
        for b in batches:
            found = []
            for n, users in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                lp = theory.log_stirling(n, K) if n >= K else None
                found.append((n, users, lp, *(theory.error_bounds(lp, 1.0, 0.99) if lp else (None, None))))
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*found, strict=True), (pa.int64(), pa.int64(), *[pa.float64()] * 3), strict=True)], names=["n", "users", "log_p", "log_worst", "log_expected"])

    return users.mapInArrow(work, "n long, users long, log_p double, log_worst double, log_expected double").select("n", "users", *[E.r6(c).alias(c) for c in ("log_p", "log_worst", "log_expected")])


@query
def assign_loss_methods(spark, d):
    """True cost of each assignment of all embeddings: greedy, marginal, blocked and nearest."""
    dist = _trial_dist(spark, d)
    out = None
    for method, options in {"greedy": {}, "marginal": {"score": "marginal"}, "parallel10": {"parallel": 10}}.items():
        one = core.pass_costs(dist.withColumn("method", F.lit(method)), "method", "id", **options)
        out = one if out is None else out.unionByName(one)
    near = dist.groupBy((F.array_position("dist", F.array_min("dist")) - 1).alias("stratum")).agg(F.count("*").alias("n"), F.sum(F.array_min("dist")).alias("s"))
    near = near.agg(F.sum(F.col("n") * F.col("s")).alias("cost")).select(F.lit("nearest").alias("method"), "cost")
    return out.unionByName(near).select("method", _cost6("cost").alias("loss"))


@query
def accuracy_summary(spark, d):
    """Mean and standard error of per-language agreement of a fixed quality rule with the labels."""
    ff = frames.documents(spark, d).filter("y is not null").withColumn("hit", (F.when(F.col("z")[4] < 0.05, 1).otherwise(0) == F.col("y")).cast("double"))
    per = ff.groupBy("env").agg(F.avg("hit").alias("acc"))
    return per.agg(F.count("*").alias("splits"), E.r6(F.avg("acc")).alias("mean_acc"), E.r6(F.stddev_samp("acc") / F.sqrt(F.count("*"))).alias("std_err"))


@query
def accuracy_pivot(spark, d):
    ff = frames.documents(spark, d).filter("y is not null")
    return ff.groupBy("env").pivot("y", [0, 1]).agg(F.count(F.lit(1))).select("env", F.coalesce(F.col("0"), F.lit(0)).alias("low"), F.coalesce(F.col("1"), F.lit(0)).alias("high"))


@query
def strata_agreement(spark, d):
    a, b = _strata(spark, d), core.assign(_dist(spark, d), "nearest")
    return R.adjusted_rand(R.contingency(a, b)).select(E.r6("ari").alias("ari"), "n")


# ---- operators around the methods -----------------------------------------------------------------------------------


@query
def scan_counts(spark, d):
    out = None
    for t in TABLES:
        one = load(spark, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query
def vector_norms(spark, d):
    return _emb(spark, d).select(F.col("id").alias("vec_id"), E.r6(F.sqrt(E.dot("z", "z"))).alias("norm"), E.r6(E.total(E.clip(E.l2_normalise("z"), -0.1, 0.1))).alias("clipped_sum"))


@query
def vector_standardise(spark, d):
    return frames.lineitem(spark, d, "null").select("id", *[E.r6(F.col("z")[i]).alias(f"z{i}") for i in range(4)])


@query
def portable_uniform(spark, d):
    return load(spark, d, "embeddings", ["vec_id"]).select("vec_id", E.portable_u(42, "u", F.col("vec_id")).alias("u"))


@query
def domain_split(spark, d):
    ff = load(spark, d, "embeddings", ["vec_id", "embedding"]).select(F.col("vec_id").alias("id"), E.vec("embedding").alias("z"))
    out = None
    for how in ("null", "soft", "hard", "affine"):
        one = frames.with_domain(ff, how).groupBy("domain").agg(F.count("*").alias("n"), E.r6(F.avg(F.col("z")[0])).alias("mean0")).withColumn("how", F.lit(how))
        out = one if out is None else out.unionByName(one)
    return out


@query
def split_counts(spark, d):
    part = F.when(E.portable_u(42, "split", F.col("id")) < 0.8, "fit").otherwise("held")
    return frames.star(spark, d).withColumn("part", part).groupBy("env", "part").agg(F.count("*").alias("n"))


@query
def doc_features(spark, d):
    f = E.text_features("text")
    return io.dealt(load(spark, d, "documents", ["doc_id", "text"])).select("doc_id", *[E.r6(v).alias(k) for k, v in f.items()])


@query
def page_features(spark, d):
    p = load(spark, d, "pages", ["page_id", "html"])
    tags, bare = F.regexp_count("html", F.lit("<[a-zA-Z]")), F.length(F.regexp_replace("html", "<[^>]*>", ""))
    return p.select("page_id", tags.cast("long").alias("tags"), E.r6(bare / F.greatest(F.length("html"), F.lit(1))).alias("text_ratio"))


@query
def conv_features(spark, d):
    c = load(spark, d, "conversations")
    return c.groupBy("conv_id").agg(F.count("*").alias("turns"), F.sum(F.when(F.col("role") == "user", 1).otherwise(0)).alias("user_turns"), E.r6(F.avg(F.length("text"))).alias("mean_chars"))


@query
def event_props(spark, d):
    e = load(spark, d, "events", ["event_type", "props"])
    k = F.get_json_object("props", "$.k").cast("long")
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.sum(k).alias("sum_k"), F.countDistinct(k).alias("distinct_k"))


@query
def event_time_features(spark, d):
    e = load(spark, d, "events", ["ts", "value"])
    return e.groupBy(F.hour("ts").alias("hour"), F.dayofweek("ts").alias("dow"), F.date_format(F.date_trunc("week", "ts"), "yyyy-MM-dd").alias("week")).agg(F.count("*").alias("n"), E.r6(F.avg(F.log1p("value"))).alias("mean_log"))


@query
def star_features(spark, d):
    return frames.star(spark, d).select("id", "env", *[E.r6(F.col("z")[i]).alias(f"z{i}") for i in range(4)])


@query
def strata_join(spark, d):
    ff = frames.lineitem(spark, d, "null")
    s = ff.select("id", F.pmod("id", F.lit(32)).cast("int").alias("stratum"))
    return ff.join(s, "id").groupBy("stratum").agg(F.count("*").alias("n"), E.r6(F.avg(F.col("z")[0])).alias("mean0"))


@query
def quantile_bins(spark, d):
    return R.quantile_bins(load(spark, d, "orders", ["o_orderkey", "o_totalprice"]), "o_orderkey", "o_totalprice", 4)


@query
def price_quartiles(spark, d):
    return load(spark, d, "part", ["p_brand", "p_retailprice"]).groupBy("p_brand").agg(*[E.r6(F.percentile("p_retailprice", F.lit(q))).alias(f"q{int(q * 100)}") for q in (0.25, 0.5, 0.75)])


@query
def approximate_measures(spark, d):
    """Whether one-pass sketches of large columns keep their stated errors: quantiles by rank, distinct counts by ratio."""
    li = load(spark, d, "lineitem", ["l_partkey", "l_extendedprice"])
    a = li.agg(F.count("*").alias("n"), F.percentile_approx("l_extendedprice", [0.25, 0.5, 0.75], 1000).alias("q"), F.approx_count_distinct("l_partkey", 0.02).alias("k")).first()
    below = [F.sum(F.when(F.col("l_extendedprice") <= F.lit(q), 1).otherwise(0)) / F.lit(a["n"]) for q in a["q"]]
    near = [(F.abs(b - F.lit(x)) < 0.005).alias(f"q{int(100 * x)}") for b, x in zip(below, (0.25, 0.5, 0.75), strict=True)]
    return li.agg(F.count("*").alias("n"), *near, (F.abs(F.lit(a["k"]) / F.countDistinct("l_partkey") - 1) < 0.1).alias("distinct_parts"))


@query
def account_unpivot(spark, d):
    """Parts' numbers as (key, measure, value) rows."""
    p = load(spark, d, "part", ["p_partkey", "p_size", "p_retailprice"]).select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return p.unpivot("p_partkey", ["size", "price"], "measure", "value")


@query
def grouped_vectors(spark, d):
    """Mean vector and covariance triangle of line items by environment, as aggregates that combine before the shuffle."""
    g = frames.lineitem(spark, d, "null").groupBy("env").agg(core.vec_mean("z", 4).alias("m"), core.vec_cov("z", 4).alias("c"))
    return g.select("env", *[E.r6(F.col("m")[i]).alias(f"m{i}") for i in range(4)], *[E.r6(F.col("c")[i]).alias(f"c{i}") for i in range(10)])


@query
def asof_strata(spark, d):
    """Each event with its user's latest purchase value at or before it."""
    e = load(spark, d, "events", ["event_id", "ts", "user_id", "event_type", "value"])
    buys = e.filter("event_type = 'purchase'").groupBy("user_id", F.col("ts").alias("buy_ts")).agg(F.max("value").alias("last_buy"))
    return R.asof(e.select("event_id", "ts", "user_id"), buys, "user_id", "ts", "buy_ts", "last_buy").select("event_id", E.r6("last_buy").alias("last_buy"))


@query
def interval_pairs(spark, d):
    e = load(spark, d, "events", ["event_id", "ts", "user_id", "event_type"])
    return R.interval_pairs(e.filter("event_type = 'purchase'"), e.filter("event_type <> 'purchase'"), "user_id", "ts", 1)


@query
def labelled_docs(spark, d):
    return load(spark, d, "documents", ["doc_id", "lang"]).join(load(spark, d, "labels", ["doc_id"]), "doc_id", "left_semi").groupBy("lang").agg(F.count("*").alias("n"))


@query
def unlabelled_docs(spark, d):
    return load(spark, d, "documents", ["doc_id", "lang"]).join(load(spark, d, "labels", ["doc_id"]), "doc_id", "left_anti").groupBy("lang").agg(F.count("*").alias("n"))


@query
def weighted_moments(spark, d):
    li = load(spark, d, "lineitem", ["l_returnflag", "l_quantity", "l_extendedprice", "l_discount"])
    w = F.col("l_quantity").cast("double")
    m = F.sum(w * F.col("l_discount")) / F.sum(w)
    return li.groupBy("l_returnflag").agg(F.count("*").alias("n"), E.r6(m).alias("w_mean"), E.r6(F.sum(w * F.col("l_discount") * F.col("l_discount")) / F.sum(w) - m * m).alias("w_var"), E.r6(F.covar_samp(F.col("l_quantity").cast("double"), F.col("l_extendedprice").cast("double")) / 1000).alias("cov"))


@query
def distinct_rows(spark, d):
    t = load(spark, d, "documents", ["text", "lang"])
    return t.groupBy("lang").agg(F.count("*").alias("n"), F.countDistinct("text").alias("distinct_n"))


def _cells(spark, d):
    return _strata(spark, d).join(_emb(spark, d).select("id", "domain", "y"), "id")


@query
def strata_cube(spark, d):
    return _cells(spark, d).cube("domain", "stratum").agg(F.count("*").alias("n"))


@query
def strata_rollup(spark, d):
    return _cells(spark, d).rollup("domain", "stratum", "y").agg(F.count("*").alias("n"))


@query
def stratum_positions(spark, d):
    w = Window.partitionBy("stratum").orderBy("id")
    s = _strata(spark, d)
    return s.select(F.col("id").alias("vec_id"), "stratum", (F.row_number().over(w) - 1).alias("pos"), F.ntile(4).over(w).alias("quarter"), E.r6(F.percent_rank().over(w)).alias("share"))


@query
def trajectory_rolling(spark, d):
    """Daily mean value with its change and the mean of three days."""
    e = load(spark, d, "events", ["ts", "value"]).groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.avg("value").alias("v"))
    w = Window.orderBy("day")  # one row a day
    return e.select("day", E.r6("v").alias("v"), E.r6(F.col("v") - F.lag("v").over(w)).alias("change"), E.r6(F.avg("v").over(w.rowsBetween(-1, 1))).alias("rolling"))


@query
def stratum_prototypes(spark, d):
    """The row nearest to each centre among its own stratum."""
    j = _strata(spark, d).join(_dist(spark, d).select("id", "dist"), "id").withColumn("own", F.col("dist")[F.col("stratum")])
    return j.groupBy("stratum").agg(F.min_by("id", F.struct("own", "id")).alias("vec_id"), E.r6(F.min("own")).alias("dist"))


@query
def topk_trials(spark, d):
    return assign_trials(spark, d).orderBy("cost", "trial").limit(2).select("trial", "cost")


@query
def env_union(spark, d):
    a = load(spark, d, "customer").select(F.lit("customer").alias("env"), F.col("c_acctbal").alias("v"))
    b = load(spark, d, "supplier").select(F.lit("supplier").alias("env"), F.col("s_acctbal").alias("v"))
    return a.unionByName(b).groupBy("env").agg(F.count("*").alias("n"), E.r6(F.avg("v")).alias("mean_v"))


@query
def draw_overlap(spark, d):
    a, b = draw_uniform(spark, d).select("vec_id"), draw_strata(spark, d).select("vec_id")
    return a.intersect(b)


@query
def draw_except(spark, d):
    a, b = draw_uniform(spark, d).select("vec_id"), draw_strata(spark, d).select("vec_id")
    return a.exceptAll(b)


@query
def size_map(spark, d):
    m = core.sizes(_strata(spark, d)).agg(F.map_from_entries(F.collect_list(F.struct("stratum", "n_h"))).alias("m"))
    return m.select(F.explode("m").alias("stratum", "n_h"))


@query
def env_pairs(spark, d):
    """Ordered pairs of languages as adaptation splits, with rows of each side."""
    n = load(spark, d, "documents", ["lang"]).groupBy("lang").agg(F.count("*").alias("n"))
    a, b = n.select(F.col("lang").alias("src"), F.col("n").alias("n_s")), n.select(F.col("lang").alias("tgt"), F.col("n").alias("n_t"))
    return a.join(F.broadcast(b), F.col("src") != F.col("tgt"))


@query
def sql_surface(spark, d):
    sqlapi.register(spark)
    _emb(spark, d).createOrReplaceTempView("strata_emb")
    return spark.sql("with c as (select z as c from strata_emb order by id limit 1) select id as vec_id, round(rbf(z, c, 0.5D), 6) as k1, round(rbf_mix(z, c), 6) as k2, portable_u('42', 'u', cast(id as string)) as u from strata_emb, c")


@query
def udtf_draws(spark, d):
    sqlapi.register(spark)
    core.sizes(_strata(spark, d)).createOrReplaceTempView("strata_sizes_view")
    return spark.sql("select iter, stratum, pos, round(weight, 6) as weight from draw_strata(TABLE(strata_sizes_view), 20, 42)")


@query
def udtf_partitions(spark, d):
    """All partitions of the kinds of line items (flag and status) into three blocks: how often a kind is in a block, and the line items in that block on average."""
    sqlapi.register(spark)
    li = load(spark, d, "lineitem", ["l_returnflag", "l_linestatus"])
    kinds = li.groupBy(F.concat("l_returnflag", "l_linestatus").alias("kind")).agg(F.count("*").alias("c"))
    kinds = kinds.withColumn("row", F.row_number().over(Window.orderBy("kind")) - 1)  # one row a kind
    io.checkpointed(kinds).createOrReplaceTempView("strata_kinds_view")
    return spark.sql("""with p as (select pid, row, block from (select count(*) as n from strata_kinds_view), lateral enumerate_partitions(cast(n as int), 3)),
    w as (select p.pid, p.block, sum(c) as c from p join strata_kinds_view using (row) group by p.pid, p.block)
    select kind, p.block, count(*) as n, round(avg(w.c), 6) + 0.0D as mean_lines from p join strata_kinds_view using (row) join w on w.pid = p.pid and w.block = p.block group by kind, p.block""")


# ---- streaming plans over batches -----------------------------------------------------------------------------------


def _events(spark, d):
    return load(spark, d, "events")


def _day(c="window_start"):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias(c)


@query
def stream_tumbling(spark, d):
    return drift.tumbling(_events(spark, d)).select(_day(), "event_type", "n", E.r6("mean_value").alias("mean_value"))


@query
def stream_sliding(spark, d):
    return drift.sliding(_events(spark, d)).select(_day(), "n", E.r6("mean_value").alias("mean_value"))


@query
def stream_session(spark, d):
    return drift.sessions(_events(spark, d)).select("user_id", F.date_format("session_start", "yyyy-MM-dd HH:mm:ss.SSSSSS").alias("session_start"), "n", E.r6("total").alias("total"))


@query
def stream_reservoir(spark, d):
    return drift.reservoir(_events(spark, d)).select(_day(), "event_type", "event_id", "n")


@query
def x16_drift(spark, d):
    e = _events(spark, d)
    return _shifts(drift.drift(e, drift.reference(e, "2024-01-08")))


def _shifts(found):
    return found.select(_day(), "n", *[E.r6(c).alias(c) for c in ("cad", "mean_shift", "med")])


@query
def x16_drift_weekly(spark, d):
    e = _events(spark, d)
    return _shifts(drift.drift(e, drift.reference(e, "2024-01-08"), "7 days"))


@query
def stream_dedup(spark, d):
    e = _events(spark, d)
    return drift.deduplicated(e.unionByName(e.filter("event_id % 3 = 0"))).groupBy("event_type").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


for _name, _f in workloads.QUERIES.items():
    QUERIES[_name] = _f


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return {k: v for k, v in SQL.items() if k in QUERIES}
