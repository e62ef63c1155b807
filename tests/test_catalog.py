"""Every catalogued query with SQL against DuckDB on whole tables, and the stream plans against their batches."""

import os
from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from strata_engine import catalog
from strata_engine.functions import exprs as E
from strata_engine.functions import frames
from strata_engine.functions.kernels import MIXTURE, RBF, FourierMap, Quadratic, map_error
from strata_engine.operators import cluster, core
from strata_engine.operators import greedy as G
from strata_engine.sources import io
from strata_engine.streaming import drift

SQL = catalog.oracle_sql()
DIR = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in io.TABLES:
        c.sql(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(SQL))
def test_oracle(spark, duck, name):
    df = catalog.queries()[name](spark, DIR)
    rel = duck.sql(SQL[name])
    cols = sorted(df.columns)
    assert sorted(rel.columns) == cols
    got = sorted(repr(tuple(r[c] for c in cols)) for r in df.collect())
    at = [rel.columns.index(c) for c in cols]
    assert got == sorted(repr(tuple(r[i] for i in at)) for r in rel.fetchall())


def test_entry(spark):
    out = catalog.entry(spark, DIR).collect()
    assert len(out) == 8 and sum(r["n_h"] for r in out) == 500


def test_partitions_do_not_matter(spark):
    ff = frames.embeddings(spark, DIR)
    d = core.centre_distances(ff, catalog._first(ff)).select("id", "dist")
    want = {r["id"]: r["stratum"] for r in core.assign(d, buckets=4).collect()}
    for n in (1, 13):
        assert {r["id"]: r["stratum"] for r in core.assign(d.repartition(n, F.rand(n)), buckets=4).collect()} == want


def test_expected_plugin_and_weights(spark):
    draws = catalog._domain_draws(spark, DIR)
    sums = draws.groupBy("domain", "iter").agg(F.sum("weight").alias("w")).collect()
    assert all(abs(r["w"] - 1) < 1e-9 for r in sums)
    same = frames.embeddings(spark, DIR, "null")
    assert core.med_exact(same, RBF()) >= 0
    moved = [core.med_exact(frames.embeddings(spark, DIR, h), MIXTURE) for h in ("null", "soft", "hard")]
    assert moved[0] < moved[1] < moved[2]


def test_ranges_of_ids_give_the_same_places(spark):
    ff = frames.embeddings(spark, DIR)
    s = ff.select("id", F.pmod("id", F.lit(5)).cast("int").alias("stratum"))
    want = {tuple(r) for r in core.positions(s).collect()}
    assert {tuple(r) for r in core.positions(s, part_rows=60).collect()} == want and len(want) == 500
    runs = {tuple(r) for r in core.equal_count(ff, 7).collect()}
    assert {tuple(r) for r in core.equal_count(ff, 7, 60).collect()} == runs
    assert sorted(Counter(x for _, x in runs).items()) == [(i + 1, 72 if i < 3 else 71) for i in range(7)]
    w = ff.select("id", (F.col("id") % 4).cast("double").alias("w"))
    big = {tuple(r) for r in core.draw_weighted(w, "w", 3, 40).collect()}
    assert len(big) == 120 and {tuple(r) for r in core.draw_weighted(w, "w", 3, 40, part_rows=60, small=0).collect()} == big


def test_bad_vectors_raise(spark):
    bad = spark.createDataFrame([(1, [1.0, 2.0]), (2, [float("nan"), 1.0]), (3, None), (4, [1.0])], "id long, z array<double>")
    with pytest.raises(ValueError, match="3 rows"):
        frames.checked(bad, 2)
    assert frames.checked(bad, 2, "drop").count() == 1
    assert spark.createDataFrame([([0.0, 0.0],)], "z array<double>").select(E.l2_normalise("z").alias("z")).first()["z"] == [0.0, 0.0]


def test_stream_equals_batch(spark, tmp_path):
    src = str(tmp_path / "in")
    spark.read.parquet(f"{DIR}/events.parquet").repartitionByRange(4, "ts").write.parquet(src)
    ref = drift.reference(spark.read.parquet(src), "2024-01-08")

    def drifting(events):
        return drift.drift(events, ref)

    for f in (drift.tumbling, drift.reservoir, drift.sliding, drift.sessions, drifting):
        name = f"s_{f.__name__}"
        q = f(io.stream(spark, src, drift.EVENT_SCHEMA, 100)).writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
        q.awaitTermination(120)
        got = {tuple(r) for r in spark.table(name).collect()}
        batch = {tuple(r) for r in f(spark.read.parquet(src)).collect()}
        near = lambda rows: {tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in rows}
        assert got and near(got) <= near(batch)  # the last windows are still open
        assert len(batch) - len(got) <= (10 if f is not drift.sessions else len(batch) // 5)


def test_stateful_streams_and_batch_sink(spark, tmp_path):
    src, out = str(tmp_path / "in"), str(tmp_path / "out")
    e = spark.read.parquet(f"{DIR}/events.parquet")
    e.unionByName(e.filter("event_id % 5 = 0")).repartitionByRange(3, "ts").write.parquet(src)
    events = io.stream(spark, src, drift.EVENT_SCHEMA, 1)
    q = drift.running_moments(events).writeStream.format("memory").queryName("moments").outputMode("update").option("checkpointLocation", str(tmp_path / "m")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    last = {}
    for r in spark.table("moments").collect():
        if r["event_type"] not in last or r["n"] > last[r["event_type"]]["n"]:
            last[r["event_type"]] = r
    for r in spark.read.parquet(src).groupBy("event_type").agg(F.count("value").alias("n"), F.avg("value").alias("m"), F.var_pop("value").alias("v")).collect():
        got = last[r["event_type"]]
        assert got["n"] == r["n"] and got["mean_value"] == pytest.approx(r["m"]) and got["var_value"] == pytest.approx(r["v"])
    for _ in range(2):  # a second run finds nothing new
        io.append_batches(drift.deduplicated(events, "400 days"), out, str(tmp_path / "d")).awaitTermination(120)
    assert spark.read.parquet(out).drop("batch").distinct().count() == spark.read.parquet(out).count() == e.count()


def test_typed_readers(spark, tmp_path):
    df = spark.createDataFrame([(1, "a", 0.5), (2, "b,c", None)], "id long, name string, x double")
    for fmt in ("json", "csv", "orc", "parquet"):
        df.write.format(fmt).option("header", "true").save(str(tmp_path / fmt))
        got = io.read_typed(spark, str(tmp_path / fmt), "id long, name string, x double", fmt)
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, df.collect()))
    spark.createDataFrame([("id,name,x\noops,x,1",)], "value string").write.text(str(tmp_path / "bad"))
    with pytest.raises(Exception, match="(?i)malformed"):
        io.read_typed(spark, str(tmp_path / "bad"), "id long, name string, x double", "csv").collect()


def test_empty_one_sided_null_and_repeated_rows(spark):
    """Frames without rows or with one domain, null vectors, ties, repeated ids and clashing columns have defined results."""
    schema = "id long, z array<double>, domain string, dist array<double>"
    none = spark.createDataFrame([], schema)
    some = spark.createDataFrame([(i, [float(i), 1.0], "s", [1.0, 1.0]) for i in range(6)] + [(3, [3.0, 1.0], "s", [1.0, 1.0])], schema)
    bad = some.unionByName(spark.createDataFrame([(9, None, "t", None)], schema))
    ident = lambda x: x
    for ff in (none, some):
        assert np.isnan(core.med_exact(ff, RBF())) and np.isnan(core.med_mapped(ff, ident))
    for f in (lambda: core.med_exact(bad, RBF()), lambda: core.med_mapped(bad, ident), lambda: cluster.stratify_frame(bad, RBF(), 2), lambda: cluster.stratify_frame(bad, None, 2, fmap=ident).count()):
        with pytest.raises(Exception, match="null vector"):
            f()
    assert cluster.stratify_frame(none, RBF(), 2).count() == 0 and cluster.stratify_frame(none, None, 2, fmap=ident).count() == 0
    assert core.assign(none).count() == 0 and core.assign(none, "nearest").count() == 0
    got = sorted((r["id"], r["stratum"]) for r in core.assign(some).collect())
    assert [s for _, s in got].count(0) == 4 and len(got) == 7  # ties go to the lowest, then sizes tell
    for how in ("greedy", "nearest"):
        assert {r["stratum"] for r in core.assign(bad, how).filter("id = 9").collect()} == {None}
    assert core.draw_uniform(none, 3, 2).count() == 0 and core.draw_distinct(none, 3, 2).count() == 0 and core.draw_weighted(none.withColumn("w", F.lit(1.0)), "w", 2, 2).count() == 0
    assert sorted(r["id"] for r in core.draw_distinct(some, 99, 1).collect()) == [0, 1, 2, 3, 3, 4, 5]
    assert core.draw_weighted(some.withColumn("w", F.when(F.col("id") == 4, 2.0).otherwise(F.when(F.col("id") == 1, -1.0))), "w", 5, 2).select("id").distinct().collect() == [(4,)]


def test_late_rows_leave_closed_windows(spark, tmp_path):
    src = str(tmp_path / "late")
    rows = [(1, "2024-01-01 00:10:00", 1, "a", 1.0, "{}"), (2, "2024-01-05 00:00:00", 1, "a", 2.0, "{}"), (3, "2024-01-09 00:00:00", 1, "a", 2.0, "{}")]
    mk = lambda r: spark.createDataFrame(r, "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    mk(rows[:2]).coalesce(1).write.mode("append").parquet(src)
    ck, late = str(tmp_path / "ck"), []
    for i, extra in enumerate((None, rows[2:], [(4, "2024-01-01 01:00:00", 1, "a", 9.0, "{}")], [(5, "2024-01-20 00:00:00", 1, "a", 1.0, "{}")])):
        if extra:
            mk(extra).coalesce(1).write.mode("append").parquet(src)
        q = drift.tumbling(io.stream(spark, src, drift.EVENT_SCHEMA)).writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", ck).outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination(120)
        late.append(drift.late_rows(q))
    out = {str(r["window_start"])[:10]: r["n"] for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert out["2024-01-01"] == 1 and late == [0, 0, 1, 0]


def test_sinks_round_trip(spark, tmp_path):
    df = frames.embeddings(spark, DIR).select("id", "domain")
    io.write_partitioned(df, str(tmp_path / "p"), "domain")
    assert sorted(os.listdir(tmp_path / "p"))[-2:] == ["domain=s", "domain=t"]
    io.write_bucketed(df, "strata_round_trip", "file://" + str(tmp_path / "b"), 4, "id")
    assert spark.table("strata_round_trip").count() == df.count()
    spark.sql("drop table strata_round_trip")
    assert io.checkpointed(df).count() == df.count()


def test_training_lowers_the_discrepancy(spark):
    from strata_engine.workloads import x14_heldout_discrepancy

    rows = x14_heldout_discrepancy(spark, DIR, n=200, steps=60, repeats=1).collect()
    got = {(r["dataset"], r["loss"], r["sampler"]): r["med"] for r in rows}
    assert len(got) == 4 * 18 and got["document_languages/de", "med", "swks"] < got["document_languages/de", "erm", "uniform"]


def test_grids_have_every_split_and_errors(spark):
    from strata_engine import workloads as W

    out = {(r["workload"], r["method"], r["sampler"]): r for r in W.x11_sampler_grid(spark, DIR, n=120, steps=6, every=3, repeats=2, methods=("med",)).collect()}
    assert {w: out[w, "med", "swks"]["splits"] for w in ("star_regions", "document_languages", "language_pairs")} == {"star_regions": 1, "document_languages": 4, "language_pairs": 12}
    assert len(out) == 24 and all(r["std_err"] is not None and r["runs"] == 2 * r["splits"] for r in out.values())
    found = W.x11_searched(spark, DIR, n=80, steps=4, every=3, repeats=2, configs=3).collect()
    assert len(found) == 24 and all(r["runs"] == 2 for r in found)
    sweep = W.x15_interval(spark, DIR, n=80, steps=30, intervals=(5, 20), repeats=2).collect()
    assert {r["every"] for r in sweep} == {"5", "20", "growing", "stale_1.2", "uniform"} and len(sweep) == 10


def test_trials_refuse_what_they_cannot_hold(spark, monkeypatch):
    monkeypatch.setattr(core, "EXACT_ROWS", 400)  # of 500 embeddings
    for name in ("assign_trials", "assign_relaxed", "assign_loss_methods", "topk_trials"):
        with pytest.raises(ValueError, match="at most 400 rows"):
            catalog.queries()[name](spark, DIR).collect()


def test_mapped_strata_gain_by_trials(spark):
    """One bucket and one round from the same seeds: the summed cost is that of the cheapest of all passes."""
    ff = frames.embeddings(spark, DIR, "null").withColumn("domain", F.lit("s")).cache()
    small = core.Small(ff)
    kernel = cluster.Linear()
    centres = small.z[cluster.seed_kpp(small.z, small.ids, kernel, 8, 42)]
    d = ((small.z[:, None] - centres[None]) ** 2).sum(2)
    costs = {}
    for trials in (1, 40):
        got = {r["id"]: r["stratum"] for r in cluster.stratify_mapped(ff, lambda x: x, 8, rounds=1, buckets=1, trials=trials).collect()}
        costs[trials] = G.assignment_cost(d, np.array([got[i] for i in small.ids]))
    assert costs[40] == pytest.approx(G.best_of(d, 40, 10, 42)[1]) and costs[40] < costs[1]


def test_strata_of_many_rows_are_one_pass(spark):
    """More than 20,000 rows by themselves, by a key and in blocks of ten: as a pass over all of them in the order of ids."""
    n = 21_003
    ff = spark.range(n).select("id", (F.col("id") % 2).cast("string").alias("domain"), F.array(*[F.round(E.portable_u(1, c, F.col("id")) + 0.5, 6) for c in range(3)]).alias("dist")).repartition(5).cache()
    rows = sorted(ff.collect())
    d = np.array([r["dist"] for r in rows])
    for parallel in (1, 10):
        got = {r["id"]: r["stratum"] for r in core.assign(ff, parallel=parallel).collect()}
        assert [got[i] for i in range(n)] == G.greedy(d, parallel=parallel).tolist()
    got = {(r["domain"], r["id"]): r["stratum"] for r in core.assign(ff, by=("domain",)).collect()}
    for dom in (0, 1):
        assert [got[str(dom), i] for i in range(dom, n, 2)] == G.greedy(d[dom::2]).tolist()


def test_costs_of_passes(spark):
    """Trials and ways over more rows than were once allowed cost what numpy's passes over all of them do."""
    n = 20_500
    ff = spark.range(n).select("id", F.array(*[E.portable_u(1, c, F.col("id")) + 0.5 for c in range(3)]).alias("dist"))
    d = np.array([r["dist"] for r in ff.orderBy("id").collect()])
    shuffled = ff.select(F.explode(F.array(F.lit(0), F.lit(1))).alias("trial"), "id", "dist").withColumn("u", E.portable_u(42, "perm", F.col("trial"), F.col("id")))
    got = {r["trial"]: r["cost"] for r in core.pass_costs(shuffled, "trial", "u", "id").collect()}
    for t in (0, 1):
        order = np.lexsort((np.arange(n), [cluster.u01(42, "perm", t, i) for i in range(n)]))
        assert got[t] == pytest.approx(G.assignment_cost(d[order], G.greedy(d[order])), rel=1e-12)


def test_pairs_in_tiles_and_chunks(spark, monkeypatch):
    """Vectors in several chunks and tiles give the sums, errors and seeds of whole arrays; no row is too many."""
    monkeypatch.setattr(core.Spread, "TILE", 100)
    ff = frames.embeddings(spark, DIR)
    small, kernel = core.Small(ff, "domain"), RBF()
    gram, own = kernel.block(small.z, small.z), small.ids % 7
    spread = core.Spread(ff, rows=150)
    one = (own[:, None] == np.arange(7)).astype(float)
    assert len(spread.chunks) == 4 and (spread.ids == small.ids).all()
    assert np.allclose(spread.sums(kernel, own, 7), gram @ one, atol=1e-9)
    total, diag = spread.own_sums(kernel, own, 7)
    assert np.allclose(total, np.einsum("ih,ij,jh->h", one, gram, one)) and np.allclose(diag, one.sum(0))
    maps = [FourierMap(kernel, 64, f) for f in (16, 64)]
    assert np.allclose(spread.map_errors(kernel, maps, 90), [map_error(kernel, m, small.z) for m in maps])
    spread.close()
    assert cluster.seed_rows(ff, kernel, 8)[0] == small.ids[cluster.seed_kpp(small.z, small.ids, kernel, 8)].tolist()


def test_exact_kernel_work_takes_more_rows_than_once(spark):
    n = 20_400
    ff = spark.range(n).select("id", F.array(F.lit(1.0), (F.col("id") % 3).cast("double")).alias("z"), F.when(F.col("id") % 2 == 0, "s").otherwise("t").alias("domain"))
    assert core.med_exact(ff, RBF()) == pytest.approx(0, abs=1e-12)
    s = ff.select("id", (F.col("id") % 3).cast("int").alias("stratum"))
    assert [(r["n_h"], round(r["scatter"], 6)) for r in core.scatter(ff, s, RBF()).orderBy("stratum").collect()] == [(n // 3, 0.0)] * 3
    far = core.kernel_distances(ff, s, RBF(), 3)
    assert far.count() == n and far.filter("abs(dist[id % 3]) > 1e-9").count() == 0


def test_strata_of_dealt_rows_are_those_of_arrays(spark, monkeypatch):
    """Pairs in tasks and trials dealt over tasks give the strata of the whole Gram matrix."""
    ff = frames.embeddings(spark, DIR)
    for kernel in (MIXTURE, lambda z: Quadratic(tuple(z.mean(0)))):
        for portable in (True, False):
            found = []
            for most in (4_000, 100):
                monkeypatch.setattr(cluster, "GRAM_ROWS", most)
                found.append(sorted(map(tuple, cluster.stratify_frame(ff, kernel, 8, trials=20, max_iter=3, portable=portable).collect())))
            assert found[0] == found[1] and len(found[0]) == 500


def test_surrogates_are_ranked_over_given_rows(spark):
    """Suppliers of line items are the populations: as many as there are, and the same whatever the partitions."""
    from strata_engine import workloads as W

    n = spark.read.parquet(f"{DIR}/lineitem.parquet").select("l_suppkey").distinct().count()
    mean = {(r["dims"], r["law"]): r for r in W.x1_surrogate_mean(spark, DIR).collect()}
    assert len(mean) == 6 and all(r["populations"] == n and -1 <= r["rho"] <= 1 for r in mean.values())
    assert all(mean[k, "isotropic"]["rho"] == pytest.approx(1.0) for k in (1, 2, 4)) and mean[1, "measured"]["rho"] == pytest.approx(1.0)
    cov = {(r["dims"], r["law"]): r for r in W.x2_surrogate_covariance(spark, DIR, batches=300).collect()}
    assert len(cov) == 6 and all(r["populations"] == n and -1 <= r["rho"] <= 1 for r in cov.values())
