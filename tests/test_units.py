"""Identities, bounds and gradients without Spark."""

import numpy as np
import pytest

from strata_engine.functions import theory as T
from strata_engine.functions.kernels import MIXTURE, RBF, FourierMap, LandmarkMap, Linear, Quadratic, map_error
from strata_engine.operators import cluster as C
from strata_engine.operators import greedy as G
from strata_engine.operators.diverse import bias_variance, dpp_sample, draws_over_rows
from strata_engine.plans.choose import choose, explain_strata
from strata_engine.train.model import METHODS, Net

R = np.random.default_rng(3)


def test_quadratic_map_is_exact():
    x = R.normal(size=(20, 5))
    k = Quadratic(tuple(x.mean(0)))
    f = k.feature_map(x)
    assert np.allclose(f @ f.T, k.block(x, x))


def test_maps_approach_the_kernel():
    x = R.normal(size=(40, 4)) * 0.3
    errors = [map_error(MIXTURE, FourierMap(MIXTURE, 4, f), x)[1] for f in (16, 256, 4096)]
    assert errors[0] > errors[1] > errors[2]
    assert map_error(RBF(), LandmarkMap(RBF(), x), x)[0] < 1e-4


def test_covariance_variance_routes_agree_and_match_simulation():
    n_h, mu, v = np.arange(1, 9) * 10.0, R.normal(size=8), R.random(8)
    out = T.scalar_covariance_variance(n_h, mu, v)
    assert out["target"] == pytest.approx(out["link"])
    assert T.scalar_covariance_variance(n_h, mu, v, printed=True)["target"] < out["target"]
    z = mu + np.sqrt(v) * R.normal(size=(400_000, 8))
    w, n = n_h / n_h.sum(), n_h.sum()
    x = z - (z @ w)[:, None]
    assert ((x * x) @ w * n / (n - 1)).var() == pytest.approx(out["target"], rel=0.02)
    a, c = T.centring(n_h)
    assert np.allclose(c @ c, c) and np.allclose(c.T @ a, a @ c)


def test_loss_variance_matches_simulation():
    s = np.diag([1.0, 2.0, 0.5])
    m = np.array([1.0, -1.0, 2.0])
    x = m + R.normal(size=(400_000, 3)) * np.sqrt(np.diag(s))
    assert (x * x).sum(1).var() == pytest.approx(T.loss_variance(s, m), rel=0.02)


def test_partitions_and_bounds():
    assert len(list(T.partitions(6, 3))) == 90 and np.exp(T.log_stirling(6, 3)) == pytest.approx(90)
    z = R.normal(size=(6, 3))
    _, f, g = T.enumerate_partitions(z, 3)
    rho, rf, rg = T.spearman(f, g), T.ranks(f), T.ranks(g)
    p = len(f)
    assert ((rf - rg) ** 2).sum() == pytest.approx(p * (p * p - 1) * (1 - rho) / 6)
    growth = np.diff(np.sort(f)).max()
    worst, expected = T.error_bounds(np.log(p), growth, rho)
    assert f[g.argmin()] - f.min() <= np.exp(worst) and expected < worst
    assert T.simulate_kernel_mean(1) == 1.0 and T.simulate_kernel_mean(8, law="isotropic") > 0.999


def test_greedy_by_hand():
    far = np.array([[0.0, 9.0]] + [[9.0, 0.5]] * 9)
    assert G.nearest(far).tolist() == [0] + [1] * 9
    assert G.greedy(np.ones((4, 2))).tolist() == [0, 1, 0, 1]  # ties to the lowest, then balance
    assert G.assignment_cost(np.array([[1.0, 2.0], [3.0, 1.0]]), np.array([0, 0])) == 8.0
    assert G.greedy(np.array([[-1e-18, 0.0]])).tolist() == [0]


def _row_by_row(dist, parallel, marginal):
    sizes, sums, out = np.zeros(dist.shape[1]), np.zeros(dist.shape[1]), []
    for at in range(0, len(dist), parallel):
        picks = [(i, int((dist[i] * (sizes + 1) + marginal * sums).argmin())) for i in range(at, min(len(dist), at + parallel))]
        for i, h in picks:
            sizes[h], sums[h] = sizes[h] + 1, sums[h] + dist[i, h]
            out.append(h)
    return np.array(out), float((sizes * sums).sum())


@pytest.mark.parametrize(("parallel", "score"), [(1, "printed"), (10, "printed"), (7, "marginal"), (1, "marginal")])
def test_a_pass_in_pieces_is_row_by_row(parallel, score):
    d = np.round(R.random((1503, 5)), 2) + 0.3  # with ties
    want, cost = _row_by_row(d, parallel, score == "marginal")
    run = G.Pass(parallel, score)
    got = np.concatenate([run.take(x) for x in np.split(d, np.sort(R.integers(0, len(d), 9)))])
    assert (got == want).all() and run.cost() == pytest.approx(cost) and (G.greedy(d, None, parallel, score) == want).all()


def test_trials_are_nested_and_blocks_contain_the_sequence():
    d = R.random((60, 5))
    few, many = G.best_of(d, 10, 1, 7), G.best_of(d, 300, 1, 7)
    assert many[1] <= few[1] and many[2][:10] == few[2]
    assert (G.best_of(d, 1, 1, orders=[np.arange(60)])[0] == G.greedy(d)).all()
    assert G.assignment_cost(d, few[0]) == pytest.approx(few[1])
    assert G.assignment_cost(d, G.polish(d, few[0])) <= few[1] + 1e-9


def test_relaxed_goes_below_integer_costs():
    u, value, rounded = G.relaxed(np.array([[1.0, 1.0]]))
    assert value == pytest.approx(0.5, abs=1e-3) and G.assignment_cost(np.array([[1.0, 1.0]]), rounded) == 1.0
    assert np.allclose(u.sum(1), 1)
    with pytest.raises(ValueError):
        G.relaxed(np.ones((2000, 1000)))


def test_stratify_invariants_and_brute_force():
    z = R.normal(size=(7, 2))
    gram = RBF().block(z, z)
    best = min(C.mean_variance(gram, np.array(b), 3) for b in T.partitions(7, 3))
    found = min(C.stratify(z, RBF(), 3, trials=20, parallel=1, seed=s, polish=True).variance for s in range(8))
    assert best - 1e-12 <= found <= 1.25 * best
    big = R.normal(size=(200, 3))
    s = C.stratify(big, RBF(), 8, trials=10, max_iter=6)
    assert s.variance == min(s.history) and set(s.strata) == set(range(8))
    assert C.uniform_variance(RBF().block(big, big), 8) > s.variance
    assert C.stratify(z, RBF(), 7).variance == 0.0
    one = C.stratify(z, RBF(), 1, trials=1, parallel=1)
    assert one.variance == pytest.approx(C.uniform_variance(gram, 1))
    with pytest.raises(ValueError):
        C.stratify(np.ones((9, 2)), RBF(), 3)


def test_unbiased_mean_over_all_tuples():
    z = R.normal(size=(6, 2))
    s = np.array([0, 0, 0, 1, 1, 2])
    means = [sum(n * z[i] for n, i in zip((3, 2, 1), (a, b, 5), strict=True)) / 6 for a in (0, 1, 2) for b in (3, 4)]
    assert np.allclose(np.mean(means, 0), z.mean(0))
    exact = np.mean([((m - z.mean(0)) ** 2).sum() for m in means])
    assert exact == pytest.approx(C.mean_variance(Linear().block(z, z), s, 3))


def test_dpp_inclusion():
    z = R.normal(size=(6, 2))
    k = RBF().block(z, z)
    val, vec = np.linalg.eigh(k)
    from itertools import combinations

    sets = list(combinations(range(6), 2))
    p = np.array([np.linalg.det(k[np.ix_(s, s)]) for s in sets])
    want = np.array([sum(q for s, q in zip(sets, p / p.sum(), strict=True) if i in s) for i in range(6)])
    got = np.zeros(6)
    for t in range(4000):
        got[dpp_sample(val, vec, 2, np.random.default_rng(t))] += 1
    assert np.abs(got / 4000 - want).max() < 0.04
    b, v = bias_variance(z, RBF(), [(np.arange(6), np.full(6, 1 / 6))])
    assert b == pytest.approx(0, abs=1e-12) and v == pytest.approx(0, abs=1e-12)


def test_draws_over_all_rows(spark):
    """Through a finite map, whatever the partitions: inclusion as by determinants, one row of every far cluster."""
    z = R.normal(size=(6, 2))
    ff = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(z)], "id long, z array<double>")
    from itertools import combinations

    k = z @ z.T
    sets = list(combinations(range(6), 2))
    p = np.array([np.linalg.det(k[np.ix_(s, s)]) for s in sets])
    want = np.array([sum(q for s, q in zip(sets, p / p.sum(), strict=True) if i in s) for i in range(6)])
    rows = draws_over_rows(ff.repartition(3), lambda x: x, 2, 1500, "dpp", 7).collect()
    assert len(rows) == 3000 and np.abs(np.bincount([r["id"] for r in rows], minlength=6) / 1500 - want).max() < 0.06
    far = np.concatenate([R.normal(c, 0.01, (20, 2)) for c in ((0, 0), (50, 0), (0, 50))])
    ff = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(far)], "id long, z array<double>")
    one, two = ([tuple(r) for r in draws_over_rows(x, lambda x: x, 3, 30, "seeding").collect()] for x in (ff.coalesce(1), ff.repartition(4)))
    assert one == two
    assert np.mean([len({i // 20 for j, i, _ in one if j == it}) == 3 for it in range(30)]) > 0.9
    assert draws_over_rows(spark.createDataFrame([], "id long, z array<double>"), lambda x: x, 3, 4, "seeding").count() == 0


@pytest.mark.parametrize("method", METHODS)
def test_gradients(method):
    xs, ys, ws, xt, wt, env = R.normal(size=(9, 5)), R.integers(0, 3, 9), R.dirichlet(np.ones(9)), R.normal(size=(7, 5)), R.dirichlet(np.ones(7)), R.integers(0, 2, 9)
    net = Net(method, 5, 4, 3, 1, 0.7, rho=0.0)
    g = net.loss(xs, ys, ws, xt, wt, 90, 70, env)[2]
    adversarial = method == "dann" or method.startswith("cdan")
    for k in g:
        for i in list(np.ndindex(net.p[k].shape))[:4]:
            old, seen = net.p[k][i], []
            for s in (1e-5, -1e-5):
                net.p[k][i] = old + s
                seen.append(net.loss(xs, ys, ws, xt, wt, 90, 70, env)[:2])
            net.p[k][i] = old
            task, da = ((seen[0][j] - seen[1][j]) / 2e-5 for j in (0, 1))
            assert g[k][i] == pytest.approx(task + (da if k in "vc" else (-net.lam if adversarial else net.lam) * da), abs=1e-7)


def test_plan_choice():
    assert choose(1000, 64, 8, RBF()).path == "exact"
    p = choose(2 * 10**11, 64, 128, Quadratic((0.0,) * 64))
    assert p.path == "mapped" and p.map_dims == 2080 and p.fit_fraction < 1e-3
    assert "path=mapped" in explain_strata(10**9, 64, 128, MIXTURE)


def test_parallel_seeding_finds_every_cluster(spark):
    rng = np.random.default_rng(1)
    z = np.concatenate([rng.normal(c, 0.05, (40, 2)) for c in ((0, 0), (9, 0), (0, 9), (9, 9))])
    ff = spark.createDataFrame([(i, v.tolist(), "s") for i, v in enumerate(z)], "id long, z array<double>, domain string").repartition(5)
    ids, f = C.seed_parallel(ff, lambda x: x, 4)
    assert sorted(int(i) // 40 for i in ids) == [0, 1, 2, 3] and np.allclose(f, z[ids])
    assert np.array_equal(ids, C.seed_parallel(ff.coalesce(1), lambda x: x, 4)[0])
    got = {r["id"]: r["stratum"] for r in C.stratify_mapped(ff, lambda x: x, 4, rounds=2, seeding="parallel", parallel=1, buckets=1).collect()}
    assert len({(i // 40, s) for i, s in got.items()}) == 4
    with pytest.raises(ValueError):
        C.seed_parallel(ff.filter("id = 0"), lambda x: x, 2)
