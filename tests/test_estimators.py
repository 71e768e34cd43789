"""Sizes, measures, estimators and baselines: exact laws, bands, and the same answer on any partitioning."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from relstrata.functions import bernoulli as bn
from relstrata.functions import bits
from relstrata.operators import baselines, estimators, genetic, istar, measures, strata
from relstrata.operators.perf import AllConnected, Connected, CutUnion, DcCascade, FlowBelow, Predicate, is_minimal_cut
from relstrata.operators.refine import SplitTree, refine
from relstrata.plans import n10
from relstrata.plans import workloads as w
from relstrata.sources.tables import Network, add_super_source


def network(edges, p=0.1, cap=None, demand=None, supply=None):
    u, v = np.array(edges).T
    n = len(edges)
    return Network(u, v, np.full(n, p), np.ones(n) if cap is None else np.array(cap, float), np.ones(n), supply or {}, demand or {})


BRIDGE = network([(0, 1), (0, 2), (1, 2), (1, 3), (2, 3)])


def exact(net, perf):
    f = bits.unpack(np.arange(1 << net.n)[None, :], net.n)
    prob = np.where(f, net.p[:, None], 1 - net.p[:, None]).prod(0)
    bad = perf.fails(f)
    return (prob * bad).sum(), int(f.sum(0)[bad].min())


# --- sizes --------------------------------------------------------------------------------------------


@pytest.mark.parametrize("n", [1.3, 2.5, 7.01])
def test_rounding_keeps_the_mean_reciprocal(n):
    lo = np.floor(n)
    stay = lo * (lo + 1 - n) / n
    assert abs(stay / lo + (1 - stay) / (lo + 1) - 1 / n) < 1e-12
    got = estimators.integer_sizes(np.full(200_000, n), np.random.default_rng(0).random(200_000))
    assert abs((1 / got).mean() - 1 / n) < 2e-3 and set(got) == {int(lo), int(lo) + 1}


def test_rounding_edges(spark):
    from pyspark.sql import functions as F

    n = [0.0, 0.2, 1.0, 3.0]
    assert estimators.integer_sizes(np.array(n), np.full(4, 0.5)).tolist() == [1, 1, 1, 3]
    df = spark.createDataFrame([(x,) for x in n], "n_real double")
    assert [r["n_int"] for r in strata.round_sizes(df, F.lit(0.5)).collect()] == [1, 1, 1, 3]


def test_no_spread_falls_back_to_proportional(spark):
    df = spark.createDataFrame([(0, 0.75, 0.0), (1, 0.25, 1.0)], "i int, lam double, p double")
    got = {r["i"]: r["n_real"] for r in strata.allocate(df, 100, "optimal").collect()}
    assert got == {0: 75.0, 1: 25.0}
    assert estimators.real_sizes(np.array([0.75, 0.25]), 100, "optimal", np.array([0.0, 1.0])).tolist() == [75.0, 25.0]
    with pytest.raises(ValueError):
        strata.allocate(df, 1, "other")


# --- measures -----------------------------------------------------------------------------------------


@settings(max_examples=20, deadline=None)
@given(st.lists(st.tuples(st.floats(0.01, 1), st.floats(0.02, 0.98)), min_size=2, max_size=6))
def test_ratios_and_alpha(spark, rows):
    lam = np.array([r[0] for r in rows])
    lam /= lam.sum()
    p = np.array([r[1] for r in rows])
    df = spark.createDataFrame([(float(a), float(b)) for a, b in zip(lam, p, strict=True)], "lam double, p double")
    r = measures.variance_ratios(df).first()
    assert -1e-9 <= r["r_opt"] <= r["r_prop"] + 1e-9 <= 1 + 2e-9
    assert abs(measures.ratio_decomposition(df).first()["r_prop"] - r["r_prop"]) < 1e-9
    n = np.random.default_rng(len(rows)).integers(1, 50, len(lam)).astype(float)
    opt = estimators.real_sizes(lam, n.sum(), "optimal", p)
    a = measures.alpha(spark.createDataFrame([(float(x), float(y)) for x, y in zip(n, opt, strict=True)], "n_int double, n_opt double")).first()
    var = lambda m: (lam**2 * p * (1 - p) / m).sum()
    assert abs(a["alpha"] - (var(n) / var(opt) - 1)) < 1e-9 * max(1, a["alpha"]) and a["alpha"] <= a["alpha_bound"] + 1e-12


def test_pure_and_equal_strata(spark):
    pure = spark.createDataFrame([(0.4, 0.0), (0.6, 1.0)], "lam double, p double")
    assert measures.variance_ratios(pure).first()["r_prop"] == 0
    flat = spark.createDataFrame([(0.4, 0.3), (0.6, 0.3)], "lam double, p double")
    r = measures.variance_ratios(flat).first()
    assert abs(r["r_prop"] - 1) < 1e-12 and abs(r["r_opt"] - 1) < 1e-12


def test_reference_cov(spark):
    df = spark.createDataFrame([(0.5, 0.2, None), (0.5, 0.4, 100)], "lam double, p double, n long")
    assert abs(measures.cov_reference(df).first()["cov"] - np.sqrt(0.25 * 0.24 / 100) / 0.3) < 1e-12


# --- structure ----------------------------------------------------------------------------------------


def test_bridge():
    perf = Connected(BRIDGE, [0], 3)
    p_f, i_star = exact(BRIDGE, perf)
    assert i_star == 2 == istar.max_flow(BRIDGE, 0, 3) == istar.istar_all(BRIDGE)
    cuts = istar.minimal_cuts(BRIDGE, [0], 3, 100)
    assert sorted(map(len, cuts)) == [2, 2, 3, 3] and all(is_minimal_cut(perf, c, 5) for c in cuts)
    assert not is_minimal_cut(perf, [0, 1, 2], 5)
    assert abs(exact(BRIDGE, CutUnion(cuts))[0] - p_f) < 1e-15
    low, high = baselines.cut_bounds(BRIDGE.p, cuts, [[0, 3], [1, 4]])
    assert low - 1e-15 <= p_f <= high
    lows = baselines.decompose_bounds(BRIDGE.p, perf, 50)
    assert abs(lows[-1][1] - p_f) < 1e-12 and abs(lows[-1][2] - p_f) < 1e-12


def test_series_and_parallel():
    series, parallel = network([(0, 1), (1, 2), (2, 3)]), network([(0, 1), (0, 1), (0, 1)])
    assert exact(series, Connected(series, [0], 3))[1] == 1 and exact(parallel, Connected(parallel, [0], 1))[1] == 3
    assert exact(parallel, FlowBelow(parallel, 0, 1, 2.0))[1] == 2
    assert exact(series, AllConnected(series))[1] == 1


def test_super_source():
    net = network([(0, 2), (1, 2), (2, 3), (1, 3)])
    sup = add_super_source(net, [0, 1])
    assert istar.max_flow(sup, -1, 3) == 2 and exact(net, Connected(net, [0, 1], 3))[1] == 2


def test_direct_current_flow():
    net = network([(0, 1), (1, 2), (0, 2)], demand={1: 1.0, 2: 1.0}, supply={0: 2.0})
    dc = DcCascade(net, 0.4, generators=1)
    flow, served = dc._flow(np.ones((3, 1), bool))
    assert np.allclose(np.abs(flow[:, 0]), [0.5, 0.0, 0.5]) and np.allclose(served, 1)
    assert np.allclose(dc.loss(np.zeros((3, 1), bool)), 0) and np.allclose(dc.loss(np.ones((3, 1), bool)), 1)
    one = np.zeros((3, 1), bool)
    one[0] = True  # node 1 hangs on the line between 1 and 2; the rest overloads and trips
    assert dc.loss(one)[0] in (0.0, 1.0)


def test_exact_scan_and_lower_bound(spark):
    perf = Connected(BRIDGE, [0], 3)
    assert istar.istar_exact(spark, perf, 5, 5) == 2 and istar.istar_exact(spark, perf, 5, 1) is None
    assert istar.istar_lower_bound(spark, perf, 5, 1) == (2, 6) and istar.istar_lower_bound(spark, perf, 5) == (2, 16)
    never = Predicate(lambda f: np.zeros(f.shape[1], bool))
    assert istar.istar_exact(spark, never, 5, 5) is None


def test_genetic_search():
    perf = Connected(BRIDGE, [0], 3)
    best, cost, states = genetic.istar_ga(perf, 5, genetic.Settings(n_pop=40))
    assert best == 2 and cost <= 32 and all(perf.fails(np.isin(np.arange(5), s)[:, None])[0] for s in states)
    assert genetic.istar_ga(perf, 5, genetic.Settings(n_pop=40, method="roulette"))[0] == 2
    assert genetic.istar_ga(Predicate(lambda f: np.zeros(f.shape[1], bool)), 5, genetic.Settings(n_pop=10, max_gen=3))[0] is None


# --- estimators ---------------------------------------------------------------------------------------


def test_unbiased_on_the_small_network(spark, sf):
    p = {r["rate"]: r["p_f"] for r in n10.Q["exact_pf_n10"](spark, sf).collect()}[1.0]
    for r in w.estimators_n10(spark, sf, runs=20).collect():
        if r["runs"] > 1:
            assert abs(r["bias"]) < 5 * np.sqrt(r["variance"] / r["runs"]) + 1e-3 * p, r
        else:
            assert abs(r["bias"]) < 0.1 * p


def test_refinement_and_allocation_pay(spark, sf):
    net = n10.network(spark, sf, 0.1)
    perf = Connected(net, [0], 4)
    p_f = float(exact(net, perf)[0])
    mass = float(bn.pmf(net.p)[4:].sum())
    got = estimators.ccr_estimate(spark, net.p, perf, 2000, 100, 4, "practical", cuts=n10.STAR, reps=20).collect()
    hat = np.array([r["p_hat"] for r in got])
    p_star = p_f / mass
    over_cmc = mass**2 * p_star * (1 - p_star) / np.mean([r["cost_sampling"] for r in got]) / hat.var(ddof=1)
    assert over_cmc > 3 and abs(hat.mean() - p_f) < 5 * hat.std() / np.sqrt(20)


def test_answer_does_not_depend_on_partitions(spark, sf):
    net = n10.network(spark, sf, 1.0)
    perf = Connected(net, [0], 4)
    before = spark.conf.get("spark.sql.shuffle.partitions")
    out = []
    try:
        for k in ("1", "4", "16"):
            spark.conf.set("spark.sql.shuffle.partitions", k)
            got = estimators.ccr_estimate(spark, net.p, perf, 500, 20, 4, "practical", cuts=n10.STAR, reps=3)
            out.append(sorted((r["rep"], round(r["p_hat"], 12), r["cost_sampling"]) for r in got.collect()))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert out[0] == out[1] == out[2]


def test_fewer_draws_than_strata(spark):
    ref = refine(SplitTree(BRIDGE.p), 20, 2)
    got = estimators.stratified_run(spark, ref.tree, ref.strata, Connected(BRIDGE, [0], 3), 2, "proportional").first()
    assert got["cost_sampling"] == got["n_strata"] == len(ref.strata)


def test_tuning_needs_no_evaluation(spark):
    t, cost = estimators.tune_steps(np.full(30, 0.05), [[0, 1], [2, 3]], 400, 0.5, 2, limit=2000)
    assert cost > 400 and t >= 1


def test_level_sampling_and_importance_sampling():
    net = network([(0, 1), (0, 2), (1, 2), (1, 3), (2, 3)], 0.05)
    perf = Connected(net, [0], 3)
    p_f = exact(net, perf)[0]
    assert abs(np.mean([baselines.ce_is(net.p, perf, 3000, k)[0] for k in range(5)]) / p_f - 1) < 0.15
    assert abs(np.mean([baselines.subset_sim(net.p, perf, 3000, k)[0] for k in range(5)]) / p_f - 1) < 0.5


def test_signature_of_k_of_n():
    perf = Predicate(lambda f: f.sum(0) >= 3)
    f = bits.unpack(np.arange(64)[None, :], 6)
    bad = perf.fails(f)
    p = [bad[f.sum(0) == i].mean() for i in range(7)]
    assert p == [0, 0, 0, 1, 1, 1, 1]
    phi = {6 - i: 1 - x for i, x in enumerate(p)}
    assert abs(baselines.reliability(phi, 6, 0.2) - bn.binomial_pmf(6, 0.2)[:3].sum()) < 1e-12
