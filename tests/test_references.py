"""Exact references, cuts and draws of the experiments, against enumeration on small networks."""

from itertools import combinations

import numpy as np
import pytest

from relstrata.functions import bits
from relstrata.operators import estimators, istar
from relstrata.operators.perf import Connected, DcCascade
from relstrata.operators.refine import SplitTree, refine
from relstrata.operators.sample import sample
from relstrata.plans import workloads as w
from relstrata.sources.tables import Network


def random_net(rng, nodes, edges):
    u = [int(rng.integers(0, k)) for k in range(1, nodes)]
    v = list(range(1, nodes))
    while len(u) < edges:
        a, b = sorted(rng.choice(nodes, 2, replace=False).tolist())
        u.append(a)
        v.append(b)
    n = len(u)
    return Network(np.array(u), np.array(v), rng.uniform(0.01, 0.2, n), rng.uniform(1, 5, n), rng.uniform(0.5, 2, n), {k: float(rng.uniform(1, 9)) for k in range(nodes)}, {k: float(rng.uniform(1, 9)) for k in range(nodes)})


@pytest.mark.parametrize("seed", range(6))
def test_all_minimal_cuts_up_to_a_size(seed):
    rng = np.random.default_rng(seed)
    net = random_net(rng, 7, 11)
    sources, target = [0, 1], 6
    perf = Connected(net, sources, target)

    def fails(c):
        x = np.zeros((net.n, 1), bool)
        x[list(c)] = True
        return bool(perf.fails(x)[0])

    want = [c for k in range(1, 5) for c in combinations(range(net.n), k) if fails(c) and not any(fails(set(c) - {d}) for d in c)]
    assert istar.cuts_up_to(net, sources, target, 4) == [list(c) for c in want]


def test_failing_states_give_exact_strata(spark):
    rng = np.random.default_rng(3)
    net = random_net(rng, 6, 10)
    perf = Connected(net, [0], 5)
    ref = refine(SplitTree(net.p), 12, 1)
    x = bits.unpack(np.arange(1 << net.n)[None, :], net.n)
    bad = perf.fails(x)
    rows = [(int(x[:, k].sum()), [int(k)], 1.0) for k in np.flatnonzero(bad)]
    states = spark.createDataFrame(rows, "k int, words array<bigint>, loss double").repartition(3)
    got = w.failing_sums(spark, ref, states)
    every = spark.createDataFrame([(int(x[:, k].sum()), [k], float(bad[k])) for k in range(1 << net.n)], "k int, words array<bigint>, loss double")
    assert np.allclose(got, w.leaf_sums(spark, ref, every, 0.5))
    prob = np.where(x, net.p[:, None], 1 - net.p[:, None]).prod(0)
    assert abs((got * ref.lam).sum() - (prob * bad)[x.sum(0) >= 1].sum()) < 1e-12


def test_pipe_reference_lies_between_its_bounds(spark, sf):
    """At small equal probabilities p_f is the number of smallest cuts times p to their size."""
    rows = w.Q["w13_water_reference"](spark, sf, steps=100, budget=2000, reps=3).collect()
    for r in rows:
        assert r["low"] <= r["high"] and r["p_f"] >= 0
        if r["model"] == "0.001":
            law = r["smallest_cuts"] * 1e-3 ** r["i_star"]
            assert 0.95 * law <= r["low"] <= 1.1 * law + 1e-12


def test_losses_of_few_lines_are_those_of_islands():
    rng = np.random.default_rng(5)
    net = random_net(rng, 12, 20)
    perf = DcCascade(net, 0.3)
    x = rng.random((net.n, 600)) < 0.12
    slow = DcCascade(net, 0.3)
    slow.joined = False
    assert np.allclose(perf.loss(x.copy()), slow.loss(x.copy()), atol=1e-9)


def test_rejection_ends_or_is_refused(spark):
    net = random_net(np.random.default_rng(1), 5, 7)
    perf = Connected(net, [0], 4)
    with pytest.raises(ValueError, match="no state"):
        estimators.conditional_mc(spark, net.p, perf, 100, net.n + 1)
    rare = estimators.conditional_mc(spark, np.full(net.n, 1e-4), perf, 200, 2, "rejection").first()
    assert rare["method"] == "conditional_count_first" and rare["cost_sampling"] == 200


def test_counts_are_drawn_whole(spark):
    got = estimators.drawn_sizes(spark, np.array([0.5, 0.3, 0.2]), 3_000_000, 2, 4).collect()
    for rep in (0, 1):
        n = {r["idx"]: r["n_int"] for r in got if r["rep"] == rep}
        assert sum(n.values()) == 3_000_000 and abs(n[0] / 3e6 - 0.5) < 2e-3


def test_replicates_together_or_alone_are_the_same(spark):
    net = random_net(np.random.default_rng(2), 6, 9)
    perf, tree = Connected(net, [0], 5), SplitTree(net.p)
    strata = refine(tree, 4, 1).strata
    sizes = estimators.sizes_frame(spark, strata, np.full((3, len(strata)), 70))
    together = {(r["rep"], r["idx"]): r["hits"] for r in sample(sizes, tree, perf, 9).collect()}
    for rep in range(3):
        alone = sample(sizes.where(f"rep = {rep}").repartition(5), tree, perf, 9).collect()
        assert all(together[rep, r["idx"]] == r["hits"] for r in alone) and len(alone) == len(strata)


def test_variance_interval():
    low, high = w.variance_interval(1.0, 10)
    assert abs(low - 9 / 19.02) < 0.01 and abs(high - 9 / 2.70) < 0.05


def test_levelwise_strata_at_many_steps(spark):
    from relstrata.operators.refine import refine_levelwise, strata_frame

    ps = np.random.default_rng(4).uniform(0.01, 0.2, 60)
    tree = SplitTree(ps)
    a = refine_levelwise(spark, tree, 3000, 2, direct=20).select("stratum_id")
    b = strata_frame(spark, refine(tree, 3000, 2)).select("stratum_id")
    assert a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0


def test_levelwise_estimate(spark):
    net = random_net(np.random.default_rng(7), 6, 10)
    perf = Connected(net, [0], 5)
    x = bits.unpack(np.arange(1 << net.n)[None, :], net.n)
    exact = float((np.where(x, net.p[:, None], 1 - net.p[:, None]).prod(0) * perf.fails(x)).sum())
    cuts = istar.cuts_up_to(net, [0], 5, 3)
    got = estimators.ccr_levelwise(spark, net.p, perf, 3000, 15, 1, cuts, reps=8, direct=4).collect()
    p = np.array([r["p_hat"] for r in got])
    assert len(p) == 8 and abs(p.mean() - exact) < 5 * p.std(ddof=1) / 8**0.5 + 1e-4
