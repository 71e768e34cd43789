"""Refinement: worked example, figures of the small network, equal results of both forms, properties."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from relstrata.operators import refine as rf
from relstrata.operators.approx import Overlap, antichain, approx_pf
from relstrata.operators.perf import CutUnion
from relstrata.functions import bits
from relstrata.plans import n10


def test_split_example():
    assert list(rf.split_counts(2, 2, 2)) == [0, 1, 2] and list(rf.split_counts(3, 2, 2)) == [1, 2]
    tree = rf.SplitTree([0.1, 0.2, 0.3, 0.4, 0.05, 0.05])
    s = rf.stratum(float(tree.pmf(2)[2] * tree.pmf(3)[0]), (2, 2), ((2, 2), (3, 0)))
    kids = rf.children(tree, s, rf.pick_cluster(tree, s))
    assert [c.clusters[:2] for c in kids] == [((4, 0), (5, 2)), ((4, 1), (5, 1)), ((4, 2), (5, 0))] or len(kids) == 2
    assert abs(sum(k.lam for k in kids) - s.lam) < 1e-15


#: Exact ratios over conditional Monte Carlo at sf0.01 after so many steps (strata, proportional, optimal, uniform).
GOLDEN = {0: (7, 0.974589, 0.857919, 4.014282), 1: (11, 0.913482, 0.263789, 1.070676), 5: (16, 0.904251, 0.174726, 0.927950), 20: (37, 0.843356, 0.099434, 0.832871), 50: (85, 0.770002, 0.061226, 0.972523), 100: (135, 0.626541, 0.035376, 0.687698)}


def test_small_network_figures(spark):
    sf = "/root/testdata/sf0.01"
    trace = n10._trace(spark, sf)
    for t, want in GOLDEN.items():
        got = trace[t]
        assert got["n_strata"] == want[0]
        assert np.allclose([got["r_prop"], got["r_opt"], got["r_uni"]], want[1:], atol=1e-6)
    for c in ("r_prop", "r_opt"):  # never rises; the uniform one may
        assert all(b[c] <= a[c] + 1e-12 for a, b in zip(trace, trace[1:], strict=False))
    assert trace[0]["r_uni"] > 1 and any(b["r_uni"] > a["r_uni"] for a, b in zip(trace, trace[1:], strict=False))


@pytest.mark.parametrize("by", ["order", "prob", "balanced_prob"])
def test_strata_partition_the_states(by):
    ps = np.linspace(0.05, 0.4, 9)
    failed = bits.unpack(np.arange(512)[None, :], 9)
    prob = np.where(failed, ps[:, None], 1 - ps[:, None]).prod(0)
    ref = rf.refine(rf.SplitTree(ps, by), 60, 2)
    at = rf.assign(ref, failed, failed.sum(0))
    assert ((at >= 0) == (failed.sum(0) >= 2)).all()
    assert np.allclose(np.bincount(at[at >= 0], prob[at >= 0], len(ref.strata)), ref.lam)
    assert all(b <= a + 1e-15 for a, b in zip(ref.popped, ref.popped[1:], strict=False))


@pytest.mark.parametrize("n,p,i_star,steps", [(46, 0.01, 2, 400), (20, 0.2, 0, 150)])
def test_levelwise_equals_greedy(spark, n, p, i_star, steps):
    tree = rf.SplitTree(np.full(n, p))
    got = {r["stratum_id"] for r in rf.refine_levelwise(spark, tree, steps, i_star).collect()}
    assert got == {s.stratum_id for s in rf.refine(tree, steps, i_star).strata}


def test_mass_is_kept_at_scale():
    ref = rf.refine(rf.SplitTree(np.full(139, 0.01)), 5000, 3)
    assert abs(ref.lam.sum() - sum(s.lam for s in rf.initial(ref.tree, 3))) < 1e-15
    done = rf.refine(rf.SplitTree([0.5, 0.5]), 10**6)
    assert len(done.strata) == 4 and abs(done.lam.sum() - 1) < 1e-15


def test_refine_until():
    tree = rf.SplitTree(np.full(12, 0.1))
    assert len(rf.refine_until(tree, lambda s: len(s) >= 40).strata) >= 40


def test_overlap_terms_against_states():
    ps = np.linspace(0.05, 0.5, 8)
    failed = bits.unpack(np.arange(256)[None, :], 8)
    prob = np.where(failed, ps[:, None], 1 - ps[:, None]).prod(0)
    cuts = [[0, 1], [1, 5, 6], [2, 7], [3, 4, 5]]
    for t in (0, 3, 20, 60):
        ref = rf.refine(rf.SplitTree(ps), t)
        at = rf.assign(ref, failed, failed.sum(0))
        bad = CutUnion(cuts).fails(failed)
        union = approx_pf(ref.tree, ref.strata, cuts, "union")
        capped = approx_pf(ref.tree, ref.strata, cuts, "capped_sum")
        joint = approx_pf(ref.tree, ref.strata, cuts, "union", normalise=False)
        over = Overlap(ref.tree)
        for k, s in enumerate(ref.strata):
            m = at == k
            assert abs((prob[m] * bad[m]).sum() / prob[m].sum() - union[k]) < 1e-9
            assert capped[k] >= union[k] - 1e-12 and abs(joint[k] - union[k] * s.lam) < 1e-12
            assert abs(over.mass(s, frozenset(cuts[0])) - (prob[m] * failed[cuts[0]][:, m].all(0)).sum()) < 1e-12
    assert approx_pf(ref.tree, ref.strata, []).sum() == 0


@settings(max_examples=200, deadline=None)
@given(st.floats(1e-6, 1), st.floats(1e-6, 1), st.floats(0, 1), st.floats(0, 1))
def test_one_split_never_costs(l1, l2, p1, p2):
    lam, p = l1 + l2, (l1 * p1 + l2 * p2) / (l1 + l2)
    gain = lam * p * (1 - p) - l1 * p1 * (1 - p1) - l2 * p2 * (1 - p2)
    assert abs(gain - l1 * l2 / lam * (p1 - p2) ** 2) < 1e-9
    sd = lambda x: max(x * (1 - x), 0) ** 0.5
    assert lam * sd(p) - l1 * sd(p1) - l2 * sd(p2) > -1e-9


def test_antichain():
    assert antichain([[1, 2], [1], [2, 3], [2, 3, 4], [5], [5]]) == [[1], [5], [2, 3]]
