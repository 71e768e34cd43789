"""Kernels: bits, uniforms, count probabilities, conditional draws."""

from itertools import product
from math import comb

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from relstrata.functions import bernoulli as bn
from relstrata.functions import bits, rng


def test_md5_uniform_is_the_agreed_one(spark):
    from pyspark.sql import functions as F

    assert rng.uniform_md5_py(7, 3, 1) == 0.6742106130699395
    assert spark.range(1).select(rng.uniform_md5(7, 3, F.lit(1))).first()[0] == 0.6742106130699395


def test_uniforms_are_uniform():
    u = rng.uniform_np(1, np.arange(20_000), 2)
    assert abs(u.mean() - 0.5) < 0.01 and abs(u.var() - 1 / 12) < 0.003
    assert np.array_equal(u, rng.uniform_np(1, np.arange(20_000), 2))


@pytest.mark.parametrize("n", [1, 61, 62, 63, 124, 125])
def test_words_at_their_boundaries(n, spark):
    from pyspark.sql import functions as F

    x = np.random.default_rng(n).random((n, 9)) < 0.4
    w = bits.pack(x)
    assert w.shape[0] == bits.n_words(n) and np.array_equal(bits.unpack(w, n), x)
    df = spark.createDataFrame([(w[:, k].tolist(),) for k in range(9)], "words array<bigint>")
    got = df.select(bits.popcount(F.col("words")).alias("k"), bits.members(F.col("words"), n).alias("m")).collect()
    for k, r in enumerate(got):
        assert r["m"] == np.flatnonzero(x[:, k]).tolist() and r["k"] == x[:, k].sum()
    assert bits.of_words(bits.to_words([0, n - 1], n)) == sorted({0, n - 1})


def test_unrank_lists_every_subset():
    for n, k in ((6, 0), (6, 3), (7, 7), (10, 4)):
        x = bits.unrank(n, k, np.arange(comb(n, k)))
        assert (x.sum(0) == k).all() and len({c.tobytes() for c in x.T.copy()}) == comb(n, k)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.floats(0, 1), min_size=1, max_size=9))
def test_count_pmf_against_enumeration(ps):
    want = np.zeros(len(ps) + 1)
    for x in product((0, 1), repeat=len(ps)):
        want[sum(x)] += np.prod([p if b else 1 - p for p, b in zip(ps, x, strict=True)])
    assert np.allclose(bn.pmf(ps), want)
    assert np.allclose(bn.tail_table(ps, len(ps))[0], want)


def test_small_counts(spark):
    from pyspark.sql import functions as F

    assert np.allclose(bn.pmf([0.1, 0.2, 0.3]), [0.504, 0.398, 0.092, 0.006])
    df = spark.createDataFrame([([0.1, 0.2, 0.3],)], "ps array<double>")
    assert np.allclose(df.select(bn.count_pmf(F.col("ps"))).first()[0], [0.504, 0.398, 0.092, 0.006])
    assert np.allclose(df.select(bn.lam_from_odds(bn.odds_sums(F.col("ps")))).first()[0], [0.504, 0.398, 0.092, 0.006])


@pytest.mark.parametrize("sampler", ["walk", "rejection"])
def test_conditional_draws_follow_the_law(sampler):
    ps, k, n = np.array([0.1, 0.4, 0.25, 0.7, 0.05]), 2, 40_000
    if sampler == "walk":
        x = bn.draw_conditional(ps, k, rng.uniform_np(3, np.arange(5)[:, None], np.arange(n)[None, :]))
    else:
        x = bn.draw_by_rejection(ps, k, n, lambda r: rng.uniform_np(4, r, np.arange(5)[:, None], np.arange(n)[None, :]))
    assert (x.sum(0) == k).all()
    code = (x * (1 << np.arange(5))[:, None]).sum(0)
    states = [s for s in range(32) if bin(s).count("1") == k]
    p = np.array([np.prod([ps[d] if s >> d & 1 else 1 - ps[d] for d in range(5)]) for s in states])
    p /= p.sum()
    seen = np.array([(code == s).mean() for s in states])
    assert (n * (seen - p) ** 2 / p).sum() < 30  # nine degrees of freedom


def test_certain_and_impossible_components():
    x = bn.draw_conditional([1.0, 0.0, 0.5, 0.5], 2, rng.uniform_np(1, np.arange(4)[:, None], np.arange(500)[None, :]))
    assert x[0].all() and not x[1].any() and (x[2] ^ x[3]).all()
    assert bn.draw_conditional([0.3, 0.4], 0, np.full((2, 3), 0.5)).sum() == 0
    assert bn.draw_conditional([0.3, 0.4], 2, np.full((2, 3), 0.5)).all()


@pytest.mark.parametrize("pushdown", ["false", "true"])
def test_state_space_source(spark, pushdown):
    from relstrata.sources.state_space import state_space

    name = "spark.sql.python.filterPushdown.enabled"
    before = spark.conf.get(name)
    spark.conf.set(name, pushdown)
    try:
        df = state_space(spark, 9, partition_size=20)
        assert df.count() == 512 and df.select("words").distinct().count() == 512
        high = df.where("k >= 7")
        assert high.count() == comb(9, 7) + comb(9, 8) + 1
        text = high._jdf.queryExecution().executedPlan().toString()
        taken = "k#" not in text.split("Filter")[1].split("\n")[0].replace("isnotnull(k#", "") if "Filter" in text else True
        assert taken == (pushdown == "true")
        assert df.where("k = 3 and k < 2").count() == 0
        assert spark.conf.get(name) == pushdown
    finally:
        spark.conf.set(name, before)


def test_uniform_draws_come_from_the_customers(spark, sf, tmp_path):
    """One draw a row of the table: twice the customers, twice the draws, and the first half stays as it was."""
    from relstrata.plans import n10
    from relstrata.sources.tables import load

    cu = load(spark, sf, "customer")
    top = cu.agg({"c_custkey": "max"}).first()[0] + 1
    cu.unionByName(cu.withColumn("c_custkey", cu["c_custkey"] + top)).write.parquet(str(tmp_path / "customer.parquet"))
    once, twice = (sorted(map(tuple, n10.Q["draw_uniform_n10"](spark, d).collect())) for d in (sf, str(tmp_path)))
    keys = [r[0] for r in cu.select("c_custkey").collect()]
    assert sorted((i, n) for i, n, _ in once) == sorted((k % 11, k // 11) for k in keys)
    assert len(twice) == 2 * len(once) and set(once) <= set(twice)
    assert all(bin(x).count("1") == i and x < 1 << n10.N for i, _, x in twice)
