"""Number of failed components and states given that number: columns and NumPy kernels.

The tables hold probabilities, not odds, so components with p = 1 need no special case.
"""

from __future__ import annotations

from math import comb

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# --- columns ---------------------------------------------------------------------------------


def count_pmf(ps: Column) -> Column:
    """ARRAY<DOUBLE> of P(i failed), i = 0..n, from an array of failure probabilities."""

    def add(pmf: Column, p: Column) -> Column:
        stay = F.transform(F.concat(pmf, F.array(F.lit(0.0))), lambda x: x * (1 - p))
        fail = F.transform(F.concat(F.array(F.lit(0.0)), pmf), lambda x: x * p)
        return F.zip_with(stay, fail, lambda a, b: a + b)

    return F.aggregate(ps, F.array(F.lit(1.0)), add)


def odds_sums(ps: Column) -> Column:
    """Elementary symmetric sums of the odds, orders 0..n; needs p < 1."""

    def add(r: Column, p: Column) -> Column:
        more = F.transform(F.concat(F.array(F.lit(0.0)), r), lambda x: x * p / (1 - p))
        return F.zip_with(F.concat(r, F.array(F.lit(0.0))), more, lambda a, b: a + b)

    return F.aggregate(ps, F.array(F.lit(1.0)), add)


def lam_from_odds(sums: Column) -> Column:
    total = F.aggregate(sums, F.lit(0.0), lambda s, x: s + x)
    return F.transform(sums, lambda x: x / total)


def ordered_p(components: DataFrame) -> DataFrame:
    """One row ``ps``: the failure probabilities in component order."""
    pairs = F.array_sort(F.collect_list(F.struct("comp_id", "p")))
    return components.agg(F.transform(pairs, lambda s: s["p"]).alias("ps"))


def count_strata(components: DataFrame) -> DataFrame:
    """(i, lam): strata by the number of failed components, any p per component."""
    return ordered_p(components).select(F.posexplode(count_pmf(F.col("ps"))).alias("i", "lam"))


def binomial_strata(spark, n: int, p: float) -> DataFrame:
    """(i, lam) for n equal components, by a running product of ratios."""
    start = F.struct(F.lit((1 - p) ** n).alias("x"), F.array(F.lit((1 - p) ** n)).alias("xs"))
    step = lambda s, i: F.struct(
        (s["x"] * (n - i + 1) / i * (p / (1 - p))).alias("x"),
        F.concat(s["xs"], F.array(s["x"] * (n - i + 1) / i * (p / (1 - p)))).alias("xs"),
    )
    return spark.range(1).select(
        F.posexplode(F.aggregate(F.sequence(F.lit(1), F.lit(n)), start, step, lambda s: s["xs"])).alias("i", "lam")
    )


def draw_uniform_subset(n: int, i: Column, u) -> Column:
    """i of n components, without replacement: those with the smallest uniforms u(d)."""
    ranked = F.array_sort(F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda d: F.struct(u(d).alias("u"), d.alias("d"))))
    return F.array_sort(F.transform(F.slice(ranked, 1, i), lambda s: s["d"]))


def draw_conditional_column(ps: list[float], i: Column, u) -> Column:
    """A state as BIGINT given i failures, component by component; u(d) are uniforms. Up to 62 components."""
    n = len(ps)
    tail = tail_table(np.array(ps), n)
    flat = F.array(*[F.array(*[F.lit(float(x)) for x in row]) for row in tail])
    p_arr = F.array(*[F.lit(float(p)) for p in ps])

    def step(s: Column, d: Column) -> Column:
        r = s["r"]
        here, after = F.element_at(flat, d + 1), F.element_at(flat, d + 2)
        pi = F.when(r > 0, F.element_at(p_arr, d + 1) * F.element_at(after, r) / F.element_at(here, r + 1)).otherwise(0.0)
        take = u(d) < pi
        return F.struct(
            (s["x"] + F.when(take, F.call_function("shiftleft", F.lit(1).cast("long"), d)).otherwise(0)).alias("x"),
            (r - F.when(take, 1).otherwise(0)).alias("r"),
        )

    start = F.struct(F.lit(0).cast("long").alias("x"), i.cast("int").alias("r"))
    return F.aggregate(F.sequence(F.lit(0), F.lit(n - 1)), start, step, lambda s: s["x"])


# --- NumPy -----------------------------------------------------------------------------------


def pmf(ps) -> np.ndarray:
    out = np.ones(1)
    for p in ps:
        out = np.append(out * (1 - p), 0.0) + np.append(0.0, out * p)
    return out


def binomial_pmf(n: int, p: float) -> np.ndarray:
    return np.array([comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(n + 1)])


def tail_table(ps, k: int) -> np.ndarray:
    """tail[j, r]: probability of exactly r failures among components j.. (rows 0..m)."""
    m = len(ps)
    out = np.zeros((m + 1, k + 1))
    out[m, 0] = 1.0
    for j in range(m - 1, -1, -1):
        out[j] = (1 - ps[j]) * out[j + 1]
        out[j, 1:] += ps[j] * out[j + 1, :-1]
    return out


def draw_conditional(ps, k: int, u: np.ndarray) -> np.ndarray:
    """failed[m, B] given k failures; u[m, B] are uniforms."""
    m, b = u.shape
    tail = tail_table(ps, k)
    left = np.full(b, k)
    out = np.zeros((m, b), bool)
    for j in range(m):
        here = tail[j, left]
        inc = np.where(left > 0, ps[j] * tail[j + 1, np.maximum(left - 1, 0)] / np.where(here > 0, here, 1), 0.0)
        out[j] = u[j] < inc
        left = left - out[j]
    return out


def draw_by_rejection(ps, k: int, draws: int, u) -> np.ndarray:
    """The same law: independent states until enough have k failures. u(round) gives [m, draws]."""
    ps = np.asarray(ps)
    got, have, r = [], 0, 0
    while have < draws:
        x = u(r) < ps[:, None]
        x = x[:, x.sum(0) == k]
        got.append(x)
        have, r = have + x.shape[1], r + 1
    return np.concatenate(got, axis=1)[:, :draws]
