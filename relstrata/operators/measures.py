"""Cost and accuracy measures. Strata rows: ``lam``, ``p`` (and sizes); groups by ``by``."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LAM, P = F.col, F.col


def _sd(p):
    return F.sqrt(F.greatest(p * (1 - p), F.lit(0.0)))


def variance_ratios(strata: DataFrame, by=()) -> DataFrame:
    """(p_f, r_prop, r_opt, r_uni) over crude Monte Carlo on the strata given.

    On strata that were cut at i* the sizes are normalised first, and the same formulas
    then compare with conditional Monte Carlo; ``p_f`` is then p*.
    """
    mass = F.sum("lam")
    a = strata.groupBy(*by).agg(
        mass.alias("m"),
        F.sum(F.col("lam") * F.col("p")).alias("a"),
        F.sum(F.col("lam") * F.col("p") * (1 - F.col("p"))).alias("within"),
        F.sum(F.col("lam") * _sd(F.col("p"))).alias("sd"),
        F.sum(F.col("lam") ** 2 * F.col("p") * (1 - F.col("p"))).alias("u"),
        F.count(F.lit(1)).alias("n_strata"),
    )
    p = F.col("a") / F.col("m")
    v = F.nullif(p * (1 - p), F.lit(0.0))  # nothing varies where all strata fail, or none: no ratio
    return a.select(
        *by, "n_strata", F.col("m").alias("mass"), p.alias("p_star"),
        (F.col("within") / F.col("m") / v).alias("r_prop"),
        ((F.col("sd") / F.col("m")) ** 2 / v).alias("r_opt"),
        (F.col("n_strata") * F.col("u") / F.col("m") ** 2 / v).alias("r_uni"),
    )


def ratio_decomposition(strata: DataFrame, by=()) -> DataFrame:
    """Proportional ratio as one minus the share of variance that lies between strata."""
    a = strata.groupBy(*by).agg(F.sum(F.col("lam") * F.col("p")).alias("p_f"), F.sum(F.col("lam") * F.col("p") ** 2).alias("q"))
    between = F.col("q") - F.col("p_f") ** 2
    return a.select(*by, "p_f", between.alias("between"), (1 - between / (F.col("p_f") - F.col("p_f") ** 2)).alias("r_prop"))


def split_gain(children: DataFrame, by=("parent",)) -> DataFrame:
    """What one split takes off Σ lam p (1-p) and Σ lam sd; both are never negative."""
    a = children.groupBy(*by).agg(
        F.sum("lam").alias("lam"), (F.sum(F.col("lam") * F.col("p")) / F.sum("lam")).alias("p"),
        F.sum(F.col("lam") * F.col("p") * (1 - F.col("p"))).alias("w"), F.sum(F.col("lam") * _sd(F.col("p"))).alias("s"),
    )
    return a.select(*by, (F.col("lam") * F.col("p") * (1 - F.col("p")) - F.col("w")).alias("gain_prop"), (F.col("lam") * _sd(F.col("p")) - F.col("s")).alias("gain_opt"))


def alpha(alloc: DataFrame, n: str = "n_int", n_opt: str = "n_opt", by=()) -> DataFrame:
    """Relative variance increase over the optimal sizes of the same total, and its bound."""
    tot = alloc.groupBy(*by).agg(F.sum(n).alias("_n"), F.sum(n_opt).alias("_o"))
    joined = alloc.join(F.broadcast(tot), list(by)) if by else alloc.crossJoin(F.broadcast(tot))
    err = (F.col(n) - F.col(n_opt) * F.col("_n") / F.col("_o")) / F.col(n)
    return joined.groupBy(*by).agg(F.sum(F.col(n) / F.col("_n") * err**2).alias("alpha"), F.max(F.abs(err) ** 2).alias("alpha_bound"))


def size_errors(alloc: DataFrame, n: str = "n_int", n_opt: str = "n_opt") -> DataFrame:
    return alloc.withColumn("size_error", (F.col(n) - F.col(n_opt)) / F.col(n))


def istar_bias(strata: DataFrame, used: int) -> DataFrame:
    """Relative bias when strata below ``used`` are dropped although some can fail."""
    return strata.agg((-F.sum(F.when(F.col("i") < used, F.col("lam") * F.col("p")).otherwise(0.0)) / F.sum(F.col("lam") * F.col("p"))).alias("rel_bias"))


def cov_reference(strata: DataFrame) -> DataFrame:
    """Coefficient of variation of the reference; strata with ``n`` null were enumerated."""
    v = F.when(F.col("n").isNotNull(), F.col("lam") ** 2 * F.col("p") * (1 - F.col("p")) / F.col("n")).otherwise(0.0)
    return strata.agg((F.sqrt(F.sum(v)) / F.sum(F.col("lam") * F.col("p"))).alias("cov"))


def rel_eff(estimates: DataFrame, p_f: float, p_star: float, mass: float, by=()) -> DataFrame:
    """Relative efficiency over conditional and crude Monte Carlo, from replicates (p_hat, cost_pilot, cost_sampling)."""
    a = estimates.groupBy(*by).agg(F.var_samp("p_hat").alias("v"), F.avg("cost_sampling").alias("c"), F.avg("cost_pilot").alias("c0"), F.avg("p_hat").alias("mean"), F.count(F.lit(1)).alias("runs"))
    cmc = F.lit(mass**2 * p_star * (1 - p_star)) / F.col("c")
    mc = F.lit(p_f * (1 - p_f)) / (F.col("c") + F.col("c0"))
    return a.select(*by, "runs", "mean", "v", (F.col("c") + F.col("c0")).alias("cost"), (cmc / F.col("v")).alias("over_cmc"), (mc / F.col("v")).alias("over_mc"))


def efficiency(mse, cost):
    return 1 / (mse * cost)


def replicate_summary(estimates: DataFrame, p_ref: float, by=()) -> DataFrame:
    """Bias, variance, mean square error and a normal interval over replicates."""
    a = estimates.groupBy(*by).agg(F.avg("p_hat").alias("mean"), F.var_samp("p_hat").alias("variance"), F.count(F.lit(1)).alias("runs"), F.avg((F.col("p_hat") - p_ref) ** 2).alias("mse"))
    half = 1.96 * F.sqrt(F.col("variance") / F.col("runs"))
    return a.withColumn("bias", F.col("mean") - p_ref).withColumn("low", F.col("mean") - half).withColumn("high", F.col("mean") + half)


def cost(pilot: int, alloc: DataFrame) -> DataFrame:
    """Evaluations of the performance function: pilot and sampling."""
    return alloc.agg((F.lit(pilot) + F.sum("n_int")).cast("long").alias("cost"))
