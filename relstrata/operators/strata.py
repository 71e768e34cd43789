"""Stratified estimators as plans over strata and draws tables.

A strata table has a row per stratum with ``lam`` (its probability) and, where known,
``p`` (failure probability inside it). Totals are one-row aggregates that are joined back,
never a window without partitions, so a strata table may have any number of rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def with_total(df: DataFrame, **totals) -> DataFrame:
    """Columns holding sums over the whole table."""
    one = df.agg(*[expr.alias(name) for name, expr in totals.items()])
    return df.crossJoin(F.broadcast(one))  # one row


def local_sd(p):
    return F.sqrt(p * (1 - p))


def drop_redundant(strata: DataFrame, i_star: int) -> DataFrame:
    """Strata that can fail, with ``lam_star``: their share of the kept mass."""
    kept = with_total(strata.where(F.col("i") >= i_star), _m=F.sum("lam"))
    return kept.withColumn("lam_star", F.col("lam") / F.col("_m")).drop("_m")


def kept_mass(strata: DataFrame, i_star: int) -> DataFrame:
    return strata.where(F.col("i") >= i_star).agg(F.sum("lam").alias("mass"))


# --- allocation: n_real per stratum ---------------------------------------------------------


def allocate(strata: DataFrame, budget: float, strategy: str, p: str = "p") -> DataFrame:
    """``n_real`` by proportional, optimal (also with approximate p), uniform or pilot shares.

    An optimal allocation without any spread falls back to the proportional one.
    """
    if strategy == "uniform":
        w = F.lit(1.0)
    elif strategy == "proportional":
        w = F.col("lam")
    elif strategy in ("optimal", "approx_optimal", "pilot"):
        w = F.col("lam") * local_sd(F.col(p))
    else:
        raise ValueError(f"unknown strategy {strategy}")
    df = with_total(strata.withColumn("_w", w), _sw=F.sum("_w"), _sl=F.sum("lam"))
    share = F.when(F.col("_sw") > 0, F.col("_w") / F.col("_sw")).otherwise(F.col("lam") / F.col("_sl"))
    return df.withColumn("n_real", F.lit(float(budget)) * share).withColumn("strategy", F.lit(strategy)).drop("_w", "_sw", "_sl")


def round_sizes(alloc: DataFrame, u) -> DataFrame:
    """``n_int``: one of the neighbouring integers, at random so that the mean of 1/n_int is 1/n_real.

    At most one becomes one; an integer stays.
    """
    n, lo = F.col("n_real"), F.floor("n_real").cast("double")
    hi = lo + 1
    stay = lo * (hi - n) / n
    out = F.when(n <= 1, 1.0).when(n == lo, lo).when(u < stay, lo).otherwise(hi)
    return alloc.withColumn("n_int", out.cast("long"))


# --- estimators and their variances ---------------------------------------------------------


def stratified_estimate(strata: DataFrame, draws: DataFrame, keys=("stratum_id",), by=()) -> DataFrame:
    """Σ lam · mean(fail). Draws are counted before they meet the strata."""
    stats = draws.groupBy(*by, *keys).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("fail").cast("long")).alias("hits"))
    met = stats.join(strata.select(*keys, "lam"), list(keys))
    return met.groupBy(*by).agg(F.sum(F.col("lam") * F.col("hits") / F.col("n")).alias("p_hat"), F.sum("n").alias("cost_sampling"))


def stratum_stats(draws: DataFrame, keys=("stratum_id",)) -> DataFrame:
    return draws.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("fail").cast("long")).alias("hits")).withColumn("p_hat", F.col("hits") / F.col("n"))


def variance_ss(strata: DataFrame, n: str = "n_real") -> DataFrame:
    return strata.agg(F.sum(F.col("lam") * F.col("lam") * F.col("p") * (1 - F.col("p")) / F.col(n)).alias("variance"))


def failure_signature(strata: DataFrame) -> DataFrame:
    return strata.select("stratum_id", "lam", "p")


# --- a population with any allocation variable -----------------------------------------------


def stratified_population(df: DataFrame, strata_cols: list, indicator, budget: int, strategy: str, seed: int, key: list) -> DataFrame:
    """One row: size, true share, the share estimated from a seeded stratified sample, its theoretical variance.

    One scan gives shares and spreads; the sample is the first n of each stratum in the order of a
    hash of ``key``. Rounding by the same hash keeps at least one row per stratum. Hashes are uniform, so
    rows beyond a bound well above the n-th hash are dropped before anything is sorted; should a stratum ever
    be left with fewer than n rows, the query fails rather than use them.
    """
    from ..functions.rng import uniform_md5

    rows = df.select(F.concat_ws("|", *[F.coalesce(c.cast("string"), F.lit("")) for c in strata_cols]).alias("stratum_id"), indicator.cast("int").alias("y"), *key)
    sizes = rows.groupBy("stratum_id").agg(F.count(F.lit(1)).alias("size"), F.avg("y").alias("p"))
    strata = with_total(sizes, _n=F.sum("size")).withColumn("lam", F.col("size") / F.col("_n")).drop("_n")
    alloc = round_sizes(allocate(strata, budget, strategy), uniform_md5(seed, F.col("stratum_id")))
    alloc = alloc.withColumn("n_int", F.least("n_int", "size"))
    order = F.md5(F.concat_ws("|", F.lit(str(seed)), *[F.col(k).cast("string") for k in key]))
    place = F.conv(F.substring("h", 1, 13), 16, 10).cast("double") / F.lit(float(2**52))
    n = F.col("n_int").cast("double")
    likely = rows.withColumn("h", order).join(F.broadcast(alloc.select("stratum_id", "n_int", "size")), "stratum_id").where(place * F.col("size") <= n + 12 * F.sqrt(n) + 50)
    rank = F.row_number().over(Window.partitionBy("stratum_id").orderBy("h", *key))
    picked = likely.withColumn("r", rank).where(F.col("r") <= F.col("n_int"))
    whole = F.when(F.count(F.lit(1)) == F.max("n_int"), F.avg("y")).otherwise(F.raise_error(F.lit("a stratum's sample is short")))
    means = picked.groupBy("stratum_id").agg(whole.cast("double").alias("p_hat"))
    joined = alloc.join(means, "stratum_id")
    return joined.agg(
        F.sum("size").alias("population"), F.sum("n_int").alias("cost"),
        F.sum(F.col("lam") * F.col("p")).alias("p_true"), F.sum(F.col("lam") * F.col("p_hat")).alias("p_hat"),
        F.sum(F.col("lam") ** 2 * F.col("p") * (1 - F.col("p")) / F.col("n_int")).alias("variance"),
    )
