"""Estimators of the failure probability: refined, count-stratified, and the baselines."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bernoulli
from ..functions.rng import uniform_np
from ..sources.scratch import written
from .approx import approx_pf
from .perf import Performance
from .refine import Refinement, SplitTree, Stratum, initial, pick_cluster, refine, refine_levelwise, stratum
from .sample import SIZES, crude_states, sample
from .strata import round_sizes


def real_sizes(lam: np.ndarray, budget: float, strategy: str, p: np.ndarray | None = None) -> np.ndarray:
    """Real sizes per stratum; optimal shares without any spread fall back to proportional ones."""
    if strategy == "uniform":
        w = np.ones(len(lam))
    elif strategy == "proportional":
        w = lam
    else:
        w = lam * np.sqrt(np.clip(p * (1 - p), 0, None))
        if not w.sum() > 0:
            w = lam
    return budget * w / w.sum()


def integer_sizes(n: np.ndarray, u: np.ndarray) -> np.ndarray:
    """A neighbouring integer, at least one, at random so that the mean of the reciprocal is kept."""
    lo = np.floor(n)
    hi = lo + 1
    stay = np.divide(lo * (hi - n), n, out=np.zeros_like(n), where=n > 0)
    return np.where(n <= 1, 1, np.where(n == lo, lo, np.where(u < stay, lo, hi))).astype(np.int64)


def sizes_frame(spark: SparkSession, strata: list[Stratum], per_rep: np.ndarray) -> DataFrame:
    """SIZES rows: per_rep[R, S] integer sizes. One row a stratum and replicate."""
    rows = [(r, k, [(int(n), int(c)) for n, c in s.clusters], int(per_rep[r, k])) for r in range(len(per_rep)) for k, s in enumerate(strata)]
    return spark.createDataFrame(rows, SIZES)


def stratified_run(
    spark: SparkSession,
    tree: SplitTree,
    strata: list[Stratum],
    perf: Performance,
    budget: float,
    strategy: str,
    p: np.ndarray | None = None,
    reps: int = 1,
    seed: int = 1,
    pilot: int = 0,
    method: str = "refined",
) -> DataFrame:
    """(method, rep, p_hat, n_strata, cost_pilot, cost_sampling): all replicates in one job."""
    lam = np.array([s.lam for s in strata])
    real = real_sizes(lam, budget, strategy, p)
    u = uniform_np(seed, 101, np.arange(reps)[:, None], np.arange(len(strata))[None, :])
    sizes = integer_sizes(np.broadcast_to(real, (reps, len(strata))), u)
    stats = sample(sizes_frame(spark, strata, sizes), tree, perf, seed)
    weights = spark.createDataFrame([(k, float(x)) for k, x in enumerate(lam)], "idx bigint, lam double")
    got = stats.join(weights, "idx")
    return got.groupBy("rep").agg(F.sum(F.col("lam") * F.col("hits") / F.col("n")).alias("p_hat"), F.count(F.lit(1)).alias("n_strata"), F.sum("n").alias("cost_sampling")).select(
        F.lit(method).alias("method"), "rep", "p_hat", "n_strata", F.lit(pilot).cast("long").alias("cost_pilot"), "cost_sampling"
    )


def ccr_estimate(spark, ps, perf, budget, steps, i_star=0, alloc="practical", cuts=None, p=None, reps=1, seed=1, pilot=0, by="order") -> DataFrame:
    """The refined estimator: refine ``steps`` times above i*, allocate, round, draw, combine.

    alloc: proportional, uniform, optimal (needs ``p`` per stratum, or a function of the strata), or practical
    (approximate p from ``cuts``).
    """
    ref: Refinement = refine(SplitTree(ps, by), steps, i_star)
    if alloc == "practical":
        p, strategy = approx_pf(ref.tree, ref.strata, cuts or []), "approx_optimal"
    else:
        strategy = alloc
        p = p(ref) if callable(p) else p
    return stratified_run(spark, ref.tree, ref.strata, perf, budget, strategy, p, reps, seed, pilot, f"ccr_{alloc}")


def ccr_levelwise(spark, ps, perf, budget, steps, i_star=0, cuts=None, reps=1, seed=1, pilot=0, by="order", direct: int = 256) -> DataFrame:
    """The refined estimator with practical sizes and no list of strata on the driver, for very many steps.

    Strata are made level by level on executors, get their approximate probabilities there batch by batch, and their
    sizes from one sum; draws are keyed by a hash of the stratum's name.
    """
    import pyarrow as pa

    tree, known = SplitTree(ps, by), cuts or []
    strata = refine_levelwise(spark, tree, steps, i_star, direct=direct)
    schema = "idx bigint, stratum_id string, clusters array<struct<node:bigint,k:int>>, lam double, p double"

    def with_p(batches):
        for b in batches:
            if b.num_rows:
                name, clusters, lam = (b.column(i).to_pylist() for i in range(1, 4))
                rows = [stratum(x, tuple(map(int, s.split("."))), tuple((c["node"], c["k"]) for c in cl)) for s, cl, x in zip(name, clusters, lam, strict=True)]
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(approx_pf(tree, rows, known), pa.float64())], ["idx", "stratum_id", "clusters", "lam", "p"])

    named = written(strata.select(F.xxhash64("stratum_id").alias("idx"), "stratum_id", "clusters", "lam").mapInArrow(with_p, schema), "levelwise-strata")
    w = F.col("lam") * F.sqrt(F.greatest(F.col("p") * (1 - F.col("p")), F.lit(0.0)))
    total = named.agg(F.sum(w).alias("w"), F.sum("lam").alias("lam")).first()
    share = w / F.lit(total["w"]) if total["w"] else F.col("lam") / F.lit(total["lam"])
    u = F.pmod(F.xxhash64(F.lit(seed), F.lit(101), "rep", "stratum_id"), F.lit(1 << 40)) / F.lit(float(1 << 40))
    each = named.withColumn("n_real", F.lit(float(budget)) * share).withColumn("rep", F.explode(F.array(*[F.lit(r) for r in range(reps)])))
    sizes = round_sizes(each, u).select("rep", "idx", "clusters", "n_int")
    got = sample(sizes, tree, perf, seed).join(named.select("idx", "lam"), "idx")
    return got.groupBy("rep").agg(F.sum(F.col("lam") * F.col("hits") / F.col("n")).alias("p_hat"), F.count(F.lit(1)).alias("n_strata"), F.sum("n").alias("cost_sampling")).select(
        F.lit("ccr_levelwise").alias("method"), "rep", "p_hat", "n_strata", F.lit(pilot).cast("long").alias("cost_pilot"), "cost_sampling"
    )


def count_stratified(spark, ps, perf, budget, i_star=0, alloc="proportional", p=None, reps=1, seed=1) -> DataFrame:
    """Strata by the number of failures only; above i* this is the conditional form."""
    tree = SplitTree(ps)
    name = ("conditional_" if i_star else "") + f"stratified_{alloc}"
    return stratified_run(spark, tree, initial(tree, i_star), perf, budget, alloc, p, reps, seed, 0, name)


def pilot_stratified(spark, ps, perf, budget, n0: int, i_star=0, reps=1, seed=1) -> DataFrame:
    """A pilot of n0 draws in each stratum gives the optimal shares; its draws count as cost."""
    tree = SplitTree(ps)
    strata = initial(tree, i_star)
    rows = sample(sizes_frame(spark, strata, np.full((1, len(strata)), n0)), tree, perf, seed + 1).collect()  # a row a count
    p = np.zeros(len(strata))
    for r in rows:
        p[r["idx"]] = r["hits"] / r["n"]
    return stratified_run(spark, tree, strata, perf, budget, "optimal", p, reps, seed, n0 * len(strata), "pilot_stratified")


def crude_mc(spark, ps, perf, n, reps=1, seed=1) -> DataFrame:
    got = crude_states(spark, ps, n, perf, seed, reps)
    return got.select(F.lit("crude").alias("method"), "rep", (F.col("hits") / F.col("n")).alias("p_hat"), F.lit(0).cast("long").alias("n_strata"), F.lit(0).cast("long").alias("cost_pilot"), F.col("n").alias("cost_sampling"))


#: Rejection is refused below this chance of a draw to be kept: it would take more draws than counting first saves.
REJECTION_FLOOR = 1e-4


def conditional_mc(spark, ps, perf, n, i_star, sampler="rejection", reps=1, seed=1) -> DataFrame:
    """At least i* failures: by rejection, or by drawing the count first and then the state.

    Without any state of i* failures the estimate has nothing to draw and a ValueError is raised; where a kept draw is
    rarer than REJECTION_FLOOR, rejection gives way to counting first (the method's name says which was used).
    """
    mass = float(bernoulli.pmf(ps)[i_star:].sum())
    if not mass > 0:
        raise ValueError("no state has i* failures")
    if sampler == "rejection" and mass < REJECTION_FLOOR:
        sampler = "count_first"
    if sampler == "rejection":
        hits = crude_states(spark, ps, n, perf, seed, reps, i_star).select("rep", F.col("hits"), "n")
    else:
        tree = SplitTree(ps)
        strata = initial(tree, i_star)
        sizes = drawn_sizes(spark, np.array([s.lam for s in strata]), n, reps, seed)
        clusters = spark.createDataFrame([(k, [(int(a), int(c)) for a, c in s.clusters]) for k, s in enumerate(strata)], "idx bigint, clusters array<struct<node:bigint,k:int>>")
        sizes = sizes.join(clusters, "idx").select("rep", "idx", "clusters", "n_int")
        hits = sample(sizes, tree, perf, seed).groupBy("rep").agg(F.sum("hits").alias("hits"), F.sum("n").alias("n"))
    return hits.select(F.lit(f"conditional_{sampler}").alias("method"), "rep", (mass * F.col("hits") / F.col("n")).alias("p_hat"), F.lit(0).cast("long").alias("n_strata"), F.lit(0).cast("long").alias("cost_pilot"), F.col("n").alias("cost_sampling"))


def drawn_sizes(spark, lam: np.ndarray, n: int, reps: int, seed: int) -> DataFrame:
    """(rep, idx, n_int): how many of n draws fall on each stratum, counted chunk by chunk in tasks."""
    import pyarrow as pa

    cum = np.cumsum(lam) / lam.sum()
    size = 1 << 20
    chunks = spark.range(reps * (-(-n // size))).select((F.col("id") % reps).cast("int").alias("rep"), (F.floor(F.col("id") / reps) * size).cast("long").alias("lo"))

    def run(batches):
        for b in batches:
            for rep, lo in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                got = np.bincount(np.searchsorted(cum[:-1], uniform_np(seed, 103, rep, np.arange(lo, min(lo + size, n))), side="right"), minlength=len(lam))
                idx = np.flatnonzero(got)
                yield pa.RecordBatch.from_pydict({"rep": pa.array(np.full(len(idx), rep, np.int32)), "idx": pa.array(idx), "n_int": pa.array(got[idx].astype(np.int64))})

    return chunks.mapInArrow(run, "rep int, idx bigint, n_int bigint").groupBy("rep", "idx").agg(F.sum("n_int").alias("n_int"))


def balanced_refined(spark, ps, perf, n, reps=1, seed=1) -> DataFrame:
    """Equal slices of [0, 1), one uniform in each, read as a state component by component."""
    import pyarrow as pa

    ps = np.asarray(ps)
    size = 4096
    chunks = spark.range(reps * (-(-n // size))).select((F.col("id") % reps).cast("int").alias("rep"), (F.floor(F.col("id") / reps) * size).cast("long").alias("lo"))

    def run(batches):
        for b in batches:
            for rep, lo in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                k = np.arange(lo, min(lo + size, n))
                u = (k + uniform_np(seed, rep, k)) / n
                x = np.zeros((len(ps), len(k)), bool)
                for d, p in enumerate(ps):
                    x[d] = u < p
                    u = np.where(x[d], u / p if p > 0 else u, (u - p) / (1 - p) if p < 1 else u)
                yield pa.RecordBatch.from_pydict({"rep": pa.array([rep], pa.int32()), "n": pa.array([len(k)]), "hits": pa.array([int(perf.fails(x).sum())])})

    got = chunks.mapInArrow(run, "rep int, n bigint, hits bigint").groupBy("rep").agg(F.sum("hits").alias("h"), F.sum("n").alias("n"))
    return got.select(F.lit("balanced").alias("method"), "rep", (F.col("h") / F.col("n")).alias("p_hat"), F.col("n").alias("n_strata"), F.lit(0).cast("long").alias("cost_pilot"), F.col("n").alias("cost_sampling"))


def tune_steps(ps, cuts, budget: float, share: float, i_star: int, seed: int = 1, limit: int = 200_000) -> tuple[int, int]:
    """(steps, cost): the first number of steps at which the rounded sizes for share·budget exceed the budget.

    Needs no evaluation of the performance function. The cost is not exactly monotone because sizes are
    rounded at random, so the search doubles and then bisects.
    """
    tree = SplitTree(ps)

    def cost(t: int) -> int:
        ref = refine(tree, t, i_star)
        p = approx_pf(tree, ref.strata, cuts)
        n = real_sizes(ref.lam, share * budget, "approx_optimal", p)
        return int(integer_sizes(n, uniform_np(seed, 105, np.arange(len(n)))).sum())

    lo, hi = 0, 1
    while cost(hi) <= budget and hi < limit:
        lo, hi = hi, 2 * hi
    while hi - lo > 1:
        mid = (lo + hi) // 2
        lo, hi = (mid, hi) if cost(mid) <= budget else (lo, mid)
    return hi, cost(hi)


def ccr_adaptive(spark, ps, perf, var_target: float, i_star=0, first: int = 2000, rounds: int = 8, seed: int = 1) -> DataFrame:
    """Rounds of sampling, splitting the strata that add most variance, and allocation, until the variance estimate is low.

    Rounds keep their own unbiased estimates, which are averaged with weights of their sizes.
    """
    tree = SplitTree(ps)
    strata = initial(tree, i_star)
    post = np.full(len(strata), 0.5)
    out = []
    for r in range(rounds):
        lam = np.array([s.lam for s in strata])
        sizes = integer_sizes(real_sizes(lam, first, "optimal", post), uniform_np(seed, 107, r, np.arange(len(lam))))
        rows = {x["idx"]: x for x in sample(sizes_frame(spark, strata, sizes[None, :]), tree, perf, seed + 31 * r).collect()}  # a row a stratum
        n = np.array([rows[k]["n"] for k in range(len(strata))])
        h = np.array([rows[k]["hits"] for k in range(len(strata))])
        post = (h + 0.5) / (n + 1)
        v = lam**2 * post * (1 - post) / n
        out.append((r, float((lam * h / n).sum()), float(v.sum()), int(n.sum()), len(strata)))
        if 1 / sum(1 / x[2] for x in out) < var_target:
            break
        grown, q = [], []
        worst = set(np.argsort(-v)[: max(1, len(strata) // 2)].tolist())
        for k, s in enumerate(strata):
            at = pick_cluster(tree, s) if k in worst else None
            from .refine import children

            kids = children(tree, s, at) if at is not None else [s]
            grown += kids
            q += [post[k]] * len(kids)
        strata, post = grown, np.array(q)
    total = sum(x[3] for x in out)
    p_hat = sum(x[1] * x[3] for x in out) / total
    return spark.createDataFrame([("ccr_adaptive", 0, p_hat, out[-1][4], 0, total)], "method string, rep int, p_hat double, n_strata long, cost_pilot long, cost_sampling long")


def assess(spark, net, perf, kind: str, budget: float, steps: int, cuts=None, seed: int = 1, reps: int = 1, ga=None) -> DataFrame:
    """The whole workflow. kind ``connectivity``: i* from the given minimal cuts' max-flow form; ``physics``: genetic search."""
    if kind == "connectivity":
        from .istar import max_flow

        if perf.target in perf.sources:
            raise ValueError("the target is a source: the system cannot fail")
        i_star = int(max_flow(_one_source(net, perf.sources), -1, perf.target))
        pilot = 0
    else:
        from .genetic import istar_ga
        from .approx import antichain

        i_star, pilot, states = istar_ga(perf, net.n, ga, seed)
        if i_star is None:
            raise ValueError("no failing state was found")
        cuts = antichain(states)
    return ccr_estimate(spark, net.p, perf, budget, steps, i_star, "practical", cuts, reps=reps, seed=seed, pilot=pilot).withColumn("i_star", F.lit(i_star))


def _one_source(net, sources):
    from ..sources.tables import add_super_source

    return add_super_source(net, list(sources), -1)
