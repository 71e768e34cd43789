"""The experiments, on networks derived from the given tables.

Physics: corridor network with direct-current flow and cascading overload. Connectivity:
pipe network with four plants. Figures of expensive references are made once a session and
kept in the shared folder.
"""

from __future__ import annotations

from collections.abc import Callable
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bernoulli as bn
from ..functions import bits
from ..functions.rng import uniform_np
from ..operators import estimators as est
from ..operators import genetic as ga
from ..operators import istar as ist
from ..operators import measures
from ..operators.approx import antichain, approx_pf
from ..operators.perf import Connected, DcCascade, evaluate
from ..operators.refine import Refinement, SplitTree, assign, refine
from ..operators.sample import sample
from ..sources import tables
from ..sources.scratch import written
from ..sources.state_space import state_space
from .n10 import corridor, once

THRESHOLDS = (0.1, 0.2, 0.3, 0.4, 0.5, 0.6)
P_GRID = (1e-3, 5e-3, 1e-2, 5e-2, 1e-1)
LOW, HIGH, MIDDLE_DRAWS, MIDDLE_CHUNK = 5, 43, 1000, 250

Q: dict[str, Callable] = {}


def query(fn):
    Q[fn.__name__] = fn
    return fn


# --- physics --------------------------------------------------------------------------------------


def grid(spark: SparkSession, sf: str) -> tables.Network:
    """The corridor network, with the three component types as its p."""
    return once(spark, "n46", sf, lambda: tables.collect_net(tables.assign_p_by_capacity(corridor(spark, sf)), tables.nation_nodes(spark, sf)))


def probabilities(net: tables.Network, model) -> np.ndarray:
    return net.p if model == "inid" else np.full(net.n, float(model))


def losses(spark: SparkSession, sf: str) -> DataFrame:
    """(k, words, loss) of all states of up to LOW failures and of HIGH or more: evaluated once for every threshold and model."""
    net = grid(spark, sf)

    def make():
        every = state_space(spark, net.n, 0, LOW, 20_000).union(state_space(spark, net.n, HIGH, net.n, 20_000))
        return evaluate(every, DcCascade(net), net.n).select("k", "words", "loss")

    return once(spark, "grid-losses", sf, make)


def unpacked(batch: pa.RecordBatch, n: int) -> np.ndarray:
    """failed[n, B] of a batch with ``words``."""
    words = batch.column(batch.schema.get_field_index("words"))
    return bits.unpack(words.flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1).T, n)


def reference(spark: SparkSession, sf: str) -> DataFrame:
    """(model, i, thr, p, n): failure probability given i failures, exact up to LOW and from HIGH on, else drawn.

    One evaluation of a state serves all thresholds. Models: iid and inid.
    """

    def make():
        net = grid(spark, sf)
        perf = DcCascade(net)
        odds = np.log(net.p / (1 - net.p))
        thr = np.array(THRESHOLDS)
        schema = "model string, i int, thr double, w double, wf double, n bigint"
        names = [f.split()[0] for f in schema.split(", ")]

        def tally(k: np.ndarray, loss: np.ndarray, w: np.ndarray, model: str) -> pa.RecordBatch:
            rows = [(model, int(i), float(t), float(w[at].sum()), float(w[at][loss[at] > t].sum()), int(at.sum())) for i in np.unique(k) for at in [k == i] for t in thr]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.string(), pa.int32(), pa.float64(), pa.float64(), pa.float64(), pa.int64()), strict=True)], names)

        def exact(batches):
            for b in batches:
                if b.num_rows:
                    k, loss = b.column(0).to_numpy(), b.column(2).to_numpy()
                    yield tally(k, loss, np.ones(len(k)), "iid")
                    yield tally(k, loss, np.exp(odds @ unpacked(b, net.n)), "inid")

        def drawn(batches):
            for b in batches:
                for i, part in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                    for model, ps in (("iid", np.full(net.n, 0.5)), ("inid", net.p)):
                        at = np.arange(part * MIDDLE_CHUNK, (part + 1) * MIDDLE_CHUNK)
                        u = uniform_np(23, i, model == "iid", np.arange(net.n)[:, None], at[None, :])
                        yield tally(np.full(len(at), i), perf.loss(bn.draw_conditional(ps, int(i), u)), np.ones(len(at)), model)

        counts = spark.range(LOW + 1, HIGH).select(F.col("id").cast("int").alias("i"))
        chunks = counts.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(MIDDLE_DRAWS // MIDDLE_CHUNK - 1))))
        middle = chunks.repartition((HIGH - LOW - 1) * (MIDDLE_DRAWS // MIDDLE_CHUNK), "i", "part").mapInArrow(drawn, schema)
        sums = losses(spark, sf).mapInArrow(exact, schema).union(middle).groupBy("model", "i", "thr").agg((F.sum("wf") / F.sum("w")).alias("p"), F.sum("n").alias("n"))
        is_exact = (F.col("i") <= LOW) | (F.col("i") >= HIGH)
        return sums.withColumn("n", F.when(~is_exact, F.col("n")))

    return once(spark, "reference", sf, make)


def lam_table(spark, sf) -> DataFrame:
    """(p_name, model, i, lam)"""
    net = grid(spark, sf)
    rows = [(str(p), "iid", i, float(x)) for p in P_GRID for i, x in enumerate(bn.binomial_pmf(net.n, p))]
    rows += [("inid", "inid", i, float(x)) for i, x in enumerate(bn.pmf(net.p))]
    return spark.createDataFrame(rows, "p_name string, model string, i int, lam double")


def istar_table(spark, sf) -> DataFrame:
    return reference(spark, sf).where("model = 'iid' and p > 0").groupBy("thr").agg(F.min("i").alias("i_star"))


@query
def w1_reference_conditionals(spark, sf):
    return reference(spark, sf).where("model = 'iid' and i between 1 and 5").join(istar_table(spark, sf), "thr").select("thr", "i", "p", "i_star").orderBy("thr", "i")


@query
def w4_inid_conditionals(spark, sf):
    return reference(spark, sf).where("model = 'inid' and i between 1 and 5").join(istar_table(spark, sf), "thr").select("thr", "i", "p", "i_star").orderBy("thr", "i")


def kept(spark, sf) -> DataFrame:
    return reference(spark, sf).join(lam_table(spark, sf), ["model", "i"]).join(F.broadcast(istar_table(spark, sf)), "thr").where("i >= i_star")


@query
def w2_w5_failure_grid(spark, sf):
    """p_f, p_star and the coefficient of variation, per threshold and component model."""
    v = F.when(F.col("n").isNotNull(), F.col("lam") ** 2 * F.col("p") * (1 - F.col("p")) / F.col("n")).otherwise(0.0)
    g = kept(spark, sf).groupBy("thr", "p_name").agg(F.sum(F.col("lam") * F.col("p")).alias("p_f"), F.sum("lam").alias("mass"), F.sqrt(F.sum(v)).alias("sd"))
    return g.select("thr", "p_name", "p_f", (F.col("p_f") / F.col("mass")).alias("p_star"), (F.col("sd") / F.col("p_f")).alias("cov")).orderBy("thr", "p_name")


@query
def w3_w6_ratios_unrefined(spark, sf):
    return measures.variance_ratios(kept(spark, sf), ["thr", "p_name"]).select("thr", "p_name", "r_prop", "r_opt").orderBy("thr", "p_name")


def ga_states(spark, sf, thr: float) -> tuple[int, int, list[list[int]]]:
    """(i*, evaluations, antichain of failing states) of one genetic search."""
    def make():
        net = grid(spark, sf)
        best, cost, states = ga.istar_ga(DcCascade(net, thr), net.n, ga.Settings(n_pop=300, max_gen=60), seed=5)
        return best, cost, antichain(states)

    return once(spark, f"ga-{thr}", sf, make)


def true_istar(spark, sf, thr: float) -> int | None:
    r = {round(x["thr"], 3): x["i_star"] for x in istar_table(spark, sf).collect()}
    return r.get(round(thr, 3))


def leaf_sums(spark, ref: Refinement, states: DataFrame, threshold: float) -> np.ndarray:
    """Failure probability of each refined stratum from all its states (k, words, loss); nan where there are none."""
    n = len(ref.tree.ps)
    logit = np.log(ref.tree.ps / (1 - ref.tree.ps))

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            failed = unpacked(b, n)
            at = assign(ref, failed, b.column(0).to_numpy())
            w = np.exp(logit @ failed)
            bad = b.column(2).to_numpy() > threshold
            ok = at >= 0
            if ok.any():
                tot, hit = np.bincount(at[ok], w[ok]), np.bincount(at[ok], (w * bad)[ok])
                idx = np.flatnonzero(tot)
                yield pa.RecordBatch.from_arrays([pa.array(idx.astype(np.int32)), pa.array(tot[idx]), pa.array(hit[idx])], ["idx", "w", "wf"])

    rows = states.mapInArrow(run, "idx int, w double, wf double").groupBy("idx").agg((F.sum("wf") / F.sum("w")).alias("p")).collect()  # a row a stratum
    p = np.full(len(ref.strata), np.nan)
    for x in rows:
        p[x["idx"]] = x["p"]
    return p


def drawn_leaves(spark, ref: Refinement, perf, which: list[int], prior: np.ndarray, draws: int, seed: int) -> np.ndarray:
    """Failure probabilities of strata from draws and one more draw's worth of ``prior``, so that none is 0 for want of a hit."""
    out = prior.copy()
    if which:
        sizes = spark.createDataFrame([(0, k, [(int(a), int(c)) for a, c in ref.strata[k].clusters], draws) for k in which], est.SIZES)
        for x in sample(sizes, ref.tree, perf, seed).collect():
            out[x["idx"]] = (x["hits"] + prior[x["idx"]]) / (x["n"] + 1)
    return out


def leaf_reference(spark, sf, ref: Refinement, perf, model: str, draws: int = 100) -> np.ndarray:
    """Failure probability of each refined stratum: states of up to LOW failures enumerated, others drawn."""
    p = leaf_sums(spark, ref, losses(spark, sf).where(F.col("k") <= LOW), perf.threshold)
    by_count = {r["i"]: r["p"] for r in reference(spark, sf).where((F.col("model") == ("inid" if model == "inid" else "iid")) & (F.abs(F.col("thr") - perf.threshold) < 1e-9)).collect()}
    prior = np.array([by_count.get(s.count, 1.0) for s in ref.strata])
    rest = [k for k, s in enumerate(ref.strata) if s.count > LOW]
    return np.where(np.isnan(p), drawn_leaves(spark, ref, perf, rest, prior, draws, 77), p)


def ratio_curve(spark, ref: Refinement, p_leaf: np.ndarray, i_star: int, every: int) -> list[tuple]:
    """(step, n_strata, r_prop, r_opt, r_uni) from the leaves' probabilities, folded up the split tree."""
    from ..operators.refine import ratio_trace

    known = {s.path: (s.lam, s.lam * q) for s, q in zip(ref.strata, p_leaf, strict=True)}

    def fold(path: tuple) -> tuple[float, float]:
        if path not in known:
            parts = [fold(kid) for kid in ref.splits[path][1].values()]
            known[path] = (sum(a for a, _ in parts), sum(b for _, b in parts))
        return known[path]

    def ref_p(s) -> float:
        lam, mass = fold(s.path)
        return mass / lam if lam > 0 else 0.0

    return [tuple(t[c] for c in ("step", "n_strata", "r_prop", "r_opt", "r_uni")) for t in ratio_trace(ref_p, ref.tree, len(ref.splits), i_star, every)]


CURVE = "model string, thr double, step int, n_strata int, r_prop double, r_opt double, r_uni double"


MODELS = ("0.001", "0.005", "0.01", "0.05", "inid")


def ratio_curves(spark, sf, thresholds: tuple, models: tuple = MODELS, steps: int = 5000, every: int = 100) -> DataFrame:
    net, rows = grid(spark, sf), []
    for thr in thresholds:
        i_star = true_istar(spark, sf, thr)
        for model in models if i_star is not None else ():
            ref = refine(SplitTree(probabilities(net, model)), steps, i_star)
            p = leaf_reference(spark, sf, ref, DcCascade(net, thr), model)
            rows += [(model, thr, *t) for t in ratio_curve(spark, ref, p, i_star, every)]
    return spark.createDataFrame(rows, CURVE)


@query
def w7_ratio_curves(spark, sf):
    """The first steps closely; the whole curves of all models are in the queries by threshold."""
    return ratio_curves(spark, sf, (0.4, 0.6), ("0.01", "inid"), 400, 20)


for _thr in (0.3, 0.4, 0.5, 0.6):
    Q[f"w7_ratio_curves_{round(100 * _thr)}"] = lambda spark, sf, thr=_thr: ratio_curves(spark, sf, (thr,))


#: Searches a cell: a quick look, and the published number.
FEW_RUNS, GA_RUNS = 10, 100


def ga_cells(spark, sf, populations: tuple, runs: int) -> DataFrame:
    net = grid(spark, sf)
    cfg = [{"n_pop": n, "f_xo": f, "max_gen": 60} for n in populations for f in (0.0, 0.4, 0.8, 1.0)]
    return ga.ga_study(spark, DcCascade(net, 0.4), net.n, cfg, runs, true_istar(spark, sf, 0.4) or 0).orderBy("n_pop", "f_xo")


@query
def w8_ga_grid(spark, sf):
    """All cells with few searches; the published number is in the queries by population."""
    return ga_cells(spark, sf, (50, 100, 200, 500), FEW_RUNS)


for _pop in (50, 100, 200, 500):
    Q[f"w8_ga_grid_{_pop}"] = lambda spark, sf, pop=_pop: ga_cells(spark, sf, (pop,), GA_RUNS)


@query
def w8b_ga_tournament(spark, sf, runs: int = GA_RUNS):
    net = grid(spark, sf)
    cfg = [{"n_pop": 100, "n_trn": n, "max_gen": 60} for n in (1, 2, 4, 8)]
    return ga.ga_study(spark, DcCascade(net, 0.4), net.n, cfg, runs, true_istar(spark, sf, 0.4) or 0).orderBy("n_trn")


@query
def w8c_ga_roulette(spark, sf, runs: int = GA_RUNS):
    net = grid(spark, sf)
    cfg = [{"n_pop": n, "method": "roulette", "max_gen": 60} for n in (50, 200)]
    return ga.ga_study(spark, DcCascade(net, 0.4), net.n, cfg, runs, true_istar(spark, sf, 0.4) or 0).orderBy("n_pop")


@query
def w9_ga_thresholds(spark, sf, runs: int = GA_RUNS):
    net, out = grid(spark, sf), None
    for thr in THRESHOLDS:
        i_star = true_istar(spark, sf, thr)
        if i_star is None:
            continue
        one = ga.ga_study(spark, DcCascade(net, thr), net.n, [{"n_pop": 500, "max_gen": 60}], runs, i_star).withColumn("thr", F.lit(thr)).withColumn("i_star", F.lit(i_star))
        out = one if out is None else out.unionByName(one)
    return out


@query
def w9b_istar_bias(spark, sf):
    """Relative bias of an i* that is one too large."""
    k = kept(spark, sf)
    lost = F.sum(F.when(F.col("i") == F.col("i_star"), F.col("lam") * F.col("p")).otherwise(0.0))
    return k.groupBy("thr", "p_name").agg((-lost / F.sum(F.col("lam") * F.col("p"))).alias("rel_bias")).orderBy("thr", "p_name")


EFF = (
    "system string, model string, target string, steps int, n_strata int, runs long, mean double, cost double, over_cmc double, over_cmc_low double, over_cmc_high double, "
    "over_mc double, alpha double, alpha_bound double, r_opt double, opt_over_cmc double, opt_run_over_cmc double"
)
EFF_COLUMNS = [c.split()[0] for c in EFF.split(", ")]


def variance_interval(v: float, runs: int, z: float = 1.96) -> tuple[float, float]:
    """Where the variance lies that ``runs`` normal results with sample variance v speak for (chi square by its cube root)."""
    f = runs - 1
    at = lambda x: f * (1 - 2 / (9 * f) + x * (2 / (9 * f)) ** 0.5) ** 3
    return v * f / at(z), v * f / max(at(-z), 1e-12)


def efficiency_row(spark, system: str, model: str, target: str, ps, perf, cuts, i_star: int, p_leaf_of, pilot: int, budget: int, steps: int, runs: int, seed: int = 3, ref: Refinement | None = None, p_leaf: np.ndarray | None = None, best_runs: dict | None = None) -> tuple:
    """One line: practical sizes against both baselines, the size penalty over all runs, and optimal sizes by formula and as runs.

    ``best_runs`` keeps the runs with optimal sizes for further lines on the same strata.
    """
    ref = ref or refine(SplitTree(ps), steps, i_star)
    lam = ref.lam
    pt = approx_pf(ref.tree, ref.strata, cuts)
    p = p_leaf_of(ref) if p_leaf is None else p_leaf
    mass = float(lam.sum())
    p_f = float((lam * p).sum())
    p_star = p_f / mass
    safe = lambda a, b: float(a / b) if b and np.isfinite(b) and np.isfinite(a) else None

    def runs_of(strategy: str, q: np.ndarray) -> tuple[np.ndarray, float]:
        rows = est.stratified_run(spark, ref.tree, ref.strata, perf, budget, strategy, q, runs, seed, pilot).collect()  # a row a run
        return np.array([x["p_hat"] for x in rows]), float(np.mean([x["cost_sampling"] for x in rows]))

    hat, cost = runs_of("approx_optimal", pt)
    best_runs = {} if best_runs is None else best_runs
    if "got" not in best_runs:
        best_runs["got"] = runs_of("optimal", p)
    best, best_cost = best_runs["got"]
    v = hat.var(ddof=1) if len(hat) > 1 else np.nan
    v_low, v_high = variance_interval(v, len(hat)) if len(hat) > 1 else (np.nan, np.nan)
    real = est.real_sizes(lam, budget, "approx_optimal", pt)
    sizes = est.integer_sizes(np.broadcast_to(real, (runs, len(lam))), uniform_np(seed, 101, np.arange(runs)[:, None], np.arange(len(lam))[None, :]))
    share = est.real_sizes(lam, 1.0, "optimal", p)
    err = (sizes - share * sizes.sum(1, keepdims=True)) / sizes
    alpha = float((sizes / sizes.sum(1, keepdims=True) * err**2).sum(1).mean())
    sd = np.sqrt(np.clip(p * (1 - p), 0, None))
    r_opt = float(((lam / mass * sd).sum()) ** 2 / (p_star * (1 - p_star))) if 0 < p_star < 1 else np.nan
    one = mass**2 * p_star * (1 - p_star)
    mc = p_f * (1 - p_f) / (cost + pilot)
    return (
        system, model, target, steps, len(lam), runs, float(hat.mean()), cost + pilot, safe(one / cost, v), safe(one / cost, v_high), safe(one / cost, v_low), safe(mc, v),
        alpha, float((err**2).max(1).mean()), safe(r_opt, 1.0), safe(1.0, r_opt), safe(one / best_cost, best.var(ddof=1)),
    )


def grid_efficiency(spark, sf, thr: float, steps: int = 5000, budget: int = 10_000, runs: int = 10) -> DataFrame:
    """Efficiency, size penalty and optimal sizes at one threshold, for all component models."""
    net, rows = grid(spark, sf), []
    i_star = true_istar(spark, sf, thr)
    if i_star is not None:
        _, cost, cuts = ga_states(spark, sf, thr)
        perf = DcCascade(net, thr)
        for model in MODELS:
            of = lambda ref, m=model: leaf_reference(spark, sf, ref, perf, m)
            rows.append(efficiency_row(spark, "grid", model, f"thr {thr}", probabilities(net, model), perf, cuts, i_star, of, cost, budget, steps, runs))
    return spark.createDataFrame(rows, EFF)


for _thr in (0.3, 0.4, 0.5, 0.6):
    Q[f"w10_w11_w17_grid_efficiency_{round(100 * _thr)}"] = lambda spark, sf, thr=_thr: grid_efficiency(spark, sf, thr)


@query
def w12_steps_against_cost(spark, sf, budgets: tuple = (1000, 2000, 5000, 10000), steps: tuple = (0, 100, 300, 1000, 5000), runs: int = 10):
    """Relative efficiency over conditional Monte Carlo, and evaluations, by refinement steps and initial size."""
    net = grid(spark, sf)
    i_star = true_istar(spark, sf, 0.4)
    _, pilot, cuts = ga_states(spark, sf, 0.4)
    ps, perf = np.full(net.n, 0.01), DcCascade(net, 0.4)
    rows = []
    for t in steps:
        ref = refine(SplitTree(ps), t, i_star)
        p = approx_pf(ref.tree, ref.strata, cuts)
        p_leaf = leaf_reference(spark, sf, ref, perf, "0.01")
        lam, mass = ref.lam, float(ref.lam.sum())
        p_star = float((lam * p_leaf).sum()) / mass
        for n in budgets:
            got = est.stratified_run(spark, ref.tree, ref.strata, perf, n, "approx_optimal", p, runs, 3, pilot)
            s = measures.rel_eff(got, p_star * mass, p_star, mass).first()
            low, high = variance_interval(s["v"], runs)
            rows.append((n, t, len(p), s["cost"] - pilot, pilot, runs, s["mean"], s["over_cmc"], s["over_cmc"] * s["v"] / high, s["over_cmc"] * s["v"] / low, s["over_mc"]))
    return spark.createDataFrame(rows, "budget int, steps int, n_strata int, cost_sampling double, cost_pilot int, runs int, mean double, over_cmc double, over_cmc_low double, over_cmc_high double, over_mc double")


@query
def tune_steps_n46(spark, sf):
    net = grid(spark, sf)
    _, _, cuts = ga_states(spark, sf, 0.4)
    return spark.createDataFrame([est.tune_steps(np.full(net.n, 0.01), cuts, 3000, 0.7, true_istar(spark, sf, 0.4), limit=4000)], "steps int, cost int")


@query
def dc_cascade_n46(spark, sf):
    """Loss of every single and double failure."""
    net = grid(spark, sf)
    return evaluate(state_space(spark, net.n, 0, 2), DcCascade(net), net.n).select("k", "state_rank", F.round("loss", 9).alias("loss"), "fail")


@query
def assess_physics(spark, sf):
    net = grid(spark, sf).with_p(0.05)
    return est.assess(spark, net, DcCascade(net, 0.3), "physics", 2000, 200, reps=2, ga=ga.Settings(n_pop=100, max_gen=30))


@query
def ga_distributed_n46(spark, sf):
    net = grid(spark, sf)
    best, cost, states = ga.ga_distributed(spark, DcCascade(net, 0.2), net.n, ga.Settings(n_pop=60, max_gen=8), 4)
    return spark.createDataFrame([(best, cost, len(antichain(states)))], "i_star int, evaluations int, minimal_states int")


# --- connectivity ---------------------------------------------------------------------------------

PLANTS = [0, 1, 2, 3]
WATER_MODELS = ("0.001", "0.005", "0.01", "0.05", "rate 0.1", "rate 0.01")


def water(spark, sf) -> tables.Network:
    return once(spark, "n139", sf, lambda: tables.collect_net(tables.assign_p_by_length(tables.pipe_net(spark, sf), 0.1)))


def water_p(net: tables.Network, model: str) -> np.ndarray:
    if model.startswith("rate"):
        return -np.expm1(-float(model.split()[1]) * net.length)
    return np.full(net.n, float(model))


def targets(spark, sf) -> dict[int, int]:
    """{minimum cut: smallest node that has it} for cuts of three and two pipes."""

    def make():
        net = water(spark, sf)
        sup = tables.add_super_source(net, PLANTS)
        out: dict[int, int] = {}
        for v in net.nodes:
            if v in PLANTS:
                continue
            c = int(ist.max_flow(sup, -1, v))
            if c in (2, 3):
                out.setdefault(c, v)
            if len(out) == 2:
                break
        return out

    return once(spark, "targets", sf, make)


def water_cuts(net: tables.Network, target: int, more: int = 0) -> list[list[int]]:
    """Obvious cuts: pipes at the target, pipes around the plants, and the smallest cut that the flow analysis finds."""
    sup = tables.add_super_source(net, PLANTS)
    cuts = [*ist.star_cuts(net, [target]), ist.source_cut(net, PLANTS), ist.min_cut(sup, -1, target)]
    return antichain(cuts + (ist.minimal_cuts(net, PLANTS, target, more) if more else []))


#: Failures above i* up to which failing states are enumerated.
BEYOND = 2


def water_failures(spark, sf, target: int, cut: int) -> tuple[list[list[int]], DataFrame]:
    """(minimal cuts of up to cut + BEYOND pipes, all of them; (k, words, loss) of all failing states of as many pipes).

    A failing state of k pipes holds a minimal cut of k pipes or fewer: each cut is filled up in every way.
    """

    def make():
        net = water(spark, sf)
        top = cut + BEYOND
        cuts = ist.cuts_up_to(net, PLANTS, target, top)
        n = net.n

        def fill(batches):
            for b in batches:
                for c in b.column(0).to_pylist():
                    rest = np.setdiff1d(np.arange(n), c)
                    for extra in range(top - len(c) + 1):
                        for at in range(0, comb(len(rest), extra), 50_000):
                            more = bits.unrank(len(rest), extra, np.arange(at, min(at + 50_000, comb(len(rest), extra))))
                            failed = np.zeros((n, more.shape[1]), bool)
                            failed[rest] = more
                            failed[c] = True
                            words = bits.pack(failed)
                            flat = pa.array(words.T.ravel(), pa.int64())
                            offsets = pa.array(np.arange(0, words.size + 1, len(words)), pa.int32())
                            m = more.shape[1]
                            yield pa.RecordBatch.from_arrays([pa.array(np.full(m, len(c) + extra), pa.int32()), pa.ListArray.from_arrays(offsets, flat), pa.array(np.ones(m))], ["k", "words", "loss"])

        rows = spark.createDataFrame([(c,) for c in cuts], "cut array<int>").repartition(max(1, len(cuts)))
        return cuts, written(rows.mapInArrow(fill, "k int, words array<bigint>, loss double").dropDuplicates(["words"]), "water-failures")

    return once(spark, f"water-failures-{target}", sf, make)


def failing_sums(spark, ref: Refinement, states: DataFrame) -> np.ndarray:
    """Probability of the given states in each refined stratum, as a share of the stratum's."""
    n = len(ref.tree.ps)
    log_p, log_q = np.log(ref.tree.ps), np.log1p(-ref.tree.ps)

    def run(batches):
        for b in batches:
            if b.num_rows:
                failed = unpacked(b, n)
                at = assign(ref, failed, b.column(0).to_numpy())
                w = np.exp(log_p @ failed + log_q @ ~failed)
                ok = at >= 0
                got = np.bincount(at[ok], w[ok])
                idx = np.flatnonzero(got)
                yield pa.RecordBatch.from_arrays([pa.array(idx.astype(np.int32)), pa.array(got[idx])], ["idx", "w"])

    out = np.zeros(len(ref.strata))
    for x in states.mapInArrow(run, "idx int, w double").groupBy("idx").agg(F.sum("w").alias("w")).collect():  # a row a stratum
        out[x["idx"]] = x["w"]
    return np.clip(out / ref.lam, 0.0, 1.0)


def water_leaf(spark, sf, target: int, cut: int, perf, ref: Refinement, draws: int = 200) -> np.ndarray:
    """Failure probability of each refined stratum: exact up to cut + BEYOND failures, above from draws beside known cuts.

    Above, a stratum's prior is the probability that some minimal cut of ``cut`` pipes has failed (a sum, at most 1).
    """
    cuts, states = water_failures(spark, sf, target, cut)
    exact = failing_sums(spark, ref, states)
    low = [s.count <= cut + BEYOND for s in ref.strata]
    rest = [k for k, x in enumerate(low) if not x]
    prior = exact.copy()
    if rest:
        prior[rest] = np.maximum(approx_pf(ref.tree, [ref.strata[k] for k in rest], [c for c in cuts if len(c) <= cut + 1][:60], "capped_sum"), 1e-12)
    return np.where(low, exact, drawn_leaves(spark, ref, perf, rest, prior, draws, 78))


@query
def w18_topology(spark, sf):
    net = water(spark, sf)
    t = targets(spark, sf)
    return spark.createDataFrame([(len(PLANTS), len(net.nodes) - len(PLANTS), net.n, t.get(3), t.get(2))], "plants int, demands int, pipes int, target_3 int, target_2 int")


@query
def w13_water_reference(spark, sf, steps: int = 800, budget: int = 4_000, reps: int = 5):
    """p_f and p_star with a standard error over runs, and bounds: the failing states of up to i* + BEYOND failures, all others as well."""
    net, rows = water(spark, sf), []
    for cut, target in sorted(targets(spark, sf).items()):
        perf = Connected(net, PLANTS, target)
        cuts, states = water_failures(spark, sf, target, cut)
        for model in WATER_MODELS:
            ps = water_p(net, model)
            lam = bn.pmf(ps)
            counts = refine(SplitTree(ps), 0, cut)
            low = float((failing_sums(spark, counts, states) * counts.lam).sum())
            got = est.ccr_estimate(spark, ps, perf, budget, steps, cut, "practical", cuts[:40], reps=reps).collect()  # a row a run
            hat = np.array([x["p_hat"] for x in got])
            mass = float(lam[cut:].sum())
            high = low + float(lam[cut + BEYOND + 1 :].sum())
            rows.append((target, cut, model, float(hat.mean()), float(hat.std(ddof=1) / reps**0.5), float(hat.mean()) / mass, low, high, sum(len(c) == cut for c in cuts), int(sum(x["cost_sampling"] for x in got))))
    return spark.createDataFrame(rows, "target int, i_star int, model string, p_f double, se double, p_star double, low double, high double, smallest_cuts int, cost int")


def water_curves(spark, sf, cut: int, steps: int = 5000, every: int = 100) -> DataFrame:
    net, rows = water(spark, sf), []
    target = targets(spark, sf).get(cut)
    for model in WATER_MODELS if target is not None else ():
        ref = refine(SplitTree(water_p(net, model)), steps, cut)
        p = water_leaf(spark, sf, target, cut, Connected(net, PLANTS, target), ref)
        rows += [(f"{target} {model}", float(cut), *t) for t in ratio_curve(spark, ref, p, cut, every)]
    return spark.createDataFrame(rows, CURVE)


def water_efficiency(spark, sf, cut: int, steps: int = 5000, budget: int = 10_000, runs: int = 10) -> DataFrame:
    """Efficiency and size penalty at the target with a given minimum cut, for all models and three sets of known cuts."""
    net, rows = water(spark, sf), []
    target = targets(spark, sf).get(cut)
    for model in WATER_MODELS if target is not None else ():
        perf, ps = Connected(net, PLANTS, target), water_p(net, model)
        ref = refine(SplitTree(ps), steps, cut)
        p, best = water_leaf(spark, sf, target, cut, perf, ref), {}
        for more in (0, 10, 40):
            cuts = water_cuts(net, target, more)
            rows.append(efficiency_row(spark, "water", model, f"node {target}, {len(cuts)} cuts", ps, perf, cuts, cut, None, 0, budget, steps, runs, ref=ref, p_leaf=p, best_runs=best))
    return spark.createDataFrame(rows, EFF)


for _cut in (2, 3):
    Q[f"w14_water_curves_{_cut}"] = lambda spark, sf, cut=_cut: water_curves(spark, sf, cut)
    Q[f"w15_w16_water_efficiency_{_cut}"] = lambda spark, sf, cut=_cut: water_efficiency(spark, sf, cut)


@query
def ccr_practical_n139(spark, sf, steps: int = 1000, budget: int = 10_000, runs: int = 2):
    """The flagship: refined estimator on the pipe network with the obvious cuts."""
    net = water(spark, sf)
    cut, target = max(targets(spark, sf).items())
    perf = Connected(net, PLANTS, target)
    return est.ccr_estimate(spark, net.p, perf, budget, steps, cut, "practical", water_cuts(net, target), reps=runs)


@query
def ccr_levelwise_n139(spark, sf, steps: int = 20_000, budget: int = 40_000):
    """The flagship's estimator at twenty times its steps, refined, allocated and drawn on executors."""
    net = water(spark, sf)
    cut, target = max(targets(spark, sf).items())
    return est.ccr_levelwise(spark, net.p, Connected(net, PLANTS, target), budget, steps, cut, water_cuts(net, target))


@query
def assess_connectivity(spark, sf):
    net = water(spark, sf)
    cut, target = max(targets(spark, sf).items())
    return est.assess(spark, net, Connected(net, PLANTS, target), "connectivity", 5000, 300, water_cuts(net, target))


@query
def istar_targets(spark, sf):
    return spark.createDataFrame(sorted(targets(spark, sf).items()), "i_star int, node int")


# --- every estimator and baseline on the small network ---------------------------------------------


@query
def estimators_n10(spark, sf, runs: int = 10):
    """Mean, bias and cost of every estimator, where the answer is known."""
    from . import n10

    net = n10.network(spark, sf, 1.0)
    perf = Connected(net, [n10.SOURCE], n10.TARGET)
    p_f = float(n10.Q["exact_pf_n10"](spark, sf).where("rate = 1.0").first()["p_f"])
    a = (spark, net.p, perf)
    cond = np.array([x["p"] for x in n10.count_strata(spark, sf, 1.0).orderBy("i").collect()])

    def leaf_p(ref: Refinement) -> np.ndarray:
        x = n10.states(spark, sf, 1.0).select(F.col("i").alias("k"), "words", F.col("fail").cast("double").alias("loss"))
        return leaf_sums(spark, ref, x, 0.5)

    frames = [
        est.crude_mc(*a, 4000, runs),
        est.conditional_mc(*a, 4000, 4, "rejection", runs),
        est.conditional_mc(*a, 4000, 4, "count_first", runs),
        est.count_stratified(*a, 4000, 0, "proportional", reps=runs),
        est.count_stratified(*a, 4000, 0, "optimal", p=cond, reps=runs),
        est.count_stratified(*a, 4000, 4, "proportional", reps=runs),
        est.count_stratified(*a, 4000, 4, "uniform", reps=runs),
        est.count_stratified(*a, 4000, 4, "optimal", p=cond[4:], reps=runs),
        est.pilot_stratified(*a, 4000, 50, 4, runs),
        est.balanced_refined(*a, 4000, runs),
        est.ccr_estimate(*a, 4000, 30, 4, "proportional", reps=runs),
        est.ccr_estimate(*a, 4000, 30, 4, "uniform", reps=runs),
        est.ccr_estimate(*a, 4000, 30, 4, "optimal", p=leaf_p, reps=runs),
        est.ccr_estimate(*a, 4000, 30, 4, "practical", cuts=n10.STAR, reps=runs),
        est.ccr_levelwise(*a, 4000, 30, 4, n10.STAR, reps=runs, direct=5),
        est.ccr_adaptive(*a, 1e-8, 4),
    ]
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    out = written(out, "estimates")
    s = measures.replicate_summary(out, p_f, ["method"])
    cost = out.groupBy("method").agg(F.avg(F.col("cost_pilot") + F.col("cost_sampling")).alias("cost"))
    return s.join(cost, "method").select("method", "runs", "mean", "bias", "variance", "mse", "cost", measures.efficiency(F.col("mse"), F.col("cost")).alias("efficiency"))


@query
def bounds_and_levels_n10(spark, sf):
    """Decomposition bounds, level sampling and importance sampling beside the exact answer."""
    from ..operators.baselines import ce_is, decompose_bounds, subset_sim
    from . import n10

    net = n10.network(spark, sf, 1.0)
    perf = Connected(net, [n10.SOURCE], n10.TARGET)
    p_f = float(n10.Q["exact_pf_n10"](spark, sf).where("rate = 1.0").first()["p_f"])
    _, low, high = decompose_bounds(net.p, perf, 60)[-1]
    rows = [("exact", p_f, 1 << 10), ("decomposition low", float(low), 120), ("decomposition high", float(high), 120)]
    rows.append(("subset simulation", *subset_sim(net.p, perf, 2000, 1)))
    rows.append(("cross-entropy", *ce_is(net.p, perf, 4000, 1)))
    return spark.createDataFrame(rows, "method string, p double, evaluations int")

