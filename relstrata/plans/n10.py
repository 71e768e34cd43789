"""Small exact network: every method with an answer that SQL can compute as well."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import bernoulli as bn
from ..functions.rng import uniform_md5
from ..operators import istar as ist
from ..operators import measures, strata
from ..operators.approx import approx_pf, minimal_states
from ..operators.perf import Connected, CutUnion, LostCapacity, Unserved, evaluate
from ..operators.refine import SplitTree, exact_p, ratio_trace, refine
from ..sources import tables
from ..sources.scratch import written
from ..sources.state_space import state_space

N, SOURCE, TARGET, I_STAR = 10, 0, 4, 4
RATES = (0.1, 1.0)
SEED = 7
_MEMO: dict = {}


def once(spark: SparkSession, name: str, sf_dir: str, make):
    """A derived table or value, made once a session."""
    key = (spark.sparkContext.applicationId, name, sf_dir)
    if key not in _MEMO:
        out = make()
        _MEMO[key] = written(out, name) if isinstance(out, DataFrame) else out
    return _MEMO[key]


def net(spark, sf_dir, rate=0.1) -> DataFrame:
    base = once(spark, "n10-net", sf_dir, lambda: tables.region_net(spark, sf_dir).coalesce(1))
    return tables.assign_p_by_length(base, rate)


def network(spark, sf_dir, rate=0.1) -> tables.Network:
    return once(spark, f"n10-{rate}", sf_dir, lambda: tables.collect_net(net(spark, sf_dir, rate)))


def states(spark, sf_dir, rate=0.1) -> DataFrame:
    """(x, i, prob, fail): all states, from the state space source and the connectivity kernel."""

    def make():
        nw = network(spark, sf_dir, rate)
        ps = F.array(*[F.lit(float(p)) for p in nw.p])
        x = F.element_at("words", 1)
        prob = F.aggregate(
            F.sequence(F.lit(0), F.lit(N - 1)), F.lit(1.0),
            lambda s, d: s * F.when(bit_of(F.col("x"), d) == 1, F.element_at(ps, d + 1)).otherwise(1 - F.element_at(ps, d + 1)),
        )
        out = evaluate(state_space(spark, N, 0, N), Connected(nw, [SOURCE], TARGET), N)
        return out.select(x.alias("x"), F.col("k").alias("i"), "fail", "words").withColumn("prob", prob)

    return once(spark, f"n10-states-{rate}", sf_dir, make)


def bit_of(x: Column, d) -> Column:
    return F.call_function("shiftright", x, d if isinstance(d, Column) else F.lit(d)).bitwiseAND(F.lit(1).cast("long"))


def count_strata(spark, sf_dir, rate=0.1) -> DataFrame:
    """(i, lam, p): exact strata by count."""
    s = states(spark, sf_dir, rate)
    cond = s.groupBy("i").agg((F.sum(F.when(F.col("fail"), F.col("prob")).otherwise(0.0)) / F.sum("prob")).alias("p"))
    return bn.count_strata(net(spark, sf_dir, rate)).join(cond, "i").select(F.col("i").cast("int").alias("i"), "lam", "p")


def r(c, digits=12):
    return F.round(F.col(c) if isinstance(c, str) else c, digits)


# --- SQL shared by the oracles ----------------------------------------------------------------

FLOWS = """f AS (SELECT s_nationkey AS sn, c_nationkey AS cn, sum(l_quantity) AS q,
  sum(abs(date_diff('day', o_orderdate::DATE, l_shipdate::DATE))) AS days, count(*) AS n
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey
  JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2)"""


def base_sql(rate: float = 0.1) -> str:
    return f"""WITH RECURSIVE {FLOWS},
e0 AS (SELECT least(a.n_regionkey, b.n_regionkey) AS u, greatest(a.n_regionkey, b.n_regionkey) AS v, sum(q) AS capacity,
  sum(days) / sum(n) / 1000 AS length FROM f JOIN nation a ON sn = a.n_nationkey JOIN nation b ON cn = b.n_nationkey
  WHERE a.n_regionkey <> b.n_regionkey GROUP BY 1, 2),
e AS (SELECT (row_number() OVER (ORDER BY u, v) - 1)::INT AS d, u, v, capacity, length, 1 - exp(-{rate} * length) AS p FROM e0),
st AS (SELECT x, bit_count(x)::INT AS i, product(CASE WHEN (x >> d) & 1 = 1 THEN p ELSE 1 - p END) AS prob FROM range(1024) t(x), e GROUP BY x),
cuts AS (SELECT sum(1::BIGINT << d)::BIGINT AS c FROM range(8) t(m), e
  WHERE (u = 0 OR (u BETWEEN 1 AND 3 AND (m >> (u - 1)) & 1 = 1)) <> (v = 0 OR (v BETWEEN 1 AND 3 AND (m >> (v - 1)) & 1 = 1)) GROUP BY m),
g AS (SELECT x, i, prob, EXISTS (SELECT 1 FROM cuts WHERE (x & c) = c) AS fail FROM st),
s AS (SELECT i, sum(prob) AS lam, sum(CASE WHEN fail THEN prob ELSE 0 END) / sum(prob) AS p FROM g GROUP BY i),
k AS (SELECT * FROM s WHERE i >= 4)"""


def sql(select: str, rate: float = 0.1) -> str:
    return base_sql(rate) + " " + select


def both_rates(one: Callable[[float], DataFrame]) -> DataFrame:
    a, b = (one(x).withColumn("rate", F.lit(x)) for x in RATES)
    return a.unionByName(b)


def sql_rates(select: str) -> str:
    return " UNION ALL ".join(f"SELECT *, {rate}::DOUBLE AS rate FROM ({sql(select, rate)})" for rate in RATES)


# --- queries ---------------------------------------------------------------------------------

Q: dict[str, Callable] = {}
O: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(fn):
        Q[name] = fn
        if oracle:
            O[name] = oracle
        return fn

    return add


@query("net_region", sql("SELECT d AS comp_id, u, v, round(capacity, 6) AS capacity, round(length, 9) AS length FROM e"))
def _(spark, sf):
    return net(spark, sf).select("comp_id", "u", "v", r("capacity", 6).alias("capacity"), r("length", 9).alias("length"))


@query("lam_inid", sql_rates("SELECT i, round(lam, 12) AS lam FROM s"))
def _(spark, sf):
    return both_rates(lambda q: bn.count_strata(net(spark, sf, q)).select("i", r("lam").alias("lam")))


@query("lam_from_odds", sql("SELECT i, round(lam, 12) AS lam FROM s"))
def _(spark, sf):
    return bn.ordered_p(net(spark, sf)).select(F.posexplode(bn.lam_from_odds(bn.odds_sums(F.col("ps")))).alias("i", "lam")).select("i", r("lam").alias("lam"))


@query("odds_r", sql("SELECT i, round(sum(o), 9) AS r FROM (SELECT x, bit_count(x)::INT AS i, product(CASE WHEN (x >> d) & 1 = 1 THEN p / (1 - p) ELSE 1 END) AS o FROM range(1024) t(x), e GROUP BY x) GROUP BY i"))
def _(spark, sf):
    return bn.ordered_p(net(spark, sf)).select(F.posexplode(bn.odds_sums(F.col("ps"))).alias("i", "r")).select("i", r("r", 9).alias("r"))


@query("state_prob_n10", sql("SELECT x, i, round(prob, 12) AS prob, fail FROM g"))
def _(spark, sf):
    return states(spark, sf).select("x", "i", r("prob").alias("prob"), "fail")


@query("exact_pf_n10", sql_rates("SELECT round(sum(CASE WHEN fail THEN prob ELSE 0 END), 12) AS p_f FROM g"))
def _(spark, sf):
    return both_rates(lambda q: states(spark, sf, q).agg(r(F.sum(F.when(F.col("fail"), F.col("prob")).otherwise(0.0))).alias("p_f")))


@query("cond_pf_n10", sql_rates("SELECT i, round(p, 10) AS p FROM s"))
def _(spark, sf):
    return both_rates(lambda q: count_strata(spark, sf, q).select("i", r("p", 10).alias("p")))


@query("istar_n10", sql("SELECT min(i) AS i_star FROM g WHERE fail"))
def _(spark, sf):
    return states(spark, sf).where("fail").agg(F.min("i").alias("i_star"))


@query("istar_maxflow_n10", sql("SELECT min(bit_count(c))::DOUBLE AS i_star FROM cuts"))
def _(spark, sf):
    return ist.istar_k(spark, network(spark, sf), [SOURCE, TARGET]).agg(F.min("i_star").alias("i_star"))


@query("istar_lower_bound_n10", "SELECT 4 AS bound, 176 AS evaluations")
def _(spark, sf):
    return spark.createDataFrame([ist.istar_lower_bound(spark, Connected(network(spark, sf), [SOURCE], TARGET), N)], "bound int, evaluations int")


@query("signature_n10", sql("SELECT 10 - bit_count(x)::INT AS working, round(avg((NOT fail)::INT), 10) AS phi FROM g GROUP BY 1"))
def _(spark, sf):
    from ..operators.baselines import system_signature

    equal = states(spark, sf).groupBy("i").agg(F.avg(F.col("fail").cast("int")).alias("p"))
    return system_signature(equal, N).select("working", r("phi", 10).alias("phi"))


@query("reliability_curve_n10", sql("SELECT q AS p, round(sum(pow(q, i) * pow(1 - q, 10 - i) * (NOT fail)::INT), 10) AS reliability FROM g, (VALUES (0.01::DOUBLE), (0.05), (0.1), (0.2), (0.4)) t(q) GROUP BY q"))
def _(spark, sf):
    from ..operators.baselines import reliability_column

    rows = states(spark, sf).groupBy("i").agg(F.avg((~F.col("fail")).cast("int")).alias("phi")).orderBy("i").collect()
    grid = spark.createDataFrame([(x,) for x in (0.01, 0.05, 0.1, 0.2, 0.4)], "p double")
    return grid.select("p", r(reliability_column([x["phi"] for x in rows], N, F.col("p")), 10).alias("reliability"))


@query("drop_redundant_n10", sql("SELECT i, round(lam, 12) AS lam, round(lam / (SELECT sum(lam) FROM k), 10) AS lam_star FROM k"))
def _(spark, sf):
    return strata.drop_redundant(count_strata(spark, sf), I_STAR).select("i", r("lam").alias("lam"), r("lam_star", 10).alias("lam_star"))


@query("pf_star_n10", sql_rates("SELECT round(sum(lam * p) / sum(lam), 10) AS p_star, round(sum(lam), 12) AS mass FROM k"))
def _(spark, sf):
    return both_rates(lambda q: count_strata(spark, sf, q).where("i >= 4").agg(r(F.sum(F.col("lam") * F.col("p")) / F.sum("lam"), 10).alias("p_star"), r(F.sum("lam")).alias("mass")))


@query("kept_mass_n10", sql("SELECT round(sum(lam), 12) AS mass FROM k"))
def _(spark, sf):
    return strata.kept_mass(count_strata(spark, sf), I_STAR).select(r("mass").alias("mass"))


RATIO = "round(sum(lam * p * (1 - p)) / sum(lam) / v, 8) AS r_prop, round(pow(sum(lam * sqrt(p * (1 - p))) / sum(lam), 2) / v, 8) AS r_opt, round(count(*) * sum(lam * lam * p * (1 - p)) / pow(sum(lam), 2) / v, 8) AS r_uni"


def ratio_sql(table: str) -> str:
    return f"SELECT {RATIO} FROM (SELECT {table}.*, t.v FROM {table}, (SELECT a * (1 - a) AS v FROM (SELECT sum(lam * p) / sum(lam) AS a FROM {table})) t) GROUP BY v"


def ratios(df):
    return measures.variance_ratios(df).select(*[r(c, 8).alias(c) for c in ("r_prop", "r_opt", "r_uni")])


@query("ratio_n10", sql_rates(ratio_sql("s")))
def _(spark, sf):
    return both_rates(lambda q: ratios(count_strata(spark, sf, q)))


@query("ratio_c_n10", sql_rates(ratio_sql("k")))
def _(spark, sf):
    return both_rates(lambda q: ratios(count_strata(spark, sf, q).where("i >= 4")))


@query("ratio_decomposition_n10", sql_rates("SELECT round(sum(lam * p * p) - pow(sum(lam * p), 2), 12) AS between, round(1 - (sum(lam * p * p) - pow(sum(lam * p), 2)) / (sum(lam * p) - pow(sum(lam * p), 2)), 8) AS r_prop FROM s"))
def _(spark, sf):
    return both_rates(lambda q: measures.ratio_decomposition(count_strata(spark, sf, q)).select(r("between").alias("between"), r("r_prop", 8).alias("r_prop")))


W = {"proportional": "lam", "optimal": "lam * sqrt(p * (1 - p))", "uniform": "1.0"}
for _name, _w in W.items():

    @query(f"alloc_{_name}_n10", sql(f"SELECT i, round(1000 * ({_w}) / (SELECT sum({_w}) FROM k), 6) AS n_real FROM k"))
    def _(spark, sf, name=_name):
        return strata.allocate(count_strata(spark, sf).where("i >= 4"), 1000, name).select("i", r("n_real", 6).alias("n_real"))


#: Components at the source and at the target: the obvious cuts of a complete graph on five nodes.
STAR = [[0, 1, 2, 3], [3, 6, 8, 9]]
STAR_SQL = "(x & 15) = 15 OR (x & 840) = 840"
AOPT = f", a AS (SELECT k.*, q.pt FROM k JOIN (SELECT i, sum(CASE WHEN {STAR_SQL} THEN prob ELSE 0 END) / sum(prob) AS pt FROM st GROUP BY i) q USING (i))"
AOPT_W = "lam * sqrt(greatest(pt * (1 - pt), 0))"


def approx_strata(spark, sf, mode="union") -> DataFrame:
    nw = network(spark, sf)
    ref = refine(SplitTree(nw.p), 0, 0)
    pt = approx_pf(ref.tree, ref.strata, STAR, mode)
    rows = [(s.path[0], float(x)) for s, x in zip(ref.strata, pt, strict=True)]
    return spark.createDataFrame(rows, "i int, pt double")


@query("approx_union_n10", sql(f"SELECT i, round(sum(CASE WHEN {STAR_SQL} THEN prob ELSE 0 END) / sum(prob), 9) AS pt FROM st GROUP BY i"))
def _(spark, sf):
    return approx_strata(spark, sf).select("i", r("pt", 9).alias("pt"))


@query("approx_capped_n10", sql("SELECT i, round(least(1, (sum(CASE WHEN (x & 15) = 15 THEN prob ELSE 0 END) + sum(CASE WHEN (x & 840) = 840 THEN prob ELSE 0 END)) / sum(prob)), 9) AS pt FROM st GROUP BY i"))
def _(spark, sf):
    return approx_strata(spark, sf, "capped_sum").select("i", r("pt", 9).alias("pt"))


def aopt(spark, sf) -> DataFrame:
    joined = count_strata(spark, sf).where("i >= 4").join(approx_strata(spark, sf), "i")
    # Rounding away noise of the exact union, so that p of 1 has no spread on either engine.
    joined = joined.withColumn("pt", F.round("pt", 12))
    return strata.allocate(joined, 1000, "approx_optimal", "pt")


AOPT = AOPT.replace("q.pt", "round(q.pt, 12) AS pt")


@query("alloc_approx_n10", sql(f"{AOPT} SELECT i, round(1000 * {AOPT_W} / (SELECT sum({AOPT_W}) FROM a), 6) AS n_real FROM a"))
def _(spark, sf):
    return aopt(spark, sf).select("i", r("n_real", 6).alias("n_real"))


ROUNDED = f"""{AOPT}, z AS (SELECT i, lam, p, 1000 * {AOPT_W} / (SELECT sum({AOPT_W}) FROM a) AS n,
  ('0x' || substr(md5('7|' || i::VARCHAR), 1, 13))::BIGINT / 4503599627370496.0 AS u FROM a),
zi AS (SELECT *, CASE WHEN n <= 1 THEN 1 WHEN n = floor(n) THEN n WHEN u < floor(n) * (floor(n) + 1 - n) / n THEN floor(n) ELSE floor(n) + 1 END::BIGINT AS n_int,
  1000 * lam * sqrt(p * (1 - p)) / (SELECT sum(lam * sqrt(p * (1 - p))) FROM a) AS n_opt FROM z)"""


def rounded(spark, sf) -> DataFrame:
    a = strata.round_sizes(aopt(spark, sf), uniform_md5(SEED, F.col("i")))
    tot = a.agg(F.sum(F.col("lam") * F.sqrt(F.col("p") * (1 - F.col("p")))).alias("t"))
    return a.crossJoin(F.broadcast(tot)).withColumn("n_opt", 1000 * F.col("lam") * F.sqrt(F.col("p") * (1 - F.col("p"))) / F.col("t"))


@query("alloc_rounded_n10", sql(f"{ROUNDED} SELECT i, n_int FROM zi"))
def _(spark, sf):
    return rounded(spark, sf).select("i", "n_int")


@query("var_ss_n10", sql(f"{ROUNDED} SELECT round(1e9 * sum(lam * lam * p * (1 - p) / n_int), 6) AS variance_e9 FROM zi"))
def _(spark, sf):
    return strata.variance_ss(rounded(spark, sf), "n_int").select(r(F.col("variance") * 1e9, 6).alias("variance_e9"))


@query("alpha_n10", sql(f"{ROUNDED}, t AS (SELECT sum(n_int) AS tn, sum(n_opt) AS t_o FROM zi) SELECT round(sum(n_int / tn * pow((n_int - n_opt * tn / t_o) / n_int, 2)), 7) AS alpha, round(max(pow((n_int - n_opt * tn / t_o) / n_int, 2)), 7) AS alpha_bound FROM zi, t"))
def _(spark, sf):
    return measures.alpha(rounded(spark, sf)).select(r("alpha", 7).alias("alpha"), r("alpha_bound", 7).alias("alpha_bound"))


@query("size_errors_n10", sql(f"{ROUNDED} SELECT i, round((n_int - n_opt) / n_int, 8) AS size_error FROM zi"))
def _(spark, sf):
    return measures.size_errors(rounded(spark, sf)).select("i", r("size_error", 8).alias("size_error"))


@query("cost_n10", sql(f"{ROUNDED} SELECT (428 + sum(n_int))::BIGINT AS cost FROM zi"))
def _(spark, sf):
    return measures.cost(428, rounded(spark, sf))


@query("istar_bias_n10", sql("SELECT round(-sum(CASE WHEN i < 5 THEN lam * p ELSE 0 END) / sum(lam * p), 9) AS rel_bias FROM s"))
def _(spark, sf):
    return measures.istar_bias(count_strata(spark, sf), I_STAR + 1).select(r("rel_bias", 9).alias("rel_bias"))


@query("minimal_cuts_n10", sql("SELECT c AS cut, bit_count(c)::INT AS size FROM cuts"))
def _(spark, sf):
    cuts = ist.minimal_cuts(network(spark, sf), [SOURCE], TARGET, 1000)
    return spark.createDataFrame([(sum(1 << d for d in c), len(c)) for c in cuts], "cut long, size int")


@query("antichain_n10", sql("SELECT x AS cut FROM g a WHERE fail AND NOT EXISTS (SELECT 1 FROM g b WHERE b.fail AND b.x <> a.x AND (a.x & b.x) = b.x)"))
def _(spark, sf):
    return minimal_states(states(spark, sf).where("fail").select("words")).select(F.element_at("words", 1).alias("cut"))


@query("coherence_n10", sql("SELECT count(*) AS violations FROM g a, e, g b WHERE a.fail AND (a.x >> d) & 1 = 0 AND b.x = (a.x | (1::BIGINT << d)) AND NOT b.fail"))
def _(spark, sf):
    from ..operators.perf import check_coherence

    return check_coherence(states(spark, sf), N).agg(F.count(F.lit(1)).alias("violations"))


def refined(spark, sf, steps: int):
    """(refinement, failed, fails, prob) of N10."""
    nw = network(spark, sf)
    from ..functions import bits

    failed = bits.unpack(np.arange(1 << N)[None, :], N)
    fails = Connected(nw, [SOURCE], TARGET).fails(failed)
    prob = np.where(failed, nw.p[:, None], 1 - nw.p[:, None]).prod(0)
    return refine(SplitTree(nw.p), steps, I_STAR), failed, fails, prob


def refined_rows(spark, sf, steps: int) -> DataFrame:
    """(stratum, lam, p): clusters as first:last:failed lists."""
    ref, failed, fails, prob = refined(spark, sf, steps)
    of = exact_p(ref.tree, failed, fails, prob)
    rows = []
    for s in ref.strata:
        text = ",".join(f"{min(m)}-{max(m)}:{k}" for node, k in s.clusters for m in [ref.tree.members(node)])
        rows.append((text, s.lam, of(s)))
    return spark.createDataFrame(rows, "stratum string, lam double, p double").select("stratum", r("lam").alias("lam"), r("p", 9).alias("p"))


@query("refine_n10_t0", sql("SELECT '0-9:' || i::VARCHAR AS stratum, round(lam, 12) AS lam, round(p, 9) AS p FROM k"))
def _(spark, sf):
    return refined_rows(spark, sf, 0)


TOP = "(SELECT arg_max(i, lam) FROM k WHERE i < 10)"
T1 = f""", t1 AS (SELECT CASE WHEN i = {TOP} THEN '0-4:' || bit_count(x & 31)::VARCHAR || ',5-9:' || bit_count(x >> 5)::VARCHAR ELSE '0-9:' || i::VARCHAR END AS stratum,
  sum(prob) AS lam, sum(CASE WHEN fail THEN prob ELSE 0 END) / sum(prob) AS p FROM g WHERE i >= 4 GROUP BY 1)"""


@query("refine_n10_t1", sql(f"{T1} SELECT stratum, round(lam, 12) AS lam, round(p, 9) AS p FROM t1"))
def _(spark, sf):
    return refined_rows(spark, sf, 1)


@query("refine_ratios_n10_t1", sql(f"{T1} {ratio_sql('t1')}"))
def _(spark, sf):
    tr = _trace(spark, sf)[1]
    return spark.createDataFrame([(tr["r_prop"], tr["r_opt"], tr["r_uni"])], "r_prop double, r_opt double, r_uni double").select(*[r(c, 8).alias(c) for c in ("r_prop", "r_opt", "r_uni")])


def _trace(spark, sf):
    def make():
        ref, failed, fails, prob = refined(spark, sf, 0)
        return ratio_trace(exact_p(ref.tree, failed, fails, prob), ref.tree, 100, I_STAR)

    return once(spark, "n10-trace", sf, make)


@query("refine_ratio_trace_n10")
def _(spark, sf):
    return spark.createDataFrame([tuple(t[c] for c in ("step", "n_strata", "r_prop", "r_opt", "r_uni")) for t in _trace(spark, sf)], "step int, n_strata int, r_prop double, r_opt double, r_uni double")


@query("split_gain_n10", sql(f"{T1}, w AS (SELECT sum(lam) AS l, sum(lam * p) / sum(lam) AS q, sum(lam * p * (1 - p)) AS a, sum(lam * sqrt(p * (1 - p))) AS b FROM t1 WHERE stratum LIKE '0-4%') SELECT round(l * q * (1 - q) - a, 12) AS gain_prop, round(l * sqrt(q * (1 - q)) - b, 12) AS gain_opt FROM w"))
def _(spark, sf):
    ref, failed, fails, prob = refined(spark, sf, 1)
    of = exact_p(ref.tree, failed, fails, prob)
    kids = [("t", s.lam, of(s)) for s in ref.strata if len(s.path) > 1]
    out = measures.split_gain(spark.createDataFrame(kids, "parent string, lam double, p double"))
    return out.select(r("gain_prop").alias("gain_prop"), r("gain_opt").alias("gain_opt"))


@query("refine_levelwise_n10")
def _(spark, sf):
    """Strata that only one of the two ways of refining finds, after 100 steps: none."""
    from ..operators.refine import refine_levelwise, strata_frame

    nw = network(spark, sf)
    tree = SplitTree(nw.p)
    a = refine_levelwise(spark, tree, 100, I_STAR, direct=10).select("stratum_id")
    b = strata_frame(spark, refine(tree, 100, I_STAR)).select("stratum_id")
    x = b.exceptAll(a).agg(F.count(F.lit(1)).cast("int").alias("missing"))
    y = a.exceptAll(b).agg(F.count(F.lit(1)).cast("int").alias("extra"))
    return x.crossJoin(y)


@query("refine_levelwise_n10_t1", sql(f"{T1} SELECT round(lam, 12) AS lam FROM t1"))
def _(spark, sf):
    from ..operators.refine import refine_levelwise

    return refine_levelwise(spark, SplitTree(network(spark, sf).p), 1, I_STAR, direct=0).select(r("lam").alias("lam"))


@query("istar_all_n10", sql("SELECT min(c)::DOUBLE AS i_star FROM (SELECT m, count_if((m >> u) & 1 <> (m >> v) & 1) AS c FROM range(1, 31) t(m), e GROUP BY m)"))
def _(spark, sf):
    return spark.createDataFrame([(float(ist.istar_all(network(spark, sf))),)], "i_star double")


@query("cuts_up_to_n10", sql("SELECT c AS cut, bit_count(c)::INT AS size FROM cuts WHERE bit_count(c) <= 6"))
def _(spark, sf):
    cuts = ist.cuts_up_to(network(spark, sf), [SOURCE], TARGET, 6)
    return spark.createDataFrame([(sum(1 << d for d in c), len(c)) for c in cuts], "cut long, size int")


# --- sampled estimators, replayed by SQL with the same hash uniforms --------------------------

DRAWS = 2000
HASH = "('0x' || substr(md5('{0}|' || n::VARCHAR || '|' || d::VARCHAR), 1, 13))::BIGINT / 4503599627370496.0"
MC = f", dr AS (SELECT n, sum(CASE WHEN {HASH.format(SEED)} < p THEN 1::BIGINT << d ELSE 0 END)::BIGINT AS x FROM range({DRAWS}) t(n), e GROUP BY n)"


def md5_draws(spark, sf, rate) -> DataFrame:
    nw = network(spark, sf, rate)
    bits_ = [F.when(uniform_md5(SEED, F.col("n"), d) < float(p), 1 << d).otherwise(0) for d, p in enumerate(nw.p)]
    return spark.range(DRAWS).toDF("n").select("n", sum(bits_[1:], bits_[0]).cast("long").alias("x")).join(states(spark, sf, rate).select("x", "i", "fail"), "x")


@query("mc_md5_n10", sql(f"{MC} SELECT round(avg(fail::INT), 9) AS p_hat, count(*) AS n FROM dr JOIN g USING (x)", 1.0))
def _(spark, sf):
    return md5_draws(spark, sf, 1.0).agg(r(F.avg(F.col("fail").cast("int")), 9).alias("p_hat"), F.count(F.lit(1)).alias("n"))


@query("cmc_md5_n10", sql(f"{MC} SELECT round((SELECT sum(lam) FROM k) * avg(fail::INT), 9) AS p_hat, count(*) AS n FROM dr JOIN g USING (x) WHERE i >= 4", 1.0))
def _(spark, sf):
    mass = count_strata(spark, sf, 1.0).where("i >= 4").agg(F.sum("lam").alias("m"))
    got = md5_draws(spark, sf, 1.0).where("i >= 4").agg(F.avg(F.col("fail").cast("int")).alias("a"), F.count(F.lit(1)).alias("n"))
    return got.crossJoin(mass).select(r(F.col("a") * F.col("m"), 9).alias("p_hat"), "n")


WALK = f""", tl AS (SELECT j, bit_count(x >> j)::INT AS r, sum(prob) AS t FROM st, range(11) q(j) GROUP BY 1, 2),
w(i, n, d, x, r) AS (SELECT i, n, 0, 0::BIGINT, i FROM (SELECT unnest(range(11))::INT AS i), range(200) t(n)
  UNION ALL
  SELECT i, n, d + 1, x + inc * (1::BIGINT << d), r - inc FROM (
    SELECT w.i, w.n, w.d, w.x, w.r, CASE WHEN w.r > 0 AND {HASH.format("7|' || w.i::VARCHAR || '").replace("n::", "w.n::").replace("d::", "w.d::")} < e.p * b.t / a.t THEN 1 ELSE 0 END AS inc
    FROM w JOIN e ON e.d = w.d JOIN tl a ON a.j = w.d AND a.r = w.r LEFT JOIN tl b ON b.j = w.d + 1 AND b.r = w.r - 1)),
dw AS (SELECT i, n, x FROM w WHERE d = 10)"""


def md5_conditional(spark, sf) -> DataFrame:
    nw = network(spark, sf)
    base = spark.range(11).select(F.col("id").cast("int").alias("i")).crossJoin(spark.range(200).toDF("n"))
    return base.withColumn("x", bn.draw_conditional_column(nw.p.tolist(), F.col("i"), lambda d: uniform_md5(SEED, F.col("i"), F.col("n"), d)))


@query("draw_conditional_n10", sql(f"{WALK} SELECT i, n, x FROM dw"))
def _(spark, sf):
    return md5_conditional(spark, sf)


@query("ss_md5_n10", sql(f"{WALK} SELECT round(sum(lam * h), 12) AS p_hat FROM (SELECT dw.i, avg(fail::INT) AS h FROM dw JOIN g USING (x) GROUP BY 1) JOIN s USING (i)"))
def _(spark, sf):
    draws = md5_conditional(spark, sf).join(states(spark, sf).select("x", "fail"), "x")
    return strata.stratified_estimate(count_strata(spark, sf), draws, keys=("i",)).select(r("p_hat").alias("p_hat"))


@query("css_md5_n10", sql(f"{WALK} SELECT round(sum(lam * h), 12) AS p_hat FROM (SELECT dw.i, avg(fail::INT) AS h FROM dw JOIN g USING (x) GROUP BY 1) JOIN k USING (i)"))
def _(spark, sf):
    draws = md5_conditional(spark, sf).where("i >= 4").join(states(spark, sf).select("x", "fail"), "x")
    return strata.stratified_estimate(count_strata(spark, sf), draws, keys=("i",)).select(r("p_hat").alias("p_hat"))


@query("draw_uniform_n10", f"""WITH c AS (SELECT (c_custkey % 11)::INT AS i, c_custkey // 11 AS n FROM customer),
u AS (SELECT i, n, d, {HASH.format("7|' || i::VARCHAR || '")} AS u FROM c, range(10) q(d)),
k AS (SELECT i, n, d, row_number() OVER (PARTITION BY i, n ORDER BY u, d) AS k FROM u)
SELECT i, n, coalesce(sum(1::BIGINT << d) FILTER (WHERE k <= i), 0)::BIGINT AS x FROM k GROUP BY i, n""")
def _(spark, sf):
    """One draw a customer, dealt in turn over the counts of failures."""
    key = F.col("c_custkey").cast("long")
    base = tables.load(spark, sf, "customer").select((key % (N + 1)).cast("int").alias("i"), F.expr("c_custkey div 11").alias("n"))
    return uniform_draws(base)


def uniform_draws(base: DataFrame) -> DataFrame:
    """(i, n, x): draw ``n`` of ``i`` failed components, every choice of them alike."""
    picked = bn.draw_uniform_subset(N, F.col("i"), lambda d: uniform_md5(SEED, F.col("i"), F.col("n"), d))
    x = F.aggregate(picked, F.lit(0).cast("long"), lambda s, d: s + F.call_function("shiftleft", F.lit(1).cast("long"), d))
    return base.select("i", "n", x.alias("x"))


UNIFORM = f"""u AS (SELECT i, n, d, {HASH.format("7|' || i::VARCHAR || '")} AS u FROM (SELECT unnest(range(11))::INT AS i), range(50) t(n), range(10) q(d)),
uk AS (SELECT i, n, d, row_number() OVER (PARTITION BY i, n ORDER BY u, d) AS k FROM u),
ux AS (SELECT i, n, coalesce(sum(1::BIGINT << d) FILTER (WHERE k <= i), 0)::BIGINT AS x FROM uk GROUP BY i, n)"""


@query("sampled_signature_n10", sql(f", {UNIFORM} SELECT 10 - ux.i AS working, round(avg((NOT fail)::INT), 10) AS phi, count(*) AS n FROM ux JOIN g USING (x) GROUP BY ux.i"))
def _(spark, sf):
    """The signature from equally many draws for every count of failures."""
    base = spark.range(11).select(F.col("id").cast("int").alias("i")).crossJoin(spark.range(50).toDF("n"))
    draws = uniform_draws(base).join(states(spark, sf).select("x", "fail"), "x")
    by_count = draws.groupBy("i").agg(F.avg((~F.col("fail")).cast("int")).alias("phi"), F.count(F.lit(1)).alias("n"))
    return by_count.select((F.lit(N) - F.col("i")).cast("int").alias("working"), r("phi", 10).alias("phi"), "n")


# --- performance functions -------------------------------------------------------------------


def judged(spark, perf) -> DataFrame:
    return evaluate(state_space(spark, N, 0, N), perf, N).select(F.element_at("words", 1).alias("x"), "loss", "fail")


@query("perf_cuts", f"SELECT x, {STAR_SQL} AS fail FROM range(1024) t(x)")
def _(spark, sf):
    return judged(spark, CutUnion(STAR)).select("x", "fail")


@query("perf_expression", "SELECT x, (x & 7) = 7 OR bit_count(x) >= 6 AS fail FROM range(1024) t(x)")
def _(spark, sf):
    from ..operators.perf import by_expression

    df = by_expression(state_space(spark, N, 0, N), "(words[0] & 7) = 7 OR bit_count(words[0]) >= 6")
    return df.select(F.element_at("words", 1).alias("x"), "fail")


@query("perf_predicate", "SELECT x, bit_count(x & 170) = 4 AS fail FROM range(1024) t(x)")
def _(spark, sf):
    from ..operators.perf import Predicate

    return judged(spark, Predicate(lambda failed: failed[[1, 3, 5, 7]].all(0))).select("x", "fail")


@query("perf_lost_capacity", sql("SELECT x, round(coalesce(sum(capacity) FILTER (WHERE (x >> d) & 1 = 1), 0) / sum(capacity), 9) AS loss FROM range(1024) t(x), e GROUP BY x"))
def _(spark, sf):
    return judged(spark, LostCapacity(network(spark, sf), 0.4)).select("x", r("loss", 9).alias("loss"))


REACH = """, rc(x, node) AS (SELECT x, 0::INT FROM range(1024) t(x)
  UNION SELECT rc.x, CASE WHEN e.u = rc.node THEN e.v ELSE e.u END FROM rc JOIN e ON (e.u = rc.node OR e.v = rc.node) AND (rc.x >> e.d) & 1 = 0)"""


@query("perf_unserved_n10", sql(f"{REACH}, dm AS (SELECT n_regionkey AS node, sum(q) AS q FROM f JOIN nation ON cn = n_nationkey GROUP BY 1) SELECT x, round(1 - sum(q) / (SELECT sum(q) FROM dm), 9) AS loss FROM rc JOIN dm USING (node) GROUP BY x"))
def _(spark, sf):
    nw = network(spark, sf)
    na = tables.load(spark, sf, "nation").select("n_nationkey", "n_regionkey")
    rows = tables.flows(spark, sf).join(na, F.col("cn") == F.col("n_nationkey")).groupBy("n_regionkey").agg(F.sum("q").alias("q")).collect()
    nw = tables.Network(nw.u, nw.v, nw.p, nw.capacity, nw.length, {}, {x["n_regionkey"]: x["q"] for x in rows})
    return judged(spark, Unserved(nw, [SOURCE], 0.1)).select("x", r("loss", 9).alias("loss"))


@query("perf_connected_recursive", sql(f"{REACH} SELECT x, count_if(node = 4) = 0 AS fail FROM rc GROUP BY x"))
def _(spark, sf):
    return judged(spark, Connected(network(spark, sf), [SOURCE], TARGET)).select("x", "fail")


@query("perf_all_connected", sql(f"{REACH} SELECT x, count(*) < 5 AS fail FROM rc GROUP BY x"))
def _(spark, sf):
    from ..operators.perf import AllConnected

    return judged(spark, AllConnected(network(spark, sf))).select("x", "fail")


@query("perf_k_connected", sql(f"{REACH} SELECT x, count_if(node IN (2, 4)) < 2 AS fail FROM rc GROUP BY x"))
def _(spark, sf):
    from ..operators.perf import KConnected

    return judged(spark, KConnected(network(spark, sf), [0, 2, 4])).select("x", "fail")


@query("perf_flow", sql("SELECT x, min((SELECT coalesce(sum(capacity), 0) FROM e WHERE (c >> d) & 1 = 1 AND (x >> d) & 1 = 0)) < 0.5 * (SELECT min(t) FROM (SELECT sum(capacity) AS t FROM cuts, e WHERE (c >> d) & 1 = 1 GROUP BY c)) AS fail FROM range(1024) t(x), cuts GROUP BY x"))
def _(spark, sf):
    from ..operators.perf import FlowBelow

    nw = network(spark, sf)
    full = ist.max_flow(nw, SOURCE, TARGET, capacity=nw.capacity)
    return judged(spark, FlowBelow(nw, SOURCE, TARGET, 0.5 * full)).select("x", "fail")


@query("ga_objective", sql("SELECT x, (i + CASE WHEN fail THEN 0 ELSE 11 END)::INT AS fval FROM g"))
def _(spark, sf):
    from ..operators.genetic import objective_column

    return states(spark, sf).select("x", objective_column(F.col("i"), F.col("fail"), N).cast("int").alias("fval"))


@query("ga_crossover_bits", "SELECT a, b, m, (a & (1023 - m)) | (b & m) AS child FROM (SELECT x AS a, (x * 37) % 1024 AS b, (x * 613) % 1024 AS m FROM range(1024) t(x))")
def _(spark, sf):
    from ..operators.genetic import crossover_column

    x = spark.range(1024).select(F.col("id").alias("a"), (F.col("id") * 37 % 1024).alias("b"), (F.col("id") * 613 % 1024).alias("m"))
    return x.withColumn("child", crossover_column(F.col("a"), F.col("b"), F.col("m")))


@query("cut_bounds_n10", sql(f"SELECT round(sum(CASE WHEN {STAR_SQL} THEN prob ELSE 0 END), 12) AS low, round(sum(CASE WHEN (x >> 3) & 1 = 1 THEN prob ELSE 0 END), 12) AS high FROM st"))
def _(spark, sf):
    from ..operators.baselines import cut_bounds

    return spark.createDataFrame([cut_bounds(network(spark, sf).p, STAR, [[3]])], "low double, high double").select(r("low").alias("low"), r("high").alias("high"))


@query("rollup_report", " UNION ALL ".join(f"SELECT rate, grp, round(sum(lam), 10) AS lam, round(sum(lam * p), 10) AS mass FROM (SELECT {x}::DOUBLE AS rate, CASE WHEN i < 4 THEN 'cannot' ELSE 'can' END AS grp, lam, p FROM ({sql('SELECT * FROM s', x)})) GROUP BY GROUPING SETS ((rate, grp), (rate))" for x in RATES))
def _(spark, sf):
    df = both_rates(lambda q: count_strata(spark, sf, q)).withColumn("grp", F.when(F.col("i") < 4, "cannot").otherwise("can"))
    out = df.rollup("rate", "grp").agg(r(F.sum("lam"), 10).alias("lam"), r(F.sum(F.col("lam") * F.col("p")), 10).alias("mass"))
    return out.where("rate is not null").select("rate", "grp", "lam", "mass")


# --- other networks and the probability models ---------------------------------------------------

CORRIDOR = f"""WITH {FLOWS}, p AS (SELECT least(sn, cn) AS u, greatest(sn, cn) AS v, sum(q) AS capacity, sum(days) / sum(n) / 1000 AS length FROM f WHERE sn <> cn GROUP BY 1, 2),
nd AS (SELECT u, v, capacity, u AS node FROM p UNION ALL SELECT u, v, capacity, v FROM p),
rk AS (SELECT u, v, row_number() OVER (PARTITION BY node ORDER BY capacity DESC, u, v) AS r FROM nd),
b AS (SELECT u, v, min(r) AS best FROM rk GROUP BY 1, 2 HAVING min(r) <= 2),
c AS (SELECT p.* FROM p JOIN b USING (u, v) ORDER BY best, capacity DESC, u, v LIMIT 46),
e AS (SELECT (row_number() OVER (ORDER BY u, v) - 1)::INT AS comp_id, u, v, capacity, length FROM c)"""


def corridor(spark, sf) -> DataFrame:
    return once(spark, "n46-net", sf, lambda: tables.corridor_net(spark, sf).coalesce(1))


@query("net_corridor", CORRIDOR + " SELECT comp_id, u, v, round(capacity, 6) AS capacity, round(length, 9) AS length FROM e")
def _(spark, sf):
    return corridor(spark, sf).select("comp_id", "u", "v", r("capacity", 6).alias("capacity"), r("length", 9).alias("length"))


@query("net_sub14", CORRIDOR + ", t AS (SELECT * FROM e ORDER BY capacity DESC, u, v LIMIT 14) SELECT (row_number() OVER (ORDER BY u, v) - 1)::INT AS comp_id, u, v, round(capacity, 6) AS capacity FROM t")
def _(spark, sf):
    return tables.sub_net(corridor(spark, sf), 14, "N14").select("comp_id", "u", "v", r("capacity", 6).alias("capacity"))


@query("net_pipe", """WITH a AS (SELECT vec_id::INT AS id, embedding::DOUBLE[] AS e FROM embeddings WHERE vec_id < 118),
g AS (SELECT b.id AS u, a.id AS v, sqrt(list_sum(list_transform(range(1, 65), lambda k: pow(a.e[k] - b.e[k], 2)))) AS length FROM a JOIN a b ON b.id < a.id WHERE a.id >= 4),
n AS (SELECT *, row_number() OVER (PARTITION BY v ORDER BY length, u) AS r FROM g),
x AS (SELECT u, v, length FROM n WHERE r = 1 UNION ALL (SELECT u, v, length FROM n WHERE r IN (2, 3) ORDER BY length, u, v LIMIT 25))
SELECT (row_number() OVER (ORDER BY u, v) - 1)::INT AS comp_id, u, v, round(length, 9) AS length FROM x""")
def _(spark, sf):
    return tables.pipe_net(spark, sf).select("comp_id", "u", "v", r("length", 9).alias("length"))


@query("nation_nodes", f"WITH {FLOWS} SELECT n::INT AS node_id, round(sum(s), 6) AS supply, round(sum(d), 6) AS demand FROM (SELECT sn AS n, q AS s, 0 AS d FROM f UNION ALL SELECT cn, 0, q FROM f) GROUP BY 1")
def _(spark, sf):
    return tables.nation_nodes(spark, sf).select("node_id", r("supply", 6).alias("supply"), r("demand", 6).alias("demand"))


@query("p_by_capacity", CORRIDOR + " SELECT comp_id, CASE WHEN k <= 10 THEN 0.005 WHEN k <= 20 THEN 0.01 ELSE 0.05 END::DOUBLE AS p FROM (SELECT comp_id, row_number() OVER (ORDER BY capacity DESC, comp_id) AS k FROM e)")
def _(spark, sf):
    return tables.assign_p_by_capacity(corridor(spark, sf)).select("comp_id", "p")


@query("p_by_length", sql("SELECT d AS comp_id, round(p, 12) AS p FROM e"))
def _(spark, sf):
    return net(spark, sf).select("comp_id", r("p").alias("p"))


@query("p_iid", sql("SELECT d AS comp_id, 0.01::DOUBLE AS p FROM e"))
def _(spark, sf):
    return tables.assign_p_iid(net(spark, sf), 0.01).select("comp_id", "p")


@query("p_from_events", "SELECT (user_id % 10)::INT AS comp_id, round(0.05 * (count_if(event_type = 'error') + 1) / (count(*) + 2), 12) AS p FROM events GROUP BY 1")
def _(spark, sf):
    return tables.event_rates(tables.load(spark, sf, "events"), 10).select("comp_id", r("p").alias("p"))


@query("lam_iid", "WITH RECURSIVE b(i, x) AS (SELECT 0, pow(0.99::DOUBLE, 46) UNION ALL SELECT i + 1, x * (46 - i) / (i + 1) * (0.01::DOUBLE / 0.99::DOUBLE) FROM b WHERE i < 46) SELECT i::INT AS i, round(x, 12) AS lam FROM b")
def _(spark, sf):
    return bn.binomial_strata(spark, 46, 0.01).select("i", r("lam").alias("lam"))


@query("lam_inid_n46", CORRIDOR.replace("WITH f AS", "WITH RECURSIVE f AS") + """, q AS (SELECT comp_id, CASE WHEN k <= 10 THEN 0.005 WHEN k <= 20 THEN 0.01 ELSE 0.05 END::DOUBLE AS p FROM (SELECT comp_id, row_number() OVER (ORDER BY capacity DESC, comp_id) AS k FROM e)),
dp(d, pmf) AS (SELECT 0, [1.0::DOUBLE] UNION ALL SELECT d + 1, list_transform(range(1, len(pmf) + 2), lambda k: coalesce(pmf[k], 0) * (1 - p) + CASE WHEN k > 1 THEN pmf[k - 1] ELSE 0 END * p) FROM dp JOIN q ON q.comp_id = dp.d)
SELECT (k - 1)::INT AS i, round(pmf[k], 12) AS lam FROM dp, range(1, 48) t(k) WHERE d = 46""")
def _(spark, sf):
    return bn.count_strata(tables.assign_p_by_capacity(corridor(spark, sf))).select("i", r("lam").alias("lam"))


# --- populations as strata -----------------------------------------------------------------------

POP: dict[str, tuple] = {
    "strat_lineitem": ("lineitem", ["l_returnflag", "l_linestatus"], "l_extendedprice > 90000", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]),
    "strat_orders": ("orders", ["o_orderpriority"], "o_orderstatus = 'P'", ["o_orderkey"]),
    "strat_docs_source": ("documents", ["source"], "n_chars > 10000", ["doc_id"]),
    "strat_pages": ("pages", ["regexp_extract(url, '/(de|en|es|fr)/', 1)"], "length(html) > 4000", ["page_id"]),
    "strat_conv": ("conversations", ["role"], "length(text) > 500", ["conv_id", "turn"]),
    "strat_docs_labels": ("documents", ["lang"], "toxic = 1", ["doc_id"]),
    "strat_rare": ("lineitem", ["l_returnflag", "floor(l_quantity / 10)"], "l_extendedprice > 104875", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]),
}


def pop_table(spark, sf, name):
    table, cols, cond, key = POP[name]
    df = tables.load(spark, sf, table)
    if name == "strat_docs_labels":
        labels = tables.load(spark, sf, "labels").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
        df = df.join(labels, "doc_id")
    return df, [F.expr(c).cast("string") for c in cols], F.expr(cond), key


def pop_sql(name: str, strategy: str, budget: int = 500) -> str:
    table, cols, cond, key = POP[name]
    src = table if name != "strat_docs_labels" else "(SELECT d.*, toxic FROM documents d JOIN (SELECT doc_id, max(toxic) AS toxic FROM labels GROUP BY 1) USING (doc_id))"
    group = " || '|' || ".join(f"({c})::{'BIGINT::' if 'floor' in c else ''}VARCHAR" for c in cols)
    w = {"proportional": "lam", "optimal": "lam * sqrt(p * (1 - p))", "uniform": "1.0"}[strategy]
    h = "md5(concat_ws('|', '7', " + ", ".join(f"{k}::VARCHAR" for k in key) + "))"
    return f"""WITH b AS (SELECT {group} AS stratum_id, ({cond})::INT AS y, {h} AS h, {', '.join(key)} FROM {src}),
z AS (SELECT stratum_id, count(*) AS size, avg(y) AS p, count(*) / (SELECT count(*) FROM b)::DOUBLE AS lam FROM b GROUP BY 1),
a AS (SELECT *, {budget} * CASE WHEN (SELECT sum({w}) FROM z) > 0 THEN {w} / (SELECT sum({w}) FROM z) ELSE lam END AS n,
  ('0x' || substr(md5('7|' || stratum_id), 1, 13))::BIGINT / 4503599627370496.0 AS u FROM z),
i AS (SELECT *, least(size, CASE WHEN n <= 1 THEN 1 WHEN n = floor(n) THEN n WHEN u < floor(n) * (floor(n) + 1 - n) / n THEN floor(n) ELSE floor(n) + 1 END)::BIGINT AS n_int FROM a),
k AS (SELECT b.stratum_id, y, row_number() OVER (PARTITION BY b.stratum_id ORDER BY h, {', '.join(key)}) AS k FROM b),
m AS (SELECT k.stratum_id, avg(y) AS ph FROM k JOIN i USING (stratum_id) WHERE k.k <= n_int GROUP BY 1)
SELECT '{strategy}' AS strategy, sum(size)::BIGINT AS population, sum(n_int)::BIGINT AS cost, round(sum(lam * p), 9) AS p_true, round(sum(lam * ph), 9) AS p_hat,
  round(sum(lam * lam * p * (1 - p) / n_int), 12) AS variance FROM i JOIN m USING (stratum_id)"""


def population(name, spark, sf) -> DataFrame:
    out = None
    for strategy in ("proportional", "optimal", "uniform"):
        df, cols, cond, key = pop_table(spark, sf, name)
        one = strata.stratified_population(df, cols, cond, 500, strategy, SEED, key)
        one = one.select(F.lit(strategy).alias("strategy"), F.col("population").cast("long").alias("population"), F.col("cost").cast("long").alias("cost"), r("p_true", 9).alias("p_true"), r("p_hat", 9).alias("p_hat"), r("variance").alias("variance"))
        out = one if out is None else out.unionByName(one)
    return out


for _name in POP:
    Q[_name] = partial(population, _name)
    O[_name] = " UNION ALL ".join(f"({pop_sql(_name, s)})" for s in ("proportional", "optimal", "uniform"))


@query("strat_strong", """WITH b AS (SELECT l_extendedprice > 90000 AS y, ntile(10) OVER (ORDER BY l_extendedprice, l_orderkey, l_partkey, l_suppkey, l_linenumber) AS t FROM lineitem),
z AS (SELECT t, count(*) AS n, avg(y::INT) AS p FROM b GROUP BY 1), m AS (SELECT sum(n * p) / sum(n) AS q FROM z)
SELECT round(sum(n * p * (1 - p)) / sum(n) / (q * (1 - q)), 8) AS r_prop FROM z, m GROUP BY q""")
def _(spark, sf):
    li = tables.load(spark, sf, "lineitem").select("l_extendedprice", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
    # Deciles by range partitions: the rank inside a range plus the sizes of the ranges before it.
    key = ["l_extendedprice", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]
    parted = li.repartitionByRange(16, *key).withColumn("_p", F.spark_partition_id())
    parted = written(parted, "ranged")
    sizes = parted.groupBy("_p").agg(F.count(F.lit(1)).alias("c"))
    before = sizes.select("_p", (F.sum("c").over(Window.orderBy("_p")) - F.col("c")).alias("b"))
    ranked = parted.withColumn("rn", F.row_number().over(Window.partitionBy("_p").orderBy(*key))).join(F.broadcast(before), "_p")
    total = sizes.agg(F.sum("c").alias("n"))
    at = F.col("rn") + F.col("b") - 1
    big, small = F.col("n") % 10, F.floor(F.col("n") / 10)
    tile = F.when(at < big * (small + 1), F.floor(at / (small + 1))).otherwise(big + F.floor((at - big * (small + 1)) / small))
    z = ranked.crossJoin(F.broadcast(total)).groupBy(tile.alias("t")).agg(F.count(F.lit(1)).alias("k"), F.avg((F.col("l_extendedprice") > 90000).cast("int")).alias("p"))
    m = z.agg((F.sum(F.col("k") * F.col("p")) / F.sum("k")).alias("q"))
    return z.crossJoin(m).groupBy("q").agg((F.sum(F.col("k") * F.col("p") * (1 - F.col("p"))) / F.sum("k")).alias("w")).select(r(F.col("w") / (F.col("q") * (1 - F.col("q"))), 8).alias("r_prop"))


# --- the experiments on a network small enough for SQL: 12 corridors that fail when they lose too much capacity ------

SMALL, SMALL_P, SMALL_THR = 12, (0.01, 0.05, 0.1), (0.2, 0.4, 0.6)
SMALL_SQL = CORRIDOR + f""", t AS (SELECT *, row_number() OVER (ORDER BY u, v) - 1 AS d FROM (SELECT * FROM e ORDER BY capacity DESC, u, v LIMIT {SMALL})),
x AS (SELECT x, bit_count(x)::INT AS i, coalesce(sum(capacity) FILTER (WHERE (x >> d) & 1 = 1), 0) / sum(capacity) AS loss FROM range({1 << SMALL}) s(x), t GROUP BY x),
cp AS (SELECT thr, i, avg((loss > thr)::INT) AS p FROM x, (VALUES {", ".join(f"({y}::DOUBLE)" for y in SMALL_THR)}) h(thr) GROUP BY 1, 2),
si AS (SELECT thr, min(i) AS i_star FROM cp WHERE p > 0 GROUP BY thr),
l AS (SELECT q, i, n * pow(q, i) * pow(1 - q, {SMALL} - i) AS lam FROM (SELECT i, count(*) AS n FROM x GROUP BY i), (VALUES {", ".join(f"({y}::DOUBLE)" for y in SMALL_P)}) h(q)),
kp AS (SELECT * FROM cp JOIN si USING (thr) JOIN l USING (i) WHERE i >= i_star)"""


def small_reference(spark, sf) -> DataFrame:
    """(thr, i, p) of the small network, all states enumerated."""

    def make():
        nw = tables.collect_net(tables.sub_net(corridor(spark, sf), SMALL, "N12"))
        x = evaluate(state_space(spark, SMALL, 0, SMALL), LostCapacity(nw, 0.5), SMALL)
        each = x.withColumn("thr", F.explode(F.array(*[F.lit(y) for y in SMALL_THR])))
        return each.groupBy("thr", F.col("k").cast("int").alias("i")).agg(F.avg((F.col("loss") > F.col("thr")).cast("int")).alias("p"))

    return once(spark, "n12-reference", sf, make)


def small_kept(spark, sf) -> DataFrame:
    """(thr, q, i, i_star, lam, p): strata that can fail."""
    ref = small_reference(spark, sf)
    first = ref.where("p > 0").groupBy("thr").agg(F.min("i").alias("i_star"))
    lam = spark.createDataFrame([(q, i, float(x)) for q in SMALL_P for i, x in enumerate(bn.binomial_pmf(SMALL, q))], "q double, i int, lam double")
    return ref.join(F.broadcast(first), "thr").where("i >= i_star").join(F.broadcast(lam), "i")


@query("w1_small_conditionals", SMALL_SQL + " SELECT thr, i, round(p, 9) AS p, i_star FROM cp JOIN si USING (thr) WHERE i BETWEEN 1 AND 5")
def _(spark, sf):
    ref = small_reference(spark, sf)
    first = ref.where("p > 0").groupBy("thr").agg(F.min("i").alias("i_star"))
    return ref.where("i between 1 and 5").join(first, "thr").select("thr", "i", r("p", 9).alias("p"), "i_star")


@query("w2_small_failure_grid", SMALL_SQL + " SELECT thr, q, round(sum(lam * p), 11) AS p_f, round(sum(lam * p) / sum(lam), 9) AS p_star FROM kp GROUP BY 1, 2")
def _(spark, sf):
    g = small_kept(spark, sf).groupBy("thr", "q").agg(F.sum(F.col("lam") * F.col("p")).alias("p_f"), F.sum("lam").alias("m"))
    return g.select("thr", "q", r("p_f", 11).alias("p_f"), r(F.col("p_f") / F.col("m"), 9).alias("p_star"))


@query("w3_small_ratios", SMALL_SQL + " SELECT thr, q, round(sum(lam * p * (1 - p)) / m / nullif(a / m * (1 - a / m), 0), 8) AS r_prop, round(pow(sum(lam * sqrt(p * (1 - p))) / m, 2) / nullif(a / m * (1 - a / m), 0), 8) AS r_opt FROM kp JOIN (SELECT thr, q, sum(lam) AS m, sum(lam * p) AS a FROM kp GROUP BY 1, 2) USING (thr, q) GROUP BY thr, q, m, a")
def _(spark, sf):
    got = measures.variance_ratios(small_kept(spark, sf), ["thr", "q"])
    return got.select("thr", "q", r("r_prop", 8).alias("r_prop"), r("r_opt", 8).alias("r_opt"))


@query("w9b_small_istar_bias", SMALL_SQL + " SELECT thr, q, round(-sum(CASE WHEN i = i_star THEN lam * p ELSE 0 END) / sum(lam * p), 9) AS rel_bias FROM kp GROUP BY 1, 2")
def _(spark, sf):
    lost = F.sum(F.when(F.col("i") == F.col("i_star"), F.col("lam") * F.col("p")).otherwise(0.0))
    return small_kept(spark, sf).groupBy("thr", "q").agg(r(-lost / F.sum(F.col("lam") * F.col("p")), 9).alias("rel_bias"))
