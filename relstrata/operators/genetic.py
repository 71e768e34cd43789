"""Genetic search for the smallest failing state; every evaluated state is kept once."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .perf import Performance


@dataclass
class Settings:
    n_pop: int = 500
    n_trn: int = 2
    p_mt: float = 0.01
    f_xo: float = 0.8
    elite: int = 1
    init_p: float = 0.5
    max_gen: int = 100
    stall: int = 20
    method: str = "tournament"


def objective(k: np.ndarray, fail: np.ndarray, n: int) -> np.ndarray:
    """Failures of the state, and n + 1 more if the system survives them."""
    return k + np.where(fail, 0, n + 1)


def objective_column(k, fail, n: int):
    return k + F.when(fail, 0).otherwise(n + 1)


def crossover_column(a, b, mask):
    """Each bit of ``mask`` takes the second parent's bit."""
    return a.bitwiseAND(F.bitwise_not(mask)).bitwiseOR(b.bitwiseAND(mask))


def select(f: np.ndarray, m: int, cfg: Settings, rng: np.random.Generator) -> np.ndarray:
    """Indices of m parents: the best of n_trn drawn with replacement, or a wheel on scaled objectives."""
    if cfg.method == "roulette":
        w = f.max() - f + 1.0
        return np.searchsorted(np.cumsum(w) / w.sum(), rng.random(m))
    draw = rng.integers(0, len(f), (m, cfg.n_trn))
    return draw[np.arange(m), np.argmin(f[draw], axis=1)]


class EvalCache:
    """States by their bytes; counts distinct evaluations."""

    def __init__(self, evaluate, n: int):
        self.evaluate, self.n, self.known = evaluate, n, {}

    def __call__(self, pop: np.ndarray) -> np.ndarray:
        keys = [x.tobytes() for x in np.packbits(pop, axis=1)]
        new = {k: i for i, k in enumerate(keys) if k not in self.known}
        if new:
            for k, bad in zip(new, self.evaluate(pop[list(new.values())].T), strict=True):
                self.known[k] = bool(bad)
        return np.array([self.known[k] for k in keys])

    @property
    def cost(self) -> int:
        return len(self.known)

    def failures(self) -> list[list[int]]:
        return [np.flatnonzero(np.unpackbits(np.frombuffer(k, np.uint8))[: self.n]).tolist() for k, bad in self.known.items() if bad]


def children(pop: np.ndarray, f: np.ndarray, cfg: Settings, rng: np.random.Generator) -> np.ndarray:
    n_new = cfg.n_pop - cfg.elite
    n_cross = round(cfg.f_xo * n_new)
    a, b = pop[select(f, n_cross, cfg, rng)], pop[select(f, n_cross, cfg, rng)]
    crossed = np.where(rng.random(a.shape) < 0.5, b, a)
    base = pop[select(f, n_new - n_cross, cfg, rng)]
    mutated = base ^ (rng.random(base.shape) < cfg.p_mt)
    return np.concatenate((pop[np.argsort(f, kind="stable")[: cfg.elite]], crossed, mutated))


def run(evaluate, n: int, cfg: Settings, seed: int) -> tuple[int | None, int, list[list[int]]]:
    """(smallest failing count, distinct evaluations, failing states met)."""
    rng = np.random.default_rng(seed)
    cache = EvalCache(evaluate, n)
    pop = rng.random((cfg.n_pop, n)) < cfg.init_p
    best, idle = np.inf, 0
    for _ in range(cfg.max_gen):
        f = objective(pop.sum(1), cache(pop), n)
        idle = 0 if f.min() < best else idle + 1
        best = min(best, f.min())
        if idle >= cfg.stall:
            break
        pop = children(pop, f, cfg, rng)
    return (int(best) if best <= n else None), cache.cost, cache.failures()


def istar_ga(perf: Performance, n: int, cfg: Settings | None = None, seed: int = 1):
    return run(perf.fails, n, cfg or Settings(), seed)


def ga_study(spark: SparkSession, perf: Performance, n: int, grid: list[dict], runs: int, i_star: int) -> DataFrame:
    """(n_pop, f_xo, n_trn, accuracy, mean_cost, runs): whole searches inside tasks, one row each."""
    rows = [(i, r) for i in range(len(grid)) for r in range(runs)]
    # Large populations first, and a task of its own for each search, so that no task is left with several long ones.
    rows.sort(key=lambda x: -grid[x[0]].get("n_pop", 500))
    df = spark.range(0, len(rows), 1, len(rows))

    def go(pdfs):
        for pdf in pdfs:
            cell = [rows[k] for k in pdf["id"]]
            got = [run(perf.fails, n, Settings(**grid[c]), 7919 * c + r)[:2] for c, r in cell]
            yield pd.DataFrame({"cfg": [c for c, _ in cell], "run": [r for _, r in cell], "hit": [float(b == i_star) for b, _ in got], "cost": [float(c) for _, c in got]})

    out = df.mapInPandas(go, "cfg int, run int, hit double, cost double").groupBy("cfg").agg(F.avg("hit").alias("accuracy"), F.avg("cost").alias("mean_cost"), F.count(F.lit(1)).alias("runs"))
    names = spark.createDataFrame([(i, c.get("n_pop", 500), float(c.get("f_xo", 0.8)), c.get("n_trn", 2)) for i, c in enumerate(grid)], "cfg int, n_pop int, f_xo double, n_trn int")
    return names.join(out, "cfg").drop("cfg")


def ga_distributed(spark: SparkSession, perf: Performance, n: int, cfg: Settings, seed: int):
    """One search whose evaluations are Spark jobs, for an expensive performance function."""
    def evaluate(failed: np.ndarray) -> np.ndarray:
        m = failed.shape[1]
        packed = [x.tobytes() for x in np.packbits(failed.T, axis=1)]
        df = spark.createDataFrame(pd.DataFrame({"i": range(m), "x": packed})).repartition(spark.sparkContext.defaultParallelism)

        def go(pdfs):
            for pdf in pdfs:
                x = np.array([np.unpackbits(np.frombuffer(b, np.uint8))[:n] for b in pdf["x"]], bool).reshape(-1, n).T
                yield pd.DataFrame({"i": pdf["i"], "fail": perf.fails(x) if len(pdf) else []})

        out = df.mapInPandas(go, "i long, fail boolean").collect()  # a population, at most n_pop rows
        return np.array([r["fail"] for r in sorted(out, key=lambda r: r["i"])])

    return run(evaluate, n, cfg, seed)
