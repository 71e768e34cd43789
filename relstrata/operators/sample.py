"""Draws inside strata: plans whose unit of work is a chunk of draws, so no stratum is a hot task.

A chunk row carries its stratum's clusters; the task draws the states cluster by cluster,
evaluates the performance function on them and returns counts. States never leave the task.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bernoulli
from ..functions.rng import uniform_np
from .perf import Performance
from .refine import SplitTree

CHUNK = 20_000
SIZES = "rep int, idx bigint, clusters array<struct<node:bigint,k:int>>, n_int bigint"


def draw_refined(tree: SplitTree, clusters, n: int, keys) -> np.ndarray:
    """failed[n_components, n]: states of one stratum; ``keys`` are (seed, rep, stratum, draw numbers)."""
    out = np.zeros((len(tree.ps), n), bool)
    for node, k in clusters:
        m = tree.members(node)
        if k == 0:
            continue
        if k == len(m):
            out[m] = True
            continue
        u = uniform_np(*[np.asarray(x)[..., None, :] if np.ndim(x) else x for x in keys], np.array(m)[:, None])
        out[m] = bernoulli.draw_conditional(tree.ps[m], k, np.broadcast_to(u, (len(m), n)))
    return out


def sample(sizes: DataFrame, tree: SplitTree, perf: Performance, seed: int) -> DataFrame:
    """(rep, idx, n, hits) per stratum from sizes (SIZES)."""
    lo = F.explode(F.sequence(F.lit(0).cast("long"), F.col("n_int") - 1, F.lit(CHUNK).cast("long")))
    chunks = sizes.where("n_int > 0").select("rep", "idx", "clusters", "n_int", lo.alias("lo"))
    chunks = chunks.select("rep", "idx", "clusters", "lo", F.least(F.col("n_int") - F.col("lo"), F.lit(CHUNK)).alias("m"))
    n = max(int(sizes.sparkSession.conf.get("spark.sql.shuffle.partitions")), sizes.sparkSession.sparkContext.defaultParallelism)

    def run(batches):
        for b in batches:
            rep, idx, lo, m = (b.column(i).to_numpy() for i in (0, 1, 3, 4))
            clusters = b.column(2)
            hits = np.zeros(b.num_rows, np.int64)
            order = np.argsort(idx, kind="stable")  # replicates of a stratum are drawn together
            at = 0
            while at < b.num_rows:  # small strata are evaluated together
                total = np.cumsum(m[order[at:]])
                upto = at + max(1, int(np.searchsorted(total, CHUNK, side="right")))
                now = order[at:upto]
                cuts = np.flatnonzero(np.append(True, idx[now][1:] != idx[now][:-1])).tolist()
                states = []
                for x, y in zip(cuts, [*cuts[1:], len(now)], strict=True):
                    j = now[x:y]
                    draws = np.concatenate([np.arange(lo[k], lo[k] + m[k]) for k in j])
                    own = [(c["node"], c["k"]) for c in clusters[int(j[0])].as_py()]
                    states.append(draw_refined(tree, own, len(draws), (seed, np.repeat(rep[j], m[j]), int(idx[j[0]]), draws)))
                bad = perf.fails(np.concatenate(states, axis=1))
                ends = np.cumsum(m[now])
                hits[now] = np.diff(np.concatenate(([0], np.concatenate(([0], np.cumsum(bad)))[ends])))
                at = upto
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(4), pa.array(hits)], ["rep", "idx", "n", "hits"])

    counted = chunks.repartition(n, F.xxhash64("idx", "lo")).mapInArrow(run, "rep int, idx bigint, n bigint, hits bigint")
    return counted.groupBy("rep", "idx").agg(F.sum("n").alias("n"), F.sum("hits").alias("hits"))


def crude_states(spark: SparkSession, ps: np.ndarray, n: int, perf: Performance, seed: int, reps: int = 1, min_count: int = 0) -> DataFrame:
    """(rep, n, hits, tried): independent states, kept if at least ``min_count`` components failed.

    Each task answers for a range of draw numbers and redraws what it rejects, so the number
    kept is exact and does not depend on partitions.
    """
    ps = np.asarray(ps)
    chunks = spark.range(reps * (-(-n // CHUNK))).select(
        (F.col("id") % reps).cast("int").alias("rep"), (F.floor(F.col("id") / reps) * CHUNK).cast("long").alias("lo")
    )

    def run(batches):
        for b in batches:
            for rep, lo in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                todo = np.arange(lo, min(lo + CHUNK, n))
                size, hits, tried, r = len(todo), 0, 0, 0
                while len(todo):
                    x = uniform_np(seed, rep, todo[None, :], r, np.arange(len(ps))[:, None]) < ps[:, None]
                    tried += len(todo)
                    ok = x.sum(0) >= min_count
                    if ok.any():
                        hits += int(perf.fails(x[:, ok]).sum())
                    todo, r = todo[~ok], r + 1
                yield pa.RecordBatch.from_pydict({"rep": pa.array([rep], pa.int32()), "n": pa.array([size]), "hits": pa.array([hits]), "tried": pa.array([tried])})

    counted = chunks.repartition(max(1, min(reps * (-(-n // CHUNK)), 4 * spark.sparkContext.defaultParallelism)), "rep", "lo").mapInArrow(run, "rep int, n bigint, hits bigint, tried bigint")
    return counted.groupBy("rep").agg(F.sum("n").alias("n"), F.sum("hits").alias("hits"), F.sum("tried").alias("tried"))
