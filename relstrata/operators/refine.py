"""Refinement of strata by counts of failed components in clusters of a split tree.

Clusters are nodes of a binary tree over the components, made on demand: a cluster's
first half holds ceil(m/2) of its members. A stratum is a set of (cluster, count); its
probability is the product of the clusters' count probabilities. A step replaces the
most probable stratum by the ways to share out the count of its most probable
divisible cluster. A child is never more probable than its parent, so the strata split
in T steps are the T most probable divisible nodes of the whole tree: the greedy heap on
the driver and the level-wise expansion on executors give the same strata.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bernoulli


class SplitTree:
    """Lazily halved clusters: node 1 is all components, node k has halves 2k and 2k+1."""

    def __init__(self, ps, by: str = "order"):
        self.ps = np.asarray(ps, float)
        n = len(self.ps)
        order = list(range(n)) if by == "order" else sorted(range(n), key=lambda d: (-self.ps[d], d))
        self.by = by
        self.parts: dict[int, list[int]] = {1: order}
        self.pmfs: dict[int, np.ndarray] = {}

    def members(self, node: int) -> list[int]:
        if node not in self.parts:
            m = self.members(node // 2)
            half = -(-len(m) // 2)
            if self.by == "balanced_prob":  # greedy: the next goes to the lighter side that has room
                sides, load = ([], []), [0.0, 0.0]
                for d in m:
                    k = 0 if (load[0] <= load[1] and len(sides[0]) < half) or len(sides[1]) >= len(m) - half else 1
                    sides[k].append(d)
                    load[k] += self.ps[d]
                self.parts[node - node % 2], self.parts[node - node % 2 + 1] = sides
            else:
                self.parts[node - node % 2], self.parts[node - node % 2 + 1] = m[:half], m[half:]
        return self.parts[node]

    def size(self, node: int) -> int:
        return len(self.members(node))

    def pmf(self, node: int) -> np.ndarray:
        if node not in self.pmfs:
            self.pmfs[node] = bernoulli.pmf(self.ps[self.members(node)])
        return self.pmfs[node]


def split_counts(k: int, m1: int, m2: int) -> range:
    """Counts that the first half can take of k failures."""
    return range(max(0, k - m2), min(k, m1) + 1)


@dataclass(order=True)
class Stratum:
    """Clusters as (node, failures), in tree order."""

    key: tuple = field(repr=False)  # (-lam, path): the most probable first
    lam: float = field(compare=False)
    path: tuple = field(compare=False)
    clusters: tuple = field(compare=False)

    @property
    def stratum_id(self) -> str:
        return ".".join(map(str, self.path))

    @property
    def count(self) -> int:
        return sum(k for _, k in self.clusters)


def stratum(lam: float, path: tuple, clusters: tuple) -> Stratum:
    return Stratum((-lam, path), lam, path, clusters)


def initial(tree: SplitTree, i_star: int = 0) -> list[Stratum]:
    pmf = tree.pmf(1)
    return [stratum(float(pmf[i]), (i,), ((1, i),)) for i in range(i_star, len(pmf)) if pmf[i] > 0]


def pick_cluster(tree: SplitTree, s: Stratum) -> int | None:
    """Place of the most probable cluster with some but not all components failed."""
    best, at = -1.0, None
    for c, (node, k) in enumerate(s.clusters):
        if 0 < k < tree.size(node) and (p := tree.pmf(node)[k]) > best:
            best, at = p, c
    return at


def children(tree: SplitTree, s: Stratum, at: int) -> list[Stratum]:
    node, k = s.clusters[at]
    left, right = 2 * node, 2 * node + 1
    rest = s.lam / tree.pmf(node)[k]
    out = []
    for a in split_counts(k, tree.size(left), tree.size(right)):
        lam = float(rest * tree.pmf(left)[a] * tree.pmf(right)[k - a])
        if lam > 0:
            out.append(stratum(lam, (*s.path, a), (*s.clusters[:at], (left, a), (right, k - a), *s.clusters[at + 1 :])))
    return out


@dataclass
class Refinement:
    tree: SplitTree
    strata: list[Stratum]
    #: split stratum by path: (node whose halves are counted, count before, {count in first half: child path})
    splits: dict[tuple, tuple[int, dict[int, tuple]]]
    popped: list[float]

    @property
    def lam(self) -> np.ndarray:
        return np.array([s.lam for s in self.strata])


def refine(tree: SplitTree, steps: int, i_star: int = 0, on_step=None) -> Refinement:
    """``steps`` greedy steps, or as many as there are divisible strata."""
    heap, done = initial(tree, i_star), []
    heapq.heapify(heap)
    splits: dict = {}
    popped: list[float] = []
    while heap and len(popped) < steps:
        s = heapq.heappop(heap)
        at = pick_cluster(tree, s)
        if at is None:
            done.append(s)
            continue
        kids = children(tree, s, at)
        node = s.clusters[at][0]
        splits[s.path] = (node, {k.path[-1]: k.path for k in kids})
        popped.append(s.lam)
        for k in kids:
            heapq.heappush(heap, k)
        if on_step:
            on_step(len(popped), s, kids)
    return Refinement(tree, sorted(heap + done), splits, popped)


def refine_until(tree: SplitTree, stop, i_star: int = 0, limit: int = 1_000_000) -> Refinement:
    """Refine until ``stop(strata)`` holds, doubling and then bisecting the number of steps."""
    lo, hi = 0, 1
    while not stop(refine(tree, hi, i_star).strata):
        lo, hi = hi, 2 * hi
        if hi > limit:
            return refine(tree, limit, i_star)
    while hi - lo > 1:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if stop(refine(tree, mid, i_star).strata) else (mid, hi)
    return refine(tree, hi, i_star)


def assign(ref: Refinement, failed: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Index of each state's stratum; -1 for states below i*. Walks the split tree in batches."""
    index = {s.path: k for k, s in enumerate(ref.strata)}
    out = np.full(len(counts), -1)
    todo = [((int(i),), np.flatnonzero(counts == i)) for i in np.unique(counts)]
    while todo:
        path, idx = todo.pop()
        if path in index:
            out[idx] = index[path]
        elif path in ref.splits:
            node, kids = ref.splits[path]
            a = failed[np.ix_(ref.tree.members(2 * node), idx)].sum(0)
            todo += [(kids[int(x)], idx[a == x]) for x in np.unique(a)]
    return out


STRATA = "stratum_id string, depth int, clusters array<struct<node:bigint,size:int,k:int,prob:double>>, lam double, splittable boolean"


def strata_frame(spark: SparkSession, ref: Refinement) -> DataFrame:
    t = ref.tree
    rows = [
        (s.stratum_id, len(s.path) - 1, [(n, t.size(n), k, float(t.pmf(n)[k])) for n, k in s.clusters], s.lam, pick_cluster(t, s) is not None)
        for s in ref.strata
    ]
    return spark.createDataFrame(rows, STRATA)


def refine_levelwise(spark: SparkSession, tree: SplitTree, steps: int, i_star: int = 0, slack: float = 0.5, direct: int = 256) -> DataFrame:
    """The same strata on executors, without a queue of their size on the driver.

    The first ``direct`` steps are made at once, so that even a single heavy stratum becomes many roots for many tasks.
    Below these, nodes at least as probable as a threshold are expanded level by level; the threshold falls until
    enough divisible nodes lie above it, and the most probable of them are the ones to split.
    """
    from ..sources.scratch import written

    schema = "stratum_id string, parent string, path array<int>, clusters array<struct<node:bigint,k:int>>, lam double, splittable boolean, open boolean"

    def expand_rows(rows: list[tuple], tau: float) -> list[tuple]:
        out = []
        for path, clusters, lam in rows:
            s = stratum(lam, tuple(path), tuple(clusters))
            at = pick_cluster(tree, s)
            if at is not None and lam >= tau:
                out += [(k.path, k.clusters, k.lam, s.stratum_id) for k in children(tree, s, at)]
        return out

    def subtree(tau: float):
        """All nodes below a root that can be reached through nodes of at least tau."""

        def run(batches):
            for b in batches:
                for path, clusters, lam in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                    todo = [(tuple(path), tuple((c["node"], c["k"]) for c in clusters), lam, None)]
                    rows = []
                    while todo:
                        now = todo
                        todo = expand_rows([x[:3] for x in now], tau)
                        rows += [(x[0], x[3], x[2], pick_cluster(tree, stratum(x[2], x[0], x[1])) is not None, x[1]) for x in now]
                    yield pa.RecordBatch.from_arrays(
                        [
                            pa.array([".".join(map(str, p)) for p, *_ in rows]), pa.array([q for _, q, *_ in rows], pa.string()),
                            pa.array([list(p) for p, *_ in rows], pa.list_(pa.int32())),
                            pa.array([[{"node": n, "k": k} for n, k in c] for *_, c in rows], pa.list_(pa.struct([("node", pa.int64()), ("k", pa.int32())]))),
                            pa.array([x for _, _, x, _, _ in rows], pa.float64()), pa.array([z for *_, z, _ in rows], pa.bool_()), pa.array([x >= tau for _, _, x, _, _ in rows], pa.bool_()),
                        ],
                        ["stratum_id", "parent", "path", "clusters", "lam", "splittable", "open"],
                    )

        return run

    first = refine(tree, min(steps, direct), i_star)
    left = steps - len(first.popped)
    made = [(list(s.path), [(n, k) for n, k in s.clusters], s.lam) for s in first.strata]
    parts = max(1, min(len(made), 4 * spark.sparkContext.defaultParallelism))
    roots = spark.createDataFrame(made, "path array<int>, clusters array<struct<node:bigint,k:int>>, lam double").repartition(parts, "path")
    tau = max(s.lam for s in first.strata)
    while True:
        tau = tau * slack if left > 0 else np.inf
        nodes = written(roots.mapInArrow(subtree(tau), schema), "nodes")
        if left <= 0 or tau < 1e-300 or nodes.where("splittable and open").count() >= left:
            break
    split = nodes.where("splittable and open").orderBy(F.desc("lam"), "path").limit(max(left, 0)).select(F.col("stratum_id").alias("s"))
    alive = nodes.join(split, nodes["parent"] == split["s"], "left_semi").union(nodes.where("parent is null"))
    return alive.join(split, alive["stratum_id"] == split["s"], "left_anti").select("stratum_id", "clusters", "lam", "splittable")


def ratio_trace(ref_p, tree: SplitTree, steps: int, i_star: int, every: int = 1) -> list[dict]:
    """(step, n_strata, r_prop, r_opt, r_uni) of the exact ratios while refining.

    ``ref_p(stratum)`` gives the failure probability inside a stratum; sums are updated, not recomputed.
    """
    roots = initial(tree, i_star)
    mass = sum(s.lam for s in roots)
    p = {s.path: ref_p(s) for s in roots}
    pf = sum(s.lam * p[s.path] for s in roots) / mass
    v = pf * (1 - pf)
    sd = lambda x: max(x * (1 - x), 0.0) ** 0.5
    acc = {"w": sum(s.lam * p[s.path] * (1 - p[s.path]) for s in roots), "s": sum(s.lam * sd(p[s.path]) for s in roots), "u": sum(s.lam**2 * p[s.path] * (1 - p[s.path]) for s in roots), "n": len(roots)}
    out: list[dict] = []

    def note(step: int) -> None:
        ratios = {"r_prop": acc["w"] / mass / v, "r_opt": (acc["s"] / mass) ** 2 / v, "r_uni": acc["n"] * acc["u"] / mass**2 / v}
        out.append({"step": step, "n_strata": acc["n"]} | {k: float(x) for k, x in ratios.items()})

    note(0)

    def on_step(step: int, s: Stratum, kids: list[Stratum]) -> None:
        for sign, group in ((-1, [s]), (1, kids)):
            for x in group:
                q = p[x.path] if x.path in p else p.setdefault(x.path, ref_p(x))
                acc["w"] += sign * x.lam * q * (1 - q)
                acc["s"] += sign * x.lam * sd(q)
                acc["u"] += sign * x.lam**2 * q * (1 - q)
                acc["n"] += sign
        if step % every == 0:
            note(step)

    refine(tree, steps, i_star, on_step)
    return out


def exact_p(tree: SplitTree, failed: np.ndarray, fails: np.ndarray, prob: np.ndarray):
    """``ref_p`` from enumerated states: a stratum keeps the indices of its states while it is split."""
    counts = failed.sum(0)
    held: dict[tuple, np.ndarray] = {}

    def of(s: Stratum) -> float:
        idx = held.get(s.path[:-1])
        if idx is None:
            idx = np.flatnonzero(counts == s.path[0])
            if len(s.path) > 1:
                idx = np.arange(len(counts))
        for node, k in s.clusters:
            idx = idx[failed[np.ix_(tree.members(node), idx)].sum(0) == k]
        held[s.path] = idx
        w = prob[idx]
        return float((w * fails[idx]).sum() / w.sum()) if w.sum() > 0 else 0.0

    return of

