"""Approximate failure probabilities inside strata from minimal cuts or known failing states.

A state that contains a known failing set counts as failing. Inside a stratum the
probability of containing a set is a product over clusters: the members' own failures times the
chance that the rest of the cluster has the failures that remain.
"""

from __future__ import annotations

import zlib
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import bernoulli, bits
from .refine import Refinement, SplitTree, Stratum
from .sample import draw_refined

#: ``auto`` takes the exact union while at most this many sets meet a stratum.
UNION_SETS = 5
PROBES = 128


class Overlap:
    """P(stratum and all of a set failed), with the clusters' tables remembered."""

    def __init__(self, tree: SplitTree):
        self.tree = tree

        @lru_cache(maxsize=200_000)
        def rest(node: int, inside: frozenset) -> tuple[float, np.ndarray]:
            m = tree.members(node)
            own = float(np.prod([tree.ps[d] for d in inside])) if inside else 1.0
            return own, bernoulli.pmf([tree.ps[d] for d in m if d not in inside])

        self.rest = rest
        self.sets = lru_cache(maxsize=100_000)(lambda node: frozenset(tree.members(node)))

    def mass(self, s: Stratum, need: frozenset) -> float:
        out = 1.0
        for node, k in s.clusters:
            inside = need & self.sets(node)
            if len(inside) > k:
                return 0.0
            own, pmf = self.rest(node, inside)
            r = k - len(inside)
            out *= own * (pmf[r] if r < len(pmf) else 0.0)
            if out == 0.0:
                return 0.0
        return out


def approx_pf(tree: SplitTree, strata: list[Stratum], cuts: list, mode: str = "auto", normalise: bool = True) -> np.ndarray:
    """Approximate conditional failure probability per stratum.

    ``union``: exact probability of the union of the cuts' events (inclusion and exclusion, branches end
    where a union no longer fits the counts). ``capped_sum``: sum of the single terms, at most 1.
    ``auto``: union where at most UNION_SETS sets meet a stratum; with more, the sum while it is small, and
    otherwise the share of PROBES states drawn in the stratum that contain a set (no evaluation of the
    performance function), kept off 0 and 1: a capped sum of 1 would leave the stratum a single draw.
    ``normalise=False`` leaves the joint probability undivided.
    """
    over = Overlap(tree)
    sets = [frozenset(c) for c in cuts]
    rows = [np.array(sorted(c)) for c in sets]

    def probed(s: Stratum) -> float:
        x = draw_refined(tree, s.clusters, PROBES, (11, zlib.crc32(s.stratum_id.encode()), np.arange(PROBES)))
        hit = np.zeros(PROBES, bool)
        for c in rows:
            hit |= x[c].all(0)
        return s.lam * float(np.clip(hit.mean(), 0.5 / PROBES, 1 - 0.5 / PROBES))

    def total(s: Stratum) -> float:
        single = [(c, m) for c in sets if (m := over.mass(s, c)) > 0]
        if mode == "capped_sum" or len(single) <= 1:
            return sum(m for _, m in single)
        if mode == "auto" and len(single) > UNION_SETS:
            upper = sum(m for _, m in single)
            return upper if upper < 0.1 * s.lam else probed(s)
        live = [(c, k) for k, (c, _) in enumerate(single)]
        out = sum(m for _, m in single)
        sign = -1.0
        while live:
            nxt = []
            for c, k in live:
                for j in range(k + 1, len(single)):
                    u = c | single[j][0]
                    m = over.mass(s, u)
                    if m > 0:
                        out += sign * m
                        nxt.append((u, j))
            live, sign = nxt, -sign
        return out

    out = np.array([total(s) for s in strata])
    if not normalise:
        return out
    return np.clip(out / np.array([s.lam for s in strata]), 0.0, 1.0)


def approx_of(ref: Refinement, cuts: list, mode: str = "auto") -> np.ndarray:
    return approx_pf(ref.tree, ref.strata, cuts, mode)


def minimal_states(states: DataFrame) -> DataFrame:
    """Failing states (words, k) that contain no other one: an anti-join on dominance, small against large.

    Exact copies fold first. The smaller side of the inequality is checked by Spark's own size limit;
    the join condition on counts prunes before the bit test.
    """
    x = states.select("words", bits.popcount(F.col("words")).alias("k")).dropDuplicates(["words"])
    y = x.select(F.col("words").alias("w2"), F.col("k").alias("k2"))
    return x.join(y, (F.col("k2") < F.col("k")) & bits.contains(F.col("words"), F.col("w2")), "left_anti")


def antichain(sets: list) -> list[list[int]]:
    """The same on the driver, for a bounded log of failing states."""
    out: list[frozenset] = []
    for s in sorted({frozenset(x) for x in sets}, key=lambda s: (len(s), sorted(s))):
        if not any(m <= s for m in out):
            out.append(s)
    return [sorted(s) for s in out]
