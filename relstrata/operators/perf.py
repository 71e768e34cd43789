"""Performance functions: does a state fail? Kernels over batches of states.

``loss(failed)`` takes failed[n, B] and gives B numbers; ``fails`` compares with the
threshold. Connectivity runs bit-parallel: one byte holds eight states of an edge.
"""

from __future__ import annotations

import numpy as np

from ..sources.tables import Network


class Performance:
    """A state fails if its loss is above ``threshold``."""

    threshold = 0.5
    coherent = True

    def loss(self, failed: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def fails(self, failed: np.ndarray) -> np.ndarray:
        return self.loss(failed) > self.threshold


def reached(net: Network, failed: np.ndarray, sources: list[int]) -> tuple[dict[int, np.ndarray], int]:
    """Per node the states, packed by bits, in which a source reaches it."""
    b = failed.shape[1]
    alive = np.packbits(~failed, axis=1)
    if net.n > len(failed):  # never-failing links behind the state vector
        alive = np.vstack([alive, np.full((net.n - len(failed), alive.shape[1]), 255, np.uint8)])
    at = {v: np.full(alive.shape[1], 255 if v in sources else 0, np.uint8) for v in {*net.nodes, *sources}}
    edges = list(zip(net.u.tolist(), net.v.tolist(), alive, strict=True))
    while True:
        moved = False
        for u, v, a in edges:
            both = (at[u] | at[v]) & a
            for x in (u, v):
                new = at[x] | both
                if not moved and not np.array_equal(new, at[x]):
                    moved = True
                at[x] = new
        if not moved:
            return at, b


class Connected(Performance):
    """Fails if no source reaches the target."""

    def __init__(self, net: Network, sources: list[int], target: int):
        self.net, self.sources, self.target = net, list(sources), target

    def loss(self, failed):
        at, b = reached(self.net, failed, self.sources)
        return 1.0 - np.unpackbits(at[self.target])[:b]


class KConnected(Performance):
    """Fails if the terminals are not all connected."""

    def __init__(self, net: Network, terminals: list[int]):
        self.net, self.terminals = net, list(terminals)

    def loss(self, failed):
        at, b = reached(self.net, failed, self.terminals[:1])
        ok = at[self.terminals[0]].copy()
        for t in self.terminals[1:]:
            ok &= at[t]
        return 1.0 - np.unpackbits(ok)[:b]


class AllConnected(KConnected):
    def __init__(self, net: Network):
        super().__init__(net, net.nodes)


class CutUnion(Performance):
    """Fails if all components of some cut fail."""

    def __init__(self, cuts: list[list[int]]):
        self.cuts = [np.array(c) for c in cuts]

    def loss(self, failed):
        out = np.zeros(failed.shape[1], bool)
        for c in self.cuts:
            out |= failed[c].all(0)
        return out.astype(float)


class LostCapacity(Performance):
    """Share of capacity on failed components."""

    def __init__(self, net: Network, threshold: float):
        self.share, self.threshold = net.capacity / net.capacity.sum(), threshold

    def loss(self, failed):
        return self.share @ failed


class Unserved(Performance):
    """Share of demand at nodes that no source reaches."""

    def __init__(self, net: Network, sources: list[int], threshold: float):
        self.net, self.sources, self.threshold = net, list(sources), threshold

    def loss(self, failed):
        at, b = reached(self.net, failed, self.sources)
        total = sum(self.net.demand.values())
        out = np.zeros(b)
        for v, d in self.net.demand.items():
            out += d / total * (1 - np.unpackbits(at[v])[:b] if v in at else 1)
        return out


class FlowBelow(Performance):
    """Fails if the maximum flow from s to t is below a demand."""

    def __init__(self, net: Network, s: int, t: int, demand: float):
        from .istar import max_flow

        self.net, self.s, self.t, self.demand, self.flow = net, s, t, demand, max_flow

    def loss(self, failed):
        return np.array([self.flow(self.net, self.s, self.t, alive=~f, capacity=self.net.capacity) < self.demand for f in failed.T], float)


class DcCascade(Performance):
    """Lost load under direct-current flow with cascading overload; need not be coherent.

    Susceptance is capacity over length. The generators are the ``generators`` strongest nodes,
    scaled to the whole demand. Each island balances by scaling its larger side; a
    line trips above (1 + tolerance) times its base flow, floored at half the mean base flow.
    """

    coherent = False

    def __init__(self, net: Network, threshold: float = 0.4, tolerance: float = 0.5, generators: int = 4, floor: float = 0.5):
        nodes = net.nodes
        index = {v: k for k, v in enumerate(nodes)}
        self.m, self.threshold = len(nodes), threshold
        self.a = np.array([index[int(x)] for x in net.u])
        self.b = np.array([index[int(x)] for x in net.v])
        self.y = net.capacity / net.length
        self.y = self.y / self.y.mean()
        demand = np.array([net.demand.get(v, 0.0) for v in nodes])
        supply = np.array([net.supply.get(v, 0.0) for v in nodes])
        top = sorted(range(self.m), key=lambda k: (-supply[k], nodes[k]))[:generators]
        gen = np.zeros(self.m)
        gen[top] = supply[top]
        self.total = demand.sum()
        self.demand, self.supply = demand / self.total, gen / gen.sum()
        self.net = net
        ends = np.zeros((net.n, self.m))
        ends[np.arange(net.n), self.a], ends[np.arange(net.n), self.b] = 1, -1
        self.outer = (ends[:, :, None] * ends[:, None, :]).reshape(net.n, -1)  # each line's part of the Laplacian
        flow, _ = self._flow_islands(np.ones((net.n, 1), bool))
        self.base = flow[:, 0]
        size = np.abs(self.base)
        self.limit = (1 + tolerance) * np.maximum(size, floor * size.mean())
        # What a line takes over from another one that is lost, while all nodes stay joined.
        x = np.zeros((self.m, self.m))
        x[1:, 1:] = np.linalg.pinv((self.y @ self.outer).reshape(self.m, self.m)[1:, 1:])
        self.take = self.y[:, None] * (ends @ x @ ends.T)
        self.joined = len(set(self._labels(np.ones((net.n, 1), bool))[:, 0])) == 1

    #: Losses up to this many lines are solved as corrections of the base flow if all nodes stay joined.
    FEW = 10

    def _flow(self, alive: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Line flows [n, B] and served demand [B]."""
        n, b = alive.shape
        lost = n - alive.sum(0)
        flow, served = np.empty((n, b)), np.empty(b)
        few = np.zeros(b, bool)
        if self.joined and (lost <= self.FEW).any():
            some = np.flatnonzero(lost <= self.FEW)
            at, _ = reached(self.net, ~alive[:, some], [self.net.nodes[0]])
            whole = np.bitwise_and.reduce([at[v] for v in self.net.nodes])
            few[some] = np.unpackbits(whole)[: len(some)].astype(bool)
        for k in np.unique(lost[few]).tolist():
            cols = np.flatnonzero(few & (lost == k))
            flow[:, cols], served[cols] = self._flow_joined(alive[:, cols], k), min(self.supply.sum(), self.demand.sum())
        rest = np.flatnonzero(~few)
        if len(rest):
            flow[:, rest], served[rest] = self._flow_islands(alive[:, rest])
        return flow, served

    def _flow_joined(self, alive: np.ndarray, k: int) -> np.ndarray:
        if not k:
            return np.repeat(self.base[:, None], alive.shape[1], axis=1)
        gone = np.nonzero(~alive.T)[1].reshape(-1, k)
        shift = np.linalg.solve(np.eye(k) - self.take[gone[:, :, None], gone[:, None, :]], self.base[gone][:, :, None])[:, :, 0]
        flow = self.base[:, None] + np.einsum("bkn,bk->nb", self.take.T[gone], shift)
        return np.where(alive, flow, 0.0)

    def _labels(self, alive: np.ndarray) -> np.ndarray:
        """Smallest node index of each node's island, [m, B]."""
        label = np.tile(np.arange(self.m, dtype=np.int16)[:, None], alive.shape[1])
        while True:
            before = label.copy()
            for e in range(len(alive)):
                low = np.minimum(label[self.a[e]], label[self.b[e]])
                for x in (self.a[e], self.b[e]):
                    np.copyto(label[x], low, where=alive[e])
            if np.array_equal(before, label):
                return label.astype(np.int64)

    def _flow_islands(self, alive: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        b = alive.shape[1]
        m, cols = self.m, np.arange(b)
        label = self._labels(alive)
        flat = (label + cols * m).ravel()
        s = np.bincount(flat, np.repeat(self.supply, b), b * m).reshape(b, m)
        d = np.bincount(flat, np.repeat(self.demand, b), b * m).reshape(b, m)
        at = (cols[None, :], label)
        served = np.minimum(s, d)
        up = np.divide(served, s, out=np.zeros_like(s), where=s > 0)[at]
        down = np.divide(served, d, out=np.zeros_like(d), where=d > 0)[at]
        inject = self.supply[:, None] * up - self.demand[:, None] * down
        w = np.where(alive, self.y[:, None], 0.0)
        lap = (w.T @ self.outer).reshape(b, m, m)
        k = np.arange(m)
        lap[:, k, k] += (label == k[:, None]).T  # ground one bus of each island
        angle = np.linalg.solve(lap, inject.T[:, :, None])[:, :, 0].T
        return w * (angle[self.a] - angle[self.b]), served.sum(1)

    def loss(self, failed):
        alive = ~failed
        b = alive.shape[1]
        out = np.zeros(b)
        open_ = np.arange(b)
        while len(open_):
            flow, served = self._flow(alive[:, open_])
            trip = (np.abs(flow) > self.limit[:, None] * (1 + 1e-9)) & alive[:, open_]
            done = ~trip.any(0)
            out[open_[done]] = 1 - served[done]
            alive[:, open_] &= ~trip
            open_ = open_[~done]
        return out


class Predicate(Performance):
    """Any function of failed[n, B] to B booleans."""

    def __init__(self, fn, coherent: bool = False):
        self.fn, self.coherent = fn, coherent

    def loss(self, failed):
        return np.asarray(self.fn(failed), float)


def evaluate(states, perf: Performance, n: int):
    """Add ``loss`` and ``fail`` to a DataFrame with ``words``: one Arrow pass, nothing shuffled."""
    import pyarrow as pa
    from pyspark.sql import types as T

    from ..functions import bits

    schema = T.StructType([*states.schema.fields, T.StructField("loss", T.DoubleType()), T.StructField("fail", T.BooleanType())])
    names = [f.name for f in schema.fields]

    def run(batches):
        for b in batches:
            w = b.column(names.index("words"))
            words = w.flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1).T if b.num_rows else np.zeros((bits.n_words(n), 0), np.int64)
            loss = perf.loss(bits.unpack(words, n)) if b.num_rows else np.zeros(0)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(loss), pa.array(loss > perf.threshold)], names)

    return states.mapInArrow(run, schema)


def by_expression(states, text: str):
    """A performance function given as SQL over the state's columns, for example ``bit_count(words[0]) >= 3``."""
    from pyspark.sql import functions as F

    return states.withColumn("fail", F.expr(text).cast("boolean"))


def check_coherence(states, n: int):
    """Failing states (rows words, k, fail) with a failing state whose one-more-failure state is safe: violations.

    ``states`` must be closed upwards by one failure; single words only.
    """
    from pyspark.sql import functions as F

    x = states.select(F.element_at("words", 1).alias("x"), "fail")
    one = F.explode(F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda d: F.call_function("shiftleft", F.lit(1).cast("long"), d)))
    up = x.where("fail").select("x", one.alias("b")).where(F.col("x").bitwiseAND(F.col("b")) == 0).select("x", F.col("x").bitwiseOR(F.col("b")).alias("y"))
    safe = x.where("not fail").select(F.col("x").alias("y"))
    return up.join(safe, "y")


def is_minimal_cut(perf: Performance, cut: list[int], n: int) -> bool:
    """Does the cut fail, and no state with one member repaired?"""
    states = np.zeros((n, len(cut) + 1), bool)
    states[cut] = True
    for k, d in enumerate(cut):
        states[d, k + 1] = False
    f = perf.fails(states)
    return bool(f[0]) and not f[1:].any()
