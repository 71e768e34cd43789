"""Python data source ``state_space``: all states with k_min..k_max of n components failed.

Partitions are intervals of ranks, so nothing is shuffled and no state is stored. The
range of ``k`` is an option, and filters on ``k`` are taken over by the source where the session
allows it: strata that cannot fail are never made.
"""

from __future__ import annotations

from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

from ..functions import bits

SCHEMA = "k int, state_rank bigint, words array<bigint>"
BATCH = 16_384


class Interval(InputPartition):
    def __init__(self, k: int, lo: int, hi: int):
        self.k, self.lo, self.hi = k, lo, hi


class StateSpaceReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n = int(options["n"])
        self.lo, self.hi = int(options.get("k_min", 0)), int(options.get("k_max", self.n))
        self.size = int(options.get("partition_size", 250_000))

    def partitions(self):
        out = []
        for k in range(max(0, self.lo), min(self.n, self.hi) + 1):
            total = comb(self.n, k)
            if total >= 2**62:
                raise ValueError(f"{total} states of {k} failures are too many to enumerate")
            out += [Interval(k, a, min(a + self.size, total)) for a in range(0, total, self.size)]
        return out

    def read(self, part: Interval):
        if part is None:
            return
        for a in range(part.lo, part.hi, BATCH):
            ranks = np.arange(a, min(a + BATCH, part.hi))
            words = bits.pack(bits.unrank(self.n, part.k, ranks))
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(len(ranks), part.k, np.int32)), pa.array(ranks), pa.FixedSizeListArray.from_arrays(pa.array(words.T.ravel()), words.shape[0]).cast(pa.list_(pa.int64()))],
                ["k", "state_rank", "words"],
            )


class PushedReader(StateSpaceReader):
    """Takes over filters on ``k``; Spark accepts such a reader only where Python filter pushdown is on."""

    def pushFilters(self, filters):
        for f in filters:
            if getattr(f, "attribute", None) != ("k",):
                yield f
            elif isinstance(f, EqualTo):
                self.lo, self.hi = max(self.lo, f.value), min(self.hi, f.value)
            elif isinstance(f, GreaterThanOrEqual):
                self.lo = max(self.lo, f.value)
            elif isinstance(f, GreaterThan):
                self.lo = max(self.lo, f.value + 1)
            elif isinstance(f, LessThanOrEqual):
                self.hi = min(self.hi, f.value)
            elif isinstance(f, LessThan):
                self.hi = min(self.hi, f.value - 1)
            else:
                yield f


class StateSpace(DataSource):
    @classmethod
    def name(cls):
        return "state_space"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return StateSpaceReader(dict(self.options))


class PushedStateSpace(StateSpace):
    @classmethod
    def name(cls):
        return "state_space_pushed"

    def reader(self, schema):
        return PushedReader(dict(self.options))


def state_space(spark, n: int, k_min: int = 0, k_max: int | None = None, partition_size: int = 250_000):
    """The states as a DataFrame. Filters on ``k`` go to the source where the session has Python filter pushdown on."""
    source = PushedStateSpace if spark.conf.get("spark.sql.python.filterPushdown.enabled", "false") == "true" else StateSpace
    spark.dataSource.register(source)
    reader = spark.read.format(source.name()).option("n", n).option("k_min", k_min)
    return reader.option("k_max", n if k_max is None else k_max).option("partition_size", partition_size).load()
