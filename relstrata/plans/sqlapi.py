"""SQL surface: functions and table functions for pure-SQL use of the methods."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..functions import bernoulli
from ..operators.refine import split_counts


def register(spark: SparkSession, ps: list[float]) -> None:
    """``local_sd(p)``, ``split_count(first, size, k)`` and ``count_pmf()`` for components with these probabilities."""
    import numpy as np

    probs = np.asarray(ps, float)
    pmf, splits = bernoulli.pmf, split_counts

    @F.udtf(returnType="a int, b int, lam double")
    class SplitCount:
        """Ways to share k failures of a cluster over its halves, with their probabilities."""

        def eval(self, first: int, size: int, k: int):
            half = -(-size // 2)
            one, two = pmf(probs[first : first + half]), pmf(probs[first + half : first + size])
            for a in splits(k, half, size - half):
                yield a, k - a, float(one[a] * two[k - a])

    @F.udtf(returnType="i int, lam double")
    class CountPmf:
        def eval(self):
            for i, x in enumerate(pmf(probs)):
                yield i, float(x)

    spark.udtf.register("split_count", SplitCount)
    spark.udtf.register("count_pmf", CountPmf)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION local_sd(p DOUBLE) RETURNS DOUBLE RETURN sqrt(greatest(p * (1 - p), 0))")
