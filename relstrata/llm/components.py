"""Connected components of an edge table, by alternating star rounds.

Each round links every node's larger neighbours, then its smaller ones, to the
smallest node around it; the number of rounds grows with the logarithm of the
graph's diameter. Rounds are written to the shared folder: nothing is collected, and a
lost executor costs a re-read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

MAX_ROUNDS = 60


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component): the smallest node reachable, for every node of some edge.

    Self-links are allowed and repeated edges ignored; edges with a null end are left out.
    """
    e = (
        edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v"))
        .where(F.col(a).isNotNull() & F.col(b).isNotNull())
        .distinct()
    )
    nodes = written(e.select(F.col("u").alias("node")).union(e.select("v")).distinct(), "nodes")
    e = written(e.where("u <> v"), "edges")
    mark = None
    for _ in range(MAX_ROUNDS):
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low2 = large.groupBy("u").agg(F.min("v").alias("m"))
        small = (
            large.join(low2, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .union(low2.select("u", F.col("m").alias("v")))
            .where("u <> v")
            .distinct()
        )
        e = written(small, "edges")
        now = e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if tuple(now) == mark:
            break
        mark = tuple(now)
    else:
        raise RuntimeError("components did not settle")
    # Settled: every edge leads from a node to its component's smallest one.
    return nodes.join(e.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("c")), "node", "left").select(
        "node", F.coalesce("c", "node").alias("component")
    )
