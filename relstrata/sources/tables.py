"""Given tables, and networks derived from them."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: A network travels in closures; its size is checked when it is collected.
MAX_EDGES = 1_000_000


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


@dataclass
class Network:
    """A collected network: edge arrays in component order."""

    u: np.ndarray
    v: np.ndarray
    p: np.ndarray
    capacity: np.ndarray
    length: np.ndarray
    supply: dict[int, float]
    demand: dict[int, float]

    @property
    def n(self) -> int:
        return len(self.u)

    @property
    def nodes(self) -> list[int]:
        return sorted({*self.u.tolist(), *self.v.tolist()})

    def with_p(self, p) -> Network:
        p = np.broadcast_to(np.asarray(p, float), (self.n,)).copy()
        return Network(self.u, self.v, p, self.capacity, self.length, self.supply, self.demand)


def flows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(sn, cn, q, days, n): quantity and day gaps by supplier and customer nation.

    Facts are aggregated by their keys before any dimension is joined by name; suppliers
    and customers are joined by key, and Spark broadcasts what it measures as small.
    """
    li = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity", F.to_date("l_shipdate").alias("ship"))
    od = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.to_date("o_orderdate").alias("day"))
    su = load(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").alias("sn"))
    cu = load(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").alias("cn"))
    joined = (
        li.join(od, F.col("l_orderkey") == F.col("o_orderkey"))
        .join(su, F.col("l_suppkey") == F.col("s_suppkey"))
        .join(cu, F.col("o_custkey") == F.col("c_custkey"))
    )
    gap = F.abs(F.datediff("ship", "day"))
    return joined.groupBy("sn", "cn").agg(F.sum("l_quantity").alias("q"), F.sum(gap).alias("days"), F.count(F.lit(1)).alias("n"))


def _pairs(df: DataFrame, a: str, b: str) -> DataFrame:
    return (
        df.where(F.col(a) != F.col(b))
        .groupBy(F.least(a, b).alias("u"), F.greatest(a, b).alias("v"))
        .agg(F.sum("q").alias("capacity"), (F.sum("days") / F.sum("n") / 1000).alias("length"))
    )


def _shape(net_id: str, df: DataFrame, order: list) -> DataFrame:
    at = F.row_number().over(Window.orderBy(*order)) - 1  # at most MAX_EDGES rows
    return df.select(
        F.lit(net_id).alias("net_id"), at.cast("int").alias("comp_id"), F.col("u").cast("int").alias("u"), F.col("v").cast("int").alias("v"),
        F.lit(None).cast("double").alias("p"), "capacity", "length", F.lit("line").alias("ctype"),
    )


def region_net(spark: SparkSession, sf_dir: str) -> DataFrame:
    """N10: all pairs of regions."""
    na = load(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    s, c = na.toDF("sk", "sr"), na.toDF("ck", "cr")
    by_region = flows(spark, sf_dir).join(F.broadcast(s), F.col("sn") == F.col("sk")).join(F.broadcast(c), F.col("cn") == F.col("ck"))
    return _shape("N10", _pairs(by_region, "sr", "cr"), ["u", "v"])


def corridor_net(spark: SparkSession, sf_dir: str, size: int = 46, per_node: int = 2) -> DataFrame:
    """N46: each nation's strongest corridors, best rank first."""
    pairs = _pairs(flows(spark, sf_dir), "sn", "cn")
    ends = pairs.select("u", "v", "capacity", F.explode(F.array("u", "v")).alias("node"))
    rank = F.row_number().over(Window.partitionBy("node").orderBy(F.desc("capacity"), "u", "v"))
    best = ends.withColumn("r", rank).groupBy("u", "v").agg(F.min("r").alias("best")).where(F.col("best") <= per_node)
    chosen = pairs.join(best, ["u", "v"]).orderBy("best", F.desc("capacity"), "u", "v").limit(size)
    return _shape("N46", chosen, ["u", "v"])


def sub_net(net: DataFrame, size: int, name: str) -> DataFrame:
    """The strongest edges of a network, renumbered (N12, N14)."""
    return _shape(name, net.orderBy(F.desc("capacity"), "u", "v").limit(size), ["u", "v"])


def nation_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(node_id, supply, demand) per nation: a full join of what is sent and received."""
    f = flows(spark, sf_dir)
    sent = f.groupBy(F.col("sn").alias("a")).agg(F.sum("q").alias("supply"))
    got = f.groupBy(F.col("cn").alias("b")).agg(F.sum("q").alias("demand"))
    return sent.join(got, F.col("a") == F.col("b"), "full").select(
        F.coalesce("a", "b").alias("node_id"), F.coalesce("supply", F.lit(0.0)).alias("supply"), F.coalesce("demand", F.lit(0.0)).alias("demand")
    )


def pipe_net(spark: SparkSession, sf_dir: str, nodes: int = 118, plants: int = 4, extra: int = 25) -> DataFrame:
    """N139: each vector joins its nearest earlier one; then the shortest second and third choices."""
    v = load(spark, sf_dir, "embeddings").where(F.col("vec_id") < nodes).select(F.col("vec_id").cast("int").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    a, b = v.toDF("v", "ev"), v.toDF("u", "eu")
    gap2 = F.aggregate(F.zip_with("ev", "eu", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    near = a.where(F.col("v") >= plants).join(F.broadcast(b), F.col("u") < F.col("v")).select("u", "v", F.sqrt(gap2).alias("length"))
    near = near.withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy("length", "u"))).where("r <= 3")
    more = near.where("r > 1").orderBy("length", "u", "v").limit(extra)
    pipes = near.where("r = 1").union(more).select("u", "v", F.lit(1.0).alias("capacity"), "length")
    return _shape("N139", pipes, ["u", "v"])


def add_super_source(net: Network, plants: list[int], source: int = -1) -> Network:
    """Never-failing links from one new node to every plant; they stay out of the state vector."""
    k = len(plants)
    return Network(
        np.concatenate((net.u, np.full(k, source))), np.concatenate((net.v, plants)), np.concatenate((net.p, np.zeros(k))),
        np.concatenate((net.capacity, np.full(k, np.inf))), np.concatenate((net.length, np.zeros(k))), net.supply, net.demand,
    )


# --- component probabilities -----------------------------------------------------------------


def assign_p_iid(net: DataFrame, p: float) -> DataFrame:
    return net.withColumn("p", F.lit(float(p)))


def assign_p_by_capacity(net: DataFrame, cuts=(10, 20), ps=(5e-3, 1e-2, 5e-2)) -> DataFrame:
    """Three types by capacity rank: the strongest components fail least."""
    r = F.row_number().over(Window.orderBy(F.desc("capacity"), "comp_id"))
    kind = F.when(r <= cuts[0], 0).when(r <= cuts[1], 1).otherwise(2)
    out = net.withColumn("_k", kind)
    p = F.element_at(F.array(*[F.lit(float(x)) for x in ps]), F.col("_k") + 1)
    return out.withColumn("p", p).withColumn("ctype", F.concat(F.lit("type"), F.col("_k").cast("string"))).drop("_k")


def assign_p_by_length(net: DataFrame, rate: float) -> DataFrame:
    """Damage points along the length at a constant rate; any one fails the component."""
    return net.withColumn("p", -F.expm1(-F.lit(float(rate)) * F.col("length")))


def event_rates(events: DataFrame, n: int, scale: float = 0.05, window: str | None = None) -> DataFrame:
    """([w_start,] comp_id, p): smoothed share of error events, per component and window."""
    keys = [F.window("ts", window).start.alias("w_start")] if window else []
    err = F.count_if(F.col("event_type") == "error")
    return events.groupBy(*keys, F.pmod("user_id", F.lit(n)).cast("int").alias("comp_id")).agg(
        (F.lit(scale) * (err + 1) / (F.count(F.lit(1)) + 2)).alias("p")
    )


def assign_p_from_events(net: DataFrame, events: DataFrame, n: int, scale: float = 0.05) -> DataFrame:
    rates = event_rates(events, n, scale)
    return net.drop("p").join(F.broadcast(rates), "comp_id", "left").fillna({"p": scale / 2}).select(*net.columns)


def collect_net(net: DataFrame, nodes: DataFrame | None = None) -> Network:
    """The edge list on the driver; at most MAX_EDGES."""
    rows = net.orderBy("comp_id").limit(MAX_EDGES + 1).collect()
    if len(rows) > MAX_EDGES:
        raise ValueError("the network has too many edges to travel in closures")
    side = {r["node_id"]: r for r in nodes.collect()} if nodes is not None else {}
    get = lambda c, t=float: np.array([r[c] if r[c] is not None else 0.0 for r in rows], t)
    return Network(
        get("u", np.int64), get("v", np.int64), get("p"), get("capacity"), get("length"),
        {k: r["supply"] for k, r in side.items()}, {k: r["demand"] for k, r in side.items()},
    )
