"""Mixing sources to target weights by Poisson replication.

Each document is repeated a Poisson number of times whose mean is its source's
target repetition rate. The number comes from inverting the distribution at a
uniform that only depends on the seed and the row's key: its doc_id, or a hash of its text
where it has none. A retry on another executor
gives the same copies; the copies are then ordered by a hash of their own, whose uniform
leading digits name a copy's partition, so no pass is needed to find the bounds.
Built-in functions only.

Defined results: rows with a null source form a source of their own; a source
without a weight is left out (weight 0); repeated rows draw the same number (they
share the key); an empty table gives an empty result; columns named like the added
ones are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Exponent of the default weights: shares are flattened by a square root.
ALPHA = 0.5
SEED = 20
#: Inversion runs until the upper tail is below 2**-53; for a mean up to 8 that is 60 terms.
#: A larger mean is a sum of draws of equal means of at most 8, each with its own uniform.
TERMS, MAX_RATE = 60, 8.0
#: Sources whose rates are broadcast, at most; more meet by shuffle.
MAX_BROADCAST = 100_000


def uniform(*parts: Column) -> Column:
    """The first 13 hex digits of an md5, over 2**52: the same double on any engine."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 13), 16, 10).cast("double") / F.lit(float(2**52))


def poisson_inverse(u: Column, rate: Column) -> Column:
    """Smallest k with u < P(Poisson(rate) <= k), by one running sum."""
    start = F.struct(F.exp(-rate).alias("term"), F.exp(-rate).alias("cdf"), F.lit(0).alias("k"))

    def step(s: Column, i: Column) -> Column:
        term = s["term"] * rate / i
        return F.struct(
            term.alias("term"),
            (s["cdf"] + term).alias("cdf"),
            (s["k"] + F.when(u >= s["cdf"], 1).otherwise(0)).alias("k"),
        )

    return F.aggregate(F.sequence(F.lit(1), F.lit(TERMS)), start, step, lambda s: s["k"])


def poisson_copies(seed: Column, key: Column, rate: Column) -> Column:
    """A Poisson number of any mean, from hashes of (seed, key) and, beyond MAX_RATE, of the part's number."""
    parts = F.ceil(rate / MAX_RATE)
    part = lambda j: poisson_inverse(uniform(seed, key, j.cast("string")), rate / parts)
    many = F.aggregate(F.sequence(F.lit(1), parts.cast("int")), F.lit(0), lambda n, j: n + part(j))
    return F.when(rate <= MAX_RATE, poisson_inverse(uniform(seed, key), rate)).otherwise(many)


def source_rates(docs: DataFrame, alpha: float = ALPHA, weights: DataFrame | None = None, max_rate: float | None = None) -> DataFrame:
    """(source, rate): target share of all rows over the source's own rows.

    Without ``weights`` (source, weight) the target share is the source's share to the
    power ``alpha``, normalised, and any rate holds. Weights that a caller gives are checked:
    a rate above ``max_rate`` (MAX_RATE unless given; infinity for none) raises when
    evaluated, rather than being cut silently.
    """
    if max_rate is None:
        max_rate = float("inf") if weights is None else MAX_RATE
    sizes = docs.groupBy("source").agg(F.count(F.lit(1)).alias("n"))
    if weights is None:
        raw = sizes.withColumn("w", F.pow(F.col("n").cast("double"), F.lit(alpha)))
    else:
        wt = weights.groupBy(F.col("source").alias("_s")).agg(F.max("weight").cast("double").alias("w"))
        raw = sizes.join(wt, F.col("source").eqNullSafe(F.col("_s")), "left").fillna({"w": 0.0}).drop("_s")
    total = raw.agg(F.sum("n").alias("all_n"), F.sum("w").alias("all_w"))
    rate = F.col("w") / F.col("all_w") * F.col("all_n") / F.col("n")
    checked = F.when(rate <= max_rate, rate).otherwise(F.raise_error(F.lit("a target rate is above MAX_RATE")))
    return raw.join(F.broadcast(total), how="cross").select("source", checked.cast("double").alias("rate"))


def replicate(
    docs: DataFrame,
    alpha: float = ALPHA,
    weights: DataFrame | None = None,
    seed: int = SEED,
    max_rate: float | None = None,
) -> DataFrame:
    """Copies of ``docs`` with ``copy_no`` (0-based) and ``order_key``, sorted by the latter.

    The rate table has a row per source and is broadcast behind a check of its size.
    The count is drawn before the explode, and only survivors go into the one shuffle of texts.
    """
    rates = source_rates(docs, alpha, weights, max_rate)
    base = docs.drop("copy_no", "order_key")
    # Null source is its own group: compare by a key that never is null.
    key = lambda c: F.coalesce(F.concat(F.lit("="), F.col(c)), F.lit("null"))
    # Rows travel as one struct, so that their columns can't clash with the ones used here.
    own = F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("null"), F.md5(F.coalesce(F.col("text"), F.lit("")))))
    rows = base.select(key("source").alias("k"), own.alias("id"), F.struct(*[F.col(f"`{c}`") for c in base.columns]).alias("row"))
    rates = rates.select(key("source").alias("k"), "rate")
    # A row a source: broadcast while there are few, so that texts aren't dealt out by a key that a hot source fills.
    few = rates.limit(MAX_BROADCAST + 1).count() <= MAX_BROADCAST
    joined = rows.join(F.broadcast(rates) if few else rates, "k")
    drawn = joined.withColumn("n", poisson_copies(F.lit(str(seed)), F.col("id"), F.col("rate"))).where("n > 0")
    copies = drawn.select("id", "row", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("copy_no"))
    order = F.md5(F.concat_ws("|", F.lit(f"order{seed}"), "id", F.col("copy_no").cast("string")))
    ranked = copies.select("row", "copy_no", order.alias("order_key"))
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    part = F.floor(F.conv(F.substring("order_key", 1, 8), 16, 10).cast("long") * n / 2**32).cast("int")
    dealt = ranked.repartitionById(n, part).sortWithinPartitions("order_key", "row.doc_id", "copy_no")
    return dealt.select("row.*", "copy_no", "order_key")


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .common import load

    return replicate(load(spark, sf_dir, "documents")).select("doc_id", "source", "copy_no", "order_key", "text")


ORACLE = """
WITH s AS (SELECT source, count(*) AS n, sqrt(count(*)::DOUBLE) AS w FROM documents GROUP BY source),
r AS (SELECT source, w / (SELECT sum(w) FROM s) * (SELECT sum(n) FROM s) / n AS rate FROM s),
u AS (
  SELECT d.*, rate,
    ('0x' || substr(md5('20|' || coalesce(doc_id::VARCHAR, 'null' || md5(coalesce(text, '')))), 1, 13))::BIGINT::DOUBLE / 4503599627370496.0 AS u
  FROM documents d JOIN r ON d.source IS NOT DISTINCT FROM r.source),
k AS (
  SELECT u.*, (SELECT count(*) FROM range(0, 60) t(i)
    WHERE u.u >= list_reduce(list_prepend(0.0::DOUBLE, list_transform(range(0, i + 1),
      lambda j: exp(-rate) * pow(rate, j) / gamma(j + 1.0))), lambda a, b: a + b)) AS c
  FROM u)
SELECT doc_id, source, copy_no::INTEGER AS copy_no,
  md5('order20|' || coalesce(doc_id::VARCHAR, 'null' || md5(coalesce(text, ''))) || '|' || copy_no::VARCHAR) AS order_key, text
FROM k, unnest(range(0, c)) x(copy_no)
"""
