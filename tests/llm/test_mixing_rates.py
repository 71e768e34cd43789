"""Sources that are rare beside the others: target rates far above MAX_RATE."""

import hashlib
import math
from collections import Counter

from pyspark.sql import functions as F

from relstrata.llm import mixing


def inverse(u, rate):
    term = cdf = math.exp(-rate)
    k = 0
    while u >= cdf:
        k += 1
        term *= rate / k
        cdf += term
    return k


def uniform(*parts):
    return int(hashlib.md5("|".join(parts).encode()).hexdigest()[:13], 16) / 2**52


def brute(seed, key, rate):
    if rate <= 8:
        return inverse(uniform(seed, key), rate)
    m = math.ceil(rate / 8)
    return sum(inverse(uniform(seed, key, str(j)), rate / m) for j in range(1, m + 1))


def test_one_row_source_in_a_large_table(spark):
    n = 4000
    df = spark.range(n).select(F.col("id").alias("doc_id"), F.lit("t").alias("text"), F.when(F.col("id") == 7, None).otherwise("big").alias("source"))
    rates = {r["source"]: r["rate"] for r in mixing.source_rates(df).collect()}
    assert abs(rates[None] - n / (math.sqrt(n - 1) + 1)) < 1e-9 and rates[None] > 60
    got = Counter(r["doc_id"] for r in mixing.replicate(df).select("doc_id").collect())
    want = {d: brute("20", str(d), rates["big" if d != 7 else None]) for d in range(n)}
    assert got == {d: k for d, k in want.items() if k}


def test_given_weights_beyond_the_check(spark):
    df = spark.createDataFrame([(i, "x", "big" if i else "small") for i in range(500)], "doc_id long, text string, source string")
    w = spark.createDataFrame([("small", 1.0)], "source string, weight double")
    got = mixing.replicate(df, weights=w, max_rate=math.inf).collect()
    assert len(got) == brute("20", "0", 500.0) and {r["source"] for r in got} == {"small"}


def test_law_at_high_rates(spark):
    for rate in (8.5, 100.0, 2000.0):
        n = 2000
        draws = spark.range(n).select(mixing.poisson_copies(F.lit("3"), F.col("id").cast("string"), F.lit(rate)).alias("k"))
        r = draws.agg(F.avg("k").alias("m"), F.var_samp("k").alias("v")).first()
        assert abs(r["m"] - rate) < 5 * math.sqrt(rate / n)
        assert abs(r["v"] / rate - 1) < 5 * math.sqrt((2 + 1 / rate) / n)
