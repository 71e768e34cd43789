"""Benchmark decontamination by spaced-seed hashing.

Fixed masks pick some of eight neighbouring tokens and ignore the others, so a hash
survives substitutions at ignored positions. Hashes of all document positions meet
the hashes of the benchmark items; around each hit the two texts are laid side by
side, and an overlap counts if some WINDOW aligned tokens hold at most MISMATCHES
substitutions. Either mask alone meets every window of 13 tokens with up to two
substitutions, so no such overlap is missed. Built-in functions only; from the split
to the hash lookup it is one generated loop over the positions.

Tokens are runs of letters and digits, lower-cased. Items of 4 to 12 tokens must occur
whole and unchanged, those of up to 7 by a hash of the whole item; items of fewer than 4
tokens are in any prose, so a document must consist of one to hold it.

Defined results: null texts have no tokens; repeated documents are reported each under
its id (one row per id and item); repeated items are reported each; of several overlaps
of a document and an item the one with most equal tokens counts, then the first;
empty tables give an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import MAX_BROADCAST, keyed, load, text_key, written

#: Token positions that each mask keeps (out of SPAN).
MASKS = [(0, 1, 3, 6, 7), (0, 1, 4, 6, 7)]
SPAN = 8
WINDOW, MISMATCHES = 13, 2
#: Items of fewer tokens are compared with whole documents.
SHORT = 4
#: Seed tables up to this many rows are broadcast (16 to 24 bytes a row); larger ones meet by shuffle.
BROADCAST_SEEDS = 2_000_000


def tokens(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), "")


def seed_rows(df: DataFrame, *ids: str, carry: tuple[str, ...] = ()) -> DataFrame:
    """(ids, carried columns, pos, seed) for each position of ``words`` with a whole span; pos is 1-based."""
    long_enough = df.where(F.size("words") >= SPAN)
    at = long_enough.withColumn("pos", F.explode(F.sequence(F.lit(1), F.size("words") - (SPAN - 1))))
    hashes = [
        F.xxhash64(F.lit(k), *(F.element_at("words", F.col("pos") + F.lit(p)) for p in mask))
        for k, mask in enumerate(MASKS)
    ]
    return at.select(*ids, *carry, "pos", F.explode(F.array(*hashes)).alias("seed"))


def short_overlaps(base: DataFrame, items: DataFrame) -> DataFrame | None:
    """(doc_id, item_id, n_equal, start) of items below SPAN tokens, by hashes of whole items; None if there are none."""
    short = items.where(F.size("words").between(1, SPAN - 1)).select("item_id", F.col("words").alias("item_words"), F.xxhash64("words").alias("seed"))
    lengths = sorted(r["n"] for r in short.select(F.size("item_words").alias("n")).distinct().collect())  # below SPAN rows
    if not lengths:
        return None
    size = F.size("words")

    def runs(n: int) -> Column:
        enough = (size == n) if n < SHORT else (size >= n)
        one = lambda i: F.struct(i.alias("pos"), F.xxhash64(F.slice("words", i, n)).alias("seed"), F.lit(n).alias("n"))
        return F.when(enough, F.transform(F.sequence(F.lit(1), size - (n - 1)), one)).otherwise(F.array().cast("array<struct<pos:int,seed:bigint,n:int>>"))

    at = base.select("doc_id", "words", F.explode(F.concat(*[runs(n) for n in lengths])).alias("r"))
    at = at.select("doc_id", F.col("r.pos").alias("pos"), F.col("r.seed").alias("seed"), F.slice("words", F.col("r.pos"), F.col("r.n")).alias("run"))
    small = short.limit(BROADCAST_SEEDS + 1).count() <= BROADCAST_SEEDS
    met = at.join(F.broadcast(short) if small else short, "seed").where(F.col("run") == F.col("item_words"))
    return met.select("doc_id", "item_id", F.size("run").alias("n_equal"), F.col("pos").alias("start"))


def overlaps(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, item_id, n_equal, start): contaminated documents and the items they hold.

    ``start`` is the 1-based token of the document that stands beside the item's first
    (it can be below 1 when the document begins inside the item).
    """
    all_items = (
        benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").alias("item_text"))
        .withColumn("words", tokens(F.col("item_text")))
        .select("item_id", "words")
    )
    items = all_items.where(F.size("words") >= SPAN)
    seeds = seed_rows(items, "item_id", carry=("words",)).select("seed", "item_id", F.col("pos").alias("item_pos"), F.size("words").alias("n_item")).distinct()
    small = seeds.limit(BROADCAST_SEEDS + 1).count() <= BROADCAST_SEEDS
    # Tokens are split once per document, before the explode that would repeat the split.
    keys = keyed(docs, id_col, text_col).where("text is not null")
    base = keys.select("doc_id", tokens(F.col("text")).alias("words"))
    diag = F.col("pos") - F.col("item_pos")
    # Only what stands beside the item leaves with a hit, not the whole document.
    beside = F.slice("words", F.greatest(F.col("diag") + 1, F.lit(1)), F.least(F.col("n_item") + F.least("diag", F.lit(0)), F.lit(1_000_000_000)))
    if small:
        met = seed_rows(base, "doc_id", carry=("words",)).join(F.broadcast(seeds), "seed").withColumn("diag", diag)
    else:  # positions travel without their documents, which meet the hits again by id and text
        named = keys.select("doc_id", text_key().alias("text_key"), tokens(F.col("text")).alias("words"))
        hits = seed_rows(named, "doc_id", "text_key").join(seeds, "seed").select("doc_id", "text_key", "item_id", "n_item", diag.alias("diag")).distinct()
        hits = hits.withColumnsRenamed({"doc_id": "_d", "text_key": "_t"})
        met = hits.join(named, F.col("_d").eqNullSafe(F.col("doc_id")) & (F.col("_t") == F.col("text_key")))
    hits = met.select("doc_id", "item_id", "diag", beside.alias("beside")).dropDuplicates(["doc_id", "item_id", "diag", "beside"])
    items = items.withColumnRenamed("words", "item_words")
    laid = hits.join(F.broadcast(items) if small else items, "item_id")
    skip = -F.least(F.col("diag"), F.lit(0))
    own = F.slice("item_words", skip + 1, F.greatest(F.size("beside"), F.lit(0)))
    equal = F.zip_with("beside", own, lambda a, b: F.when(a == b, 1).otherwise(0))
    width = F.least(F.lit(WINDOW), F.size("item_words"))
    allowed = F.when(F.size("item_words") >= WINDOW, MISMATCHES).otherwise(0)
    need = F.col("width") - F.col("allowed")
    total = lambda e: F.aggregate(e, F.lit(0), lambda s, x: s + x)
    starts = F.sequence(F.lit(1), F.col("n_side") - F.col("width") + 1)
    judged = (
        laid.withColumn("equal", equal).withColumn("width", width).withColumn("allowed", allowed).withColumn("n_side", F.size("equal"))
        .where("n_side >= width")
        .where(F.exists(starts, lambda i: total(F.slice("equal", i, F.col("width"))) >= need))
        .select("doc_id", "item_id", total(F.col("equal")).alias("n_equal"), (F.col("diag") + 1).alias("start"))
    )
    if (short := short_overlaps(base, all_items)) is not None:
        judged = judged.unionByName(short)
    best = F.max(F.struct("n_equal", (-F.col("start")).alias("m")))
    return judged.groupBy("doc_id", "item_id").agg(best.alias("b")).select(
        "doc_id", "item_id", F.col("b.n_equal").cast("long").alias("n_equal"), (-F.col("b.m")).cast("long").alias("start")
    )


def decontaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without the contaminated rows, each judged by its own text whatever its id."""
    one = F.xxhash64(F.col(id_col).cast("long"), F.col(text_col).cast("string"))
    rows = docs.select(one.alias("doc_id"), F.col(text_col).alias("text"))
    bad = written(overlaps(rows, benchmark).select(F.col("doc_id").alias("_bad")).distinct(), "contaminated")
    few = bad.limit(MAX_BROADCAST + 1).count() <= MAX_BROADCAST
    return docs.join(F.broadcast(bad) if few else bad, one == F.col("_bad"), "left_anti")


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return overlaps(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))


#: Any window of 13 tokens with two substitutions holds four equal tokens in a row: candidates by those, then the same test.
ORACLE = r"""
WITH dw AS (SELECT doc_id, list_filter(string_split_regex(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM documents),
iw AS (SELECT item_id, list_filter(string_split_regex(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM benchmark),
dg AS (SELECT doc_id, p, array_to_string(w[p:p+3], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 2)) AS p FROM dw)),
ig AS (SELECT item_id, p, array_to_string(w[p:p+3], ' ') AS g FROM (SELECT item_id, w, unnest(range(1, len(w) - 2)) AS p FROM iw WHERE len(w) >= 8)),
hit AS (SELECT DISTINCT doc_id, item_id, dg.p - ig.p AS diag FROM dg JOIN ig USING (g)),
side AS (SELECT doc_id, item_id, diag, dw.w AS dw, iw.w AS iw, len(iw.w) AS n,
           greatest(1, 1 - diag) AS a, least(len(iw.w), len(dw.w) - diag) AS b
         FROM hit JOIN dw USING (doc_id) JOIN iw USING (item_id)),
eq AS (SELECT doc_id, item_id, diag, n, list_transform(range(a, b + 1), lambda k: (dw[k + diag] = iw[k])::INTEGER) AS e FROM side),
ok AS (SELECT doc_id, item_id, diag, e FROM eq
       WHERE len(e) >= least(13, n) AND len(list_filter(range(1, len(e) - least(13, n) + 2),
         lambda s: list_sum(e[s:s + least(13, n) - 1]) >= least(13, n) - CASE WHEN n >= 13 THEN 2 ELSE 0 END)) > 0),
short AS (SELECT doc_id, item_id, len(iw.w) AS n, p, dw.w[p:p + len(iw.w) - 1] = iw.w AS same, len(dw.w) AS m
          FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS p FROM dw) dw JOIN iw ON len(iw.w) BETWEEN 1 AND 7 AND dw.w[p] = iw.w[1]),
hits AS (SELECT doc_id, item_id, list_sum(e) AS n_equal, diag + 1 AS start FROM ok
         UNION ALL SELECT doc_id, item_id, n, p FROM short WHERE same AND (n >= 4 OR n = m)),
pick AS (SELECT doc_id, item_id, n_equal::BIGINT AS n_equal, start::BIGINT AS start,
           row_number() OVER (PARTITION BY doc_id, item_id ORDER BY n_equal DESC, start) AS k FROM hits)
SELECT doc_id, item_id, n_equal, start FROM pick WHERE k = 1
"""
