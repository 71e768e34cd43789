"""Line dedup by a deletion-neighbourhood join.

A line is the sequence of its words. Two lines of MIN_WORDS words or more are near if
one word inserted, deleted or replaced turns one into the other; shorter lines must be
equal. Every line emits a key for each of its one-word deletions (the place, and hashes of
what stands before and after) and one for each of its gaps, where another line may have a word more:

* lines with the same deletion at the same place differ by a replacement there;
* a line whose gap equals another one's deletion lacks one word of it.

All lines of a key are near each other, so each line's earliest near line is a minimum
over equal keys: no pairs are made. Halves and keys are made of distinct lines, so a line that a
third of all documents repeat is one row there; verdicts meet their places by hash, and those of a
frequent line are repeated to meet its places in many tasks.
Before variants are emitted, lines are dropped that share neither half with another
one: a single edit leaves one half untouched, so no near pair is lost.

A line goes if a near or equal line occurs earlier (smaller doc_id, then smaller line
number), whether or not that one stays. Built-in functions only.

Defined results: lines without words stay; null texts stay null with zero lines; null
doc_ids come before all others; rows that share a doc_id tie line by line and keep both;
an empty table gives an empty result; columns named like the added ones are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import load, written

MIN_WORDS = 10
#: A line is frequent above this many places, and above a quarter of an even partition: a bounded number of lines is.
FREQUENT = 1_000


def words_of(line: Column) -> Column:
    return F.array_remove(F.split(line, r"[\x20\x09-\x0D]+"), "")


def two_hashes(words: Column) -> Column:
    """128 bits of a word sequence."""
    return F.struct(F.xxhash64(words).alias("x"), F.xxhash64(F.lit(7), words).alias("y"))


def line_rows(docs: DataFrame) -> DataFrame:
    """(at, words): one row per line with words; at = (doc_id, line number)."""
    return (
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.split("text", "\n").alias("lines"))
        .select("doc_id", F.posexplode("lines").alias("line_no", "line"))
        # Tested on the line: a filter on the words would split every line twice.
        .where(F.col("line").rlike(r"[^\x20\x09-\x0D]"))
        .select(F.struct("doc_id", "line_no").alias("at"), words_of(F.col("line")).alias("words"))
    )


def half_keys(words: Column, n: Column) -> Column:
    """Keys of the halves that a near line can share; the length of the shorter line is part of each."""

    def of(m: Column) -> list[Column]:
        p = F.floor(m / 2).cast("int")
        return [
            F.xxhash64(F.lit(0), m, F.slice(words, 1, p)),
            F.xxhash64(F.lit(1), m, F.slice(words, n - (m - p) + 1, m - p)),
        ]

    shorter = F.when(n > MIN_WORDS, F.array(*of(n - 1))).otherwise(F.array().cast("array<bigint>"))
    return F.concat(F.array(*of(n)), shorter)


def sharing_a_half(distinct: DataFrame) -> DataFrame:
    """Hashes of lines that share a half with a different line: one shuffle of narrow rows."""
    half = distinct.select("h", F.explode("halves").alias("k"))
    group = Window.partitionBy("k")
    alone = (F.min("h.x").over(group) == F.max("h.x").over(group)) & (F.min("h.y").over(group) == F.max("h.y").over(group))
    return half.withColumn("alone", alone).where("not alone").select("h").distinct()


def near_lines(docs: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(lines, distinct, verdicts): all line places with their hash, and (h, first, n) and near per distinct line; n: its places."""
    rows = line_rows(docs)
    n = F.size("words")
    lines = written(
        rows.select("at", two_hashes(F.col("words")).alias("h"), F.when(n >= MIN_WORDS, half_keys(F.col("words"), n)).alias("halves")),
        "lines",
    )
    firsts = lines.groupBy("h").agg(F.min(F.struct("at", "halves")).alias("f"), F.count(F.lit(1)).alias("n"))
    distinct = written(firsts.select("h", F.col("f.at").alias("first"), F.col("f.halves").alias("halves"), "n"), "distinct-lines")
    # The candidates' first places go to their documents; only those lines' words are kept.
    places = distinct.join(sharing_a_half(distinct), "h").select(F.col("first.doc_id").alias("doc_id"), F.struct("first.line_no", "h", "first").alias("w"))
    places = places.groupBy("doc_id").agg(F.collect_list("w").alias("wanted"))
    texts = (
        docs.select(F.col("doc_id").cast("long").alias("_d"), "text")
        .join(places, F.col("_d").eqNullSafe(F.col("doc_id")))
        .select(F.split("text", "\n").alias("lines"), "wanted")
        .select("lines", F.explode("wanted").alias("w"))
        .select("w.h", "w.first", words_of(F.get("lines", F.col("w.line_no"))).alias("words"))
        .where(two_hashes(F.col("words")) == F.col("h"))
        .dropDuplicates(["h"])
    )
    cand = written(texts, "near-candidates")
    hashed = cand.select("first", F.size("words").alias("n"), running_hashes(F.col("words")).alias("before"), running_hashes(F.reverse("words")).alias("after"))
    parts = [F.col(c) for c in ("n", "before", "after")]
    keys = hashed.select("first", F.explode(F.concat(deletions(*parts), gaps(*parts))).alias("k"))
    # All lines of a group are within one edit of each other; the earliest is a near line of the rest.
    group = Window.partitionBy("k.at", "k.before", "k.after")
    best = keys.withColumn("e", F.min("first").over(group)).where("e < first").groupBy("first").agg(F.min("e").alias("e"))
    # Verify the word edit distance against the witness itself, one row per line.
    own = cand.select("first", "h", F.col("words").alias("a"))
    other = cand.select(F.col("first").alias("e"), F.col("words").alias("b"))
    near = best.join(own, "first").join(other, "e").where(within_one_edit(F.col("a"), F.col("b"))).select("h", F.lit(True).alias("near"))
    verdicts = distinct.join(near, "h", "left").select("h", "first", "n", F.coalesce("near", F.lit(False)).alias("near"))
    return lines.select("at", "h"), distinct, verdicts


def running_hashes(words: Column) -> Column:
    """Hashes of the first 0, 1, ... n words, each from the one before."""
    return F.aggregate(words, F.array(F.lit(17).cast("bigint")), lambda acc, w: F.concat(acc, F.array(F.xxhash64(F.element_at(acc, -1), w))))


def deletions(n: Column, before: Column, after: Column) -> Column:
    """One key per one-word deletion: its place and the hashes of what stands before and after."""
    return F.transform(F.sequence(F.lit(1), n), lambda i: _key(i, F.get(before, i - 1), F.get(after, n - i)))


def gaps(n: Column, before: Column, after: Column) -> Column:
    """One key per place where a word may be missing; equals that of the longer line's deletion there."""
    return F.transform(F.sequence(F.lit(1), n + 1), lambda i: _key(i, F.get(before, i - 1), F.get(after, n + 1 - i)))


def _key(at: Column, before: Column, after: Column) -> Column:
    return F.struct(at.alias("at"), before.alias("before"), after.alias("after"))


def within_one_edit(a: Column, b: Column) -> Column:
    """Word edit distance of at most one, from the common ends of both sequences."""

    def common(x: Column, y: Column) -> Column:
        same = F.zip_with(x, y, lambda p, q: F.coalesce(p == q, F.lit(False)))
        miss = F.array_position(same, False)
        return F.when(miss > 0, miss - 1).otherwise(F.least(F.size(x), F.size(y)).cast("long"))

    ends = common(a, b) + common(F.reverse(a), F.reverse(b))
    longer = F.greatest(F.size(a), F.size(b))
    return (F.abs(F.size(a) - F.size(b)) <= 1) & (ends >= longer - 1)


def dedup_lines(docs: DataFrame) -> DataFrame:
    """``docs`` with ``text`` less repeated and near-repeated lines, ``n_lines`` and ``removed`` (line numbers)."""
    lines, distinct, verdicts = near_lines(docs)
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    often = F.col("n") > max(FREQUENT, lines.count() // (4 * parts))  # at most four lines a partition
    frequent = F.broadcast(distinct.where(often).select("h", F.lit(True).alias("often")))
    salt = F.when(F.col("often"), F.pmod(F.xxhash64("at"), F.lit(parts)).cast("int")).otherwise(0)
    salts = F.when(often, F.sequence(F.lit(0), F.lit(parts - 1))).otherwise(F.array(F.lit(0)))
    places = lines.join(frequent, "h", "left").select("at", "h", salt.alias("salt"))
    met = places.join(verdicts.where("near or n > 1").withColumn("salt", F.explode(salts)), ["h", "salt"])
    gone = (
        met.where(F.col("near") | (F.col("at") > F.col("first")))
        .groupBy(F.col("at.doc_id").alias("_d"))
        .agg(F.sort_array(F.collect_set("at.line_no")).alias("_gone"))
    )
    base = docs.drop("n_lines", "removed")
    parts = F.split("text", "\n")
    joined = base.join(gone, F.col("doc_id").cast("long").eqNullSafe(F.col("_d")), "left").withColumn("removed", F.coalesce("_gone", F.array().cast("array<int>")))
    # A line number is looked up by position, not searched in the list.
    flags = F.map_from_entries(F.transform("removed", lambda k: F.struct(k, F.lit(True))))
    kept = F.when(F.size("removed") == 0, F.col("text")).otherwise(
        F.array_join(F.filter(parts, lambda x, k: ~F.coalesce(F.element_at(F.col("_flags"), k), F.lit(False))), "\n")
    )
    return joined.withColumn("n_lines", F.coalesce(F.size(parts), F.lit(0))).withColumn("_flags", flags).withColumn("text", kept).drop("_d", "_gone", "_flags")


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = dedup_lines(load(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select(
        "doc_id",
        F.when(F.col("text").isNull(), 0).otherwise(F.col("n_lines")).cast("long").alias("n_lines"),
        F.size("removed").cast("long").alias("n_removed"),
        F.concat_ws(",", F.transform("removed", lambda k: k.cast("string"))).alias("removed_lines"),
        F.md5(F.coalesce("text", F.lit(""))).alias("kept_md5"),
    )


ORACLE = r"""
WITH l AS (
  SELECT doc_id, p - 1 AS line_no, lines[p] AS line,
    list_filter(string_split_regex(lines[p], '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w
  FROM (SELECT doc_id, lines, unnest(range(1, len(lines) + 1)) AS p FROM (SELECT doc_id, string_split(text, chr(10)) AS lines FROM documents))),
k AS (SELECT *, array_to_string(w, ' ') AS key, len(w) AS n, doc_id * 1000000 + line_no AS pos FROM l WHERE len(w) > 0),
f AS (SELECT key, any_value(w) AS w, any_value(n) AS n, min(pos) AS first FROM k GROUP BY key),
v AS (SELECT key, first, n, i, array_to_string(list_concat(w[1:i - 1], w[i + 1:]), ' ') AS var
      FROM (SELECT *, unnest(range(1, n + 1)) AS i FROM f WHERE n >= 10)),
g AS (SELECT var, i, min(first) AS e FROM v GROUP BY var, i),
near AS (
  SELECT v.key FROM v JOIN g USING (var, i) WHERE g.e < v.first
  UNION SELECT v.key FROM v JOIN f ON v.var = f.key AND f.n >= 10 WHERE f.first < v.first
  UNION SELECT f.key FROM v JOIN f ON v.var = f.key AND f.n >= 10 WHERE v.first < f.first),
gone AS (SELECT doc_id, line_no FROM k JOIN f USING (key) LEFT JOIN near ON near.key = k.key WHERE near.key IS NOT NULL OR pos > first),
a AS (
  SELECT l.doc_id, count(*) AS n_lines, count(gone.line_no) AS n_removed,
    coalesce(string_agg(gone.line_no::VARCHAR, ',' ORDER BY l.line_no), '') AS removed_lines,
    md5(coalesce(string_agg(CASE WHEN gone.line_no IS NULL THEN l.line END, chr(10) ORDER BY l.line_no), '')) AS kept_md5
  FROM l LEFT JOIN gone ON l.doc_id = gone.doc_id AND l.line_no = gone.line_no GROUP BY l.doc_id)
SELECT * FROM a
"""
