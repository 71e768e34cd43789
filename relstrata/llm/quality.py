"""Quality rules: fixed base rules, then an isolation forest on the rule statistics.

Every document gets rule statistics from its whole text; the forest sees them as rates. Trees of random splits are grown on a hash sample of at most SAMPLE rows
labelled good. Their cuts fall anywhere between the low and high ends of all labelled rows, good
and bad, so what lies where no good row does is alone after few splits: a short average path
length marks an anomalous document, which is rejected. The limit is set on all labelled rows: of
the scores that keep GOOD_KEPT of the good rows, those that reject the most bad ones, and of
these the middle between the bad rows and the good ones below. Short texts say little, so
their rates are drawn towards the ordinary ones as if they had PRIOR_WORDS ordinary words more.

Defined results: a null or empty text has no words and fails the base (unless ``min_words`` is 0); ties in the
sample order are broken by doc_id; repeated rows are scored alike; without labels of
both kinds nothing beyond the base is rejected; an empty table gives an empty result;
repeated or contradicting labels of a document count as bad.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import column, hash_sample, keyed, load, slices, text_key, with_fields, written

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SYMBOLS = "#*$%&|<>"
MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50

#: Forest: trees, rows a tree, and the bound of the fitting sample.
TREES, PER_TREE, SAMPLE, SEED = 150, 256, 20_000, 11
#: Bins of the score when the cut is set.
BINS = 4096
FEATURES = ["symbol_rate", "word_length", "dup_line_rate", "repeat_rate"]
#: Rates of counts are taken as log(1 + SCALE * rate): most documents have none, and a few per thousand words count.
SCALE = 1000
#: Share of good labelled rows that the limit keeps at least.
GOOD_KEPT = 0.998
#: Ends of the labelled rows: quantiles of each statistic.
ENDS = (0.001, 0.999)
PRIOR_WORDS, PRIOR_LENGTH = 20, 5

STATS_SCHEMA = (
    "doc_id long, text_key long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, "
    "base_failed boolean, " + ", ".join(f"{f} double" for f in FEATURES)
)


def repeated_words(words: list[str]) -> int:
    """Words inside 3-word windows that occur twice or more."""
    n = len(words)
    ids: dict[str, int] = {}
    seq = np.fromiter((ids.setdefault(w, len(ids)) for w in words), np.int64, n)
    if n < 3:
        return 0
    v = len(ids)
    if v < 2_000_000:
        key = (seq[:-2] * v + seq[1:-1]) * v + seq[2:]
    else:
        pair = np.unique(seq[:-1] * v + seq[1:], return_inverse=True)[1].astype(np.int64)
        key = pair[:-1] * v + seq[2:]
    order = np.argsort(key, kind="stable")
    s = key[order]
    same = s[1:] == s[:-1]
    if not same.any():
        return 0
    twice = np.zeros(n - 2, bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    cover = np.zeros(n, bool)
    for k in range(3):
        cover[k : n - 2 + k] |= twice
    return int(cover.sum())


def statistics(text: str | None, min_words: int = MIN_WORDS) -> tuple:
    """The contract's counts, the base verdict, and the forest's features of one text."""
    text = text or ""
    words = WORD.findall(text)
    n = len(words)
    chars = sum(map(len, words))
    symbols = sum(map(text.count, SYMBOLS))
    seen: set[str] = set()
    dup = lines = 0
    for line in text.split("\n"):
        if WORD.search(line):
            dup += line in seen
            lines += 1
            seen.add(line)
    repeat = repeated_words(words)
    failed = n < min_words or 100 * repeat > MAX_REPEAT_PERCENT * n
    per = n + PRIOR_WORDS
    rate = lambda count, of: math.log1p(SCALE * count / of)
    length = PRIOR_LENGTH + (chars - PRIOR_LENGTH * n) / per
    return n, chars, symbols, dup, repeat, failed, rate(symbols, per), length, rate(dup, lines + 1), rate(repeat, per)


def rule_statistics(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """One row of statistics per row of ``docs``."""
    names = [f.split()[0] for f in STATS_SCHEMA.split(", ")]
    kinds = [pa.int64()] * 5 + [pa.bool_()] + [pa.float64()] * len(FEATURES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 500):
            rows = [statistics(t, min_words) for t in column(b, "text").to_pylist()]
            cols = list(zip(*rows, strict=True)) if rows else [[]] * len(kinds)
            yield pa.RecordBatch.from_arrays([column(b, "doc_id"), column(b, "text_key"), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names)

    return keyed(docs, id_col, text_col).withColumn("text_key", text_key()).mapInArrow(run, STATS_SCHEMA)


def mean_path(n: np.ndarray | float) -> np.ndarray | float:
    """Mean depth of an unsuccessful search in a random tree of n leaves."""
    n = np.maximum(np.asarray(n, float), 1.0)
    return np.where(n > 2, 2 * (np.log(np.maximum(n - 1, 1)) + 0.5772156649015329) - 2 * (n - 1) / n, np.where(n > 1, 1.0, 0.0))


class IsolationForest:
    """Random axis splits of a box over bounded samples; all arrays, so it ships with a closure.

    ``low``, ``high``: the box that the first split divides, the rows' own ends by default. A part without rows
    is a leaf, so places away from the rows have short paths.
    """

    def __init__(self, rows: np.ndarray, low=None, high=None, trees: int = TREES, per_tree: int = PER_TREE, seed: int = SEED):
        rng = np.random.default_rng(seed)
        self.size = min(per_tree, len(rows))
        self.limit = int(np.ceil(np.log2(max(self.size, 2))))
        self.trees = []
        if len(rows) > 1:
            self.low = np.minimum(rows.min(0), rows.min(0) if low is None else low)
            self.high = np.maximum(rows.max(0), rows.max(0) if high is None else high)
            self.trees = [self._grow(rows[rng.choice(len(rows), self.size, replace=False)], rng) for _ in range(trees)]

    def _grow(self, rows: np.ndarray, rng: np.random.Generator) -> tuple[np.ndarray, ...]:
        feature, cut, left, right, depth = [], [], [], [], []

        def node(part: np.ndarray, lo: np.ndarray, hi: np.ndarray, at: int) -> int:
            k = len(feature)
            for x in (feature, cut, left, right, depth):
                x.append(0)
            open_ = np.flatnonzero(hi > lo)
            if at >= self.limit or not len(part) or not len(open_):
                feature[k], depth[k] = -1, at + float(mean_path(len(part)))
                return k
            f = int(rng.choice(open_))
            c = float(rng.uniform(lo[f], hi[f]))
            below = part[:, f] < c
            feature[k], cut[k] = f, c
            mid_hi, mid_lo = hi.copy(), lo.copy()
            mid_hi[f] = mid_lo[f] = c
            left[k], right[k] = node(part[below], lo, mid_hi, at + 1), node(part[~below], mid_lo, hi, at + 1)
            return k

        node(rows, self.low, self.high, 0)
        return tuple(np.array(x, t) for x, t in ((feature, np.int64), (cut, float), (left, np.int64), (right, np.int64), (depth, float)))

    def score(self, rows: np.ndarray) -> np.ndarray:
        """Anomaly score in (0, 1]; 0 without a forest."""
        if not self.trees:
            return np.zeros(len(rows))
        total = np.zeros(len(rows))
        each = np.arange(len(rows))
        for feature, cut, left, right, depth in self.trees:
            at = np.zeros(len(rows), np.int64)
            for _ in range(self.limit + 1):
                f = feature[at]
                go = f >= 0
                if not go.any():
                    break
                nxt = np.where(rows[each, np.maximum(f, 0)] < cut[at], left[at], right[at])
                at = np.where(go, nxt, at)
            total += depth[at]
        return np.exp2(-total / len(self.trees) / float(mean_path(self.size)))


def labelled(stats: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``stats`` that pass the base and have a label, with ``good``."""
    per_doc = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg((F.min("quality") > 0).alias("good"))
    return stats.where(~F.col("base_failed")).join(per_doc, "doc_id")


def fit_forest(stats: DataFrame, labels: DataFrame) -> IsolationForest:
    """On at most SAMPLE good rows that pass the base rules, taken by hash, in the box of all labelled rows."""
    rows = labelled(stats, labels)
    ends = rows.groupBy("good").agg(F.count(F.lit(1)).alias("n"), *[F.percentile_approx(f, list(ENDS), 10_000).alias(f) for f in FEATURES]).collect()  # two rows
    n_good = sum(r["n"] for r in ends if r["good"])
    good = hash_sample(rows.where("good"), F.col("doc_id"), SAMPLE, SEED, n_good).select(*FEATURES).toPandas().to_numpy(float)
    if len(ends) < 2:
        return IsolationForest(good[:0])
    return IsolationForest(good, *(pick([[r[f][k] for f in FEATURES] for r in ends], axis=0) for k, pick in enumerate((np.min, np.max))))


def with_score(stats: DataFrame, forest: IsolationForest) -> DataFrame:
    schema = with_fields(stats, "anomaly double")
    names = [*stats.columns, "anomaly"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.column_stack([column(b, f).to_numpy(zero_copy_only=False) for f in FEATURES]) if b.num_rows else np.zeros((0, len(FEATURES)))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(forest.score(x), pa.float64())], names)

    return stats.mapInArrow(run, schema)


def calibrate(scored: DataFrame, labels: DataFrame) -> float:
    """The score from which a document is rejected, from all labelled rows that pass the base."""
    bins = (
        labelled(scored, labels)
        .groupBy(F.floor(F.col("anomaly") * BINS).cast("int").alias("bin"))
        .agg(F.count_if("good").alias("good"), F.count_if(~F.col("good")).alias("bad"))
        .collect()
    )  # at most BINS + 1 rows
    good, bad = np.zeros(BINS + 2), np.zeros(BINS + 2)
    for r in bins:
        good[r["bin"]], bad[r["bin"]] = r["good"], r["bad"]
    if not good.sum() or not bad.sum():
        return 1.0 + 1.0 / BINS
    kept, caught = np.cumsum(good) / good.sum(), 1 - np.cumsum(bad) / bad.sum()  # if the limit is after this bin
    fits = np.flatnonzero(kept >= min(GOOD_KEPT, 1 - 1 / good.sum()) - 1e-12)  # a single wrong label never moves the limit
    best = fits[caught[fits] >= caught[fits].max() - 1e-12]
    return (int(best[0]) + int(best[-1]) + 2) / 2 / BINS


def judge_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """Statistics, ``anomaly`` and ``kept`` for every row of ``docs``.

    Texts are read once: the statistics are written to the shared folder, and fitting,
    calibration and the verdicts read those narrow rows. ``min_words``: the base rule's least number of words.
    """
    stats = written(rule_statistics(docs, id_col, text_col, min_words), "rule-stats")
    labels = labels.select(F.col("doc_id").cast("long").alias("doc_id"), "quality")
    scored = written(with_score(stats, fit_forest(stats, labels)), "rule-scores")
    return scored.withColumn("kept", ~F.col("base_failed") & (F.col("anomaly") < F.lit(calibrate(scored, labels))))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = judge_quality(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "anomaly")
