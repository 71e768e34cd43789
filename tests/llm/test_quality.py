import numpy as np
import pytest

from relstrata.llm import quality


def brute(text):
    import re

    text = text or ""
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    tri = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    cover = set()
    for i, t in enumerate(tri):
        if tri.count(t) >= 2:
            cover |= {i, i + 1, i + 2}
    lines = text.split("\n")
    dup = sum(1 for k, x in enumerate(lines) if re.search(r"[^\x20\x09-\x0D]", x) and x in lines[:k])
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), dup, len(cover), len(w) < 50 or 100 * len(cover) > 50 * len(w)


def test_counts(corpus):
    for t in [*corpus[:-1], "a a a a", "x y z x y z", "#a $b\n#a $b\n\n \n"]:
        assert quality.statistics(t)[:6] == brute(t), t


def labels(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, quality int, toxic int")


def junk(rng, n):
    return " ".join(rng.choice(["tha***", "ing$$$", "est&&&", "re%%%"]) + str(i) for i in range(n))


def test_forest_finds_junk(spark):
    import random

    from .conftest import sentence

    rng = random.Random(0)
    rows = [(i, sentence(rng, 80 + i % 60)) for i in range(300)] + [(1000 + i, junk(rng, 80 + i)) for i in range(20)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    lab = labels(spark, [(i, 1, 0) for i in range(0, 300, 2)] + [(1000 + i, 0, 0) for i in range(0, 20, 2)])
    got = {r["doc_id"]: r["kept"] for r in quality.judge_quality(docs, lab).collect() if not r["base_failed"]}
    good, bad = [k for k in got if k < 1000], [k for k in got if k >= 1000]
    assert np.mean([got[k] for k in good]) > 0.95
    assert np.mean([got[k] for k in bad]) < 0.1


@pytest.mark.parametrize("name", ["docs", "odd_docs", "no_docs"])
def test_edges(name, request, spark):
    df = request.getfixturevalue(name)
    got = quality.judge_quality(df, labels(spark, [(0, 1, 0), (0, 0, None), (None, 1, 1), (2, None, 0)]))
    assert got.count() == df.count()
    assert not got.where("base_failed and kept").count()


def test_without_labels_only_the_base_rejects(docs, spark):
    got = quality.judge_quality(docs, labels(spark, []))
    assert got.where("kept = base_failed").count() == 0


def brute_score(forest, x):
    """Mean depth of the leaf of ``x`` over the trees, walked node by node, as a score."""
    total = 0.0
    for feature, cut, left, right, depth in forest.trees:
        k = 0
        while feature[k] >= 0:
            k = left[k] if x[feature[k]] < cut[k] else right[k]
        total += depth[k]
    return 2 ** (-total / len(forest.trees) / float(quality.mean_path(forest.size)))


def test_verdicts_against_brute_force(spark, sf):
    """Scores by walking trees, the limit by trying every bin, on the given tables."""
    docs, lab = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    stats = quality.rule_statistics(docs)
    forest = quality.fit_forest(stats, lab)
    good = {r["doc_id"]: r["quality"] > 0 for r in lab.collect()}
    rows = [r for r in stats.collect() if not r["base_failed"]]
    score = {r["doc_id"]: brute_score(forest, [r[f] for f in quality.FEATURES]) for r in rows}
    best = []
    for k in range(quality.BINS + 1):
        kept = [score[d] < (k + 1) / quality.BINS for d, g in good.items() if g and d in score]
        caught = [score[d] >= (k + 1) / quality.BINS for d, g in good.items() if not g and d in score]
        if np.mean(kept) >= min(quality.GOOD_KEPT, 1 - 1 / len(kept)) - 1e-12:
            best.append((np.mean(caught), k))
    top = [k for c, k in best if c == max(best)[0]]
    limit = (top[0] + top[-1] + 2) / 2 / quality.BINS
    got = {r["doc_id"]: r["kept"] for r in quality.judge_quality(docs, lab).collect()}
    assert all(abs(score[d] - limit) < 1e-9 or got[d] == (score[d] < limit) for d in score)
    assert not any(got[d] for d in got if d not in score)


def test_held_out_accuracy(spark):
    """Limits from every other labelled row: the rest is judged as labelled."""
    docs, lab = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    got = {r["doc_id"]: r for r in quality.judge_quality(docs, lab.where("doc_id % 2 = 0"), min_words=0).collect()}
    rest = lab.where("doc_id % 2 = 1").collect()
    assert np.mean([got[r["doc_id"]]["kept"] for r in rest if r["quality"]]) >= 0.99
    assert np.mean([not got[r["doc_id"]]["kept"] for r in rest if not r["quality"]]) >= 0.95


def test_path_length():
    assert float(quality.mean_path(2)) == 1.0 and float(quality.mean_path(1)) == 0.0
    assert abs(float(quality.mean_path(256)) - 10.24) < 0.05


def test_forest_is_deterministic():
    x = np.random.default_rng(0).normal(size=(500, 3))
    assert np.array_equal(quality.IsolationForest(x).score(x), quality.IsolationForest(x).score(x))
    x[0] = 25
    s = quality.IsolationForest(x).score(x)
    assert s.argmax() == 0
