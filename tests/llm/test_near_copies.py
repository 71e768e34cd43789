import random

import corpus_pipeline
import numpy as np
import pytest
from relstrata.llm import near_copies, simhash
from relstrata.llm.common import load

from .conftest import sentence


def brute_set(text):
    w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))}


def brute_classes(rows):
    """rows: (id, text) with ids; the smallest id of each row's component over all pairs of 0.8 or more."""
    sets = [brute_set(t) for _, t in rows]
    label = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            k = len(sets[i] & sets[j])
            if 5 * k >= 4 * (len(sets[i]) + len(sets[j]) - k):
                old, new = label[i], label[j]
                label = [new if x == old else x for x in label]
    return [min(r[0] for r, m in zip(rows, label, strict=True) if m == x) for x in label]


def edited():
    """Texts of 120 words with one to four words changed: similarities around 0.8."""
    rng = random.Random(11)
    out = []
    for _ in range(6):
        base = sentence(rng, 120).split(" ")
        out.append(" ".join(base))
        for n in (1, 2, 3, 4):
            w = list(base)
            for at in rng.sample(range(len(w)), n):
                w[at] = f"new{at}"
            out.append(" ".join(w))
    return list(enumerate(out))


def test_pipeline_stage_against_all_pairs(spark, sf):
    rows = edited()
    df = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    want = {d for (d, _), c in zip(rows, brute_classes(rows), strict=True) if c == d}
    assert {r["doc_id"] for r in corpus_pipeline.near_dedup(spark, df, sf).collect()} == want
    assert {r["doc_id"] for r in simhash.dedup(df).collect()} != want


@pytest.mark.parametrize("name", ["docs", "odd_docs"])
def test_against_all_pairs(name, request):
    df = request.getfixturevalue(name)
    rows = [(r["doc_id"], r["text"]) for r in df.collect()]
    with_id = [r for r in rows if r[0] is not None]
    got = sorted(tuple(r) for r in near_copies.near_copies(df).where("doc_id is not null").drop("text_key").collect())
    assert got == sorted((d, c) for (d, _), c in zip(with_id, brute_classes(with_id), strict=True))
    assert near_copies.near_copies(df).count() == df.count()


def test_given_table(spark, sf):
    df = load(spark, sf, "documents")
    rows = [(r["doc_id"], r["text"]) for r in df.collect()]
    assert sorted(tuple(r) for r in near_copies.near_copies(df).drop("text_key").collect()) == sorted((d, c) for (d, _), c in zip(rows, brute_classes(rows), strict=True))


def test_links_connect_what_pairs_connect():
    rng = np.random.default_rng(2)
    base = np.arange(100, dtype=np.uint64)
    sets = [np.unique(np.concatenate([rng.choice(base, 92, replace=False), rng.integers(1000, 10**6, 4).astype(np.uint64)])) for _ in range(60)]
    rows = [(i, s) for i, s in enumerate(sets)]
    near = {(i, j) for i, a in rows for j, b in rows[:i] if 5 * len(np.intersect1d(a, b)) >= 4 * len(np.union1d(a, b))}
    assert set(near_copies.near_links(sets)) <= near and len(near) > len(near_copies.near_links(sets)) > 0


def test_empty(no_docs):
    assert near_copies.dedup(no_docs).count() == 0
