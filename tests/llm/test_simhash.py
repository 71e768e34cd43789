import re

import numpy as np
import pytest
import xxhash

from relstrata.llm import simhash
from relstrata.llm.components import components


def brute_fp(text, width=3):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not w:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(w[i : i + width]).encode(), 42) for i in range(max(1, len(w) - width + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(fps):
    """fps: (id, fp) with ids; class of each row by union of all pairs within three bits."""
    parent = list(range(len(fps)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if bin(fps[i][1] ^ fps[j][1]).count("1") <= 3:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    low = {}
    for i, (d, _) in enumerate(fps):
        if d is not None:
            low[find(i)] = min(d, low.get(find(i), d))
    return [low.get(find(i)) for i in range(len(fps))]


@pytest.mark.parametrize("name", ["docs", "odd_docs"])
def test_against_all_pairs(name, request):
    df = request.getfixturevalue(name)
    rows = [(r["doc_id"], brute_fp(r["text"])) for r in df.collect()]
    want = sorted(((d, f"{f:016x}", c) for (d, f), c in zip(rows, brute_components(rows), strict=True)), key=str)
    got = sorted(((r["doc_id"], r["fingerprint"], r["component_id"]) for r in simhash.near_duplicates(df).collect()), key=str)
    assert got == want


def test_empty(no_docs):
    assert simhash.near_duplicates(no_docs).count() == 0
    assert simhash.dedup(no_docs).count() == 0


def test_every_key_family_meets_every_near_pair():
    rng = np.random.default_rng(0)
    for _ in range(500):
        a = rng.integers(0, 2**63, dtype=np.uint64)
        b = a ^ np.uint64(sum(1 << int(x) for x in rng.choice(64, 3, replace=False)))
        assert simhash.shared_bytes(np.array([a]), np.array([b]))[0] >= simhash.MIN_SHARED
        by = [(int(a) >> 8 * p & 255, int(b) >> 8 * p & 255) for p in range(8)]
        assert any(all(by[p][0] == by[p][1] for p in pos) for pos in simhash.KEYS)


def near_prints(n):
    rng = np.random.default_rng(1)
    c = rng.integers(0, 2**63, dtype=np.uint64)
    return np.unique(np.array([c ^ np.uint64(sum(1 << int(x) for x in rng.choice(40, int(rng.integers(1, 9)), replace=False))) for _ in range(n)], np.uint64))


def test_blocks_link_like_pairs(monkeypatch):
    fps = near_prints(1200)
    monkeypatch.setattr(simhash, "ROWS_AT_ONCE", 100)
    monkeypatch.setattr(simhash, "COLUMNS_AT_ONCE", 330)
    assert len(simhash.posting_links(fps)) == len(fps) - _classes(fps)


@pytest.mark.parametrize("small", [10, 100_000])
def test_postings_that_are_split(spark, small, monkeypatch):
    monkeypatch.setattr(simhash, "SMALL", small)
    fps = near_prints(600)
    df = spark.createDataFrame(list(zip(fps.view(np.int64).tolist(), range(len(fps)), strict=True)), "fp long, rep long")
    links = simhash.fingerprint_links(df).collect()
    assert all(bin(int(fps[a] ^ fps[b])).count("1") <= 3 for a, b in links)
    parent = list(range(len(fps)))
    for a, b in links:
        old, new = parent[a], parent[b]
        parent = [new if x == old else x for x in parent]
    assert len(set(parent)) == _classes(fps)


def _classes(fps):
    left = set(range(len(fps)))
    n = 0
    while left:
        todo = [left.pop()]
        n += 1
        while todo:
            i = todo.pop()
            near = [j for j in np.flatnonzero(np.bitwise_count(fps ^ fps[i]) <= 3).tolist() if j in left]
            left.difference_update(near)
            todo += near
    return n


def test_components_of_a_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (7, 7), (None, 3)], "a long, b long")
    got = {r["node"]: r["component"] for r in components(edges).collect()}
    assert got == {**dict.fromkeys(range(41), 0), 100: 100, 101: 100}


def test_dedup_keeps_one(odd_docs):
    kept = simhash.dedup(odd_docs).collect()
    ids = [r["doc_id"] for r in kept if r["doc_id"] is not None]
    assert len(ids) == len(set(ids)) and sum(r["doc_id"] is None for r in kept) == 2
