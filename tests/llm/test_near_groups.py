import numpy as np
import pytest
from relstrata.llm import near_copies as nc


def near_family(rng, m, size, changed):
    """Sets near one base: each has other elements in some places."""
    base = rng.integers(0, 2**64 - 1, size, dtype=np.uint64)
    sets = []
    for _ in range(m):
        s = base.copy()
        s[rng.choice(size, changed, replace=False)] = rng.integers(0, 2**64 - 1, changed, dtype=np.uint64)
        sets.append(np.unique(s))
    return sets


def packed(spark, sets, blocks):
    """What a table of fingerprints becomes in segments, by segment and pair of blocks."""
    rows = [(i * 7, len(s), fp.tobytes(), None) for i, (s, fp) in enumerate(zip(sets, nc.fingerprints(sets), strict=True))]
    return nc.segments(spark.createDataFrame(rows, "node long, n int, plain binary, fine binary"), blocks)


def linked(pairs):
    label = {}
    for a, b in pairs:
        for x in (a, b):
            label.setdefault(x, x)
        old, new = label[a], label[b]
        label = {k: new if v == old else v for k, v in label.items()}
    return label


@pytest.mark.parametrize("blocks", [1, 3])
@pytest.mark.parametrize("hot", [4, 256])
def test_links_of_a_segment_grow_with_its_members(spark, blocks, hot):
    """A segment gives one link less than a group's members at most, not one a pair, and no near pair falls apart."""
    rng = np.random.default_rng(blocks)
    families = [near_family(rng, m, 200, 8) for m in (150, 2, 1)]
    sets = [s for f in families for s in f]
    rows = packed(spark, sets, blocks)
    by = ["family", "segment", "pair"]
    met = rows.repartition(*by).sortWithinPartitions(*by).mapInArrow(nc._segment_stream(hot), "a long, b long").collect()
    tasks = rows.select(*by).distinct().count()
    assert tasks == nc.BYTES // nc.SEGMENT * (3 if blocks == 3 else 1)
    assert len(met) <= tasks * (len(sets) - 1)
    label = linked(tuple(r) for r in met)
    where = [label.get(i * 7) for i in range(len(sets))]
    assert len(set(where[:150])) == 1 and len(set(where[150:152])) == 1
    assert where[0] != where[150] and where[152] is None


def test_links_of_all_groups_connect_what_pairs_connect():
    """Chains, and groups whose members are all just too different: exactly the classes of all pairs."""
    rng = np.random.default_rng(9)
    for changed in (5, 11, 12, 13, 40):
        sets = [s for m in (9, 14, 1) for s in near_family(rng, m, 100, changed)]
        near = [(i, j) for i, a in enumerate(sets) for j, b in enumerate(sets[:i]) if 5 * len(np.intersect1d(a, b)) >= 4 * len(np.union1d(a, b))]
        links = nc.near_links(sets)
        assert set(links) <= set(near)
        assert len(links) < len(sets)

        def classes(pairs):
            label = list(range(len(sets)))
            for i, j in pairs:
                old, new = max(label[i], label[j]), min(label[i], label[j])
                label = [new if x == old else x for x in label]
            return label

        assert classes(links) == classes(near)


def test_parts_of_a_large_group_meet(spark, docs, monkeypatch):
    want = sorted(tuple(r) for r in nc.near_copies(docs).collect())
    monkeypatch.setattr(nc, "MEMBERS", 2)
    monkeypatch.setattr(nc, "BLOCK", 9)
    assert sorted(tuple(r) for r in nc.near_copies(docs).collect()) == want
