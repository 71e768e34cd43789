import hashlib

import numpy as np
import pyarrow as pa
import pytest

from relstrata.llm import induced_sort, suffix_dedup


def brute(rows, length=50):
    """rows: (row number, doc_id or None, text)."""
    low = {}
    key = lambda d: -(2**70) if d is None else d
    for _, d, t in rows:
        raw = (t or "").encode()
        for i in range(len(raw) - length + 1):
            w = raw[i : i + length]
            low[w] = min(low.get(w, key(d)), key(d))
    out = []
    for _, d, t in rows:
        raw = (t or "").encode()
        gone = np.zeros(len(raw), bool)
        for i in range(len(raw) - length + 1):
            if low[raw[i : i + length]] < key(d):
                gone[i : i + length] = True
        spans = int((gone & ~np.concatenate(([False], gone[:-1]))).sum()) if len(raw) else 0
        kept = bytes(b for b, g in zip(raw, gone, strict=True) if not g)
        out.append((d, len(raw), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def found(df):
    cols = ("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
    return sorted((tuple(r[c] for c in cols) for r in suffix_dedup.dedup_substrings(df).collect()), key=str)


@pytest.mark.parametrize("name", ["docs", "odd_docs"])
def test_against_brute_force(name, request):
    df = request.getfixturevalue(name)
    rows = [(0, r["doc_id"], r["text"]) for r in df.collect()]
    if name == "docs":
        rows = [r for r in rows if r[2] is None or len(r[2]) < 5000]
        df = df.where("text is null or length(text) < 5000")
    assert found(df) == brute(rows)


def test_repeats_and_runs(spark):
    rng = np.random.default_rng(2)
    a = "".join(rng.choice(list("abc"), 300))
    texts = [a, "=" * 120, "-" + "=" * 200 + "-", a[40:120] + "x" + a[100:180], "é" * 60, "q" + "é" * 40, a[:49], "\x00" * 80, "\x00" * 90, a[10:90] * 3]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert found(df) == brute([(0, d, t) for d, t in enumerate(texts)])


def test_texts_longer_than_a_buffer(spark):
    rng = np.random.default_rng(3)
    long = "".join(rng.choice(list("abcdefgh "), suffix_dedup.CHUNK + 5000))
    cut = suffix_dedup.CHUNK
    df = spark.createDataFrame([(0, long[cut - 300 : cut + 300]), (1, long), (2, long[-200:])], "doc_id long, text string")
    got = {r[0]: r for r in found(df)}
    assert got[1][2] == 600 and got[1][3] == 1 and got[2][2] == 200


def test_empty(no_docs):
    assert found(no_docs) == []


def common(a, b, depth):
    k = 0
    while k < min(len(a), len(b), depth) and a[k] == b[k]:
        k += 1
    return k


#: (names a range, records a block, names that end the recursion): small ones make every path run.
SIZES = [(1 << 15, 1 << 17, 1 << 19), (2, 16, 0), (5, 64, 20), (3, 1000, 0)]


@pytest.mark.parametrize("memory", [0, 1 << 30])
@pytest.mark.parametrize("names,block,small", SIZES)
def test_suffix_order_and_prefixes(names, block, small, memory, monkeypatch):
    for name, x in (("RANGE", names), ("BLOCK", block), ("SMALL", small)):
        monkeypatch.setattr(induced_sort, name, x)
    rng = np.random.default_rng(4)
    cases = [rng.integers(1, 1 + rng.integers(1, 6), rng.integers(0, 300)) for _ in range(60)]
    cases += [np.tile([3, 3, 1, 2], 100), np.full(200, 7), np.tile(np.arange(1, 90), 6)]
    for t in cases:
        t = np.append(t, 0).astype(np.uint8)
        raw = t.tobytes()
        places, prefixes = induced_sort.suffix_order(t, 64, memory)
        want = sorted(range(len(raw)), key=lambda i: raw[i:])
        assert places.tolist() == want
        assert prefixes.tolist() == [0] + [common(raw[a:], raw[b:], 64) for a, b in zip(want, want[1:], strict=False)]


def test_queues_spill_and_keep_order():
    q = induced_sort.RangeQueue(np.array([0, 10, 20]), limit=100, block=4)
    for k in range(50):
        t = np.zeros(3, induced_sort.TUPLE)
        t["symbol"], t["place"] = (3, 15, 3), (3 * k, 3 * k + 1, 3 * k + 2)
        q.put(t)
    assert q.file is not None
    assert q.take_all(0)["place"].tolist() == [x for x in range(150) if x % 3 != 1] and q.take(0) is None
    assert q.take_all(1)["place"].tolist() == list(range(1, 150, 3)) and not len(q.take_all(2))
    q.close()


def test_runs_merge():
    runs = induced_sort.Runs(block=100)
    rng = np.random.default_rng(1)
    key = rng.integers(0, 50, 5000).astype(np.uint64)
    for a in range(0, 5000, 37):
        runs.add(key[a : a + 37], np.arange(a, min(a + 37, 5000)))
    got = list(runs)
    assert np.array_equal(np.concatenate([k for k, _ in got]), np.sort(key))
    assert np.array_equal(key[np.concatenate([v for _, v in got])], np.sort(key))


def shard_rows(texts, per=1):
    """Batches as a shard reads them: whole texts of 50 to 84 bytes with an anchor in the middle."""
    out = [(1, d, 0, (d << 12) | (t.index(b"ANCHORANCHORABCD") << 6) | (len(t) - 49), t) for d, t in enumerate(texts)]
    for a in range(0, len(out), per):
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out[a : a + per], strict=True), [pa.int64()] * 4 + [pa.binary()], strict=True)], suffix_dedup.TEXTS)


def brute_shard(texts):
    low = {}
    for d, t in enumerate(texts):
        for i in range(len(t) - 49):
            low.setdefault(t[i : i + 50], d)
    return sorted((d, i) for d, t in enumerate(texts) for i in range(len(t) - 49) if low[t[i : i + 50]] < d)


@pytest.mark.parametrize("memory", [1 << 26, 1 << 12])
def test_a_shard_many_times_the_memory(memory, monkeypatch):
    monkeypatch.setattr(induced_sort, "SMALL", 50)
    rng = np.random.default_rng(6)
    half = lambda n: rng.choice(list(b"ab"), 6).astype(np.uint8).tobytes() + b"x" * (n - 6)
    texts = [half(int(rng.integers(17, 35))) + b"ANCHORANCHORABCD" + half(int(rng.integers(17, 35))) for _ in range(1500)]
    got = []
    for b in suffix_dedup._shard_stream(shard_rows(texts, 100), memory):
        for d, place in zip(b.column(0).to_pylist(), b.column(2).to_pylist(), strict=True):
            got += [(d, (place >> 12) - d + k) for k in range(place & 63)]
    assert sorted(got) == brute_shard(texts) and sum(map(len, texts)) > 20 * (1 << 12)


def test_frequent_anchors_in_pieces(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "SHARD", 500)
    rng = np.random.default_rng(8)
    side = lambda n: "".join(rng.choice(list("abc"), n))
    middles = [side(40), side(25), side(18)]
    rows = []
    for d in range(150):
        m = middles[d % 3]
        rows.append((d, side(int(rng.integers(0, 9))) + "tail of words " * (d % 2) + m + "next words are " * (d % 4 > 1) + side(int(rng.integers(0, 9)))))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    assert found(df) == brute([(0, d, t) for d, t in rows])


def test_many_null_ids(spark, corpus):
    rows = [(None, t) for t in corpus[:8]] + [(1, t) for t in corpus[:8]] + [(1, corpus[0] + "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert found(df) == brute([(0, *r) for r in rows])


def test_equal_stretches_are_sorted_once(monkeypatch):
    """Copies of a passage in one shard: the smallest document's is sorted, twins of that document share its fate."""
    rng = np.random.default_rng(12)
    word = lambda n: bytes(rng.integers(97, 123, n, np.uint8))
    passage = word(64)
    part = passage[:55]
    # (doc, part, bytes): the passage often, twice in document 3; a longer stretch of document 2 holds its first six windows.
    rows = [(d, k, passage) for k, d in enumerate([9, 3, 7, 3, *range(20, 120)])] + [(2, 500, part + word(9)), (4, 501, part + word(9))]
    m = len(rows)
    place = [(100 * k) << suffix_dedup.START_BIT | 14 << suffix_dedup.TO_BIT | len(raw) - 49 for k, (_, _, raw) in enumerate(rows)]
    cols = [pa.array([1] * m), pa.array([r[0] for r in rows]), pa.array([r[1] for r in rows]), pa.array(place), pa.array([r[2] for r in rows], pa.binary())]
    sizes = []
    whole = suffix_dedup.suffix_blocks
    monkeypatch.setattr(suffix_dedup, "suffix_blocks", lambda text, n, *rest: (sizes.append(n), whole(text, n, *rest)))
    got = set()
    for b in suffix_dedup._shard_stream(iter([pa.RecordBatch.from_arrays(cols, suffix_dedup.TEXTS)])):
        for d, p, x in zip(*(c.to_pylist() for c in b.columns), strict=True):
            start, n = x >> suffix_dedup.START_BIT, x & suffix_dedup.LOW
            new = {(d, p, w) for w in range(start, start + n)}
            assert not new & got
            got |= new
    low = {}
    for d, _, raw in rows:
        for i in range(len(raw) - 49):
            low[raw[i : i + 50]] = min(d, low.get(raw[i : i + 50], d))
    want = {(d, p, 100 * k + i) for k, (d, p, raw) in enumerate(rows) for i in range(len(raw) - 49) if low[raw[i : i + 50]] < d}
    assert got == want and {p for d, p, _ in got if d == 3} == {1, 3}
    assert sizes and sizes[0] < 5 * len(passage)
