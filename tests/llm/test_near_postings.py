import numpy as np
import pyarrow as pa
import pytest

from relstrata.llm import near_copies as nc


def plain_simhash(hashes):
    """Bit by bit, one hash after another."""
    ones = np.zeros(8 * nc.BYTES, int)
    for h in hashes.tolist():
        z = [h * int(m) % 2**64 for m in nc._multipliers(nc.BYTES // 8, nc.SEED)]
        ones += [(x ^ x >> 32) >> j & 1 for x in z for j in range(64)]
    return [sum(int(2 * ones[8 * p + j] > len(hashes)) << j for j in range(8)) for p in range(nc.BYTES)]


def test_fingerprints_are_simhashes():
    rng = np.random.default_rng(3)
    sets = [np.unique(rng.integers(0, 2**64 - 1, n, dtype=np.uint64)) for n in (1, 2, 30, 31, 32, 63, 200)]
    sets.append(np.unique(rng.integers(0, 2**64 - 1, 31 * 260, dtype=np.uint64)))  # more than one stretch
    assert nc.fingerprints(sets).tolist() == [plain_simhash(s) for s in sets]
    assert nc.fingerprints(sets[::-1])[::-1].tolist() == nc.fingerprints(sets).tolist()


@pytest.mark.parametrize("n,shared", [(4, 4), (18, 16), (400, 356)])
def test_bytes_agree_as_often_as_the_bound_says(n, shared):
    """Sets of similarity 0.8: a byte agrees with probability 0.27, also in small sets."""
    rng = np.random.default_rng(4)
    left, right = [], []
    for _ in range(100):
        h = rng.integers(0, 2**64 - 1, 2 * n - shared + (n == 4), dtype=np.uint64)
        a, b = h[:n], h[len(h) - n - (n == 4) :]
        left.append(nc.spread(a) if n <= nc.FINE else a)
        right.append(nc.spread(b) if n <= nc.FINE else b)
    assert (nc.fingerprints(left) == nc.fingerprints(right)).mean() > 0.255


def posting_rows(rng, size):
    cols = [np.sort(rng.integers(0, 12, size)), np.arange(size), rng.integers(60, 140, size).astype(np.int32)]
    cols += [rng.integers(0, 5, (size, 8), dtype=np.uint8).view(np.int64)[:, 0] for _ in range(2)]
    return cols


def batches_of(cols, names, step):
    for at in range(0, len(cols[0]), step):
        yield pa.RecordBatch.from_arrays([pa.array(c[at : at + step]) for c in cols], names)


def wanted(k, node, n, w0, w1):
    out = set()
    for i in range(len(k)):
        for j in range(i):
            same = sum(int(x[i]).to_bytes(8, "little", signed=True)[p] == int(x[j]).to_bytes(8, "little", signed=True)[p] for x in (w0, w1) for p in range(8))
            if k[i] == k[j] and 5 * min(n[i], n[j]) >= 4 * max(n[i], n[j]) and same >= nc.MIN_SHARED:
                out.add((int(node[j]), int(node[i])))
    return out


@pytest.mark.parametrize("hot", [2, 9, 10**6])
@pytest.mark.parametrize("step", [1, 7, 1000])
def test_every_pair_of_a_posting_is_met(hot, step):
    """In small postings at once; in large ones by the first member or between groups, here each member its own."""
    cols = posting_rows(np.random.default_rng(hot), 130)
    met = pa.Table.from_batches(nc._meeting(hot)(batches_of(cols, ["k", "node", "n", "w0", "w1"], step))).to_pylist()
    pairs = {(r["a"], r["b"]) for r in met if r["b"] is not None}
    want = wanted(*cols)
    assert want and pairs <= want
    members = [r for r in met if r["b"] is None]
    assert bool(members) == (hot < 100)
    if members:
        rest = [np.array([r[c] for r in members]) for c in ("k", "a", "n", "w0", "w1", "a")]
        rest[2] = rest[2].astype(np.int32)
        across = nc._across(batches_of(rest, ["k", "a", "n", "w0", "w1", "c"], step))
        pairs |= {(r["a"], r["b"]) for b in across for r in b.to_pylist()}
    assert pairs == want
