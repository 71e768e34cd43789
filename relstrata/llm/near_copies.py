"""Near-copy groups of the pipeline: SimHash postings by positional bytes, verified by shingle sets.

Two texts are near if the Jaccard similarity of their sets of five-word shingles is
MIN_SIMILARITY or more. A text's fingerprint is the SimHash of its set in BYTES positional
bytes: at a similarity of 0.8 a bit differs with probability 0.1515 at most, so a byte agrees
with probability 0.27 and no number of shared bytes is certain. Each two neighbouring bytes, in a ring,
make a posting key; beside it lie the next TALLIED bytes. In a posting the shared ones of those
are tallied, and a pair with MIN_SHARED or more (and of sizes that allow 0.8) is a candidate. A pair
of 0.8 is one in no posting with probability 1.5e-7 (computed over the ring cut open, for independent
bits), less above. Sets of FINE shingles at most have a second fingerprint of SPREAD hashes a shingle, as sums of few bits tie too often.

Postings travel by segments: SEGMENT keys that follow each other and the bytes after them, WIDTH in all, once for
each text. A segment's candidates that differ in more than MOST_BITS of its bits are dropped (at 0.8: with
probability 4e-6 in each segment); the others join groups, and a link to each group's first member leaves the segment, never its pairs.
Groups joined over all segments are verified: exact intersections link what is near, no estimate does, and at most
one link less than its members leaves a group. Groups of more than MEMBERS texts are verified part against part.

Defined results: copies (equal words) fold before anything is posted; texts of fewer than
WORDS words have one shingle, the whole text; null and empty texts are copies of each
other; rows without doc_id get a component but never name one; repeated rows stay; an
empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import MAX_BROADCAST, column, keyed, slices, text_key, written
from .components import components
from .simhash import keep_first

WORDS, MIN_SIMILARITY, SEED = 5, 0.8, 42
#: Bytes of a fingerprint; bytes tallied in a posting, and how many of them a candidate shares.
BYTES, TALLIED, MIN_SHARED = 288, 16, 2
#: Sets up to this size have a spread fingerprint; those from FINE * MIN_SIMILARITY on the plain one.
FINE, SPREAD = 20, 16
#: Members of a posting that are all compared; pairs that are looked at together.
HOT, AT_ONCE = 256, 1 << 17
#: Keys of a segment and its bytes; bits of them in which a candidate differs, at most.
SEGMENT = 16
WIDTH, MOST_BITS = SEGMENT + 1 + TALLIED, 66
ROW = np.dtype([("node", "<i8"), ("n", "<i4"), ("bytes", "u1", (WIDTH,))])
#: Texts of a block, of which one or two meet in a task, and members of a group that are verified together.
BLOCK, MEMBERS = 1_000_000, 10_000
#: Hashes whose bits are summed 64 at a time, a power of two less one; such groups worked on at once.
SUMMED = 31
IN_CACHE = 4096
_BYTE_ONES = np.uint64(0x0101010101010101)
#: Similarity in whole numbers: near if DEN * shared >= NUM * united.
NUM, DEN = 4, 5


def shingles(words: list[bytes], width: int = WORDS) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the runs of ``width`` words."""
    import xxhash

    n = max(1, len(words) - width + 1)
    digest = xxhash.xxh64_intdigest
    return np.unique(np.fromiter((digest(b" ".join(words[i : i + width]), SEED) for i in range(n)), np.uint64, n))


def split_words(text: str | None) -> list[bytes]:
    return (text or "").encode().lower().split()  # as in simhash: ASCII case and white space only


def _multipliers(n: int, seed: int) -> np.ndarray:
    """Odd ones: each makes other bits of a 64-bit hash."""
    return np.random.default_rng(seed).integers(0, 2**63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def _add(a: np.ndarray, b: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sum and carry of three bits, 64 at a time."""
    u = a ^ b
    total = u ^ c
    u &= c
    carry = a & b
    carry |= u
    return total, carry


def _planes(rows: np.ndarray) -> list[np.ndarray]:
    """Bitwise sums of SUMMED rows, by binary places."""
    out = []
    layer = list(rows)
    while layer:
        total, carries = layer[0], []
        for i in range(1, len(layer), 2):
            total, carry = _add(total, layer[i], layer[i + 1])
            carries.append(carry)
        out.append(total)
        layer = carries
    return out


def fingerprints(sets: list[np.ndarray]) -> np.ndarray:
    """SimHash of each set of 64-bit hashes, BYTES wide; a bit is 1 if set in over half of them."""
    size = np.array([len(s) for s in sets])
    groups = -(-size // SUMMED)
    flat = np.zeros(int(groups.sum()) * SUMMED, np.uint64)  # a hash of zero adds no bit
    for at, s in zip((np.cumsum(groups) - groups) * SUMMED, sets, strict=True):
        flat[at : at + len(s)] = s
    # Stretches of one set, of 255 groups at most: counts of a place fit a byte.
    owner, length = [], []
    for d, g in enumerate(groups.tolist()):
        for at in range(0, g, 255):
            owner.append(d)
            length.append(min(255, g - at))
    owner_, ends = np.array(owner), np.cumsum(length)
    counts = np.zeros((len(sets), BYTES, 8), np.int64)
    places = SUMMED.bit_length()
    shift = [np.uint64(j) for j in range(8)]
    lo = 0
    while lo < len(owner):
        before = int(ends[lo - 1]) if lo else 0
        hi = max(lo + 1, int(np.searchsorted(ends, before + IN_CACHE, side="right")))
        rows = flat[SUMMED * before : SUMMED * int(ends[hi - 1])].reshape(-1, SUMMED).T.copy()
        starts = ends[lo:hi] - np.array(length[lo:hi]) - before
        firsts = np.flatnonzero(np.diff(owner_[lo:hi], prepend=-1))
        z, high, bits = np.empty_like(rows), np.empty_like(rows), np.empty_like(rows[0])
        sums = np.empty((places, 8, hi - lo), np.uint64)
        for k, m in enumerate(_multipliers(BYTES // 8, SEED)):
            np.multiply(rows, m, out=z)
            np.right_shift(z, np.uint64(32), out=high)
            np.bitwise_xor(z, high, out=z)
            for of_place, plane in zip(sums, _planes(z), strict=True):
                for j, out in zip(shift, of_place, strict=True):
                    np.right_shift(plane, j, out=bits)
                    np.bitwise_and(bits, _BYTE_ONES, out=bits)
                    np.add.reduceat(bits, starts, out=out)
            tally = sums.astype("<u8").view(np.uint8).reshape(places, 8, hi - lo, 8)
            total = sum(t.astype(np.int64) << place for place, t in enumerate(tally))  # by bit, stretch, byte
            counts[owner_[lo:hi][firsts], 8 * k : 8 * k + 8] += np.add.reduceat(total.transpose(1, 2, 0), firsts)
        lo = hi
    return np.packbits(2 * counts > size[:, None, None], axis=2, bitorder="little")[:, :, 0]


def spread(hashes: np.ndarray) -> np.ndarray:
    """SPREAD hashes for each: sums of their bits tie far less often."""
    return ((hashes ^ (hashes >> np.uint64(29)))[:, None] * _multipliers(SPREAD, SEED + 1)).ravel()


def sketches(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_key, x, y, n, plain, fine) per row of ``docs``: 128 bits of the words, size of the set, fingerprints."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for b in slices(batches, 100):
            whole, sets = [], []
            for t in column(b, "text").to_pylist():
                words = split_words(t)
                whole.append(xxhash.xxh3_128_digest(b" ".join(words)))
                sets.append(shingles(words))
            xy = np.frombuffer(b"".join(whole), np.int64).reshape(-1, 2)
            n = np.array([len(s) for s in sets], np.int32)
            prints = []
            for on, made in ((DEN * n >= NUM * FINE, lambda s: s), (n <= FINE, spread)):
                of = np.flatnonzero(on).tolist()
                got: list[bytes | None] = [None] * len(n)
                for i, fp in zip(of, fingerprints([made(sets[i]) for i in of]) if of else [], strict=True):
                    got[i] = fp.tobytes()
                prints.append(pa.array(got, pa.binary()))
            yield pa.RecordBatch.from_arrays(
                [column(b, "doc_id"), column(b, "text_key"), pa.array(xy[:, 0].copy()), pa.array(xy[:, 1].copy()), pa.array(n), *prints],
                ["doc_id", "text_key", "x", "y", "n", "plain", "fine"],
            )

    schema = "doc_id long, text_key long, x long, y long, n int, plain binary, fine binary"
    return keyed(docs, id_col, text_col).withColumn("text_key", text_key()).mapInArrow(run, schema)


def near_links(sets: list[np.ndarray]) -> list[tuple[int, int]]:
    """Index pairs that connect all sets of MIN_SIMILARITY or more, by exact intersections.

    A set is compared with all others unless it is in the largest group when its turn comes: of a pair
    from two groups one is outside that.
    """
    m = len(sets)
    size = np.array([len(s) for s in sets])
    ends = np.cumsum(size)
    _, inverse = np.unique(np.concatenate(sets), return_inverse=True)
    # Members of each shingle, in rising order, in one array.
    order = np.argsort(inverse, kind="stable")
    member = np.repeat(np.arange(m), size)[order]
    first = np.searchsorted(inverse[order], np.arange(inverse.max() + 1))
    count = np.diff(np.append(first, len(member)))
    group = np.arange(m)
    links: list[tuple[int, int]] = []
    left = np.ones(m, bool)
    largest = m - 1
    while (left & (group != largest)).any():
        i = int(np.argmax(left & (group != largest)))
        left[i] = False
        mine = inverse[ends[i] - size[i] : ends[i]]
        n = count[mine]
        at = np.repeat(first[mine] - np.cumsum(n) + n, n) + np.arange(n.sum())
        shared = np.bincount(member[at], minlength=m)
        near = np.flatnonzero(DEN * shared >= NUM * (size + size[i] - shared))
        near = near[group[near] != group[i]]
        if len(near):
            others, where = np.unique(group[near], return_index=True)
            links += [(max(i, j), min(i, j)) for j in near[where].tolist()]
            group[np.isin(group, others)] = group[i]
            largest = int(np.bincount(group).argmax())
    return links


def segments(prints: DataFrame, blocks: int) -> DataFrame:
    """(family, segment, pair, packed) out of (node, n, plain, fine): stretches of the ring of SEGMENT keys and the bytes after them.

    ``packed`` holds many members of one block, ROW each. Of ``blocks`` blocks each two (or the one) meet under a number of their own.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 4096):
            for family, name in enumerate(("plain", "fine")):
                of = column(b, name).is_valid()
                node, n, fp = (column(b, c).filter(of) for c in ("node", "n", name))
                if not len(fp):
                    continue
                ring = np.frombuffer(b"".join(fp.to_pylist()), np.uint8).reshape(len(fp), BYTES)
                ring = np.concatenate([ring, ring[:, : TALLIED + 1]], axis=1)
                rows = np.zeros(len(fp), ROW)
                rows["node"], rows["n"] = node.to_numpy(), n.to_numpy()
                block = block_of(rows["node"], blocks)
                for mine in range(blocks):
                    members = np.flatnonzero(block == mine)
                    if not len(members):
                        continue
                    part = rows[members]
                    packed = []
                    for at in range(0, BYTES, SEGMENT):
                        part["bytes"] = ring[members, at : at + WIDTH]
                        packed.append(part.tobytes())
                    for other in range(blocks):
                        if blocks > 1 and other == mine:
                            continue
                        pair = min(mine, other) * blocks + max(mine, other)
                        m = len(packed)
                        cols = [pa.array([family] * m, pa.int32()), pa.array(range(m), pa.int32()), pa.array([pair] * m, pa.int32()), pa.array(packed, pa.binary())]
                        yield pa.RecordBatch.from_arrays(cols, ["family", "segment", "pair", "packed"])

    return prints.mapInArrow(run, "family int, segment int, pair int, packed binary")


def block_of(node: np.ndarray, blocks: int) -> np.ndarray:
    """One of ``blocks`` for each node, by high bits of a product: nodes are no random numbers."""
    return ((node.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)) % np.uint64(blocks)


def _candidates(n: list[np.ndarray], w0: list[np.ndarray], w1: list[np.ndarray]) -> np.ndarray:
    """Which pairs may be near by their sizes and share MIN_SHARED of the tallied bytes."""
    small, large = np.minimum(*n), np.maximum(*n)
    fit = np.flatnonzero(DEN * small >= NUM * large)
    same = sum((((x[fit] ^ y[fit]).view(np.uint8) == 0).reshape(-1, 8).sum(1) for x, y in (w0, w1)), np.zeros(len(fit), np.int64))
    return fit[same >= MIN_SHARED]


#: Candidates (a < b), and members of large postings (b null).
MET = "a long, b long, k long, n int, w0 long, w1 long"


def _meeting(hot: int):
    """Postings out of rows sorted by key: all pairs of a small one; of a large one the first member's, and its members."""

    def rows(a: np.ndarray, b: np.ndarray | None, rest: list[np.ndarray] | None) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64())
        others = [pa.array(c) for c in rest] if rest else [pa.nulls(len(a), t) for t in kinds]
        return pa.RecordBatch.from_arrays([pa.array(a), pa.nulls(len(a), pa.int64()) if b is None else pa.array(b), *others], [c.split()[0] for c in MET.split(", ")])

    def pairs(i: np.ndarray, j: np.ndarray, left: list[np.ndarray], right: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        ok = _candidates(*([x[i], y[j]] for x, y in zip(left[2:], right[2:], strict=True)))
        a, b = left[1][i[ok]], right[1][j[ok]]
        if len(a):
            yield rows(np.minimum(a, b), np.maximum(a, b), None)

    def large(first: list[np.ndarray], cols: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        every = np.arange(len(cols[0]))
        other = every[cols[1] != first[1][0]]
        yield from pairs(np.zeros(len(other), np.int64), other, first, cols)
        yield rows(cols[1], None, [cols[0], *cols[2:]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] | None = None
        first: list[np.ndarray] | None = None  # of a large posting that goes on

        def done(cols: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
            """Whole postings."""
            k = cols[0]
            at = np.flatnonzero(np.diff(k, prepend=k[0] - 1))
            size = np.diff(np.append(at, len(k)))
            for lo, m in zip(at[size > hot].tolist(), size[size > hot].tolist(), strict=True):
                part = [c[lo : lo + m] for c in cols]
                yield from large([c[:1] for c in part], part)
            few = np.flatnonzero(np.repeat((size > 1) & (size <= hot), size))
            small = [c[few] for c in cols]
            apart = 1
            live = np.arange(len(few))
            while len(live := live[live + apart < len(few)]) and len(live := live[small[0][live] == small[0][live + apart]]):
                yield from pairs(live, live + apart, small, small)
                apart += 1

        for b in batches:
            cols = [column(b, c).to_numpy() for c in ("k", "node", "n", "w0", "w1")]
            if not len(cols[0]):
                continue
            if first is not None:
                cut = int(np.searchsorted(cols[0], first[0][0], side="right"))
                if cut:
                    yield from large(first, [c[:cut] for c in cols])
                if cut == len(cols[0]):
                    continue
                first, cols = None, [c[cut:] for c in cols]
            if held is not None:
                cols = [np.concatenate(c) for c in zip(held, cols, strict=True)]
            last = int(np.searchsorted(cols[0], cols[0][-1], side="left"))
            if last:
                yield from done([c[:last] for c in cols])
            held = [c[last:] for c in cols]
            if len(held[0]) > hot:
                first = [c[:1] for c in held]
                yield from large(first, held)
                held = None
        if held is not None:
            yield from done(held)

    return run


def _across(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Candidates between different groups out of members of large postings, sorted by key."""
    names = ("k", "a", "n", "w0", "w1", "c")
    held: list[list[np.ndarray]] = []

    def flush() -> Iterator[pa.RecordBatch]:
        cols = [np.concatenate(c) for c in zip(*held, strict=True)]
        for i in range(len(cols[0]) - 1):
            j = np.flatnonzero(cols[5][i + 1 :] != cols[5][i]) + i + 1
            ok = j[_candidates(*([np.repeat(c[i], len(j)), c[j]] for c in cols[2:5]))]
            if len(ok):
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(cols[1][i], cols[1][ok])), pa.array(np.maximum(cols[1][i], cols[1][ok]))], ["a", "b"])

    for b in batches:
        cols = [column(b, c).to_numpy() for c in names]
        at = [0, *(np.flatnonzero(np.diff(cols[0])) + 1).tolist(), len(cols[0])]
        for lo, hi in zip(at, at[1:], strict=False):
            if hi > lo:
                if held and held[0][0][0] != cols[0][lo]:
                    yield from flush()
                    held = []
                held.append([c[lo:hi] for c in cols])
    if held:
        yield from flush()


def join_roots(root: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Joins the groups of a[i] and b[i]; ``root`` names the smallest member of each one's group, before and after."""
    while True:
        ra, rb = root[a], root[b]
        apart = ra != rb
        if not apart.any():
            return
        a, b, ra, rb = a[apart], b[apart], ra[apart], rb[apart]
        np.minimum.at(root, np.maximum(ra, rb), np.minimum(ra, rb))
        while (further := root[root]).tobytes() != root.tobytes():
            root[:] = further


def segment_groups(rows: np.ndarray, family: int, segment: int, hot: int) -> np.ndarray:
    """Of each of ``rows`` (of rising node) the first one of its group: groups join candidates of all postings of a segment that differ in few bits there."""
    every = rows["bytes"]
    words = np.zeros((len(rows), -(-WIDTH // 8) * 8), np.uint8)
    words[:, :WIDTH] = every
    words = words.view(np.uint64)
    root = np.arange(len(rows))
    names = ["k", "node", "n", "w0", "w1"]
    sizes = rows["n"].copy()

    def near(pairs: list[pa.RecordBatch]) -> None:
        if not pairs:
            return
        a, b = (np.concatenate([column(p, c).to_numpy() for p in pairs]) for c in ("a", "b"))
        apart = root[a] != root[b]
        a, b = a[apart], b[apart]
        for at in range(0, len(a), AT_ONCE):
            i, j = a[at : at + AT_ONCE], b[at : at + AT_ONCE]
            ok = np.bitwise_count(words[i] ^ words[j]).sum(1, dtype=np.int64) <= MOST_BITS
            join_roots(root, i[ok], j[ok])

    for slot in range(SEGMENT):
        key = every[:, slot].astype(np.uint16) << 8 | every[:, slot + 1]
        order = np.argsort(key, kind="stable")
        key = key[order]
        alike = key[1:] == key[:-1]
        order_ = order[np.append(alike, False) | np.append(False, alike)]  # postings of one meet nobody
        if not len(order_):
            continue
        w = np.ascontiguousarray(every[order_, slot + 2 : slot + 2 + TALLIED]).view(np.int64)
        k = (np.int64(segment * SEGMENT + slot + BYTES * family) << 16) | (every[order_, slot].astype(np.int64) << 8) | every[order_, slot + 1]
        posting = pa.RecordBatch.from_arrays([pa.array(c) for c in (k, order_, sizes[order_], w[:, 0].copy(), w[:, 1].copy())], names)
        held, large, n = [], [], 0
        for met in _meeting(hot)(iter([posting])):
            if met.column(1).null_count:
                large.append(met)
                continue
            held.append(met)
            n += met.num_rows
            if n >= AT_ONCE:
                near(held)
                held, n = [], 0
        near(held)
        if large:
            of = [pa.RecordBatch.from_arrays([*(column(m, c) for c in ("k", "a", "n", "w0", "w1")), pa.array(root[column(m, "a").to_numpy()])], ["k", "a", "n", "w0", "w1", "c"]) for m in large]
            for met in _across(iter(of)):
                near([met])
    return root


def _segment_stream(hot: int):
    """Members of a segment, packed, out of rows sorted by (family, segment, pair); links (a, b) to the first one of each group."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key: tuple[int, int, int] | None = None
        packed: list[bytes] = []

        def flush() -> Iterator[pa.RecordBatch]:
            if not packed:
                return
            rows = np.frombuffer(b"".join(packed), ROW)
            rows = rows[np.argsort(rows["node"])]
            root = segment_groups(rows, key[0], key[1], hot)
            of = np.flatnonzero(root != np.arange(len(root)))
            if len(of):
                yield pa.RecordBatch.from_arrays([pa.array(rows["node"][root[of]].copy()), pa.array(rows["node"][of].copy())], ["a", "b"])

        for batch in batches:
            for *k, data in zip(*(column(batch, c).to_pylist() for c in ("family", "segment", "pair", "packed")), strict=True):
                if tuple(k) != key:
                    yield from flush()
                    key, packed = tuple(k), []
                packed.append(data)
        yield from flush()

    return run


def candidate_groups(distinct: DataFrame) -> DataFrame:
    """(node, component) of ``distinct`` (node, n, plain, fine): no near pair lies in two groups; nodes that no candidate has are left out."""
    total = distinct.count()
    hot = max(HOT, 4 * total >> 16)
    packed = segments(distinct.select("node", "n", "plain", "fine"), max(1, -(-total // BLOCK)))
    by = ["family", "segment", "pair"]
    met = packed.repartition(*by).sortWithinPartitions(*by).mapInArrow(_segment_stream(hot), "a long, b long")
    return components(written(met.distinct(), "near-met"))


def _link_stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Members of groups out of rows sorted by (c, pair, node); verified links out."""
    key: tuple[int, int] | None = None
    nodes: list[int] = []
    sets: list[np.ndarray] = []

    def flush() -> Iterator[pa.RecordBatch]:
        if len(nodes) > 1 and (pairs := near_links(sets)):
            i, j = np.array(pairs).T
            r = np.array(nodes)
            yield pa.RecordBatch.from_arrays([pa.array(r[i]), pa.array(r[j])], ["a", "b"])

    for batch in batches:
        for c, pair, node, hashes in zip(*(column(batch, c).to_pylist() for c in ("c", "pair", "node", "hashes")), strict=True):
            if (c, pair) != key:
                yield from flush()
                key, nodes, sets = (c, pair), [], []
            if not nodes or nodes[-1] != node:  # rows repeat where a table's rows do
                nodes.append(node)
                sets.append(np.frombuffer(hashes, np.uint64))
    yield from flush()


def copy_links(docs: DataFrame, distinct: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(a, b) between nodes of ``distinct`` (rep, rep_key, node, n, plain, fine): enough links to connect all near ones."""
    named = distinct.where("rep is not null")
    grouped = named.join(candidate_groups(named), "node").select("rep", "rep_key", "node", F.col("component").alias("c"))
    sizes = grouped.groupBy("c").agg(F.ceil(F.count(F.lit(1)) / MEMBERS).alias("parts"))
    grouped = written(grouped.join(sizes, "c"), "near-groups")
    few = grouped.limit(MAX_BROADCAST + 1).count() <= MAX_BROADCAST
    # Rows that share an id may differ in text: its key says which one is meant.
    same = (F.col(id_col).cast("long") == F.col("rep")) & (text_key(text_col) == F.col("rep_key"))
    theirs = docs.select(id_col, text_col).join(F.broadcast(grouped) if few else grouped, same)
    theirs = theirs.select(F.col(text_col).cast("string").alias("text"), "node", "c", "parts")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 100):
            sets = [shingles(split_words(t)).tobytes() for t in column(b, "text").to_pylist()]
            yield pa.RecordBatch.from_arrays([*(column(b, c) for c in ("node", "c", "parts")), pa.array(sets, pa.binary())], ["node", "c", "parts", "hashes"])

    sets = theirs.mapInArrow(run, "node long, c long, parts long, hashes binary")
    # Each two parts of a very large group meet.
    mine = F.pmod(F.xxhash64("node"), F.col("parts"))
    pairs = F.transform(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1), lambda t: F.least(mine, t) * F.col("parts") + F.greatest(mine, t))
    rows = sets.select("c", F.explode(pairs).alias("pair"), "node", "hashes")
    return rows.repartition("c", "pair").sortWithinPartitions("c", "pair", "node").mapInArrow(_link_stream, "a long, b long")


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_key, component_id) for every row of ``docs``."""
    rows = written(sketches(docs, id_col, text_col), "near-sketches")
    firsts = [F.first(c).alias(c) for c in ("n", "plain", "fine")]
    distinct = rows.groupBy("x", "y").agg(F.min("doc_id").alias("rep"), F.min_by("text_key", "doc_id").alias("rep_key"), *firsts)
    distinct = written(distinct.withColumn("node", F.monotonically_increasing_id()), "near-distinct")
    linked = components(written(copy_links(docs, distinct, id_col, text_col), "near-links"))
    named = distinct.join(linked, "node", "left").select("x", "y", "rep", F.coalesce("component", "node").alias("c"))
    named = written(named, "near-named")
    least = named.groupBy("c").agg(F.min("rep").alias("component_id"))
    return rows.join(named.join(least, "c"), ["x", "y"]).select("doc_id", "text_key", "component_id")


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` less all but the smallest id of each group; rows without an id stay."""
    return keep_first(docs, near_copies(docs, id_col, text_col), id_col, text_col)
