"""Suffix-array dedup of byte strings of LENGTH bytes.

A byte goes if a LENGTH-byte string covers it that also starts in a document with a
smaller doc_id. Strings are judged on the input, matches never cross documents.

1. Each LENGTH-byte window is owned by one anchor inside it: the 16-byte gram with the
   smallest hash. Equal windows have equal owners, so windows of one anchor form a
   segment, and only segments of equal anchors can share a window.
2. Segments meet by anchor. Whole segments that repeat are settled there: all but those of
   the smallest doc_id go. What is left, distinct segments of one anchor, goes to shards.
   Before they are dealt out, each work buffer settles its own repeats and sends an anchor
   with several segments as one mark, its segments to places of their own: a frequent
   anchor is a row a buffer.
3. A shard lies in files of its task. Pieces of segments (windows at neighbouring distances to
   the anchor) can't repeat if the bytes that all their windows share occur once, and are left
   out; of equal stretches one stays, and the rest is put in suffix order by external induced sorting; neighbours that share
   LENGTH bytes are equal windows, of which the smallest doc_id stays. Segments of an anchor
   that would fill a shard are dealt out in pieces, by those shared bytes.
4. Removed windows go back to their documents.

Only narrow rows about anchors and the texts of contested segments are shuffled, besides
the documents themselves; nothing is collected, and every group is read as a sorted stream.

Defined results: null and empty texts have zero bytes; null doc_ids count as one document
before all others; rows with one doc_id count as one document, each with its own text
(told apart by a 64-bit hash); an empty table gives an empty result; extra columns don't matter.
"""

from __future__ import annotations

import hashlib
import tempfile
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import column, keyed, load, slices, written
from .induced_sort import MEMORY, Runs, Space, suffix_blocks

LENGTH, GRAM = 50, 16
#: Windows of a segment by their distance to the anchor: PIECE neighbouring ones share all but PIECE - 1 bytes.
PIECE = 7
PIECES = -(-(LENGTH - GRAM + 1) // PIECE)
#: Bytes of one work buffer; longer documents are read in overlapping buffers.
CHUNK_BITS = 20
#: Bytes that a shard has on average; an anchor with more is dealt out in pieces.
SHARD = 8_000_000
CHUNK = 1 << CHUNK_BITS
NO_ID = -(2**63)
#: Kinds of segment rows, above the 48 bits of an anchor: to meet by anchor, known as contested, settled.
OPEN, CONTESTED, SETTLED = 0, 1, 2
KIND_BIT = 48
#: A place holds, from the top: first byte, bytes from there to the anchor, windows.
START_BIT, TO_BIT, LOW = 12, 6, 63

_A, _B, _C = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xD6E8FEB86659FD93))
_BASE = np.uint64(0x5851F42D4C957F2D)


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, np.uint64(base), np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


_TABLES: dict[str, np.ndarray] = {}


def _tables() -> tuple[np.ndarray, np.ndarray]:
    if not _TABLES:
        _TABLES["pow"] = _powers(int(_BASE), CHUNK + 1)
        _TABLES["inv"] = _powers(pow(int(_BASE), -1, 2**64), CHUNK + 1)
    return _TABLES["pow"], _TABLES["inv"]


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(29))) * _C
    return x ^ (x >> np.uint64(32))


def gram_hashes(buf: np.ndarray) -> np.ndarray:
    """A hash of the GRAM bytes from each position."""
    n = len(buf)
    u = np.empty(n - 7, np.uint64)
    for s in range(8):
        k = (n - s) // 8
        u[s::8] = buf[s : s + 8 * k].view("<u8")[: len(u[s::8])]
    return _mix((u[:-8] * _A) ^ ((u[8:] + _A) * _B))


def segments(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, ...]:
    """(anchor hash, segment hash, first window, windows, bytes from there to the anchor) of every segment in a buffer.

    ``starts``, ``ends``: the documents' places in the buffer.
    """
    n = len(buf)
    none = tuple(np.zeros(0, np.int64) for _ in range(5))
    whole = ends - starts >= LENGTH
    if n < LENGTH or not whole.any():
        return none
    h = gram_hashes(buf)
    m = len(h)
    low = np.uint64(CHUNK - 1)
    v = (h & ~low) | np.arange(m, dtype=np.uint64)
    grams = LENGTH - GRAM + 1
    width = 1
    while 2 * width <= grams:
        v = np.minimum(v[:-width], v[width:])
        width *= 2
    if width < grams:
        v = np.minimum(v[: len(v) - (grams - width)], v[grams - width :])
    owner = (v & low).astype(np.int32)  # one per window start
    w = len(owner)
    edge = np.zeros(w + 1, np.int8)
    edge[starts[whole]] += 1
    edge[ends[whole] - LENGTH + 1] -= 1
    valid = np.cumsum(edge[:-1]).astype(bool)
    begin = valid.copy()
    begin[1:] &= (owner[1:] != owner[:-1]) | ~valid[:-1]
    begin[starts[whole]] = True
    s = np.flatnonzero(begin)
    stop = np.searchsorted(ends, s, side="right")
    e = np.minimum(np.append(s[1:], w), ends[stop] - LENGTH + 1)
    power, inverse = _tables()
    total = np.zeros(m + 1, np.uint64)
    np.cumsum(h * power[:m], out=total[1:])
    past = e + LENGTH - GRAM  # grams that begin in the segment
    seg = _mix(((total[past] - total[s]) * inverse[s]) ^ (e - s).astype(np.uint64) * _A)
    anchor = (h[owner[s]] >> np.uint64(16)).astype(np.int64)
    return anchor, seg.view(np.int64), s, e - s, owner[s] - s


def _buffers(batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(bytes, starts, ends, row, offset in the row's text) of work buffers over a batch."""
    text = column(batch, "text")
    if not len(text):
        return
    text = text.fill_null("")
    off = np.frombuffer(text.buffers()[1], np.int32)[text.offset : text.offset + len(text) + 1].astype(np.int64)
    data = np.frombuffer(text.buffers()[2] or b"", np.uint8)
    row = 0
    while row < len(text):
        if off[row + 1] - off[row] > CHUNK:  # a long text alone, in pieces that overlap by LENGTH - 1
            for at in range(int(off[row]), int(off[row + 1]) - LENGTH + 1, CHUNK - LENGTH + 1):
                end = min(at + CHUNK, int(off[row + 1]))
                yield data[at:end], np.array([0]), np.array([end - at]), np.array([row]), np.array([at - int(off[row])])
            row += 1
            continue
        last = max(row + 1, int(np.searchsorted(off, off[row] + CHUNK, side="right")) - 1)
        a = off[row]
        yield data[a : off[last]], off[row:last] - a, off[row + 1 : last + 1] - a, np.arange(row, last), np.zeros(last - row, np.int64)
        row = last


ROW = ["anchor", "seg", "doc", "part", "place"]


def _segment_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        doc, part = column(batch, "doc").to_numpy(), column(batch, "part").to_numpy()
        for buf, starts, ends, rows, base in _buffers(batch):
            anchor, seg, s, n, to = segments(buf, starts, ends)
            if not len(s):
                continue
            k = np.searchsorted(ends, s, side="right")
            place = ((s - starts[k] + base[k]) << START_BIT) | (to << TO_BIT) | n
            cols = _told_apart(anchor, seg, doc[rows[k]], part[rows[k]], place)
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in cols], ROW)


def _told_apart(anchor: np.ndarray, seg: np.ndarray, doc: np.ndarray, part: np.ndarray, place: np.ndarray) -> list[np.ndarray]:
    """Segment rows of a buffer with their kinds: its own repeats settled, anchors with several segments marked by one row."""
    order = np.argsort(anchor, kind="stable")
    a = anchor[order]
    same = a[1:] == a[:-1]
    several = order[np.append(same, False) | np.append(False, same)]
    if not len(several):
        return [anchor, seg, doc, part, place]
    several = several[np.lexsort((doc[several], seg[several], anchor[several]))]
    a, x, d = anchor[several], seg[several], doc[several]
    new_a = np.append(True, a[1:] != a[:-1])
    new = new_a | np.append(True, x[1:] != x[:-1])
    group = np.cumsum(new) - 1
    low = d[new][group]
    per_anchor = np.bincount(np.cumsum(new_a) - 1, new).astype(np.int64)
    contested = (per_anchor > 1)[np.cumsum(new_a) - 1]
    kind = np.where(d > low, SETTLED, np.where(contested, CONTESTED, OPEN))
    out = anchor.copy()
    out[several] |= kind.astype(np.int64) << KIND_BIT
    marks = a[new_a][per_anchor > 1]
    m = len(marks)
    none = np.zeros(m, np.int64)
    return [np.append(x, y) for x, y in ((out, marks), (seg, none + NO_ID), (doc, none), (part, none), (place, none - 1))]


def _settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (anchor, seg, doc): repeated segments out as removed, contested ones as candidates.

    Holds one batch and the last segment's rows of its smallest document.
    """
    names = ["doc", "part", "place", "anchor", "contested"]
    held: list[list[np.ndarray]] = []  # of the open segment: documents (equal), parts, places
    key: tuple[int, int] | None = None
    first = 0
    before = False  # did a segment of the same anchor come before the open one?

    def out(cols: list[np.ndarray], anchor: np.ndarray, contested: bool) -> Iterator[pa.RecordBatch]:
        real = cols[2] >= 0  # marks end here
        if real.any():
            pure = anchor & ((1 << KIND_BIT) - 1)
            yield pa.RecordBatch.from_arrays([pa.array(x[real]) for x in (*cols, pure, np.full(len(pure), contested))], names)

    def release(contested: bool) -> Iterator[pa.RecordBatch]:
        if contested or key[0] >> KIND_BIT == CONTESTED:
            for cols in held:
                yield from out(cols, np.full(len(cols[0]), key[0]), True)
        held.clear()

    for batch in batches:
        a, x, *cols = (column(batch, c).to_numpy() for c in ROW)
        settled = a >> KIND_BIT == SETTLED
        if settled.any():
            yield from out([c[settled] for c in cols], a[settled], False)
            a, x, *cols = (c[~settled] for c in (a, x, *cols))
        n = len(a)
        if not n:
            continue
        d = cols[0]
        new = np.concatenate(([True], (a[1:] != a[:-1]) | (x[1:] != x[:-1])))
        if key is not None and key == (a[0], x[0]):
            new[0] = False
        at = np.flatnonzero(new)
        # The smallest document of each row's segment: its first row, or the open segment's.
        where = np.maximum.accumulate(np.where(new, np.arange(n), -1))
        low = np.where(where >= 0, d[np.maximum(where, 0)], first)
        gone = d > low
        if gone.any():
            yield from out([c[gone] for c in cols], a[gone], False)
        stay = ~gone
        head = int(at[0]) if len(at) else n
        if head and stay[:head].any():
            held.append([c[:head][stay[:head]] for c in cols])
        if not len(at):
            continue
        # Close the open segment, then all but the last of this batch.
        if key is not None:
            yield from release(before or a[at[0]] == key[0])
        anchors = a[at]
        prior = np.concatenate(([key is not None and key[0] == anchors[0]], anchors[1:] == anchors[:-1]))
        after = np.concatenate((anchors[1:] == anchors[:-1], [False]))
        contested = np.repeat(prior | after | (anchors >> KIND_BIT == CONTESTED), np.diff(np.append(at, n)))
        last = int(at[-1])
        mid = slice(int(at[0]), last)
        pick = stay[mid] & contested[: last - int(at[0])]
        if pick.any():
            yield from out([c[mid][pick] for c in cols], a[mid][pick], True)
        key, first, before = (a[last], x[last]), d[last], bool(prior[-1])
        held.append([c[last:][stay[last:]] for c in cols])
    if key is not None:
        yield from release(before)


TEXTS = ["key", "doc", "part", "place", "bytes"]


def _pieces(raw: bytes, anchor: int, place: int) -> Iterator[tuple[int, int, bytes]]:
    """(key, place, bytes) of a segment in pieces of PIECE windows, by their distance to the anchor.

    The key is a hash of what all windows of a piece share, so equal windows stay together.
    """
    start, to, n = place >> START_BIT, place >> TO_BIT & LOW, place & LOW
    i = 0
    while i < n:
        far = (to - i) // PIECE * PIECE  # distances of the piece: far to far + PIECE - 1
        end = min(n, to - far + 1)
        shared = raw[to - far : to - far - PIECE + 1 + LENGTH]
        key = int.from_bytes(hashlib.blake2b(shared, digest_size=8, salt=far.to_bytes(2, "little"), key=anchor.to_bytes(8, "little")).digest(), "little", signed=True)
        yield key, (start + i) << START_BIT | (to - i) << TO_BIT | (end - i), raw[i : end + LENGTH - 1]
        i = end


def _segment_texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts of the wanted segments of each document; those of a frequent anchor in pieces."""
    for batch in batches:
        for b in slices([batch], 500):
            if not b.num_rows:
                continue
            want = column(b, "wanted")
            sizes = np.diff(want.offsets.to_numpy())
            flat = want.flatten()
            place, anchor, frequent = (flat.field(k).to_numpy(zero_copy_only=False) for k in range(3))
            start = place >> START_BIT
            ends = (start + (place & LOW) + LENGTH - 1).tolist()
            spans = iter(zip(start.tolist(), ends, strict=True))
            out: list[bytes] = []
            for text, n in zip(column(b, "text").to_pylist(), sizes.tolist(), strict=True):
                raw = (text or "").encode()
                out += [raw[s:e] for s, e in islice(spans, n)]
            doc, part = (np.repeat(column(b, c).to_numpy(), sizes) for c in ("doc", "part"))
            whole = np.flatnonzero(~frequent)
            yield pa.RecordBatch.from_arrays(
                [*(pa.array(x[whole]) for x in (anchor, doc, part, place)), pa.array([out[k] for k in whole.tolist()], pa.binary())], TEXTS
            )
            cut = [(k, *p) for k in np.flatnonzero(frequent).tolist() for p in _pieces(out[k], int(anchor[k]), int(place[k]))]
            if cut:
                of, key, places, raw = zip(*cut, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(key, pa.int64()), pa.array(doc[list(of)]), pa.array(part[list(of)]), pa.array(places, pa.int64()), pa.array(raw, pa.binary())], TEXTS)


class Spool:
    """Arrays put end to end: in memory up to a limit of bytes, in a temporary file beyond it."""

    def __init__(self, kind, limit: int):
        self.kind, self.n = np.dtype(kind), 0
        self.file = tempfile.SpooledTemporaryFile(max(limit, 1))

    def add(self, x: np.ndarray) -> None:
        self.file.write(np.ascontiguousarray(x, self.kind).data)
        self.n += len(x)

    def array(self) -> np.ndarray:
        if self.file._rolled:
            self.file.flush()
            return np.asarray(np.memmap(self.file._file, self.kind, "r", shape=(self.n,))) if self.n else np.zeros(0, self.kind)
        self.file.seek(0)
        return np.frombuffer(self.file.read(), self.kind)


def piece_keys(word: np.ndarray, begin: np.ndarray, place: np.ndarray) -> np.ndarray:
    """A hash per piece of each segment, of the bytes that its windows share; 0 for a piece without windows.

    ``word``: the eight bytes from each place of the shard.
    """
    to, n = place >> TO_BIT & LOW, place & LOW
    out = np.zeros((len(begin), PIECES), np.uint64)
    size = LENGTH - PIECE + 1
    for q in range(PIECES):
        far = q * PIECE
        has = np.flatnonzero((far <= to) & (far + PIECE > to - n + 1))
        p = begin[has] + to[has] - far
        h = np.full(len(p), np.uint64(q + 1))
        for k in (*range(0, size - 8, 8), size - 8):
            h = _mix((h ^ word[p + k].astype(np.uint64)) * _A) + _B
        out[has, q] = h
    return out.ravel()


def kept_windows(twice: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(segment, first window, past the last one) of neighbouring pieces that are to be compared."""
    flag = np.zeros((len(place), PIECES + 2), bool)
    flag[:, 1:-1] = twice.reshape(-1, PIECES)[:, ::-1]  # the furthest windows come first
    of, hi = np.nonzero(flag[:, 1:-1] & ~flag[:, :-2])
    _, lo = np.nonzero(flag[:, 1:-1] & ~flag[:, 2:])
    to, n = place[of] >> TO_BIT & LOW, place[of] & LOW
    first = to - (PIECES - hi) * PIECE + 1
    last = to - (PIECES - 1 - lo) * PIECE + 1
    return of, np.maximum(first, 0), np.minimum(last, n)


def equal_stretches(raw: np.ndarray, begin: np.ndarray, length: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """For each stretch of the shard the one that stands for all equal ones: the first in the smallest document.

    A hash brings equal ones together, their bytes decide.
    """
    import xxhash

    view = memoryview(raw)
    spans = list(zip(begin.tolist(), (begin + length).tolist(), strict=True))
    key = np.fromiter((xxhash.xxh3_64_intdigest(view[a:b]) for a, b in spans), np.uint64, len(spans))
    order = np.argsort(key, kind="stable")
    group = np.arange(len(key))
    for k in np.flatnonzero(key[order[1:]] == key[order[:-1]]).tolist():
        i, j = order[k], order[k + 1]
        (a, b), (c, d) = spans[i], spans[j]
        if b - a == d - c and view[a:b].tobytes() == view[c:d].tobytes():
            group[j] = group[i]
    order = np.lexsort((doc, group))
    first = np.append(True, np.diff(group[order]) != 0)
    out = np.empty(len(key), np.int64)
    out[order] = order[first][np.cumsum(first) - 1]
    return out


def repeated(keys: np.ndarray, space: Space) -> np.ndarray:
    """True where a key (not 0) occurs again."""
    runs = Runs()
    for at in range(0, len(keys), 1 << 17):
        x = keys[at : at + (1 << 17)]
        some = np.flatnonzero(x)
        runs.add(x[some], some + at)
    out = space.array(len(keys), bool)
    out[:] = False
    open_: tuple | None = None
    for key, where in runs:
        same = key[1:] == key[:-1]
        twice = np.append(same, False) | np.append(False, same)
        if open_ is not None and open_[0] == key[0]:
            twice[0] = out[open_[1]] = True
        out[where[twice]] = True
        open_ = key[-1], where[-1]
    return out


class Windows:
    """Equal windows out of suffixes in falling order; ``hits`` gets the places of those in a larger document."""

    def __init__(self, segment_of, doc: np.ndarray):
        self.segment_of, self.doc = segment_of, doc
        self.hits = Runs()
        self.low: int | None = None  # smallest document of the open run so far, its places
        self.held: list[np.ndarray] = []
        self.last = -1

    def _hit(self, place: np.ndarray) -> None:
        if len(place):
            self.hits.add(place, place)

    def _extend(self, place: np.ndarray) -> None:
        """More windows of the open run; only those of its smallest document are held."""
        if not len(place):
            return
        d = self.doc[self.segment_of(place)]
        low = int(d.min())
        if self.low is not None and low > self.low:
            low = self.low
        if self.low is None or low < self.low:
            for p in self.held:
                self._hit(p)
            self.held, self.low = [], low
        self._hit(place[d > low])
        self.held.append(place[d == low])

    def __call__(self, place: np.ndarray, prefix: np.ndarray) -> None:
        new = np.flatnonzero(prefix < LENGTH)
        head = int(new[0]) if len(new) else len(place)
        if head:
            if self.low is None:
                self._extend(np.array([self.last]))
            self._extend(place[:head])
        if not len(new):
            return
        self.low, self.held = None, []
        end = int(new[-1])
        size = np.diff(new)
        many = np.flatnonzero(size > 1)
        if len(many):
            run = np.repeat(np.arange(len(many)), size[many])
            first = np.cumsum(size[many]) - size[many]
            at = place[np.repeat(new[many] - first, size[many]) + np.arange(len(run))]
            d = self.doc[self.segment_of(at)]
            self._hit(at[d > np.minimum.reduceat(d, first)[run]])
        if end + 1 < len(place):
            self._extend(place[end:])
        self.last = int(place[-1])


def _shard_stream(batches: Iterator[pa.RecordBatch], memory: int = MEMORY) -> Iterator[pa.RecordBatch]:
    """One shard per partition: (doc, part, place) of windows that start in a smaller document as well."""
    share = memory // 8
    spools = [Spool(k, share) for k in (np.int64, np.int64, np.int64, np.uint8, np.int32)]
    for b in batches:
        for name, spool in zip(TEXTS[1:4], spools, strict=False):
            spool.add(column(b, name).to_numpy())
        raw = column(b, "bytes")
        off = np.frombuffer(raw.buffers()[1], np.int32)[raw.offset : raw.offset + len(raw) + 1]
        if len(raw):
            spools[3].add(np.frombuffer(raw.buffers()[2], np.uint8)[off[0] : off[-1]])
            spools[4].add(np.diff(off))
    if spools[0].n < 2:
        return
    spools[3].add(np.zeros(8, np.uint8))
    doc, part, place, raw, size = (x.array() for x in spools)
    space = Space(memory // 2)
    m = len(doc)
    begin = space.array(m, np.int64)
    begin[:] = np.cumsum(size, dtype=np.int64) - size
    keys = space.array(PIECES * m, np.uint64)
    word = np.ndarray((len(raw) - 7,), "<u8", raw, 0, (1,))
    step = 1 << 16
    for a in range(0, m, step):
        keys[PIECES * a : PIECES * (a + step)] = piece_keys(word, begin[a : a + step], place[a : a + step])
    of, first, last = kept_windows(repeated(keys, space), place)
    if len(of) < 2:
        return
    length = last - first + LENGTH - 1
    # Equal stretches are sorted once: those of a larger document go, those of the same one share their fate.
    stands = equal_stretches(raw, begin[of] + first, length, doc[of])
    own = np.flatnonzero(stands == np.arange(len(of)))
    others = np.flatnonzero(stands != np.arange(len(of)))
    larger = doc[of[others]] > doc[of[stands[others]]]
    gone, twins = others[larger], others[~larger]
    if len(gone):
        s = of[gone]
        start = (place[s] >> START_BIT) + first[gone]
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in (doc[s], part[s], (start << START_BIT) | (last - first)[gone])], ["doc", "part", "place"])
    twins = twins[np.argsort(stands[twins], kind="stable")]
    twin_of = np.searchsorted(own, stands[twins])
    twin_part, twin_start = part[of[twins]], (place[of[twins]] >> START_BIT) + first[twins]
    of, first, last, length = (x[own] for x in (of, first, last, length))
    if len(of) < 2:
        return
    total = int(length.sum()) + len(of) + 1
    text = space.array(total + 8, np.uint8)
    text[:] = 1  # ends a segment; 0 ends the shard, bytes move up by two (UTF-8 stays below 254)
    text[total - 1 :] = 0
    at = np.cumsum(length + 1) - length - 1  # where each one begins
    for a in range(0, len(of), 1 << 13):
        k = slice(a, a + (1 << 13))
        inside = np.arange(int(length[k].sum())) - np.repeat(np.cumsum(length[k]) - length[k], length[k])
        text[np.repeat(at[k], length[k]) + inside] = raw[np.repeat(begin[of[k]] + first[k], length[k]) + inside] + np.uint8(2)
    found = Windows(lambda p: of[np.searchsorted(at, p, side="right") - 1], doc)
    suffix_blocks(text, total, found, LENGTH, memory)
    for hit, _ in found.hits:
        hit = hit.astype(np.int64)
        k = np.searchsorted(at, hit, side="right") - 1
        hit = hit[hit - at[k] <= length[k] - LENGTH]  # the last 49 bytes of a segment with its end are no window
        if not len(hit):
            continue
        # Neighbouring windows of a segment become one interval; segments are further apart than that.
        cut = np.flatnonzero(np.append(True, np.diff(hit) != 1))
        count = np.diff(np.append(cut, len(hit)))
        k = np.searchsorted(at, hit[cut], side="right") - 1
        s = of[k]
        inside = hit[cut] - at[k]
        start = (place[s] >> START_BIT) + first[k] + inside
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in (doc[s], part[s], (start << START_BIT) | count)], ["doc", "part", "place"])
        low, high = np.searchsorted(twin_of, k), np.searchsorted(twin_of, k, side="right")
        n = high - low
        if n.any():
            t = np.repeat(low - np.cumsum(n) + n, n) + np.arange(n.sum())
            start = twin_start[t] + np.repeat(inside, n)
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (np.repeat(doc[s], n), twin_part[t], (start << START_BIT) | np.repeat(count, n))], ["doc", "part", "place"])


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches, 1000):
        text = column(batch, "text").to_pylist()
        gone = column(batch, "gone")
        rows = []
        for i, t in enumerate(text):
            raw = (t or "").encode()
            if not gone[i].is_valid:
                rows.append((len(raw), 0, 0, hashlib.sha256(raw).hexdigest(), raw.decode()))
                continue
            place = np.sort(gone[i].values.to_numpy())
            start, end = place >> START_BIT, (place >> START_BIT) + (place & LOW) + LENGTH - 1
            reach = np.maximum.accumulate(end)
            new = np.concatenate(([True], start[1:] > reach[:-1]))
            first, last = start[new], reach[np.append(np.flatnonzero(new)[1:] - 1, len(start) - 1)]
            kept = b"".join(raw[a:b] for a, b in zip([0, *last.tolist()], [*first.tolist(), len(raw)], strict=True))
            rows.append((len(raw), int((last - first).sum()), len(first), hashlib.sha256(kept).hexdigest(), kept.decode(errors="replace")))
        n, r, k, h, t = zip(*rows, strict=True) if rows else ([], [], [], [], [])
        yield pa.RecordBatch.from_arrays(
            [column(batch, "doc_id"), pa.array(n, pa.int64()), pa.array(r, pa.int64()), pa.array(k, pa.int64()), pa.array(h, pa.string()), pa.array(t, pa.string())],
            ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "text"],
        )


def dedup_substrings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256 and the remaining ``text``.

    Where a cut falls inside a character, ``text`` holds a replacement mark for what is left of it;
    the digest is of the exact bytes.
    """
    base = keyed(docs, id_col, text_col).withColumn("doc", F.coalesce("doc_id", F.lit(NO_ID)))
    repeats = base.groupBy("doc").agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).count()
    # A hash of the text tells apart the texts under one id, and spreads an id that many rows share.
    base = base.withColumn("part", F.xxhash64("text") if repeats else F.lit(0).cast("long"))
    each = ["doc", "part"]
    rows = base.select(*each, "text").mapInArrow(_segment_rows, ", ".join(f"{c} long" for c in ROW))
    kind = F.shiftright("anchor", KIND_BIT)
    where = F.when(kind == OPEN, F.col("anchor")).when(kind == CONTESTED, F.col("seg")).otherwise(F.xxhash64("doc", "place"))
    settled = written(
        rows.repartition(where).sortWithinPartitions("anchor", "seg", "doc").mapInArrow(_settle, "doc long, part long, place long, anchor long, contested boolean"),
        "segments",
    )
    contested = settled.where("contested").drop("contested")
    size = F.sum(F.col("place").bitwiseAND(LOW) + (LENGTH - 1)).alias("size")
    frequent = written(contested.groupBy("anchor").agg(size).where(F.col("size") > SHARD).select("anchor", F.lit(True).alias("frequent")), "frequent-anchors")
    wanted = (
        contested.join(frequent, "anchor", "left")
        .groupBy(*each)
        .agg(F.collect_list(F.struct("place", "anchor", F.coalesce("frequent", F.lit(False)))).alias("wanted"))
    )
    texts = base.select(*each, "text").dropDuplicates(each) if repeats else base.select(*each, "text")
    segment_texts = texts.join(wanted, each).select(*each, "text", "wanted").mapInArrow(_segment_texts, "key long, doc long, part long, place long, bytes binary")
    shards = max(int(base.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-(contested.agg(size).first()[0] or 0) // SHARD))
    windows = written(segment_texts.repartition(shards, "key").mapInArrow(_shard_stream, "doc long, part long, place long"), "windows")
    gone = settled.where("not contested").select(*each, "place").union(windows).groupBy(*each).agg(F.collect_list("place").alias("gone"))
    out = base.join(gone, each, "left").select("doc_id", "text", "gone")
    return out.mapInArrow(_cut, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, text string")


def op10_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = dedup_substrings(load(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
