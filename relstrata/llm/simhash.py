"""SimHash near-dedup over a byte-position inverted index with count filtering.

A 64-bit fingerprint is eight positional bytes. Two fingerprints within three bits
differ in at most three bytes, so they share at least five: the guaranteed minimum.
Any five of the eight positions hold three within the first or within the second
half, so the postings are keyed by three positional bytes of one half (eight keys a
fingerprint): no pair with five shared bytes is missed. Inside a posting the shared
bytes of candidates are tallied, pairs below five are dropped, and the rest verified
bit by bit.

A posting with more than SMALL members is split by two further positional bytes, in every
choice of two of the five that are left: pairs of five shared bytes meet in one of these, and
are counted there like in any other. Copies were folded before, so members are distinct
fingerprints (16 bytes each); a task holds one posting or part of one, compares its members in
blocks, and only links that join two parts of it leave the task, never all pairs.

Defined results: null and empty texts have fingerprint zero and are linked like any
other; rows without doc_id get a component but never name one; repeated rows stay;
an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import column, keyed, load, slices, text_key, without, written
from .components import components

WORDS, SEED, BITS, MAX_DIFF, MIN_SHARED = 3, 42, 64, 3, 5
#: Positions of each posting key: every five of eight positions contain one of these.
KEYS = [c for half in (range(4), range(4, 8)) for c in combinations(half, 3)]
#: Postings above this size are split by two further bytes; members compared at once.
SMALL = 2_000
ROWS_AT_ONCE, COLUMNS_AT_ONCE = 256, 4096
#: The choices of two of the five positions that a posting's key leaves.
FURTHER = list(combinations(range(5), 2))


def fingerprint(text: str | None, width: int = WORDS) -> int:
    """SimHash of the shingles of a lower-cased text, as an unsigned 64-bit integer."""
    import xxhash

    words = (text or "").encode().lower().split()  # bytes: A-Z only, and ASCII white space only
    if not words:
        return 0
    line = b" ".join(words)
    n = max(1, len(words) - width + 1)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))[:n].tolist()
    ends = ends[min(width, len(words)) - 1 :].tolist()
    digest = xxhash.xxh64_intdigest
    h = np.fromiter((digest(line[a:b], SEED) for a, b in zip(starts, ends, strict=True)), np.uint64, n)
    counts = np.zeros(BITS, np.int64)
    for at in range(0, n, 65536):  # bounded memory for very long texts
        bits = np.unpackbits(h[at : at + 65536].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
        counts += bits.sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > n).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WORDS) -> DataFrame:
    """(doc_id, text_key, fp) per row of ``docs``; fp is the signed form of the 64 bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 500):
            fp = np.array([fingerprint(t, width) for t in column(b, "text").to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([column(b, "doc_id"), column(b, "text_key"), pa.array(fp)], ["doc_id", "text_key", "fp"])

    return keyed(docs, id_col, text_col).withColumn("text_key", text_key()).mapInArrow(run, "doc_id long, text_key long, fp long")


def shared_bytes(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Tally of equal positional bytes of each pair of fingerprints."""
    x = (a ^ b).view(np.uint8).reshape(*np.broadcast(a, b).shape, 8)
    return (x == 0).sum(-1)


def _root(parent: np.ndarray, i: int) -> int:
    while parent[i] != i:
        parent[i] = parent[parent[i]]
        i = parent[i]
    return int(i)


def posting_links(fps: np.ndarray) -> list[tuple[int, int]]:
    """Index pairs that connect the members of one posting that are within three bits."""
    m = len(fps)
    parent = np.arange(m)
    links: list[tuple[int, int]] = []
    for i0 in range(0, m, ROWS_AT_ONCE):
        for j0 in range(i0, m, COLUMNS_AT_ONCE):
            x, y = fps[i0 : i0 + ROWS_AT_ONCE, None], fps[None, j0 : j0 + COLUMNS_AT_ONCE]
            i, j = np.nonzero(shared_bytes(x, y) >= MIN_SHARED)
            i, j = i + i0, j + j0
            near = (i < j) & (np.bitwise_count(fps[i] ^ fps[j]) <= MAX_DIFF)
            for a, b in zip(i[near].tolist(), j[near].tolist(), strict=True):
                u, v = _root(parent, a), _root(parent, b)
                if u != v:
                    parent[max(u, v)] = min(u, v)
                    links.append((a, b))
    return links


def _link_stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Postings out of rows sorted by (slot, bytes, further); links out."""
    key: tuple[int, int, int] | None = None
    fps: list[np.ndarray] = []
    reps: list[np.ndarray] = []

    def flush() -> Iterator[pa.RecordBatch]:
        if key is None or sum(map(len, fps)) < 2:
            return
        f, r = np.concatenate(fps), np.concatenate(reps)
        if pairs := posting_links(f):
            i, j = np.array(pairs).T
            yield pa.RecordBatch.from_arrays([pa.array(r[i]), pa.array(r[j])], ["a", "b"])

    for batch in batches:
        parts = [column(batch, c).to_numpy() for c in ("slot", "part", "further")]
        fp = column(batch, "fp").to_numpy().view(np.uint64)
        rep = column(batch, "rep").to_numpy()
        if not len(fp):
            continue
        cuts = np.flatnonzero(np.any([p[1:] != p[:-1] for p in parts], axis=0)) + 1
        at = [0, *cuts.tolist(), len(fp)]
        for a, b in zip(at, at[1:], strict=False):
            k = tuple(int(p[a]) for p in parts)
            if k != key:
                yield from flush()
                key, fps, reps = k, [], []
            fps.append(fp[a:b])
            reps.append(rep[a:b])
    yield from flush()


def _bytes_at(positions: tuple[int, ...]) -> Column:
    """The positional bytes of ``fp`` as one number."""
    return sum(((F.shiftrightunsigned("fp", 8 * p).bitwiseAND(F.lit(255))) * (256**n) for n, p in enumerate(positions)), F.lit(0)).cast("int")


def fingerprint_links(distinct: DataFrame) -> DataFrame:
    """(a, b) between representatives of ``distinct`` (fp, rep): enough links to connect all near ones."""
    parts = [F.struct(F.lit(k).alias("slot"), _bytes_at(pos).alias("part")) for k, pos in enumerate(KEYS)]
    posted = distinct.withColumn("_k", F.explode(F.array(*parts))).select("_k.slot", "_k.part", "fp", "rep")
    # A posting of one can't link: leave it out before rows go to Python.
    sizes = posted.groupBy("slot", "part").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    met = posted.join(sizes, ["slot", "part"])
    # Two further bytes and which ones they are; the positions left depend on the slot.
    left = [[p for p in range(8) if p not in pos] for pos in KEYS]
    choices = F.element_at(
        F.array(*[F.array(*[(_bytes_at((rest[a], rest[b])) * len(FURTHER) + F.lit(c + 1)).cast("int") for c, (a, b) in enumerate(FURTHER)]) for rest in left]),
        F.col("slot") + 1,
    )
    split = F.when(F.col("n") > SMALL, choices).otherwise(F.array(F.lit(0)))
    rows = met.select("slot", "part", F.explode(split).alias("further"), "fp", "rep")
    by = ["slot", "part", "further"]
    return rows.repartition(*by).sortWithinPartitions(*by).mapInArrow(_link_stream, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WORDS) -> DataFrame:
    """(doc_id, text_key, fp, fingerprint, component_id) for every row of ``docs``.

    Copies fold into one representative (their smallest id) before anything is posted;
    a third of all rows being copies of one text costs one row from there on.
    """
    prints = written(fingerprints(docs, id_col, text_col, width), "fingerprints")
    distinct = written(prints.groupBy("fp").agg(F.min("doc_id").alias("first")), "distinct-fp")
    distinct = distinct.withColumnRenamed("first", "rep")  # null where no row of the fingerprint has an id
    linked = components(written(fingerprint_links(distinct.where("rep is not null").select("fp", "rep")), "fp-links"))
    named = distinct.join(linked, distinct["rep"] == linked["node"], "left").select(
        "fp", F.coalesce("component", "rep").alias("component_id")
    )
    return prints.join(named, "fp").select(
        "doc_id", "text_key", "fp", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id"
    )


def dedup(docs: DataFrame, width: int = WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` less all but the smallest id of each group; rows without an id stay."""
    return keep_first(docs, near_duplicates(docs, id_col, text_col, width), id_col, text_col)


def keep_first(docs: DataFrame, classes: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of ``docs`` whose id names their class in ``classes`` (doc_id, text_key, component_id), and rows without an id.

    Of repeated rows with the same id one is kept.
    """
    classes = written(classes.where("doc_id is not null").select("doc_id", "text_key", "component_id"), "classes")
    kept = without(docs, classes.where("doc_id <> component_id"), id_col, text_col)
    first = classes.where("doc_id = component_id").groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))
    if first.where("n > 1").limit(1).count():
        with_id = kept.where(F.col(id_col).isNotNull()).dropDuplicates([id_col])
        kept = with_id.unionByName(kept.where(F.col(id_col).isNull()))
    return kept


def op1_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(load(spark, sf_dir, "documents")).select("doc_id", "fingerprint", "component_id")
