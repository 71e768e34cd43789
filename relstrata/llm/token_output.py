"""Token-ID output: texts to ids, ids to checksummed coded blocks in Parquet, and back.

Documents go to range partitions by doc_id; each partition writes its ids as one run,
cut into blocks that can each be read alone (see ``mixing_coder``, and ``id_coder`` for where it runs). A row of the files is
a block: its partition and number, how many ids come before it in the partition, the
pieces of documents in it, where its first document began, and the coded bytes. Spark's commit
protocol writes the files, so a lost executor's part is written again and never twice. Files are
read where they lie; of a document whose blocks two tasks read, the checksums are put together.

Ids are the tokenizers library's for the file that is given, whatever its pre-tokenizer, special tokens
and size (ids below 2**32 - 1). Where the file has the byte-level pattern, the library encodes each distinct piece between
two safe cuts once (see ``PieceCodes``); with any other file, or a special token in it, a text goes to it whole.

Defined results: a null or empty text is the end id alone; documents with the same id
follow each other in text order; null doc_ids come first; an empty table writes no block.
"""

from __future__ import annotations

import json
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import id_coder, mixing_coder
from .common import column, keyed, load, slices, written

END_ID = 2
#: Ids coded together, blocks at most and ids at least in each.
GROUP, LANES, MIN_BLOCK = 1 << 21, 1024, 1024
BLOCKS = "part int, block int, before long, n_ids long, first_begin long, doc_ids array<long>, piece_ids array<long>, begins array<boolean>, payload binary"
#: Pieces of documents as read: where the document begins and the piece lies in its partition, size and checksum.
PIECES = "part int, begin long, doc_id long, at long, n long, crc long"


def tokenizer_file(path: str | None = None) -> str:
    """Place of the tokenizer's file; a parameter, the public vocabulary by default."""
    if path:
        return path
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


#: Stands before a comma or full stop at a cut; a text that holds it goes to the library whole.
MARK = "\0"
#: A comma or full stop that does not follow a letter or digit: what is before it may belong to the same part of the pattern.
BESIDE = re.compile("(?:^|[^0-9A-Za-zÀ-ÖØ-öø-ÿ])[,.]")


def appended(held: np.ndarray, n: int, parts: list[np.ndarray]) -> np.ndarray:
    """``held`` with the parts after its first n elements, in place while there is room."""
    size = n + sum(map(len, parts))
    if size > len(held):
        held = np.concatenate([held[:n], np.zeros(max(size, 2 * n) - n, held.dtype)])
    for p in parts:
        held[n : n + len(p)] = p
        n += len(p)
    return held


class Pieces(dict):
    """Code of each piece of text seen, by the piece less a space before it; new ones are kept for the library."""

    def __init__(self, codes: PieceCodes, later: bool):
        super().__init__()
        self.codes, self.later = codes, later

    def __missing__(self, piece: str) -> int:
        codes = self.codes
        if self.later and piece.isalpha() and (piece.isascii() or max(piece) <= "ÿ"):
            code = self[piece] = codes.add(" " + piece, codes.words)
            return code
        if self.later and piece[:1] == MARK:
            whole = inner = piece[1:]
        else:
            whole = " " + piece if self.later and piece[:1] != "\n" else piece
            inner = whole[1:] if self.later else whole
        odd = not inner or inner[0].isspace() or inner[-1].isspace()
        if odd:
            codes.odd.add(codes.codes)
        code = self[piece] = codes.add(whole, codes.joined if self.later and not odd and piece[:1] != MARK else None)
        return code


class PieceCodes:
    """The library's ids of pieces: each distinct one is encoded once, a text is put together from them.

    Pieces are cut before a single space or line end between two characters that are no white space. There the pre-tokenizer
    always cuts and looks neither ahead nor back over the place, so the ids of a text are those of its pieces in turn (``apart``).
    The same holds before a comma or full stop after a letter or digit. Of a space and letters the pattern makes one part, so
    such pieces go to the library's model without its pattern, in the characters that it has for their bytes.
    """

    #: Pieces and their characters that are held, at most; then all is begun anew.
    MOST, MOST_CHARS = 1 << 20, 1 << 24
    #: New pieces that the library encodes as one text.
    TOGETHER = 512
    #: New words that are worth a call of their own.
    WORDS = 64

    def __init__(self, tok):
        self.tok = tok
        config = json.loads(tok.to_str())
        added = config.get("added_tokens") or []
        #: Texts that hold one of these go to the library whole.
        self.whole = [t["content"] for t in added] + [MARK]
        self.apart = self._apart(config) and all(t["content"] and not t["normalized"] and len(t["content"].split()) == 1 for t in added)
        if self.apart:
            vocabulary = tok.get_vocab(with_added_tokens=True)
            #: Bytes of each id, as many as characters in the file.
            self.width = np.zeros(max(vocabulary.values(), default=0) + 1, np.int64)
            self.width[list(vocabulary.values())] = list(map(len, vocabulary))
            self._by_word()
        self.clear()

    def _by_word(self) -> None:
        """The library's model behind a plain cut at spaces, and its characters for a space and the letters of Latin-1."""
        from tokenizers import Tokenizer, pre_tokenizers

        self.by_word = Tokenizer(self.tok.model)
        self.by_word.pre_tokenizer = pre_tokenizers.CharDelimiterSplit(" ")
        as_bytes = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        self.space = as_bytes.pre_tokenize_str(" ")[0][0]
        self.letters = {c: as_bytes.pre_tokenize_str(chr(c))[0][0] for c in range(128, 256) if chr(c).isalpha()}

    @staticmethod
    def _apart(config: dict) -> bool:
        """Whether the file says what the cuts rest on: bytes by the usual pattern, nothing before or after, no chance."""
        pre, model = config.get("pre_tokenizer") or {}, config.get("model") or {}
        if pre.get("type") != "ByteLevel" or pre.get("add_prefix_space") is not False or pre.get("use_regex") is not True:
            return False
        if any(config.get(k) for k in ("normalizer", "post_processor", "truncation", "padding")):
            return False
        return model.get("type") == "BPE" and not model.get("dropout")

    def clear(self) -> None:
        self.first, self.later = Pieces(self, False), Pieces(self, True)
        self.new: list[str] = []
        #: Places in ``new`` of what may follow another piece, and of a space and letters alone.
        self.joined: list[int] = []
        self.words: list[int] = []
        #: Codes of pieces that are empty or have white space at an end. Code 0 is the end id.
        self.odd: set[int] = set()
        self.codes = 1
        self.ids, self.starts, self.sizes, self.chars = np.array([END_ID], np.uint32), np.zeros(1, np.int64), np.ones(1, np.int64), 0
        #: How much of ``ids`` is filled; it and the places grow by doubling.
        self.filled = self.placed = 1

    def add(self, piece: str, places: list[int] | None) -> int:
        if places is not None:
            places.append(len(self.new))
        self.new.append(piece)
        self.chars += len(piece)
        self.codes += 1
        return self.codes - 1

    @staticmethod
    def cut(text: str) -> str:
        """The text with a space at each cut."""
        cut = text.replace("\n", " \n")
        return cut if BESIDE.search(text) else cut.replace(",", f" {MARK},").replace(".", f" {MARK}.")

    def of(self, texts: list[str]) -> list[np.ndarray]:
        """Codes of the pieces of each text and of its end. Of pieces that come twice in these texts, one is looked up."""
        heads = [(t, "", "") if any(w in t for w in self.whole) else self.cut(t).partition(" ") for t in texts]
        lists = pc.split_pattern(pa.array([rest if space else None for _, space, rest in heads], pa.large_string()), " ")
        distinct = lists.flatten().dictionary_encode()
        known = np.fromiter(map(self.later.__getitem__, distinct.dictionary.to_pylist()), np.int64, len(distinct.dictionary))
        codes = known[distinct.indices.to_numpy(zero_copy_only=False)]
        odd = np.zeros(self.codes, bool)
        odd[list(self.odd)] = True
        ends = np.cumsum(pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False))
        odds = np.concatenate([[0], np.cumsum(odd[codes])])
        out, a = [], 0
        for (head, space, rest), b in zip(heads, ends.tolist(), strict=True):
            # An empty head or one with white space at an end is the start of the piece after it.
            if space and (odds[a] < odds[b] or not head or head[0].isspace() or head[-1].isspace()):
                out.append(np.array([*self._merged(head, rest.split(" ")), 0], np.int64))
            else:
                out.append(np.concatenate([[self.first[head]], codes[a:b], [0]]))
            a = b
        return out

    def _merged(self, head: str, rest: list[str]) -> list[int]:
        """As ``of``, where some of the cuts have white space beside them."""
        spans, held = [], [head]
        for word in rest:
            if word[:1] == MARK:
                spans.append("".join(held))
                held = [word]
                continue
            line = word[:1] == "\n"
            inner = word[1:] if line else word
            if inner and not inner[0].isspace() and held[-1] and not held[-1][-1].isspace():
                spans.append("".join(held))
                held = [word]
            else:
                held.append(word if line else " " + word)
        spans.append("".join(held))
        return [self.first[spans[0]], *map(self.later.__getitem__, spans[1:])]

    def _learn(self) -> None:
        """The library's ids of the new pieces."""
        n = len(self.new)
        if len(self.words) < self.WORDS:
            self.joined, self.words = sorted(self.joined + self.words), []
        starts, sizes = np.zeros(n, np.int64), np.zeros(n, np.int64)
        ids = []
        at = self.filled
        alone = np.ones(n, bool)
        for kind, lo in [(k, lo) for k in (self.joined, self.words) for lo in range(0, len(k), self.TOGETHER)]:
            of = kind[lo : lo + self.TOGETHER]
            pieces = [self.new[k] for k in of]
            text, by = "".join(pieces), self.tok
            ends = np.cumsum([len(p) for p in pieces] if text.isascii() else [len(p.encode()) for p in pieces])
            if kind is self.words:
                latin = text if text.isascii() else text.translate(self.letters)
                text, by = latin.replace(" ", " " + self.space)[1:], self.by_word
            got = np.array(by.encode_batch_fast([text], add_special_tokens=False)[0].ids, np.uint32)
            reached = np.cumsum(self.width[got])
            last = np.searchsorted(reached, ends)
            if not len(reached) or reached[-1] != ends[-1] or (reached[last] != ends).any():
                continue  # a vocabulary that lacks bytes: each piece by itself
            sizes[of] = np.diff(last, prepend=-1)
            starts[of] = at + last + 1 - sizes[of]
            alone[of] = False
            ids.append(got)
            at += len(got)
        rest = np.flatnonzero(alone).tolist()
        for k, e in zip(rest, self.tok.encode_batch_fast([self.new[k] for k in rest], add_special_tokens=False), strict=True):
            ids.append(np.array(e.ids, np.uint32))
            starts[k], sizes[k] = at, len(e.ids)
            at += len(e.ids)
        self.ids = appended(self.ids, self.filled, ids)
        self.starts, self.sizes = (appended(x, self.placed, [new]) for x, new in ((self.starts, starts), (self.sizes, sizes)))
        self.filled, self.placed = at, self.placed + n
        self.new, self.joined, self.words = [], [], []

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Each text's ids and the end id."""
        if self.codes > self.MOST or self.chars > self.MOST_CHARS:
            self.clear()
        of = self.of(texts)
        self._learn()
        out = []
        for codes in of:
            n = self.sizes[codes]
            ends = np.cumsum(n)
            out.append(self.ids[np.repeat(self.starts[codes] - ends + n, n) + np.arange(ends[-1])])
        return out


def worker_encoder(path: str):
    """One encoder a worker process: this module comes with each task anew, the library's module stays."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    import tokenizers

    held = tokenizers.__dict__.setdefault("_held_encoders", {})
    if path not in held:
        held.clear()
        held[path] = PieceCodes(tokenizers.Tokenizer.from_file(path))
    return held[path]


def encode_all(encoder: PieceCodes, texts: list[str]) -> list[np.ndarray]:
    """Each text's ids and the end id."""
    if encoder.apart:
        return encoder.encode(texts)
    return [np.array([*e.ids, END_ID], np.uint32) for e in encoder.tok.encode_batch_fast(texts, add_special_tokens=False)]


def plain(blocks: list[np.ndarray]) -> list[bytes]:
    """Ids as ``id_coder`` takes them."""
    return [b.astype("<u4").tobytes() for b in blocks]


def _group_rows(part: int, block: int, before: int, docs: list, ids: np.ndarray, opened: int | None, code=mixing_coder.encode) -> pa.RecordBatch:
    """Blocks of one group. docs: (doc_id, ids) pieces; opened: where the first piece's document began, if earlier."""
    lanes = max(1, min(LANES, len(ids) // MIN_BLOCK))
    size = -(-len(ids) // lanes)
    cuts = list(range(0, len(ids), size))
    blobs = code([ids[a : a + size] for a in cuts])
    ends = np.cumsum([n for _, n in docs])
    doc_ids, pieces, begins, first = [], [], [], []
    for a in cuts:
        b = min(a + size, len(ids))
        lo, hi = int(np.searchsorted(ends, a, side="right")), int(np.searchsorted(ends, b, side="left"))
        own = range(lo, hi + 1)
        starts = [int(ends[k] - docs[k][1]) for k in own]
        doc_ids.append([docs[k][0] for k in own])
        pieces.append([min(b, int(ends[k])) - max(a, s) for k, s in zip(own, starts, strict=True)])
        begins.append([s >= a and not (opened is not None and k == 0) for k, s in zip(own, starts, strict=True)])
        first.append(opened if opened is not None and lo == 0 else before + starts[0])
    n = len(cuts)
    return pa.RecordBatch.from_arrays(
        [
            pa.array([part] * n, pa.int32()), pa.array(range(block, block + n), pa.int32()),
            pa.array([before + a for a in cuts], pa.int64()), pa.array([min(size, len(ids) - a) for a in cuts], pa.int64()),
            pa.array(first, pa.int64()), pa.array(doc_ids, pa.list_(pa.int64())), pa.array(pieces, pa.list_(pa.int64())),
            pa.array(begins, pa.list_(pa.bool_())), pa.array(blobs, pa.binary()),
        ],
        ["part", "block", "before", "n_ids", "first_begin", "doc_ids", "piece_ids", "begins", "payload"],
    )


def text_slices(batches: Iterator[pa.RecordBatch], rows: int, most: int) -> Iterator[pa.RecordBatch]:
    """Slices of so many rows and so many bytes of text at most, and of a row at least."""
    for b in batches:
        at, ends = 0, np.cumsum(pc.fill_null(pc.binary_length(column(b, "text")), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
        while at < b.num_rows:
            begun = int(ends[at - 1]) if at else 0
            to = max(at + 1, min(at + rows, int(np.searchsorted(ends, begun + most, side="right"))))
            yield b.slice(at, to - at)
            at = to


def coded_blocks(docs: DataFrame, tokenizer: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of coded blocks, in ascending doc_id order by (part, block)."""
    path = tokenizer_file(tokenizer)
    in_jvm = id_coder.available(docs.sparkSession)
    code = plain if in_jvm else mixing_coder.encode

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        tok = worker_encoder(path)
        held: list[np.ndarray] = []
        docs: list[tuple[int | None, int]] = []
        n = block = before = 0
        opened: int | None = None
        for b in text_slices(batches, 2000, 1 << 23):
            texts = [t or "" for t in column(b, "text").to_pylist()]
            for doc_id, ids in zip(column(b, "doc_id").to_pylist(), encode_all(tok, texts), strict=True):
                begin = before + n
                while n + len(ids) >= GROUP:  # a group is full; a document may go on in the next one
                    take = GROUP - n
                    out = _group_rows(part, block, before, [*docs, (doc_id, take)], np.concatenate([*held, ids[:take]]), opened, code)
                    block, before = block + out.num_rows, before + GROUP
                    yield out
                    held, docs, n, ids = [], [], 0, ids[take:]
                    opened = begin if len(ids) else None
                if len(ids):
                    held.append(ids)
                    docs.append((doc_id, len(ids)))
                    n += len(ids)
        if n:
            yield _group_rows(part, block, before, docs, np.concatenate(held), opened, code)

    base = keyed(docs, id_col, text_col)
    n = int(base.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    # The head of the text tells apart the rows that share an id (or have none), in the order of the files.
    head = F.substring("text", 1, 32)
    blocks = base.repartitionByRange(n, "doc_id", head).sortWithinPartitions("doc_id", "text").mapInArrow(run, BLOCKS)
    return blocks.withColumn("payload", id_coder.encoded(docs.sparkSession, "payload")) if in_jvm else blocks


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Blocks of ids in the order of their files to pieces of documents; pieces that follow each other are one."""
    names = [c.split()[0] for c in PIECES.split(", ")]
    kinds = (pa.int32(), *[pa.int64()] * 5)

    def rows(pieces: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*pieces, strict=True), kinds, strict=True)], names)

    open_: list | None = None
    for b in slices(batches, LANES):
        done = []
        ids = [np.frombuffer(x.as_buffer(), "<u4") for x in column(b, "payload")]
        cols = [column(b, c).to_pylist() for c in ("part", "before", "first_begin", "doc_ids", "piece_ids", "begins")]
        for raw, part, at, begin, docs, sizes, begins in zip(ids, *cols, strict=True):
            lo = 0
            for doc_id, n, new in zip(docs, sizes, begins, strict=True):
                begin = at + lo if new else begin
                piece = raw[lo : lo + n].data
                if open_ is not None and open_[:2] == [part, begin] and open_[3] + open_[4] == at + lo:
                    open_[4] += n
                    open_[5] = zlib.crc32(piece, open_[5])
                else:
                    if open_ is not None:
                        done.append(open_)
                    open_ = [part, begin, doc_id, at + lo, n, zlib.crc32(piece)]
                lo += n
        if done:
            yield rows(done)
    if open_ is not None:
        yield rows([open_])


def _read_coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """As ``_read``, from coded blocks."""

    def ids(b: pa.RecordBatch) -> pa.RecordBatch:
        blocks = mixing_coder.decode(column(b, "payload").to_pylist()) if b.num_rows else []
        return b.set_column(b.schema.get_field_index("payload"), "payload", pa.array(plain(blocks), pa.binary()))

    return _read(ids(b) for b in slices(batches, LANES))


def joined_crc(a: int, b: int, n: int) -> int:
    """crc32 of x + y from those of x and y, where y has n bytes: a shift by n zero bytes is linear over bits."""

    def apply(m: list[int], v: int) -> int:
        out = k = 0
        while v:
            if v & 1:
                out ^= m[k]
            v, k = v >> 1, k + 1
        return out

    square = lambda m: [apply(m, x) for x in m]
    step = [0xEDB88320, *(1 << k for k in range(31))]  # one zero bit
    for _ in range(3):
        step = square(step)
    while n:
        if n & 1:
            a = apply(step, a)
        n >>= 1
        if n:
            step = square(step)
    return a ^ b


def _whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(part, doc_id, before, n_tokens, ids_crc32) of documents from their pieces in order."""
    names = ["part", "doc_id", "before", "n_tokens", "ids_crc32"]
    for b in batches:
        crc, n = [], []
        for pieces in column(b, "pieces").to_pylist():
            c = pieces[0]["crc"]
            for p in pieces[1:]:
                c = joined_crc(c, p["crc"], 4 * p["n"])
            crc.append(c)
            n.append(sum(p["n"] for p in pieces))
        yield pa.RecordBatch.from_arrays([*(column(b, c) for c in ("part", "doc_id", "begin")), pa.array(n, pa.int64()), pa.array(crc, pa.int64())], names)


def documents_of(blocks: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, decoded from the blocks.

    Offsets of partitions are summed over one row a partition, whose number is set by the job.
    """
    sizes = blocks.groupBy("part").agg(F.sum("n_ids").alias("n"))
    offsets = sizes.select("part", (F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")).alias("offset"))
    read = _read
    if id_coder.available(blocks.sparkSession):
        blocks = blocks.withColumn("payload", id_coder.decoded(blocks.sparkSession, "payload"))
    else:
        read = _read_coded
    pieces = blocks.select("part", "before", "first_begin", "doc_ids", "piece_ids", "begins", "payload").mapInArrow(read, PIECES)
    docs = (
        pieces.groupBy("part", "begin", "doc_id")
        .agg(F.sort_array(F.collect_list(F.struct("at", "n", "crc"))).alias("pieces"))
        .mapInArrow(_whole, "part int, doc_id long, before long, n_tokens long, ids_crc32 long")
    )
    return docs.join(F.broadcast(offsets), "part").select("doc_id", (F.col("offset") + F.col("before")).alias("start"), "n_tokens", "ids_crc32")


def ids_of(blocks: DataFrame) -> DataFrame:
    """(part, block, ids) of every block, each read alone."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, LANES):
            ids = mixing_coder.decode(column(b, "payload").to_pylist()) if b.num_rows else []
            yield pa.RecordBatch.from_arrays([column(b, "part"), column(b, "block"), pa.array([x.astype(np.int64) for x in ids], pa.list_(pa.int64()))], ["part", "block", "ids"])

    return blocks.select("part", "block", "payload").mapInArrow(run, "part int, block int, ids array<long>")


def write_tokens(docs: DataFrame, tokenizer: str | None = None) -> DataFrame:
    """Write the files into the shared folder and return their rows, read back."""
    return written(coded_blocks(docs, tokenizer), "token-blocks")


def op2_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return documents_of(write_tokens(load(spark, sf_dir, "documents")))
