"""Secret scans: fixed patterns, then a token-efficiency test for random strings.

Ordinary words and names become few tokens of many characters under a byte-level
vocabulary; random strings become many tokens of few. A run of key characters of any
alphabet with letters that averages few characters a token (KEY_RATIO, or WORD_RATIO
where it could be words) is reported, unless it is a known digest (a hash with its name
before it, or listed), a UUID, part of a url, path or mail address, or overlaps a
pattern's span.

Defined results: a null text is an empty one and gives zero counts and an empty
span list; repeated rows are reported alike; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
import re
from bisect import bisect_left
from collections.abc import Iterator
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import column, keyed, load, slices

# Fixed patterns of the contract; the shortest accepted lengths beside them.
ASSIGN = re.compile(r"((?i:password|passwd|secret|token|api_?key))[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{32,}")
ASSIGN_MIN, ACCESS_MIN = 8, 16
KINDS = ("assign", "access", "hex", "random")

#: The method's own limits: shortest run, and the longest average of characters a token by what a run looks like.
#: (short runs, runs of LONG_RUN or more); words of the given texts are above those of WORD_RATIO.
MIN_RUN, LONG_RUN = 16, 20
KEY_RATIO, WORD_RATIO = (1.8, 2.0), (1.55, 1.9)
RUN = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
#: Letters of one case or capitalised, as words are, with or without separators.
WORD_LIKE = re.compile(r"[+/_=-]*(?:[A-Z]?[a-z]*[+/_=-]+)*[A-Z]?[a-z]*|[A-Z+/_=-]+")
UUID = re.compile(r"[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}")
DIGEST_NAME = re.compile(r"(?:md5|sha-?1|sha-?224|sha-?256|sha-?384|sha-?512|blake2[bs]|integrity|checksum|etag|commit)[\"'\s:=_-]*$", re.I)
#: Urls, mail addresses and paths up to the run; a dot alone doesn't make one (tokens of dotted parts).
IDENTIFIER_BEFORE = re.compile(r"(?:[a-z][a-z0-9+.-]*://\S*|www\.\S*|[\w.+-]+@[\w.-]*|(?:^|[\"'(=])(?:[a-z]:|[~.]+)?[/\\]\S*|[\w.]+[/\\])$", re.I)

#: After a dot: the rest of a host's name, or of a relative path, and a slash.
PLACE = re.compile(r"[a-z-]*/")


def vocabulary(path: str | None = None) -> str:
    """Place of the ranks file; a parameter, the public vocabulary by default."""
    if path:
        return path
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def encoder(path: str):
    import tiktoken

    pattern = r"'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


def pattern_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the contract's patterns."""
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_MIN]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_MIN]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(out)


def is_random(run: str, enc) -> bool:
    """Whether the vocabulary finds too little in ``run``; numbers look the same either way, so a letter is needed."""
    if not re.search("[A-Za-z]", run):
        return False
    limit = (WORD_RATIO if WORD_LIKE.fullmatch(run) else KEY_RATIO)[len(run) >= LONG_RUN]
    return len(run) <= limit * len(enc.encode_ordinary(run))


def random_spans(text: str, taken: list[tuple[int, int, int]], enc, known: frozenset[str]) -> list[tuple[int, int, int]]:
    """(start, 3, end) of runs that the token-efficiency test exposes."""
    out = []
    starts = [s for s, _, _ in taken]
    reach = list(accumulate((e for _, _, e in taken), max))  # how far the spans up to each one go
    for m in RUN.finditer(text):
        a, b = m.span()
        before_b = bisect_left(starts, b)
        if before_b and reach[before_b - 1] > a:
            continue
        run = m[0]
        before = text[max(0, a - 200) : a]
        if UUID.search(run) or DIGEST_NAME.search(before[-40:]) or IDENTIFIER_BEFORE.search(before.rsplit(None, 1)[-1] if before and not before[-1].isspace() else ""):
            continue
        if before[-1:] in (".", "~") and PLACE.match(run):
            continue
        if hashlib.sha256(run.encode()).hexdigest() in known:
            continue
        if is_random(run, enc):
            out.append((a, 3, b))
    return out


def listed(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in sorted(spans))


def scan(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    vocab: str | None = None,
    known_digests: frozenset[str] = frozenset(),
) -> DataFrame:
    """Counts, the digest of the pattern spans, and all spans, for every row of ``docs``.

    ``known_digests``: sha256 of strings that are public (test keys, sample values);
    a fixed list of the caller's, sent with the code.
    """
    path = vocabulary(vocab)
    schema = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = None
        for b in slices(batches, 500):
            rows = []
            for text in column(b, "text").to_pylist():
                text = text or ""
                base = pattern_spans(text)
                extra = []
                if RUN.search(text):
                    enc = enc or encoder(path)
                    extra = random_spans(text, base, enc, known_digests)
                n = [sum(k == x for _, k, _ in base) for x in range(3)]
                rows.append((*n, hashlib.sha256(listed(base).encode()).hexdigest(), listed(base + extra)))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
            kinds = [pa.int64()] * 3 + [pa.string()] * 2
            yield pa.RecordBatch.from_arrays(
                [column(b, "doc_id"), *(pa.array(c, t) for c, t in zip(cols, kinds, strict=True))],
                ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"],
            )

    return keyed(docs, id_col, text_col).mapInArrow(run, schema)


def redact(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", mask: str = "[secret]", **options) -> DataFrame:
    """(doc_id, text) with every span replaced; overlapping spans become one mask."""
    path = vocabulary(options.get("vocab"))
    known = options.get("known_digests", frozenset())

    def clean(text: str, enc) -> str:
        base = pattern_spans(text)
        out, at = [], 0
        for a, _, b in sorted(base + random_spans(text, base, enc, known)):
            if a >= at:
                out += [text[at:a], mask]
            at = max(at, b)
        return "".join(out) + text[at:]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        for b in slices(batches, 500):
            texts = [None if t is None else clean(t, enc) for t in column(b, "text").to_pylist()]
            yield pa.RecordBatch.from_arrays([column(b, "doc_id"), pa.array(texts, pa.string())], ["doc_id", "text"])

    return keyed(docs, id_col, text_col).mapInArrow(run, "doc_id long, text string")


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(load(spark, sf_dir, "documents"))
