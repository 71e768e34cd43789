"""Main text of web pages by the maximum-scoring contiguous token region.

A page is a sequence of tokens: words and tags. A word's score is the log odds of
standing in the main text given where it stands (its nearest block element with
class or id, and whether a boilerplate element is open around it), or nothing where these
speak against it: such a stretch of words then counts as one more tag. A tag costs a fixed amount,
a stretch of boilerplate another. Word scores and both costs come from labelled pages: pages whose
author marked the article element serve as labels, and the marks themselves are not scored. One linear
scan finds the contiguous region of the highest total; its words that have a score are the text.
As all words between two block tags have one score, a region never ends inside a block, and
the scan goes from block to block.

Defined results: null or empty html gives an empty text; a page without any positive
word gives an empty text; unclosed tags and a cut-off end are read as browsers do;
an empty table gives an empty result; repeated rows stay repeated.
"""

from __future__ import annotations

import html as html_lib
import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import column, hash_sample, load, slices, with_fields

#: Labelled pages that weights are fitted on, at most; taken by hash, so any run takes the same.
FIT_PAGES = 2_000
#: Contexts whose weights are kept; a rarer one falls back to its element, then to the default.
FIT_CONTEXTS = 1_000
#: Costs that are tried on the labelled pages: of a tag, and of a stretch of words without a score.
TAG_COSTS = (0.05, 0.1, 0.2, 0.4, 0.8, 1.6)
BOILER_COSTS = (0.5, 1.0, 2.0, 4.0)
Model = tuple[dict[str, float], float, float]

# Element names by their role in HTML, and words that name boilerplate in class and id.
RAW = {"script", "style", "noscript", "template", "textarea", "iframe", "svg", "title"}
INLINE = {"a", "abbr", "b", "bdi", "bdo", "cite", "code", "data", "dfn", "em", "font", "i", "kbd", "mark", "q", "s", "samp", "small", "span", "strong", "sub", "sup", "time", "tt", "u", "var", "wbr", "ins", "del", "img"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"}
BOILER = {"nav", "header", "footer", "aside", "form", "menu", "dialog", "head", "button", "select"}
BOILER_WORDS = {"ad", "ads", "advert", "advertisement", "banner", "breadcrumb", "breadcrumbs", "comment", "comments", "consent", "cookie", "cookies", "footer", "header", "menu", "nav", "navbar", "newsletter", "notice", "popup", "promo", "related", "share", "sidebar", "social", "sponsor", "sponsored", "subscribe", "widget"}

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*)/?>|<[!?][^>]*>", re.S)
NAMES = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
PART = re.compile(r"[a-z]+")


class Block:
    """One run of text between block boundaries: its context, its words, the tags before it."""

    __slots__ = ("context", "tags", "marked", "pieces")

    def __init__(self, context: str, tags: int, marked: bool):
        self.context, self.tags, self.marked, self.pieces = context, tags, marked, []

    def text(self) -> str:
        return " ".join(html_lib.unescape("".join(self.pieces)).split())


def blocks(page: str) -> tuple[list[Block], bool]:
    """Text blocks in page order, and whether an article element marks the main text."""
    out: list[Block] = []
    stack: list[tuple[str, str, bool]] = []  # element, its name with class or id, boilerplate opened here
    boiler = marked_depth = 0
    seen_mark = False
    now: Block | None = None
    tags = 0
    at = 0

    def close(upto: int) -> None:
        nonlocal boiler, marked_depth
        for name, _, bad in stack[upto:]:
            boiler -= bad
            marked_depth -= name == "article"
        del stack[upto:]

    def put(text: str) -> None:
        nonlocal now, tags
        if now is None:
            if not text.strip():
                return
            where = next((label for name, label, _ in reversed(stack) if name not in INLINE), "")
            now = Block(("!" if boiler else "") + where, tags, marked_depth > 0)
            out.append(now)
            tags = 0
        now.pieces.append(text)

    for m in TOKEN.finditer(page):
        if m.start() < at:
            continue
        if m.start() > at:
            put(page[at : m.start()])
        at = m.end()
        name = (m[2] or "").lower()
        if not name:
            continue
        if name != "article":
            tags += 1
        if name in RAW:
            if not m[1]:
                end = re.compile(rf"</{name}\b[^>]*>", re.I).search(page, at)
                at = end.end() if end else len(page)
            now = None if name not in INLINE else now
            continue
        if name not in INLINE:
            now = None
        if m[1]:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == name:
                    close(k)
                    break
            continue
        if name in VOID:
            continue
        if name == "p":  # a paragraph ends where the next one begins
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == "p":
                    close(k)
                    break
                if stack[k][0] not in INLINE:
                    break
        if name in ("li", "tr", "td", "th", "dt", "dd", "option") and stack and stack[-1][0] == name:
            close(len(stack) - 1)
        words = {w for g in NAMES.findall(m[3] or "") for w in PART.findall(" ".join(g).lower())}
        bad = name in BOILER or bool(words & BOILER_WORDS)
        if name in ("html", "body", "main", "article"):
            bad = False
        label = name + "".join("." + w for w in sorted(words))[:80]
        boiler += bad
        if name == "article":
            marked_depth += 1
            seen_mark = True
        else:
            stack.append((name, label, bad))
            continue
        stack.append((name, "", False))
    if at < len(page):
        put(page[at:])
    return out, seen_mark


def best_region(scores: list[tuple[float, float]]) -> tuple[int, int]:
    """(first, past last) block of the highest total; (0, 0) if none is positive.

    Each entry is (cost of the tags before the block, score of its words).
    """
    best, region = 0.0, (0, 0)
    total, start = 0.0, 0
    for k, (cost, gain) in enumerate(scores):
        if total - cost <= 0:
            total, start = 0.0, k
        else:
            total -= cost
        total += gain
        if total > best:
            best, region = total, (start, k + 1)
    return region


def word_weight(weights: dict[str, float], context: str) -> float:
    if context in weights:
        return weights[context]
    return weights.get(context.split(".")[0], -1.0 if context.startswith("!") else 1.0)


def parsed(page: str) -> list[tuple[Block, str, int]]:
    """(block, text, words) of the blocks with words."""
    return [(b, t, t.count(" ") + 1) for b in blocks(page)[0] if (t := b.text())]


def region_text(found: list[tuple[Block, str, int]], model: Model) -> str:
    """Text of the best region: the words with a score, block by block."""
    weights, tag_cost, boiler_cost = model
    scored = []
    for b, _, n in found:
        w = word_weight(weights, b.context)
        scored.append((tag_cost * b.tags, w * n if w > 0 else -boiler_cost))
    lo, hi = best_region(scored)
    return "\n".join(t for (_, t, _), (_, gain) in zip(found[lo:hi], scored[lo:hi], strict=True) if gain > 0)


def main_text(page: str | None, model: Model) -> str:
    """The main text of one page."""
    return region_text(parsed(page), model) if page else ""


def labelled_text(page: str) -> str | None:
    """What the author marked as the article, less boilerplate in it; None without a mark."""
    found, marked = blocks(page)
    if not marked:
        return None
    return "\n".join(t for b in found if b.marked and not b.context.startswith("!") and (t := b.text()))


def fit(pages: DataFrame, html_col: str = "html") -> Model:
    """Weights per context and both costs, from at most FIT_PAGES labelled pages."""
    marked = pages.select(F.col(html_col).alias("html")).where(F.col("html").contains("<article"))
    sample = hash_sample(marked, F.col("html"), FIT_PAGES, 5, pages.count()).repartition(6)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        inside: Counter[str] = Counter()
        outside: Counter[str] = Counter()
        for b in batches:
            for page in column(b, "html").to_pylist():
                for block in blocks(page)[0]:
                    n = len(block.text().split())
                    (inside if block.marked else outside)[block.context] += n
                    (inside if block.marked else outside)[block.context.split(".")[0]] += n if "." in block.context else 0
        keys = sorted(inside | outside)
        yield pa.RecordBatch.from_pydict({"context": pa.array(keys, pa.string()), "inside": pa.array([inside[k] for k in keys], pa.int64()), "outside": pa.array([outside[k] for k in keys], pa.int64())})

    rows = (
        sample.mapInArrow(count, "context string, inside long, outside long")
        .groupBy("context")
        .agg(F.sum("inside").alias("i"), F.sum("outside").alias("o"))
        .orderBy(F.desc(F.col("i") + F.col("o")), "context")
        .limit(FIT_CONTEXTS)
        .collect()
    )
    weights = {r["context"]: max(-4.0, min(4.0, math.log((r["i"] + 0.5) / (r["o"] + 0.5)))) for r in rows}

    costs = [(t, b) for t in TAG_COSTS for b in BOILER_COSTS]

    def hits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        right = np.zeros(len(costs), np.int64)
        for b in batches:
            for page in column(b, "html").to_pylist():
                want, found = labelled_text(page), parsed(page)
                right += [region_text(found, (weights, *c)) == want for c in costs]
        yield pa.RecordBatch.from_pydict({"k": pa.array(range(len(costs)), pa.int32()), "right": pa.array(right)})

    tally = {r["k"]: r["r"] for r in sample.mapInArrow(hits, "k int, right long").groupBy("k").agg(F.sum("right").alias("r")).collect()}
    best = max(range(len(costs)), key=lambda k: (tally.get(k, 0), -abs(costs[k][0] - 0.2) - abs(costs[k][1] - 1.0)))
    return (weights, *costs[best])


def extract(pages: DataFrame, model: Model, html_col: str = "html") -> DataFrame:
    """``pages`` with ``text`` and ``n_chars`` (code points); every page, whole."""
    kept = [c for c in pages.columns if c not in ("text", "n_chars", html_col)]
    schema = with_fields(pages.select(*kept), "text string, n_chars long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 256):
            texts = [main_text(p, model) for p in column(b, "_html").to_pylist()]
            cols = [column(b, c) for c in kept] + [pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())]
            yield pa.RecordBatch.from_arrays(cols, [*kept, "text", "n_chars"])

    return pages.select(*kept, F.col(html_col).alias("_html")).mapInArrow(run, schema)


def op9_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages").select("page_id", "url", "html")
    return extract(pages, fit(pages)).select("page_id", "url", "text", "n_chars")
