from html.parser import HTMLParser

import pytest

from relstrata.llm import html_main as h

PAGE = """<!DOCTYPE html><html><head><title>T x</title><style>p{}</style><script>var t="</p>";</script></head><body>
<nav><ul><li><a href="/a">one</a></li><li><a href="/b">two</a></li></ul></nav><!-- ad --><div class="ad">buy this now it is good</div>
<article><h1>Head  line &amp; more</h1><p><b>First para.<br><p>Second&nbsp;para <i>with</i>
 inline.</p><div class="ad">advert inside</div><p>Third.</p></article><div class="comments"><p>nice post friend</p></div><footer>&copy; host words here</footer>"""
WANT = "Head line & more\nFirst para.\nSecond para with inline.\nThird."


def weights():
    return {"p": 4.0, "h1": 4.0, "!footer": -4.0, "!li": -4.0, "!div": -4.0, "!p": -4.0}, 0.2, 1.0


def test_page():
    assert h.main_text(PAGE, weights()) == WANT
    assert h.labelled_text(PAGE) == WANT


def test_best_region_is_the_maximum():
    import random

    rng = random.Random(1)
    for _ in range(300):
        s = [(rng.random(), rng.uniform(-3, 3)) for _ in range(rng.randrange(8))]

        def total(a, b, s=s):
            return sum(g for _, g in s[a:b]) - sum(c for c, _ in s[a + 1 : b])

        best = max([total(a, b) for a in range(len(s)) for b in range(a + 1, len(s) + 1)], default=0.0)
        a, b = h.best_region(s)
        assert abs((total(a, b) if b > a else 0.0) - max(best, 0.0)) < 1e-9


def test_region_is_the_best_of_all_token_runs():
    """Word by word and tag by tag, over all runs of tokens: the best one holds the same words."""
    import random

    rng = random.Random(2)
    for _ in range(60):
        page = "".join(f"<{(t := rng.choice(['p', 'h1', 'footer', 'li']))}>" + " ".join(["w"] * rng.randrange(5)) + f"</{t}>" for _ in range(rng.randrange(1, 9)))
        model = {k: rng.uniform(-2, 3) for k in ("p", "h1", "!footer", "li")}, rng.choice([0.2, 0.9, 2.1]), rng.choice([0.5, 2.0])
        tokens = []  # (score, block or None)
        for k, (b, _, n) in enumerate(h.parsed(page)):
            w = model[0][b.context]
            tokens += [(-model[1], None)] * b.tags + ([(w, k)] * n if w > 0 else [(-model[2], None)])
        best, words = 0.0, 0
        for a in range(len(tokens)):
            total = 0.0
            for z in range(a, len(tokens)):
                total += tokens[z][0]
                if total > best + 1e-9:
                    best, words = total, sum(k is not None for _, k in tokens[a : z + 1])
        assert len(h.main_text(page, model).split()) == words


class Outline(HTMLParser):
    """Another reading of a page: the article's blocks by the standard library's parser, without its boilerplate."""

    BLOCK = {"p", "h1", "h2", "h3", "div", "li", "ul", "ol", "article", "nav", "footer", "aside", "section", "form", "table", "tr", "td", "blockquote", "pre", "header", "main", "body"}
    SKIP = {"script", "style", "nav", "footer", "aside", "form", "header", "noscript"}

    def __init__(self, page):
        super().__init__(convert_charrefs=True)
        self.open, self.out, self.now = [], [], []
        self.feed(page)
        self.close()
        self.cut()

    def cut(self):
        if text := " ".join("".join(self.now).split()):
            self.out.append(text)
        self.now = []

    def handle_starttag(self, tag, attrs):
        if tag in self.BLOCK:
            self.cut()
        if tag == "p" and self.open and self.open[-1][0] == "p":
            self.open.pop()
        names = " ".join(v or "" for k, v in attrs if k in ("class", "id")).split()
        if tag not in ("br", "img", "meta", "link", "hr", "input"):
            self.open.append((tag, tag in self.SKIP or bool({"ad", "comments", "sidebar", "notice", "cookie", "comment", "share", "related", "newsletter"} & set(names))))

    def handle_endtag(self, tag):
        if tag in self.BLOCK:
            self.cut()
        if any(t == tag for t, _ in self.open):
            while self.open.pop()[0] != tag:
                pass

    def handle_data(self, data):
        if any(t == "article" for t, _ in self.open) and not any(bad for _, bad in self.open):
            self.now.append(data)


def test_pages_against_another_parser(spark):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    got = {r["page_id"]: r["text"] for r in h.extract(pages, h.fit(pages)).collect()}
    rows = [r for r in pages.collect() if "<article" in (r["html"] or "")]
    wrong = [r["page_id"] for r in rows if "\n".join(Outline(r["html"]).out) != got[r["page_id"]]]
    assert rows and len(wrong) <= 0.02 * len(rows), wrong[:10]


def test_held_out_accuracy(spark, sf):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    fit, rest = pages.where("page_id % 2 = 0"), pages.where("page_id % 2 = 1")
    got = {r["page_id"]: r for r in h.extract(rest, h.fit(fit)).collect()}
    rows = rest.collect()
    right = sum(got[r["page_id"]]["text"] == h.labelled_text(r["html"]) for r in rows)
    assert right >= 0.98 * len(rows)
    assert all(r["n_chars"] == len(r["text"]) for r in got.values())


@pytest.mark.parametrize("page", [None, "", "plain words", "<p>", "<div><p>a<p>b", "</p></div>text", "<script>x", "<a href='>'>q</a>", "&lt;p&gt; &#x41; &bad;", "<!-- open", "< b", "a" * 200_000])
def test_odd_pages(page):
    assert isinstance(h.main_text(page, weights()), str)


def test_edges(spark):
    schema = "page_id long, url string, html string, text string, n_chars string"
    df = spark.createDataFrame([(1, None, None, "clash", "c"), (1, "u", PAGE, "clash", "c"), (None, "u", "", None, None)], schema)
    model = h.fit(df)
    assert h.extract(df, model).count() == 3
    assert h.extract(df.limit(0), h.fit(df.limit(0))).count() == 0
