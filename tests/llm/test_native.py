"""Operators of built-in functions only: plans without Python, and results against brute force or SQL."""

import math
from collections import Counter

import pytest

from relstrata.llm import decontaminate, line_dedup, mixing, url_filter


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_no_python_in_native_plans(docs, spark):
    bench = spark.createDataFrame([(1, "one two three four five six seven eight nine ten eleven twelve thirteen")], "item_id long, text string")
    for df in (mixing.replicate(docs), decontaminate.overlaps(docs, bench), line_dedup.dedup_lines(docs.select("doc_id", "text"))):
        assert not any(x in plan(df) for x in ("Python", "Pandas", "Arrow"))


# --- mixing ------------------------------------------------------------------------------------------


def test_poisson_inverse(spark):
    from pyspark.sql import functions as F

    for rate in (0.1, 1.0, 5.0):
        df = spark.range(1, 1000).select((F.col("id") / 1000).alias("u"))
        for r in df.select("u", mixing.poisson_inverse(F.col("u"), F.lit(rate)).alias("k")).collect():
            cdf, k = math.exp(-rate), 0
            term = cdf
            while r["u"] >= cdf:
                k += 1
                term *= rate / k
                cdf += term
            assert r["k"] == k


def test_rates_meet_targets(spark):
    rows = [(i, "t", "a" if i < 9000 else "b") for i in range(12_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    rates = {r["source"]: r["rate"] for r in mixing.source_rates(df).collect()}
    assert abs(rates["a"] * 9000 + rates["b"] * 3000 - 12_000) < 1e-6
    assert abs(rates["a"] * 9000 / (rates["b"] * 3000) - math.sqrt(3)) < 1e-9
    n = Counter(r["source"] for r in mixing.replicate(df).select("source").collect())
    for s, size in (("a", 9000), ("b", 3000)):
        assert abs(n[s] - rates[s] * size) < 5 * math.sqrt(rates[s] * size)


def test_given_weights_and_limits(spark, docs):
    w = spark.createDataFrame([("src1", 1.0), ("src1", 1.0), ("none", 3.0)], "source string, weight double")
    assert {r["source"] for r in mixing.replicate(docs.limit(12), weights=w).select("source").collect()} <= {"src1"}
    tiny = spark.createDataFrame([(i, "x", "big" if i else "small") for i in range(500)], "doc_id long, text string, source string")
    with pytest.raises(Exception, match="MAX_RATE"):
        mixing.replicate(tiny, weights=spark.createDataFrame([("small", 1.0)], "source string, weight double")).collect()


@pytest.mark.parametrize("name", ["docs", "odd_docs", "no_docs"])
def test_mixing_is_repeatable_and_sorted(name, request):
    df = request.getfixturevalue(name)
    a = [(r["doc_id"], r["copy_no"], r["order_key"]) for r in mixing.replicate(df).collect()]
    b = [(r["doc_id"], r["copy_no"], r["order_key"]) for r in mixing.replicate(df.repartition(5)).collect()]
    assert Counter(a) == Counter(b) and [x[2] for x in a] == sorted(x[2] for x in a)


# --- decontamination ---------------------------------------------------------------------------------


def brute_overlaps(docs, items):
    import re

    tok = lambda t: [w for w in re.split(r"[\W_]+", (t or "").lower()) if w]
    out = set()
    for d, text in docs:
        a = tok(text)
        for i, item in items:
            b = tok(item)
            if len(b) < 8:  # held whole; in fewer than 4 tokens only a document of nothing else
                if b and (b == a if len(b) < 4 else any(a[k : k + len(b)] == b for k in range(len(a)))):
                    out.add((d, i))
                continue
            width = min(13, len(b))
            for diag in range(-len(b), len(a)):
                eq = [a[k + diag] == b[k] for k in range(len(b)) if 0 <= k + diag < len(a)]
                if any(sum(eq[s : s + width]) >= width - (2 if len(b) >= 13 else 0) for s in range(len(eq) - width + 1)):
                    out.add((d, i))
    return out


def test_overlaps_against_brute_force(spark, corpus):
    import random

    rng = random.Random(5)
    items = [(k, " ".join(corpus[k].split(" ")[10 : 10 + n])) for k, n in ((0, 40), (1, 13), (2, 20), (3, 9), (4, 5))] + [(9, None), (10, ""), (11, "a b"), (12, "the"), (13, "the the the the")]
    rows = [(i, t) for i, t in enumerate(corpus) if t is None or len(t) < 3000]
    for k, w in ((100, 30), (101, 13), (102, 18)):
        words = items[k - 100][1].split(" ")
        for place in rng.sample(range(len(words)), 2):
            words[place] = "zz"
        rows.append((k, "before text " + " ".join(words) + " after"))
    got = decontaminate.overlaps(
        spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    ).collect()
    assert {(r["doc_id"], r["item_id"]) for r in got} == brute_overlaps(rows, items)
    assert {11, 13} <= {r["item_id"] for r in got} and 12 not in {r["item_id"] for r in got}


def test_seeds_that_are_not_broadcast(spark, corpus, odd_docs, monkeypatch):
    items = spark.createDataFrame([(k, " ".join((corpus[k] or "").split(" ")[10:40])) for k in range(5)] + [(7, "a b")], "item_id long, text string")
    for df in (odd_docs, spark.createDataFrame(list(enumerate(corpus)), "doc_id long, text string")):
        want = sorted(map(str, decontaminate.overlaps(df, items).collect()))
        with monkeypatch.context() as m:
            m.setattr(decontaminate, "BROADCAST_SEEDS", 3)
            assert sorted(map(str, decontaminate.overlaps(df, items).collect())) == want and want


def test_one_mask_meets_every_window():
    from itertools import combinations

    for mask in decontaminate.MASKS:
        for lost in combinations(range(decontaminate.WINDOW), decontaminate.MISMATCHES):
            assert any(not any(s + p in lost for p in mask) for s in range(decontaminate.WINDOW - decontaminate.SPAN + 1))


def test_decontamination_edges(spark, odd_docs, no_docs, docs):
    bench = spark.createDataFrame([(1, None), (2, "short"), (3, "  "), (None, "a b c d e f g h i")], "item_id long, text string")
    for df in (odd_docs, no_docs, docs):
        assert decontaminate.decontaminated(df, bench).count() == df.count()
    assert decontaminate.overlaps(docs, bench.limit(0)).count() == 0


# --- line dedup --------------------------------------------------------------------------------------


def distance_at_most_one(a, b):
    if abs(len(a) - len(b)) > 1:
        return False
    p = 0
    while p < min(len(a), len(b)) and a[p] == b[p]:
        p += 1
    return a[p + (len(a) >= len(b)) :] == b[p + (len(b) >= len(a)) :] or a == b


def brute_lines(rows):
    seen, out = [], {}
    for d, text in sorted(rows, key=lambda r: r[0]):
        gone = []
        for k, line in enumerate((text or "").split("\n")):
            w = line.split()
            if not w:
                continue
            if any(w == v or (min(len(w), len(v)) >= 10 and distance_at_most_one(w, v)) for v in seen):
                gone.append(k)
            seen.append(w)
        out[d] = gone
    return out


def test_lines_against_brute_force(spark):
    import random

    from .conftest import sentence

    rng = random.Random(8)
    pool = [sentence(rng, n).split(" ") for n in (9, 10, 11, 12, 12, 15, 30, 3)]
    lines = []
    for w in pool * 3:
        v = list(w)
        kind = rng.randrange(4)
        at = rng.randrange(len(v))
        if kind == 0:
            v[at] = "new"
        elif kind == 1:
            del v[at]
        elif kind == 2:
            v.insert(at, rng.choice(["new", v[at]]))
        lines.append(" ".join(v))
    lines += [" ".join(w) for w in pool] + ["", "  ", "a a a a a a a a a a", "a a a a a a a a a"]
    rng.shuffle(lines)
    rows = [(d, "\n".join(lines[d * 3 : d * 3 + 3])) for d in range(len(lines) // 3)] + [(900, None), (901, "")]
    out = line_dedup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string"))
    got = {r["doc_id"]: r for r in out.collect()}
    want = brute_lines(rows)
    for d, text in rows:
        assert got[d]["removed"] == want[d], d
        kept = None if text is None else "\n".join(x for k, x in enumerate(text.split("\n")) if k not in want[d])
        assert got[d]["text"] == kept


@pytest.mark.parametrize("name", ["docs", "odd_docs", "no_docs"])
def test_line_edges(name, request):
    df = request.getfixturevalue(name)
    assert line_dedup.dedup_lines(df).count() == df.count()


# --- urls --------------------------------------------------------------------------------------------


def test_url_rules(spark):
    cases = {
        "http://A.Example.COM/en/77?x": ("a.example.com", "/en/77", "example.com/en/7", "allow"),
        "https://x.com/en/": ("x.com", "/en/", "com/en/", "block"),
        "https://x.com/en": ("x.com", "/en", None, "allow"),
        "https://example.net/de/8#f": ("example.net", "/de/8", "example.net/de/8", "block"),
        "https://notexample.com/en/7": ("notexample.com", "/en/7", "com/en/", "block"),
        "no scheme": ("", "", None, "allow"),
        "http://": ("", "", None, "allow"),
        "http://org/es/a://b/es/": ("org", "/es/a://b/es/", "org/es/", "block"),
        "http://a..org/es/": ("a..org", "/es/", "org/es/", "block"),
        None: ("", "", None, "allow"),
        "": ("", "", None, "allow"),
    }
    rows = [(i, u, 1) for i, u in enumerate(cases)] * 2
    df = spark.createDataFrame(rows, "page_id long, url string, rule int")
    got = url_filter.judge(df, url_filter.rule_table(spark, url_filter.CONTRACT_RULES)).collect()
    assert len(got) == len(rows)
    for r in got:
        assert (r["host"], r["path"], r["rule"], r["verdict"]) == cases[r["url"]], r["url"]


def test_url_without_rules(spark):
    df = spark.createDataFrame([(1, "http://a.b/c")], "page_id long, url string")
    none = spark.createDataFrame([], "verdict string, rule string")
    assert url_filter.judge(df, none).first()["verdict"] == "allow"
    assert url_filter.judge(df.limit(0), none).count() == 0


def test_frequent_lines_in_many_tasks(spark, monkeypatch):
    common, near = "one two three four five six seven eight nine ten", "one two three four five six seven eight nine TEN"
    rows = [(d, "\n".join([f"own words of {d}", common, near if d % 2 else "short"])) for d in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    want = sorted(map(str, line_dedup.dedup_lines(df).collect()))
    monkeypatch.setattr(line_dedup, "FREQUENT", 3)
    assert sorted(map(str, line_dedup.dedup_lines(df).collect())) == want
    assert sum("own words" in r["text"] and common not in r["text"] for r in line_dedup.dedup_lines(df).collect()) == 59


def test_every_rule_of_the_contract_by_its_own_word(spark):
    """The contract's list, rule by rule; each on its own host and on a subdomain."""
    rules = {"com/en/": "block", "example.com/en/7": "allow", "net/de/": "allow", "example.net/de/8": "block", "org/es/": "block"}
    rows = [(k, f"https://{sub}{rule}", rule, word) for k, sub in enumerate(("", "a.b.")) for rule, word in rules.items()]
    df = spark.createDataFrame(rows, "page_id long, url string, want_rule string, want_verdict string")
    # A block by default, so that an allow can only come from its rule.
    got = url_filter.judge(df, url_filter.rule_table(spark, url_filter.CONTRACT_RULES), default="block").collect()
    assert len(got) == len(rows)
    assert all((r["rule"], r["verdict"]) == (r["want_rule"], r["want_verdict"]) for r in got), got
