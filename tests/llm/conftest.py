import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, fp long, words string, h string, part int, place long, rate double, first long, _k string, node long"


def sentence(rng, n):
    return " ".join(rng.choice(["ther", "onle", "ing", "was", "Ndre", "tion", "ha", "est", "from", "by", "wherea", "blein", "shor"]) + rng.choice(["", "s", "ed", ","]) for _ in range(n))


def texts() -> list:
    """Small corpus: copies, near copies, shared passages, junk, nulls, empty and long texts."""
    rng = random.Random(3)
    base = [sentence(rng, rng.randint(60, 150)) for _ in range(14)]
    out = list(base)
    out += [base[0], base[1], base[1]]
    for k in (2, 3, 4):
        w = base[k].split(" ")
        w[len(w) // 2] = "changed"
        out.append(" ".join(w))
    passage = sentence(rng, 55)
    out += [base[5] + "\n" + passage, passage + "\n" + base[6], "x" + passage]
    out += ["\n".join([base[7], base[8][:200], base[7]]), "a b", "", "  \t\n ", None, "the the the " * 40, "é" * 70 + "ß" * 70]
    out.append(" ".join(sentence(rng, 2000) for _ in range(5)))
    return out


def rows_of(ts) -> list:
    return [(i, t, "en", f"src{i % 3}" if i % 7 else None, len(t or ""), 1, "w", "h", 2, 3, 0.5, 4, "k", 5) for i, t in enumerate(ts)]


@pytest.fixture(scope="session")
def corpus():
    return texts()


@pytest.fixture(scope="session")
def docs(spark, corpus):
    return spark.createDataFrame(rows_of(corpus), SCHEMA).repartition(3)


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def odd_docs(spark, corpus):
    """Null and repeated ids beside ordinary ones."""
    rows = rows_of(corpus[:6])
    rows += [(None, corpus[0], *rows[0][2:]), (None, None, *rows[0][2:]), (3, corpus[3], *rows[3][2:]), (3, "another text under the same id", *rows[3][2:])]
    return spark.createDataFrame(rows, SCHEMA)
