import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from relstrata.llm import mixing_coder, token_output


@settings(max_examples=40, deadline=None)
@given(st.lists(st.lists(st.integers(0, 65534), max_size=60), min_size=1, max_size=6))
def test_coder_round_trip(blocks):
    arrays = [np.array(b, np.uint16) for b in blocks]
    for a, b in zip(arrays, mixing_coder.decode(mixing_coder.encode(arrays)), strict=True):
        assert np.array_equal(a, b)


def test_coder_compresses_what_it_can_predict():
    ids = np.tile(np.arange(50, dtype=np.uint16) * 31, 80)
    assert len(mixing_coder.encode([ids])[0]) < len(ids) / 4


def test_blocks_are_independent_and_checked():
    a = [np.arange(300, dtype=np.uint16), np.repeat(np.uint16(7), 500)]
    blobs = mixing_coder.encode(a)
    assert np.array_equal(mixing_coder.decode([blobs[1]])[0], a[1])
    bad = bytearray(blobs[0])
    bad[30] ^= 1
    with pytest.raises(ValueError):
        mixing_coder.decode([bytes(bad)])
    with pytest.raises(ValueError):
        mixing_coder.decode([blobs[0][:-2]])


def reference(rows):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(token_output.tokenizer_file())
    start, out = 0, []
    for d, t in rows:
        ids = tok.encode(t or "", add_special_tokens=False).ids + [2]
        out.append((d, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    return out


@pytest.mark.parametrize("name", ["docs", "odd_docs"])
def test_documents_come_back(name, request, monkeypatch):
    monkeypatch.setattr(token_output, "GROUP", 700)  # documents span groups and blocks
    monkeypatch.setattr(token_output, "MIN_BLOCK", 64)
    df = request.getfixturevalue(name)
    rows = sorted(((r["doc_id"], r["text"]) for r in df.collect()), key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or ""))
    got = token_output.documents_of(token_output.write_tokens(df)).collect()
    assert sorted(map(tuple, got), key=lambda r: r[1]) == reference(rows)


def test_block_reading(docs):
    blocks = token_output.write_tokens(docs)
    n = sum(len(r["ids"]) for r in token_output.ids_of(blocks).collect())
    assert n == sum(r["n_ids"] for r in blocks.select("n_ids").collect())


def test_empty(no_docs):
    assert token_output.documents_of(token_output.write_tokens(no_docs)).count() == 0


ODD = ["it's we'll 'sab", "  two  spaces\n\n\nlines ", "a <|endoftext|> b", "<|endoftext|><|endoftext|>", "中文 123abc !!??", "\x00\x01 z", "a\u00a0b\u2003c", None, ""]


def test_ids_are_the_librarys_with_its_defaults(spark):
    from tokenizers import Tokenizer

    assert Tokenizer.from_file(token_output.tokenizer_file()).encode("a <|endoftext|> b", add_special_tokens=False).ids == [64, 220, 50256, 275]
    df = spark.createDataFrame(list(enumerate(ODD)), "doc_id long, text string").repartition(3)
    got = sorted(map(tuple, token_output.documents_of(token_output.write_tokens(df)).collect()), key=lambda r: r[1])
    assert got == reference(list(enumerate(ODD)))


def test_ids_of_a_large_vocabulary():
    rng = np.random.default_rng(5)
    blocks = [rng.integers(0, 2**32 - 1, 300).astype(np.uint32), np.array([2**32 - 2, 0, 70_000] * 30, np.uint32), rng.integers(0, 200_000, 500).astype(np.uint32)]
    assert all(np.array_equal(a, b) for a, b in zip(blocks, mixing_coder.decode(mixing_coder.encode(blocks)), strict=True))


@pytest.mark.parametrize("a,b", [(b"", b"x"), (b"abc", b""), (b"abc", b"defg" * 1000), (b"\x00" * 7, b"\x00" * 9)])
def test_joined_checksums(a, b):
    assert token_output.joined_crc(zlib.crc32(a), zlib.crc32(b), len(b)) == zlib.crc32(a + b)


def test_blocks_read_by_several_tasks(docs, monkeypatch):
    """Documents over several blocks, and blocks dealt out in another order."""
    monkeypatch.setattr(token_output, "GROUP", 900)
    monkeypatch.setattr(token_output, "MIN_BLOCK", 64)
    blocks = token_output.write_tokens(docs)
    want = sorted(map(tuple, token_output.documents_of(blocks).collect()))
    assert sorted(map(tuple, token_output.documents_of(blocks.repartition(7)).collect())) == want


def test_many_rows_under_one_id(spark, corpus):
    rows = [(None if k % 3 else 5, t) for k, t in enumerate([*corpus[:12], *ODD])]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    rows = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, (r[1] or "").encode()))
    got = sorted(map(tuple, token_output.documents_of(token_output.write_tokens(df)).collect()), key=lambda r: r[1])
    assert got == reference(rows)
