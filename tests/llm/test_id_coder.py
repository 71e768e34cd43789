"""The coder as Spark runs it and as Python does."""

import numpy as np
import pytest
from relstrata.llm import id_coder, mixing_coder, token_output


def blocks():
    rng = np.random.default_rng(11)
    words = rng.zipf(1.3, 6000) % 50_000
    made = [words, np.tile(np.arange(50) * 31, 80), np.repeat(7, 30_000), [], [0], rng.integers(0, 2**32 - 1, 3000), [2**32 - 2, 0, 70_000] * 30, rng.integers(0, 70_000, 9000)]
    return [np.array(b, np.uint32) for b in made]


def test_both_coders_write_the_same_bytes_and_read_them(spark):
    made = blocks()
    df = spark.createDataFrame([(k, b) for k, b in enumerate(token_output.plain(made))], "k int, ids binary").repartition(3)
    coded = df.withColumn("code", id_coder.encoded(spark, "ids"))
    for r in coded.withColumn("back", id_coder.decoded(spark, "code")).collect():
        assert bytes(r["code"]) == mixing_coder.encode([made[r["k"]]])[0]
        assert bytes(r["back"]) == bytes(r["ids"])


@pytest.mark.parametrize("spoil", [lambda b: b[:-2], lambda b: b[:30] + bytes([b[30] ^ 1]) + b[31:], lambda b: b[:10], lambda b: b"x" + b[1:]])
def test_a_spoilt_block_fails(spark, spoil):
    code = mixing_coder.encode([np.arange(300, dtype=np.uint32)])[0]
    with pytest.raises(Exception, match="token block"):
        spark.createDataFrame([(spoil(code),)], "code binary").select(id_coder.decoded(spark, "code")).collect()


def test_no_worker_codes_in_python(docs, monkeypatch):
    """Coding in Python workers took 4.6 microseconds an id, beyond the budget by itself."""

    def never(_):
        raise AssertionError("coded in Python")

    want = sorted(map(tuple, token_output.documents_of(token_output.write_tokens(docs)).collect()))
    monkeypatch.setattr(mixing_coder, "encode", never)
    monkeypatch.setattr(mixing_coder, "decode", never)
    blocks = token_output.write_tokens(docs)
    assert sorted(map(tuple, token_output.documents_of(blocks).collect())) == want
    monkeypatch.undo()
    monkeypatch.setattr(id_coder, "available", lambda spark: False)
    assert sorted(map(tuple, token_output.documents_of(blocks).collect())) == want
    assert sorted(map(tuple, token_output.documents_of(token_output.write_tokens(docs)).collect())) == want
