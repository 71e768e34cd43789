import random

import pytest
from relstrata.llm import token_output

ALPHABET = [*"     \n\n\t", " ", " ", "\x1c", "\x85", "a", "b", "'s", "'", "1", "²", "é", "中", "!", "_", "\x00", "<|endoftext|>", "<|endo", "́", "😀"]


def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(token_output.tokenizer_file())


class Counted:
    """The library, with the characters it was given."""

    def __init__(self):
        self.tok, self.chars = library(), 0

    def encode_batch_fast(self, texts, **kw):
        self.chars += sum(map(len, texts))
        return self.tok.encode_batch_fast(texts, **kw)

    def __getattr__(self, name):
        return getattr(self.tok, name)


@pytest.mark.parametrize("most,together", [(1 << 19, 512), (50, 3)])
def test_pieces_give_the_librarys_ids(monkeypatch, most, together):
    monkeypatch.setattr(token_output.PieceCodes, "MOST", most)
    monkeypatch.setattr(token_output.PieceCodes, "TOGETHER", together)
    rng, tok = random.Random(5), library()
    encoder = token_output.PieceCodes(library())
    assert encoder.apart
    texts = ["".join(rng.choice(ALPHABET) for _ in range(rng.randint(0, 14))) for _ in range(20_000)]
    for at in range(0, len(texts), 500):
        some = texts[at : at + 500]
        want = [[*e.ids, token_output.END_ID] for e in tok.encode_batch_fast(some, add_special_tokens=False)]
        assert [x.tolist() for x in token_output.encode_all(encoder, some)] == want


def test_a_piece_is_encoded_once():
    counted = Counted()
    encoder = token_output.PieceCodes(counted)
    texts = ["one two\nthree two one"] * 50
    for _ in range(3):
        token_output.encode_all(encoder, texts)
    assert counted.chars == len("one") + len(" two") + len("\nthree") + len(" one")


def test_other_files_take_whole_texts():
    from tokenizers import Tokenizer, models, pre_tokenizers

    tok = Tokenizer(models.WordLevel({"a": 0, "b": 1, "?": 3}, unk_token="?"))
    tok.pre_tokenizer = pre_tokenizers.Whitespace()
    encoder = token_output.PieceCodes(tok)
    assert not encoder.apart
    assert [x.tolist() for x in token_output.encode_all(encoder, ["a b c", ""])] == [[0, 1, 3, 2], [2]]


@pytest.mark.parametrize("words", [64, 10**9])
def test_words_go_to_the_model_without_its_pattern(monkeypatch, words):
    """Latin letters, and commas and full stops after and beside them; a mark in a text."""
    monkeypatch.setattr(token_output.PieceCodes, "WORDS", words)
    rng, tok = random.Random(6), library()
    counted = Counted()
    encoder = token_output.PieceCodes(counted)
    letters = [*"abcdefgthersion", *"ABÀÉéñöüßÿªºµ"]
    ends = ["", "", "", ",", ".", "...", ",,", " ,", "!.", ".5", "'s,", ",'s", "\n", ".\n", "\n.", ",a", "\x00", "\x00,", "²,", "ā,", "<|endoftext|>."]
    texts = ["".join(rng.choice(["", " ", "  "]) + "".join(rng.choices(letters, k=rng.randint(1, 9))) + rng.choice(ends[: rng.choice([5, len(ends)])]) for _ in range(rng.randint(0, 9))) for _ in range(20_000)]
    texts += [",", ".a", " .", "a.", "a. b", "", " ", "a\x00,b"]
    for at in range(0, len(texts), 3000):
        some = texts[at : at + 3000]
        want = [[*e.ids, token_output.END_ID] for e in tok.encode_batch_fast(some, add_special_tokens=False)]
        assert [x.tolist() for x in token_output.encode_all(encoder, some)] == want


def test_slices_of_long_texts():
    import pyarrow as pa

    texts = ["a" * n for n in (5, 50, 3, 3, 3, 0, 0, 0, 0, 20)] + [None, "b"]
    batch = pa.RecordBatch.from_arrays([pa.array(texts)], ["text"])
    got = [b.column(0).to_pylist() for b in token_output.text_slices(iter([batch, batch.slice(0, 0)]), 4, 10)]
    assert [t for b in got for t in b] == texts and [len(b) for b in got] == [1, 1, 4, 3, 1, 2]
