import random
import string

import pytest

from relstrata.llm import secret_scan as s

LOWER, UPPER, DIGITS = string.ascii_lowercase, string.ascii_uppercase, string.digits


@pytest.fixture(scope="module")
def enc():
    return s.encoder(s.vocabulary())


def found(text, enc):
    return [text[a:b] for a, _, b in s.random_spans(text, [], enc, frozenset())]


@pytest.mark.parametrize(
    "alphabet,length,share",
    [
        (LOWER + DIGITS, 40, 0.98), (UPPER + DIGITS, 40, 0.98), (LOWER + UPPER, 40, 0.98), (LOWER + UPPER + DIGITS, 40, 0.98), (LOWER, 40, 0.85), (UPPER, 40, 0.95),
        (LOWER + DIGITS, 16, 0.9), (UPPER + DIGITS, 16, 0.9), (LOWER + UPPER, 17, 0.9), (LOWER + UPPER + DIGITS, 18, 0.95),
    ],
)
def test_random_strings_of_any_alphabet(enc, alphabet, length, share):
    rng = random.Random(length)
    keys = ["".join(rng.choice(alphabet) for _ in range(length)) for _ in range(300)]
    assert sum(found(f"value {k} end", enc) == [k] for k in keys) >= share * len(keys)


def test_dotted_tokens(enc):
    rng = random.Random(4)
    parts = ["".join(rng.choice(LOWER + UPPER + DIGITS + "_-") for _ in range(n)) for n in (36, 80, 43)]
    assert found(f"bearer {'.'.join(parts)} end", enc) == parts


def test_words_numbers_and_places_stay(enc):
    key = "k9Xv2Qz7LmP4tRw8Yb3Nc6Hd1"
    for text in (
        "internationalization counterrevolutionaries Donaudampfschifffahrtsgesellschaft getElementsByTagName XMLHttpRequestFactoryBean",
        "user_account_settings_page INTERNATIONALIZATION_AND_LOCALIZATION well-known-uniform-resource-identifiers com.example.configuration.properties",
        "4708096362725454 2024-01-02-10-11-12 +49-170-1234567-890 -=-=-=-=-=-=-=-=-=-= ____________________",
        f"/home/user/x.{key} C:\\data\\{key} a.person@{key} www.host.example/{key} host.example/{key} ./{key}",
    ):
        assert found(text, enc) == [], text
