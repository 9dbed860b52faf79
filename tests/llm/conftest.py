from __future__ import annotations

import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, n long, words string, length long"


@pytest.fixture(scope="session")
def odd(spark):
    """Documents with nulls, empty and long texts, repeated rows, and extra columns whose names clash with the operators' own."""
    rng = random.Random(3)
    words = ["alpha", "beta", "gamma", "delta", "the", "of", "in", "über", "niño", "x1"]
    long = " ".join(rng.choice(words) + str(rng.randrange(3000)) for _ in range(20_000))
    texts = [None, "", "   \n\t ", "one", "one two three four five", "ÀÉ 日本語 текст", long, "no-letters 123 !!! ...", "\n\n\n", "a" * 5000, "mail a@b.co now", "<|endoftext|> twice <|endoftext|>"]
    rows = [(i, t, None if i % 3 == 0 else "en", None, None if t is None else len(t), 7, "w", 1) for i, t in enumerate(texts)]
    rows += [rows[4], rows[4], (None, "a null id here", "en", "s", 14, 7, "w", 1)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="session")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)
