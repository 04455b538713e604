from __future__ import annotations

import random

import pytest

CLASHING = "doc_id long, text string, lang string, source string, n_chars long, key long, id long, label int, spans string"


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in every column, empty and long texts, ties, repeated rows, extra columns with clashing names."""
    rnd = random.Random(5)
    words = [f"w{rnd.randrange(400)}" for _ in range(30_000)]
    base = " ".join(words[:300])
    rows = [
        (1, base, "en", "a", 1, 1, 1, 1, "x"),
        (1, base, "en", "a", 1, 1, 1, 1, "x"),
        (2, base, "en", "b", 1, 1, 1, 1, "x"),
        (3, base.replace("w1 ", "w9 ", 1), None, None, None, None, None, None, None),
        (4, None, "en", "a", 0, 1, 1, 1, "x"),
        (None, "one two three", "de", "a", 3, 1, 1, 1, "x"),
        (None, None, None, None, None, None, None, None, None),
        (5, "", "en", "a", 0, 1, 1, 1, "x"),
        (6, " \n\t ", "en", "a", 0, 1, 1, 1, "x"),
        (7, " ".join(words), "en", "a", 9, 1, 1, 1, "x"),
        (8, "x" * 200_000, "en", "a", 9, 1, 1, 1, "x"),
    ]
    rows += [(100 + i, " ".join(rnd.choices(words, k=80)), "en", "a", 1, 1, 1, 1, "x") for i in range(60)]
    return spark.createDataFrame(rows, CLASHING)
