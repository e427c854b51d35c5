from __future__ import annotations

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"

#: Texts that every operator on documents has to take: nulls, blanks, ties, repeats, long runs.
AWKWARD = [
    (1, "a b c d e f g h i j k l m n o p", "en", "s1", 31), (2, None, None, None, None), (3, "", "en", "s1", 0), (4, " \t\n\x0b\x0c\r ", "en", None, 7),
    (5, "a b c d e f g h i j k l m n o p", "en", "s1", 31), (6, "x a b  c d e f g h i j\tk l m z", "fr", "s2", 30), (7, "w" * 5000, "en", "s2", 5000),
    (8, "the cat " * 3000, "en", "s2", 24000), (9, "café  naïve \U0001f600   x", "fr", "sé", 20), (9, "café  naïve \U0001f600   x", "fr", "sé", 20),
    (10, "mail a.b@example.com ip 10.0.0.1 card 4111 1111 1111 1111 tel +1 (555) 123-4567", "en", "s1", 80), (None, "no id at all", "en", "s1", 12),
]


@pytest.fixture(scope="session")
def awkward(spark):
    return spark.createDataFrame(AWKWARD, SCHEMA)
