import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, key string, n int, label int, hub int, row int, part int, size int, copy int"


def documents(spark, rows):
    """Documents with many extra columns, whose names the operators use inside."""
    return spark.createDataFrame([(i, t, "en", s, len(t or ""), "k", 1, 2, 3, 4, 5, 6, 7) for i, t, s in rows], SCHEMA)


def prose(seed, words):
    r = random.Random(seed)
    return " ".join("".join(r.choice(["th", "er", "on", "an", "re", "ing", "ou", "é"]) for _ in range(r.randint(1, 4))) for _ in range(words))


ODD = [
    (0, None, "a"),
    (1, "", "a"),
    (2, " \n\t ", None),
    (3, "one", "b"),
    (4, "Ünïcode ΑΣ ﬁ ½ 日本語 ́x é é <|endoftext|> <|startoftext|> don't", "b"),
    (5, prose(5, 40) + "\n" + prose(6, 30), "a"),
    (5, prose(5, 40) + "\n" + prose(6, 30), "a"),
    (None, "no id here at all, really", None),
    (7, "x" * 3000 + " " + prose(7, 3000), "c"),
    (8, "a  b   c\n\n d e　f​g\x1ch", "c"),
]


@pytest.fixture(scope="session")
def odd(spark):
    return documents(spark, ODD)


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)
