import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _at string, key long, bucket int, kind int, h long, rank int, line int"


def make_docs(spark, rows):
    """Rows of (doc_id, text) as documents with extra columns whose names clash with the operators' own."""
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), "x", 1, 2, 3, 4, 5, 6) for i, t in rows], SCHEMA)


@pytest.fixture(scope="session")
def docs_of(spark):
    return lambda rows: make_docs(spark, rows)


def prose(rng, n):
    parts = ["the", "re", "tion", "er", "an", "sta", "lor", "ble", "in", "ou", "é", "ß"]
    return " ".join("".join(rng.choice(parts) for _ in range(rng.randint(1, 4))) for _ in range(n))


@pytest.fixture(scope="session")
def odd_rows():
    """Null, empty, blank and long texts, ties, repeated rows, near copies, shared passages, a null id."""
    rng = random.Random(3)
    passage = prose(rng, 90)
    base = prose(rng, 160)
    words = base.split()
    rows = [(0, None), (1, ""), (2, "  \n\t "), (3, "one"), (4, base), (5, base), (5, base), (6, " ".join(words[:80] + ["changed"] + words[81:]))]
    rows += [(10 + k, prose(rng, 60) + " " + passage + " " + prose(rng, 40)) for k in range(4)]
    rows += [(20, "a " * 300), (21, prose(rng, 9000)), (22, passage + "\n" + passage), (None, base), (30, "x\n" * 50 + "y")]
    return rows
