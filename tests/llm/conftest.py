import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, id long, key string, words string, `a.b` int"


def words(seed, n, size=4000):
    rng = random.Random(seed)
    return [f"w{rng.randrange(size)}x" for _ in range(n)]


@pytest.fixture(scope="session")
def frame(spark):
    """Documents from (doc_id, text) or (doc_id, text, source), with extra columns whose names clash with internal ones."""

    def make(rows):
        full = [(r[0], r[1], None, r[2] if len(r) > 2 else "s", None, 7, "k", "w", 1) for r in rows]
        return spark.createDataFrame(full, SCHEMA)

    return make


@pytest.fixture(scope="session")
def odd(frame):
    """Nulls, empty texts, a very long text, ties, and a repeated row."""
    long = " ".join(words(5, 60_000))
    return frame([(None, "no id here"), (1, None), (2, ""), (3, long), (4, "same text twice"), (4, "same text twice"), (5, "\n\n \t"), (6, "é Ünïcode ﬁ ÀB")])
