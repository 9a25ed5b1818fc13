import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long, n_words string, shard string, tokens string"


def rows(pairs):
    """Documents with clashing extra columns."""
    return [(i, t, "en", "s", None if t is None else len(t), "x", "y", "z") for i, t in pairs]


@pytest.fixture
def make(spark):
    return lambda pairs: spark.createDataFrame(rows(pairs), DOCS)


def words(n, start=0):
    return " ".join(f"w{start + i}" for i in range(n))


#: Nulls, empty texts, no words, repeated rows, a repeated id, a null id, ties and a long text.
AWKWARD = [
    (1, None), (2, ""), (3, " \t\n"), (4, words(60)), (4, words(60)), (5, words(60)), (6, words(40) + " " + words(30, 500)), (None, words(30, 500)), (7, "!!! ???"), (8, words(20_000, 1000)),
    (9, "x"), (9, "y"), (10, "É " + words(25) + "  z"),
]
