import pytest

DOCUMENTS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture
def frame(spark):
    """documents of (doc_id, text) pairs; extra columns clash with names that operators use inside."""

    def make(rows, lang="en", source="s"):
        full = [(d, t, lang, source, len(t) if t else None) for d, t in rows]
        df = spark.createDataFrame(full, DOCUMENTS)
        for name in ("node", "key", "n", "label", "score", "epoch", "bucket", "copy", "_score"):
            df = df.selectExpr("*", f"'clash' AS `{name}`")
        return df

    return make


@pytest.fixture(scope="session")
def words():
    import random

    rng = random.Random(3)
    vocabulary = ["".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(2, 9))) for _ in range(4000)]

    def text(n, seed):
        own = random.Random(seed)
        return " ".join(own.choice(vocabulary) for _ in range(n))

    return text


#: Nulls, empty and blank texts, marks only, one word, ties, a very long text.
HARD = [(1, None), (2, ""), (3, "   "), (4, "\n\n"), (5, "!!!"), (6, "word"), (7, "word"), (8, "ÄÖ 日本語 текст"), (9, "x" * 50_000), (10, "a b c d"), (11, "tab\there  double\r\nline ")]
