import random

import pytest

#: Columns whose names the operators use inside.
CLASHING = ("g", "b", "row", "items", "t", "key", "fp", "h", "k", "part", "label", "_id", "n_words", "kept")


def words(n, seed, vocabulary=400):
    rng = random.Random(seed)
    return [f"w{rng.randrange(vocabulary)}" for _ in range(n)]


@pytest.fixture(scope="session")
def make_docs(spark):
    def make(rows, extra=False):
        """rows: (doc_id, text, lang, source)."""
        schema = "doc_id long, text string, lang string, source string, n_chars long"
        data = [(*r, None if r[1] is None else len(r[1])) for r in rows]
        if extra:
            schema += "".join(f", {c} string" for c in CLASHING)
            data = [(*r, *["x"] * len(CLASHING)) for r in data]
        return spark.createDataFrame(data, schema)

    return make


@pytest.fixture(scope="session")
def odd_rows():
    """Nulls in every column, empty and long texts, repeated rows, ties."""
    base = " ".join(words(120, 1))
    passage = " ".join(words(60, 2))
    return [
        (1, base, "en", "a"), (2, base, "en", "a"), (2, base, "en", "a"), (3, None, "en", "b"), (4, "", None, None), (None, " ".join(words(80, 3)), "de", "b"),
        (5, passage + "\n" + " ".join(words(50, 4)), None, "a"), (6, " ".join(words(50, 5)) + " " + passage, "fr", None), (7, " ".join(words(9000, 6)), "en", "c"), (8, "  \t\n ", "en", "c"),
        (9, "Äpfel ▁ 🙂 naïve x \x0b end", "de", "c"), (10, base + " tail", "en", "b"), (11, "a " * 60, "en", "b"), (12, "word", "en", "a"),
    ]
