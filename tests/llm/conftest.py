import random

import pytest


@pytest.fixture(scope="session")
def rough(spark):
    """Nulls, empty and long texts, copies, near copies, ties, and columns that clash with working names."""
    rng = random.Random(3)
    words = ["".join(rng.choice("abcdefghij") for _ in range(rng.randint(1, 8))) for _ in range(60)]
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    base = text(120)
    texts = [None, "", " \n\t ", "one", "ONE", "one two", base, base, base.upper(), base + " x", text(3000), "é ü ñ 漢字 😀 " * 30, "a " * 500, "line\n" * 40, "#$% &&& |||", *[text(rng.randint(1, 90)) for _ in range(40)]]
    texts += [texts[20]] * 30
    rows = [(i, t, rng.choice(["en", "fr", None]), rng.choice(["hot", "hot", "s1", "s2", None]), len(t or ""), i, str(i), "m") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, slot long, block string, media string").repartition(5)


@pytest.fixture(scope="session")
def empty(rough):
    return rough.filter("doc_id < 0")
