"""Documents with nulls, empty and very long texts, ties, repeated rows, and extra columns whose names clash."""

import random

import pytest
from pyspark.sql import functions as F

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def words(rng, n, vocab=4000):
    return [f"w{rng.randrange(vocab)}" for _ in range(n)]


def make_rows():
    rng = random.Random(5)
    rows, k = [], 0

    def add(text, source="a", doc_id=-1):
        nonlocal k
        rows.append((k if doc_id == -1 else doc_id, text, "en", source, len(text) if text is not None else None))
        k += 1

    for _ in range(40):
        add(" ".join(words(rng, rng.randrange(20, 200))), rng.choice(["a", "b", "c", None]))
    base = words(rng, 120)
    add(" ".join(base), "b")
    add(" ".join(base).upper(), "b")
    for j in range(6):  # near copies, in a chain too
        base = list(base)
        base[7 + 15 * j] = f"x{j}"
        add(" ".join(base), "c")
    passage = words(rng, 60)
    for _ in range(4):
        add(" ".join([*words(rng, 30), *passage, *words(rng, 30)]), "a")
    add(" ".join(passage[:35]), "a")
    add(" ".join(passage[:34]), "a")
    add(" ".join(["Ha"] * 200), "b")
    add("same line\nsame line\n\n same line\nother one here " * 3, "b")
    for t in (None, "", "  \t\n\x0b\x0c\r ", "one", "one two three", "one two three", "a\x85b c d e ñ 😀", "\x1c\x1f x"):
        add(t, "a")
    add(" ".join(words(rng, 30000)), "d")  # very long
    add("y" * 300_000, None)  # very long without a gap
    add(None, None)
    rows.append(rows[0])  # a repeated row
    rows.append((None, "a row without an id " + " ".join(words(rng, 40)), "en", "a", 1))
    return rows


@pytest.fixture(scope="session")
def rows():
    return make_rows()


@pytest.fixture(scope="session")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(5).cache()


@pytest.fixture(scope="session")
def plain(docs):
    """Without the row that repeats an id."""
    return docs.dropDuplicates()


@pytest.fixture(scope="session")
def clashing(docs):
    names = ["size", "kept", "node", "component", "copies", "n_words", "band", "in_0_", "text_key", "spans", "host_", "tie", "rank_", "digest", "source_", "words_"]
    return docs.withColumns({n: F.lit(1) for n in names})


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)
