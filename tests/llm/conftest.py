"""Awkward tables that every corpus operator must survive."""

from __future__ import annotations

import random

import pytest

LONG = " ".join(f"w{i % 977} x{i}" for i in range(40_000))


def words(n, seed, pool=400):
    rng = random.Random(seed)
    return " ".join(f"word{rng.randrange(pool)}" for _ in range(n))


@pytest.fixture(scope="session")
def shipped(spark):
    from ivfspark.plans.shipping import ship

    return ship(spark)


@pytest.fixture(scope="session")
def awkward(shipped):
    """Nulls in every column, empty and very long texts, repeated rows, ties, extra columns."""
    texts = [
        (1, "", "a"),
        (2, None, "b"),
        (3, words(80, 1), None),
        (4, words(80, 1), "a"),
        (4, words(80, 1), "a"),
        (None, words(90, 2), "b"),
        (None, None, None),
        (7, "  \n\t ", "a"),
        (8, LONG, "b"),
        (9, "Ünï çödé Straße ☃ " * 30, "a"),
        (10, words(60, 3) + "\n" + words(60, 1), "a"),
        (11, "a", "a"),
        (12, "same same same " * 40, "c"),
    ]
    rows = [(i, t, "en", s, len(t or ""), 1, "x", 2.0) for i, t, s in texts]
    schema = "doc_id long, text string, lang string, source string, n_chars long, size long, host string, fp double"
    return shipped.createDataFrame(rows, schema)


@pytest.fixture(scope="session")
def empty(shipped, awkward):
    return shipped.createDataFrame([], awkward.schema)
