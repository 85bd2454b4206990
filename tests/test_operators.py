"""Helpers that other operators stand on: components, prefix sums, scratch tables."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from ivfspark.operators.graph import connected_components
from ivfspark.operators.prefix import running_total
from ivfspark.plans.scratch import materialize, shared_dir


def _components(edges):
    parent: dict[int, int] = {}

    def root(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        ra, rb = root(a), root(b)
        parent[max(ra, rb)] = min(ra, rb)
    return {x: root(x) for x in parent}


@pytest.mark.parametrize("shape", ["random", "chain", "star"])
def test_components(spark, shape):
    rng = random.Random(3)
    edges = {
        "random": [(rng.randrange(200), rng.randrange(200)) for _ in range(120)],
        "chain": [(i, i + 1) for i in range(60)],
        "star": [(500, i) for i in range(40)],
    }[shape]
    edges = [(a, b) for a, b in edges if a != b]
    df = spark.createDataFrame([*edges, edges[0], (7, 7), (None, 3)], "a long, b long")
    assert {r.node: r.component for r in connected_components(df).collect()} == _components(edges)


def test_no_components(spark):
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_running_total(spark):
    rows = [(k, i, (i * 7) % 5) for k in ("x", "y") for i in range(100)]
    df = spark.createDataFrame(rows, "k string, i long, n long")
    got = running_total(df, F.floor(F.col("i") / 16), [F.col("i")], F.col("n"), "before", ["k"]).collect()
    for r in got:
        assert r.before == sum((j * 7) % 5 for j in range(r.i))


def test_scratch(spark):
    kept = materialize(spark.range(5), "t")
    assert kept.count() == 5
    assert shared_dir(spark).removeprefix("file://") in kept.inputFiles()[0]
