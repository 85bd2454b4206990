"""Connected components of a link table, by alternating star contractions.

Every round is two aggregations and two joins on node ids; no component, adjacency list or
label set is ever gathered in one task or on the driver. The joined tables are materialised, so
that a hub's rows can be split by adaptive skew handling.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ivfspark.plans.scratch import materialize


def _contract(edges: DataFrame, both_directions: bool) -> DataFrame:
    """Link each larger neighbour (or the node itself) to the least id around the node."""
    if both_directions:
        around = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    else:
        around = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    around = materialize(around, "around")
    least = materialize(around.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m")), "least")
    linked = around.join(least, "a")
    if both_directions:
        moved = linked.where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        moved = linked.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(
            least.select("a", F.col("m").alias("b"))
        )
    return moved.where(F.col("a") != F.col("b")).distinct()


def _all_stars(edges: DataFrame) -> bool:
    """Whether every node hangs from one node at most, and none that hangs has others below it."""
    ends = edges.select(F.col("a").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("down"))
    ends = ends.unionByName(edges.select(F.col("b").alias("node"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    nodes = ends.groupBy("node").agg(F.sum("up").alias("ups"), F.max("down").alias("down"))
    return nodes.where("ups > 1 or ups = 1 and down = 1").agg(F.count("*")).first()[0] == 0


def connected_components(edges: DataFrame) -> DataFrame:
    """``edges(a long, b long)`` to ``(node, component)``, component = least id reachable.

    Only nodes with at least one link to another node are returned. Null ends and self links are
    ignored; repeated links count once.
    """
    current = materialize(
        edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        .where(F.col("a").isNotNull() & F.col("b").isNotNull() & (F.col("a") != F.col("b")))
        .distinct(),
        "edges",
    )
    while not _all_stars(current):  # a logarithm of the nodes in rounds
        current = materialize(_contract(_contract(current, True), False), "stars")
    stars = current.select(F.col("a").alias("node"), F.col("b").alias("component"))
    centres = current.select(F.col("b").alias("node")).distinct()
    return stars.unionByName(centres.select("node", F.col("node").alias("component")))
