"""Connected components of a table of links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import checkpointed


def _rooted(hooks: DataFrame) -> DataFrame:
    """hooks (node, up), every up at or below its node, with ups replaced by the roots of their trees: each turn doubles the
    length of the way that is skipped."""
    while True:
        over = hooks.select(F.col("node").alias("at"), F.col("up").alias("further")).where("further < at")
        hooks = checkpointed(hooks.join(over, F.col("up") == F.col("at"), "left").select("node", F.coalesce("further", "up").alias("up"), F.col("further").isNotNull().alias("moved")))
        if hooks.where("moved").isEmpty():
            return hooks.select("node", "up")


def connected(links: DataFrame) -> DataFrame:
    """(node, label): the smallest node that each node of the links (a, b) reaches.

    Each round hooks every node to its smallest neighbour (or to itself), replaces hooks by the roots of the trees that they form, carries the
    edges over to the roots and drops those that have become loops or repeats, so the graph shrinks until no edge is left.
    A chain of any order takes rounds in the logarithm of its length; each round is materialised."""
    canonical = lambda a, b: (F.least(a, b).alias("a"), F.greatest(a, b).alias("b"))
    edges = checkpointed(links.select(*canonical("a", "b")).where("a < b").distinct())
    labels = None
    while not edges.isEmpty():
        near = edges.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("up")).unionByName(edges.groupBy(F.col("a").alias("node")).agg(F.min("a").alias("up")))
        hooks = _rooted(checkpointed(near.groupBy("node").agg(F.min("up").alias("up"))))
        if labels is None:
            labels = hooks.select("node", F.col("up").alias("label"))
        else:
            to = hooks.select(F.col("node").alias("at"), "up")
            labels = checkpointed(labels.join(to, F.col("label") == F.col("at"), "left").select("node", F.coalesce("up", "label").alias("label")))
        first, second = hooks.select(F.col("node").alias("na"), F.col("up").alias("ua")), hooks.select(F.col("node").alias("nb"), F.col("up").alias("ub"))
        moved = edges.join(first, F.col("a") == F.col("na")).join(second, F.col("b") == F.col("nb"))
        edges = checkpointed(moved.where("ua <> ub").select(*canonical("ua", "ub")).distinct())
    if labels is None:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("label"))
    return labels
