"""Connected components by hooking and contraction, on written tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import discard, staged


def connected_components(edges: DataFrame) -> DataFrame:
    """edges (a, b) -> (node, label) for every node of an edge; label is the least node of its component.

    In a round every label hooks to its least neighbour and hooks are followed to the fourth; the edges between labels
    that are still apart are all that the next round reads, so they shrink geometrically. When none is left,
    neighbours share labels, and the least node of a component, which never hooks, gives it its own.
    """
    left = staged(edges.select("a", "b").union(edges.select("b", "a")).filter("a <> b").distinct(), "links")
    rounds = []
    while not rounds or not left.isEmpty():
        hook = staged(left.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("to")), "hooks")
        far = _followed(_followed(hook))
        rounds.append(staged(far, "labels"))
        side = lambda c: rounds[-1].select(F.col("node").alias(c), F.col("to").alias(f"{c}_to"))
        rest = left.join(side("a"), "a").join(side("b"), "b").filter("a_to <> b_to")
        before, left = left, staged(rest.select(F.col("a_to").alias("a"), F.col("b_to").alias("b")).distinct(), "links")
        discard(before, hook)
    labels = rounds[0].select("node", F.col("to").alias("label"))
    for more in rounds[1:]:
        labels = labels.join(more.select(F.col("node").alias("label"), "to"), "label", "left").select("node", F.coalesce("to", "label").alias("label"))
    return labels


def _followed(hook: DataFrame) -> DataFrame:
    up = hook.select(F.col("node").alias("to"), F.col("to").alias("next"))
    return hook.join(up, "to").select("node", F.col("next").alias("to"))
