"""Connected components of an edge table by repeated contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rgsketch.llm.common import materialize


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every end of edges (a, b); root is the smallest node of the component.

    A round points every node at its smallest neighbour, follows pointers twice, and joins the edges' ends with the
    result, so that stars vanish in one round and paths shrink by a factor. Only edges between different roots go on.
    """
    live = materialize(edges.select("a", "b").where("a <> b").distinct())
    labels = None
    while True:
        both = live.unionByName(live.select(F.col("b").alias("a"), F.col("a").alias("b")))
        up = materialize(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("up")))
        for _ in range(2):
            nxt = up.select(F.col("node").alias("up"), F.col("up").alias("far"))
            up = up.join(nxt, "up").select("node", F.col("far").alias("up"))
        up = materialize(up)
        labels = up.select("node", F.col("up").alias("root")) if labels is None else labels.join(up.select(F.col("node").alias("root"), "up"), "root", "left").select("node", F.coalesce("up", "root").alias("root"))
        labels = materialize(labels)
        ends = live.join(up.select(F.col("node").alias("a"), F.col("up").alias("ra")), "a").join(up.select(F.col("node").alias("b"), F.col("up").alias("rb")), "b")
        live = materialize(ends.where("ra <> rb").select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct())
        if live.isEmpty():
            return labels
