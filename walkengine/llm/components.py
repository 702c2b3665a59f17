"""Connected components by contraction, for edge tables of any size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkengine.llm.common import spread_join, staged


def components(edges: DataFrame) -> DataFrame:
    """(node, component) of every node of ``edges`` (a, b); component is the smallest node that can be reached.

    Each round maps a node to the one among itself and its neighbours whose hash comes first (another hash each round,
    so chains shrink by a constant factor), and goes on with the edges between different images.  Minima and counts are
    taken by partial aggregation, and the joins of edges deal a hub's rows over several tasks, as the last join does with
    a large component's; within the rounds a large component's nodes are left to adaptive splitting of skewed joins.
    """
    edges = staged(edges.where("a <> b").select("a", "b").distinct(), "edges")
    at = staged(edges.select(F.explode(F.array("a", "b")).alias("node")).distinct().withColumn("now", F.col("node")), "nodes")
    turn = 0
    while not edges.isEmpty():
        turn += 1
        mark = lambda c: F.struct(F.xxhash64(c, F.lit(turn)).alias("h"), F.col(c).alias("to"))  # noqa: B023, E731
        both = edges.select("a", "b").union(edges.select("b", "a"))
        image = both.groupBy("a").agg(F.min(mark("b")).alias("near"), F.count("*").alias("n"))
        image = staged(image.select("a", F.least("near", mark("a"))["to"].alias("to"), "n"), "images")
        moved = spread_join(edges, image, "a", "n", "inner").select(F.col("to").alias("x"), F.col("b").alias("a"))
        moved = spread_join(moved, image, "a", "n", "inner").select(F.col("x").alias("a"), F.col("to").alias("b"))
        now = image.select(F.col("a").alias("now"), "to")
        at = staged(at.join(now, "now", "left").select("node", F.coalesce("to", "now").alias("now")), "nodes")
        edges = staged(moved.where("a <> b").distinct(), "edges")
    least = staged(at.groupBy("now").agg(F.min("node").alias("component"), F.count("*").alias("n")), "least")
    return spread_join(at, least, "now", "n", "inner").select("node", "component")
