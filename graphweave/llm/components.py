"""Connected components of a link table: alternating star contraction, nothing collected to the driver.

Two passes in turn link every vertex to the least of its neighbourhood, until no link changes; the number of
rounds grows as the logarithm of the longest path. Each round is two aggregations with map-side combine and
two joins that AQE can split, so a hub costs no single task more than its share.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweave.llm.common import materialize, settled


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root) for every node in a link, root the least node reachable. Null ends and loops are ignored."""
    edges = links.select(F.col(a).alias("a"), F.col(b).alias("b")).where("a is not null and b is not null and a <> b")
    edges = materialize(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    before = None
    while True:
        # Larger neighbours of every node go to the least node of its neighbourhood.
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        least = settled(least, "u")
        edges = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        # Smaller neighbours, and the node itself, go to the least one.
        edges = materialize(edges)
        least = settled(edges.groupBy("u").agg(F.min("v").alias("m")), "u")
        joined = edges.join(least, "u")
        edges = (
            joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v"))).distinct()
        )
        edges = materialize(edges)
        now = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if now == before:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).union(edges.select("v", "v").distinct())
        before = now
