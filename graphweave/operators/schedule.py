"""Skew-aware scheduling: contiguous chunks of destinations, by equal vertices or by equal edges, and makespans."""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from graphweave.sources.graphs import PropertyGraph


def in_degrees(g: PropertyGraph) -> DataFrame:
    counts = g.edges.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("degree"))
    return g.vertices.select("vid").join(counts, "vid", "left").select("vid", F.coalesce("degree", F.lit(0)).alias("degree"))


def chunks(g: PropertyGraph, policy: str, count: int, ids: int | None = None, block: int = 1024) -> DataFrame:
    """(vid, degree, chunk): static cuts the id range evenly; balanced cuts the running edge count evenly.

    Running counts are taken inside blocks of ids and over blocks, never in one window over all vertices.
    """
    rows = in_degrees(g)
    if policy == "static":
        top = ids if ids is not None else (rows.agg(F.max("vid")).first()[0] or 0) + 1
        return rows.withColumn("chunk", F.floor(F.col("vid") * count / top).cast("int"))
    rows = rows.withColumn("block", F.floor(F.col("vid") / block).cast("long"))
    sums = rows.groupBy("block").agg(F.sum("degree").alias("n"))
    total = sums.agg(F.sum("n")).first()[0] or 0
    before_block = F.coalesce(F.sum("n").over(W.orderBy("block").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    sums = sums.select("block", before_block.alias("before"))
    inside = W.partitionBy("block").orderBy("vid").rowsBetween(W.unboundedPreceding, -1)
    before = F.col("before") + F.coalesce(F.sum("degree").over(inside), F.lit(0))
    cut = F.least(F.floor(before * count / F.lit(max(total, 1))), F.lit(count - 1)).cast("int")
    return rows.join(sums, "block").withColumn("chunk", cut).select("vid", "degree", "chunk")


def loads(chunked: DataFrame) -> DataFrame:
    return chunked.groupBy("chunk").agg(F.count("*").alias("vertices"), F.sum("degree").alias("edges"))


def makespan(work: list[float], workers: int, dynamic: bool) -> float:
    """Time until all chunks are done: handed out as workers become free, or dealt in equal contiguous shares."""
    if not dynamic:
        share = -(-len(work) // workers) or 1
        return max((sum(work[i : i + share]) for i in range(0, len(work), share)), default=0.0)
    free = [0.0] * workers
    for load in work:
        heapq.heappush(free, heapq.heappop(free) + load)
    return max(free)
