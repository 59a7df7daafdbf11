"""Blocked aggregation: source (or destination) vertices in blocks, partial results folded per destination.

A block bounds what one task holds of the features, as a cache-sized block does on one machine. The fold is
another application of the same reduction, so any associative and commutative one gives the unblocked result.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweave.operators.aggregate import completed, messages, reduce_arrow, reduce_wide, width_of
from graphweave.plans.spec import AggSpec
from graphweave.sources.graphs import PropertyGraph


def block_size_for(n: int, num_blocks: int) -> int:
    return max(1, -(-n // num_blocks))


def apply(g: PropertyGraph, num_blocks: int | None = None, block_size: int | None = None, side: str = "src", kernel: str = "wide", **options) -> DataFrame:
    """The aggregation with ids of one side cut into blocks of equal id ranges; one fold at the end.

    Kernel "arrow" reduces a block's rows as sorted runs of arrays before the fold, "wide" in columns.
    """
    spec = AggSpec(**options)
    width = width_of(g, spec)
    if block_size is None:
        top = g.vertices.agg(F.max("vid")).first()[0] or 0
        block_size = block_size_for(top + 1, num_blocks or 1)
    block = F.floor(F.col(side) / block_size).cast("int")
    cut = PropertyGraph(g.vertices, g.edges.withColumn("block", block), g.width, g.edge_width)
    rows = messages(cut, spec, ("block",))
    if spec.reduce == "mean":
        rows = rows.withColumn("m", F.concat("m", F.transform("m", lambda x: F.when(x.isNotNull(), 1.0).otherwise(0.0))))
        folded = reduce_wide(reduce_wide(rows, ["block", "dst"], "sum", 2 * width, out="m"), ["dst"], "sum", 2 * width, out="m")
        halves = F.zip_with(F.slice("m", 1, width), F.slice("m", width + 1, width), lambda s, n: F.try_divide(s, n))
        return completed(g, folded.select("dst", halves.alias("feat")), spec, width)
    inner = reduce_arrow if kernel == "arrow" else reduce_wide
    partial = inner(rows, ["block", "dst"], spec.reduce, width, out="m")
    return completed(g, reduce_wide(partial, ["dst"], spec.reduce, width), spec, width)


def touch_counts(g: PropertyGraph, block_size: int) -> DataFrame:
    """(block, sources, destinations, edges): what one pass over a block reads and writes."""
    rows = g.edges.select(F.floor(F.col("src") / block_size).cast("int").alias("block"), "src", "dst")
    return rows.groupBy("block").agg(F.countDistinct("src").alias("sources"), F.countDistinct("dst").alias("destinations"), F.count("*").alias("edges"))


def choose(g: PropertyGraph, cache_vectors: int, candidates: tuple[int, ...] = (1, 2, 4, 8, 16, 32, 64)) -> tuple[int, dict[int, float]]:
    """The block count with the least modelled memory traffic, and the traffic of every candidate."""
    from graphweave.operators.measures import walked_io

    traffic = {n: walked_io(g, n, cache_vectors)["total_bytes"] for n in candidates}
    return min(traffic, key=lambda n: (traffic[n], n)), traffic


def blocks_for_memory(n: int, width: int, task_bytes: int) -> int:
    """Blocks so that one block's features take a quarter of a task's memory."""
    return max(1, math.ceil(n * width * 8 / (task_bytes / 4)))
