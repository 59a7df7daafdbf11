"""Helpers on graphs and tables around the aggregation: filters, degrees, frontiers, components, triangles, kNN."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from graphweave.operators import wedges
from graphweave.storage import checkpointed


def degrees(edges: DataFrame, side: str = "both") -> DataFrame:
    ends = {"in": [F.col("dst")], "out": [F.col("src")], "both": [F.col("src"), F.col("dst")]}[side]
    return edges.select(F.explode(F.array(*ends)).alias("vid")).groupBy("vid").agg(F.count("*").alias("degree"))


def degree_filter(edges: DataFrame, least: int, most: int) -> DataFrame:
    """Edges whose two ends have an in-degree in range."""
    fine = degrees(edges, "in").where(F.col("degree").between(least, most)).select("vid")
    return induced(edges, fine)


def induced(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges with both ends among the vertices."""
    for end in ("src", "dst"):
        edges = edges.join(vertices.select(F.col("vid").alias(end)), end, "left_semi")
    return edges.select("src", "dst")


def relabel(ids: DataFrame, block: int = 1024) -> DataFrame:
    """(vid, dense): numbers 0 to n - 1 in id order, ranked in blocks and over blocks."""
    rows = ids.select("vid", F.floor(F.col("vid") / block).cast("long").alias("block"))
    first = F.coalesce(F.sum("n").over(W.orderBy("block").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    counts = rows.groupBy("block").agg(F.count("*").alias("n")).select("block", first.alias("first"))
    rank = F.row_number().over(W.partitionBy("block").orderBy("vid")) - 1
    return rows.join(counts, "block").select("vid", (F.col("first") + rank).alias("dense"))


def frontier(edges: DataFrame, seeds: DataFrame, hops: int) -> DataFrame:
    """(vid, hop): the first hop that reaches a vertex along edges, up to hops."""
    seen = seeds.select("vid", F.lit(0).alias("hop")).distinct()
    edge = seen
    for hop in range(1, hops + 1):
        new = edges.join(edge.select(F.col("vid").alias("src")), "src").select(F.col("dst").alias("vid")).distinct()
        edge = checkpointed(new.join(seen, "vid", "left_anti").select("vid", F.lit(hop).alias("hop")))
        seen = seen.union(edge)
    return seen


def components(edges: DataFrame, vertices: DataFrame, most_rounds: int = 100) -> DataFrame:
    """(vid, component): least vertex id of the weakly connected component.

    Each round takes the least label of the neighbourhood (the primitive with copy and min) and follows labels
    once more (pointer jumping), so rounds grow as the logarithm of the diameter in most graphs.
    """
    both = checkpointed(edges.select("src", "dst").union(edges.select("dst", "src")).distinct())
    labels = checkpointed(vertices.select("vid", F.col("vid").alias("label")))
    for _ in range(most_rounds):
        least = both.join(labels.withColumnRenamed("vid", "src"), "src").groupBy(F.col("dst").alias("vid")).agg(F.min("label").alias("near"))
        nearer = labels.join(least, "vid", "left").select("vid", "label", F.least("label", F.coalesce("near", "label")).alias("next"))
        nearer = checkpointed(nearer)
        jump = nearer.select(F.col("vid").alias("next"), F.col("next").alias("far"))
        new = checkpointed(nearer.join(jump, "next", "left").select("vid", F.least("next", "far").alias("label"), (F.least("next", "far") != F.col("label")).alias("moved")))
        labels = new.select("vid", "label")
        if not new.where("moved").limit(1).count():
            break
    return labels.select("vid", F.col("label").alias("component"))


def triangles(edges: DataFrame) -> DataFrame:
    """(vid, triangles) from the end of lower degree, so hubs open few wedges, which never leave their task."""
    return wedges.counts(wedges.blocks(edges))


def clustering(edges: DataFrame) -> DataFrame:
    """(vid, clustering): triangles over pairs of neighbours."""
    packed = wedges.blocks(edges)
    rows = wedges.degrees(packed).where("degree > 1").join(wedges.counts(packed), "vid", "left")
    return rows.select("vid", (2 * F.coalesce("triangles", F.lit(0)) / (F.col("degree") * (F.col("degree") - 1))).alias("clustering"))


def homophily(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(edges, equal_share) over edges whose ends both have a label; labels is (vid, y)."""
    rows = edges.select("src", "dst")
    for end in ("src", "dst"):
        rows = rows.join(labels.select(F.col("vid").alias(end), F.col("y").alias(f"y_{end}")), end)
    return rows.agg(F.count("*").alias("edges"), F.avg((F.col("y_src") == F.col("y_dst")).cast("double")).alias("equal_share"))


def knn(vectors: DataFrame, k: int, block: int = 2048) -> DataFrame:
    """(vid, neighbour, rank, score): the k largest inner products, ties by id; vectors is (vid, feat).

    Vectors are packed into blocks. Each pair of blocks is one matrix product in a task, which keeps the k best of
    every query; what leaves it is k rows a query and block, never a row a pair of vectors.
    """
    blocks = max(1, -(-vectors.count() // block))
    packed = checkpointed(vectors.select("vid", "feat", F.pmod(F.xxhash64("vid"), F.lit(blocks)).cast("int").alias("block")).groupBy("block").agg(F.collect_list("vid").alias("ids"), F.flatten(F.collect_list("feat")).alias("flat")))
    others = packed.select(F.col("block").alias("other"), F.col("ids").alias("other_ids"), F.col("flat").alias("other_flat"))
    queries = packed.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))

    def products(batches):
        for batch in batches:
            for i in range(len(batch)):
                ids, names = (batch.column(c)[i].values.to_numpy() for c in (0, 2))
                q, x = (batch.column(c)[i].values.to_numpy().astype(float).reshape(len(n), -1) for c, n in ((1, ids), (3, names)))
                order = np.argsort(names)
                names, scores = names[order], q @ x[order].T
                scores[ids[:, None] == names] = -np.inf
                best = np.argsort(-scores, axis=1, kind="stable")[:, :k]  # equal scores stay in order of id
                rows, score = np.repeat(ids, best.shape[1]), np.take_along_axis(scores, best, axis=1).reshape(-1)
                real = np.isfinite(score)
                yield pa.RecordBatch.from_arrays([pa.array(rows[real]), pa.array(names[best].reshape(-1)[real]), pa.array(score[real])], names=["vid", "neighbour", "score"])

    tiles = queries.join(others, "other").select("ids", "flat", "other_ids", "other_flat")
    best = tiles.mapInArrow(products, "vid long, neighbour long, score double")
    outer = W.partitionBy("vid").orderBy(F.desc("score"), "neighbour")
    return best.withColumn("rank", F.row_number().over(outer)).where(F.col("rank") <= k).select("vid", "neighbour", "rank", "score")


def ranked(df: DataFrame, *order, partitions: int | None = None) -> DataFrame:
    """df with place, from 1, in a global order: a range sort, counts of its partitions, then ranks inside each."""
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = checkpointed(df.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("__part", F.spark_partition_id()))
    sizes = rows.groupBy("__part").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(W.orderBy("__part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    rank = F.row_number().over(W.partitionBy("__part").orderBy(*order))
    joined = rows.join(F.broadcast(sizes.select("__part", before.alias("__before"))), "__part")
    return joined.withColumn("place", F.col("__before") + rank).drop("__part", "__before")


def asof(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """left with the last value of right at or before its time, by key: one union and one ordered window."""
    tagged = left.select(key, time, F.lit(1).alias("side"), F.struct(*left.columns).alias("row"), F.lit(None).cast(right.schema[value].dataType).alias("v"))
    other = right.select(key, time, F.lit(0).alias("side"), F.lit(None).cast(tagged.schema["row"].dataType).alias("row"), F.col(value).alias("v"))
    order = W.partitionBy(key).orderBy(time, "side").rowsBetween(W.unboundedPreceding, 0)
    rows = tagged.union(other).withColumn("latest", F.last("v", ignorenulls=True).over(order)).where("side = 1")
    return rows.select("row.*", "latest")


def interval_join(left: DataFrame, right: DataFrame, key: str, a: str, b: str, seconds: int) -> DataFrame:
    """Pairs of one key with 0 < b - a <= seconds: an equi-join on time buckets that each left row enters twice."""
    bucket = lambda c: F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / seconds).cast("long")
    rows = left.withColumn("__bucket", F.explode(F.array(bucket(a), bucket(a) + 1)))
    joined = rows.join(right.withColumn("__bucket", bucket(b)), [key, "__bucket"])
    return joined.where((F.col(b) > F.col(a)) & (F.col(b) <= F.col(a) + F.expr(f"interval {seconds} seconds"))).drop("__bucket")
