"""The competitor that samples: mini-batches of seeds, fixed fan-outs per hop, aggregation over the sample."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from graphweave.operators import aggregate
from graphweave.sources.graphs import PropertyGraph
from graphweave.storage import checkpointed, scratch, stored


def draw(a: Column, b: Column, seed: int = 0) -> Column:
    """An arithmetic pseudo-random rank that any engine can repeat."""
    return (a * 1009 + b * 9176 + seed * 331) % 65521


def minibatches(seeds: DataFrame, size: int, sockets: int) -> DataFrame:
    """(vid, socket, batch): seeds dealt over sockets by rank, then cut into batches; seeds is (vid).

    Ranks are taken in blocks of ids and over blocks, as everywhere.
    """
    block = F.floor(F.col("vid") / 1024).cast("long")
    rows = seeds.select("vid", block.alias("block"))
    first = F.coalesce(F.sum("n").over(W.orderBy("block").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    counts = rows.groupBy("block").agg(F.count("*").alias("n")).select("block", first.alias("first"))
    rank = F.col("first") + F.row_number().over(W.partitionBy("block").orderBy("vid")) - 1
    ranked = rows.join(counts, "block").select("vid", rank.alias("rank"))
    socket = (F.col("rank") % sockets).cast("int")
    return ranked.select("vid", socket.alias("socket"), F.floor(F.col("rank") / sockets / size).cast("int").alias("batch"))


def sampled_edges(edges: DataFrame, frontier: DataFrame, fanout: int, seed: int = 0) -> DataFrame:
    """At most fanout in-edges of each frontier vertex, those of least rank; frontier is (vid)."""
    rows = edges.select("src", "dst").join(frontier.select(F.col("vid").alias("dst")), "dst", "left_semi")
    rank = draw(F.col("src"), F.col("dst"), seed)
    rows = rows.withColumn("rank", rank).withColumn("salt", F.pmod(F.xxhash64("src"), F.lit(32)))
    # A hub's in-edges are thinned in 32 groups first, so none is sorted in one task.
    first = W.partitionBy("dst", "salt").orderBy("rank", "src")
    rows = rows.withColumn("r", F.row_number().over(first)).where(F.col("r") <= fanout)
    order = W.partitionBy("dst").orderBy("rank", "src")
    return rows.withColumn("r", F.row_number().over(order)).where(F.col("r") <= fanout).select("src", "dst")


def neighbours(edges: DataFrame, seeds: DataFrame, fanouts: tuple[int, ...], seed: int = 0) -> tuple[list[DataFrame], list[DataFrame]]:
    """(frontiers, sampled edges) from the seeds outward: each hop adds the sampled in-neighbours."""
    frontiers, samples = [seeds.select("vid").distinct()], []
    for hop, fanout in enumerate(fanouts):
        samples.append(sampled_edges(edges, frontiers[-1], fanout, seed + hop))
        frontiers.append(frontiers[-1].union(samples[-1].select(F.col("src").alias("vid"))).distinct())
    return frontiers, samples


def sampled_aggregate(g: PropertyGraph, seeds: DataFrame, fanout: int, seed: int = 0, reduce: str = "mean") -> DataFrame:
    """(vid, feat) of the seeds over their sampled in-neighbours."""
    sample = PropertyGraph(g.vertices, sampled_edges(g.edges, seeds, fanout, seed), g.width)
    return aggregate.apply(sample, reduce=reduce, keep_isolated=False)


def batch_work(frontiers: list[int], fanouts: tuple[int, ...], widths: tuple[int, ...]) -> float:
    """Operations of one batch: vertices times fan-out times width, over hops."""
    return float(sum(n * f * w for n, f, w in zip(frontiers, fanouts, widths)))


def adjacency(edges: DataFrame, most: int = 8192) -> DataFrame:
    """(dst, srcs, groups): in-neighbours as lists; those of a hub in groups of about ``most``, so that none is held whole."""
    rows = edges.select("src", "dst")
    groups = rows.groupBy("dst").agg(F.ceil(F.count("*") / most).cast("int").alias("groups"))
    rows = rows.join(groups, "dst").withColumn("salt", F.pmod(F.xxhash64("src"), F.col("groups")))
    return rows.groupBy("dst", "groups", "salt").agg(F.collect_list("src").alias("srcs")).select("dst", "srcs", "groups")


def sampled_of_batches(lists: DataFrame, frontier: DataFrame, fanout: int, seed: int) -> DataFrame:
    """(batch, src, dst): what ``sampled_edges`` draws for each batch with the seed plus its number, for all batches in one pass.

    lists is an adjacency; frontier is (batch, vid), each once.
    """

    def run(batches):
        for rows in batches:
            if not len(rows):
                continue
            srcs = rows.column(2)
            sizes = srcs.value_lengths().to_numpy(zero_copy_only=False)
            of, src = np.repeat(np.arange(len(rows)), sizes), srcs.flatten().to_numpy()
            batch, dst = (rows.column(i).to_numpy().astype(np.int64) for i in (0, 1))
            rank = np.fmod(src * 1009 + dst[of] * 9176 + (seed + batch[of]) * 331, 65521)
            order = np.lexsort((src, rank, of))
            at = np.arange(len(order)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
            kept = order[at < fanout]
            groups = rows.column(3).to_numpy()
            columns = (batch[of[kept]], src[kept], dst[of[kept]], rank[kept], groups[of[kept]])
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["batch", "src", "dst", "rank", "groups"])

    met = frontier.join(lists.withColumnRenamed("dst", "vid"), "vid").select(F.col("batch").cast("long").alias("batch"), "vid", "srcs", F.col("groups").cast("long").alias("groups"))
    drawn = met.mapInArrow(run, "batch long, src long, dst long, rank long, groups long")
    order = W.partitionBy("batch", "dst").orderBy("rank", "src")
    hubs = drawn.where("groups > 1").withColumn("r", F.row_number().over(order)).where(F.col("r") <= fanout)
    return drawn.where("groups = 1").select("batch", "src", "dst").union(hubs.select("batch", "src", "dst"))


def neighbours_of_batches(lists: DataFrame, seeds: DataFrame, fanouts: tuple[int, ...], seed: int) -> tuple[DataFrame, DataFrame]:
    """(batch, vid) and (batch, src, dst): vertices and distinct edges of the sampled neighbourhoods of all batches; seeds is (batch, vid)."""
    frontier, samples = stored(seeds.select("batch", "vid").distinct()), None
    for hop, fanout in enumerate(fanouts):
        found = stored(sampled_of_batches(lists, frontier, fanout, seed + hop))
        samples = found if samples is None else samples.union(found)
        frontier = stored(frontier.union(found.select("batch", F.col("src").alias("vid"))).distinct())
    return frontier, samples.distinct()


def _by_batch(df: DataFrame) -> str:
    """The path of df written in one file a batch."""
    path = scratch(df.sparkSession, "batches")
    df.repartition("batch").write.partitionBy("batch").parquet(path)
    return path


def _arrow(spark: SparkSession, path: str, schema) -> pa.Table:
    """A batch's rows; a batch without rows has no folder."""
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if not folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(folder):
        return spark.createDataFrame([], schema).toArrow()
    return spark.read.schema(schema).parquet(path).toArrow()


def fit(g: PropertyGraph, labels: DataFrame, dims: list[int], size: int, fanouts: tuple[int, ...], epochs: int, lr: float = 0.01, seed: int = 0) -> list[dict]:
    """Mini-batch training: each step takes one gradient step on a batch's sampled neighbourhood.

    The neighbourhoods of an epoch's batches are sampled together and written by batch. A batch's subgraph is
    trained on in the driver: size and fan-outs bound it, whatever the size of the graph. labels is (vid, y, split).
    """
    import time

    from graphweave.experiments import ArrayTrainer
    from graphweave.operators.train import Model, Optimiser

    spark = labels.sparkSession
    batched = checkpointed(minibatches(labels.where("split = 'train'").select("vid"), size, 1).select("batch", "vid"))
    last = batched.agg(F.max("batch")).first()[0]
    kinds = {"used": g.vertices.select("vid", "feat").schema, "edges": g.edges.select("src", "dst").schema, "known": labels.select("vid", "y").schema}
    model, optimiser, history = Model.fresh(dims, seed), Optimiser(lr=lr), []
    lists = checkpointed(adjacency(g.edges)) if last is not None else None
    known_at = _by_batch(batched.join(labels.select("vid", "y"), "vid")) if last is not None else None
    for epoch in range(epochs):
        began, losses = time.monotonic(), []
        if last is not None:
            used, edges = neighbours_of_batches(lists, batched, fanouts, seed + 1000 * epoch)
            at = {"used": _by_batch(used.join(g.vertices.select("vid", "feat"), "vid")), "edges": _by_batch(edges), "known": known_at}
        for batch in range(0 if last is None else last + 1):
            part = {k: _arrow(spark, f"{path}/batch={batch}", kinds[k]) for k, path in at.items()}
            vectors = part["used"].sort_by("vid")
            ids = vectors["vid"].to_numpy()
            x = vectors["feat"].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(ids), -1)
            place = np.searchsorted(ids, part["known"]["vid"].to_numpy())
            y, split = np.zeros(len(ids), np.int64), np.full(len(ids), "", dtype=object)
            y[place], split[place] = part["known"]["y"].to_numpy(), "train"
            src, dst = (np.searchsorted(ids, part["edges"][end].to_numpy()) for end in ("src", "dst"))
            step = ArrayTrainer(src, dst, np.zeros(len(src), np.int64), x, y, split, dims, "sync_full", optimiser=optimiser)
            step.model = model
            grads, measured = step.gradients()
            optimiser.update(model, grads)
            losses.append(measured["loss"])
        history.append({"epoch": epoch, "seconds": time.monotonic() - began, "loss": float(np.mean(losses)) if losses else 0.0})
    return history
