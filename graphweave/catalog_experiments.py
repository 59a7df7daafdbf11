"""The experiment workloads as queries: sweeps over methods, partitions, delays, blocks and optimisation steps."""

from __future__ import annotations

import time
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphweave.catalog import pairs1, query, w1
from graphweave.experiments import MOST_EDGES, ArrayTrainer
from graphweave.operators import aggregate, blocked, layout, measures, partition, sampling
from graphweave.operators.train import Optimiser, Trainer
from graphweave.sources import graphs
from graphweave.storage import checkpointed, checkpointed_as_dealt, released, stored


def _arrays(spark: SparkSession, d: str):
    """The document graph with random features and languages as classes, as arrays; its size is checked first."""
    g = graphs.document_similarity(spark, d)
    edges = stored(g.edges.select("src", "dst"))
    if (n := edges.count()) > MOST_EDGES:
        raise ValueError(f"{n} edges are too many for one machine; use the distributed trainer")
    vertices = g.vertices.join(graphs.language_labels(spark, d), "vid", "left").select("vid", "feat", F.coalesce("y", F.lit(-1)).alias("y"), "split").orderBy("vid").toArrow()
    ids = vertices["vid"].to_numpy()
    x = vertices["feat"].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float, copy=False).reshape(len(ids), -1)
    edges = edges.toArrow()
    src, dst = (np.searchsorted(ids, edges[end].to_numpy()) for end in ("src", "dst"))
    named = vertices["split"].combine_chunks().dictionary_encode()  # each name is one object, not one a vertex
    split = np.array([*named.dictionary.to_pylist(), None], dtype=object)[named.indices.fill_null(len(named.dictionary)).to_numpy()]
    return src, dst, x, vertices["y"].to_numpy().astype(np.int64), split


def _greedy_parts(src: np.ndarray, dst: np.ndarray, parts: int, piece: int = 65_536) -> np.ndarray:
    """The greedy cut of unordered pairs in hash order, both directions of a pair together; pairs become Python numbers in pieces."""
    low, high = np.minimum(src, dst).astype(np.int64), np.maximum(src, dst).astype(np.int64)
    n = int(high.max(initial=0)) + 1
    pairs, of = np.unique(low * n + high, return_inverse=True)
    low, high = pairs // n, pairs % n
    order = np.lexsort((high, low, (low * 7919 + high * 104729) % 1000003))
    part, state = np.empty(len(pairs), np.int64), partition.Greedy(parts)
    for i in range(0, len(order), piece):
        some = order[i : i + piece]
        part[some] = state.place_all(low[some].tolist(), high[some].tolist())
    return part[of]


def _accuracy(data, parts: int, mode: str, delay: int, epochs: int) -> float:
    src, dst, x, y, split = data
    part = _greedy_parts(src, dst, parts) if parts > 1 else np.zeros(len(src), np.int64)
    trainer = ArrayTrainer(src, dst, part, x, y, split, [x.shape[1], 16, int(y.max()) + 1], mode, delay, optimiser=Optimiser("adam", 0.02))
    return trainer.fit(epochs)[-1]["test_accuracy"]


@query("exp_accuracy_modes")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Test accuracy by mode and partitions, with the gap to one partition."""
    data = _arrays(spark, d)
    base = _accuracy(data, 1, "sync_full", 0, 100)
    rows = [(1, "sync_full", base, 0.0)]
    for parts in (2, 4, 8):
        for mode in ("sync_full", "delayed", "local_only"):
            found = _accuracy(data, parts, mode, 5, 100)
            rows.append((parts, mode, found, found - base))
    return spark.createDataFrame(rows, "parts int, mode string, test_accuracy double, gap double")


@query("exp_delay_sweep")
def _(spark: SparkSession, d: str) -> DataFrame:
    data = _arrays(spark, d)
    rows = [(r, _accuracy(data, 4, "delayed" if r else "sync_full", r, 100)) for r in (0, 1, 2, 5, 10)]
    return spark.createDataFrame(rows, "delay int, test_accuracy double")


@query("exp_replication_sweep")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Replication and balance of the greedy and the random cut, by graph and partitions, on three shapes of graph."""
    counts = (2, 4, 8, 16, 32, 64, 128)
    shapes = {"co_purchase": pairs1(spark, d)} | {n: partition.prepare(g.edges) for n, g in (("customer_supplier", graphs.customer_supplier(spark, d)), ("documents", graphs.document_similarity(spark, d)))}
    kept = []
    for n, p in shapes.items():  # one graph's shuffles at a time are on disk
        kept.append(stored(p.select(F.lit(n).alias("graph"), "src", "dst", "ord")))
        released(spark)
    pairs = reduce(DataFrame.union, kept)
    profiles = [f(pairs, counts).withColumn("method", F.lit(n)) for n, f in (("greedy", partition.greedy_profiles), ("random", partition.random_profiles))]
    found = reduce(DataFrame.union, profiles).groupBy("graph", "parts", "method").agg(
        (F.sum("clones") / F.max("vertices")).alias("replication"),
        (F.max("edges") * F.col("parts") / F.sum("edges")).alias("edge_balance"),
        F.avg(F.try_divide(F.col("split"), F.col("clones")) * 100).alias("split_share"),
    )
    every = spark.createDataFrame([(n, p, m) for n in shapes for p in counts for m in ("greedy", "random")], "graph string, parts int, method string")
    return every.join(found, ["graph", "parts", "method"], "left")  # a graph without edges has its rows too


@query("exp_times_by_mode")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Mean seconds of an epoch, and in it of local sums, of synchronisation and of waiting, by mode and partitions."""
    g, rows = w1(spark, d), []
    features = g.vertices.select("vid", F.transform("feat", lambda x: x / 50).alias("feat"))
    labels = g.vertices.select("vid", (F.col("vid") % 3).cast("int").alias("y"), graphs.split_of(F.col("vid")).alias("split"))
    pairs = checkpointed(partition.prepare(g.edges))
    for parts in (1, 4):
        cut = checkpointed(partition.random_edge(pairs, parts))
        cloned = layout.clones(cut)
        roles = layout.with_roles(cloned, layout.trees(cloned))
        for mode in ("local_only", "sync_full", "delayed"):
            trainer = Trainer(partition.both_ways(cut), roles, features, labels, [4, 16, 3], mode, delay=1, overlap=mode == "delayed")
            history = trainer.fit(3 if mode == "delayed" else 2)
            steady = history[2:] if mode == "delayed" else history[1:]
            spent = measures.local_and_remote(steady)
            rows.append((parts, mode, measures.epoch_time(history, mode, 1), spent["local"], spent["remote"], spent["wait"], measures.ap_share(steady)))
    return spark.createDataFrame(rows, "parts int, mode string, epoch_seconds double, local_seconds double, remote_seconds double, wait_seconds double, aggregation_share double")


@query("exp_blocks_time_and_io")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Seconds and modelled traffic of one aggregation by number of blocks, on the dense and the sparse graph.

    Graphs are dealt and sorted by source once, before the clock starts, so that no aggregation deals its edges out again.
    """
    rows, counts = [], (1, 2, 4, 8, 16, 32, 64)
    slots = int(spark.conf.get("spark.sql.shuffle.partitions"))
    laid = lambda df, key: checkpointed_as_dealt(df.repartition(slots, key).sortWithinPartitions(key))
    for name, g in (("dense", w1(spark, d)), ("sparse", graphs.sparse_part_order(spark, d))):
        g = graphs.PropertyGraph(laid(g.vertices, "vid"), laid(g.edges, "src"), g.width)
        top = g.vertices.agg(F.max("vid")).first()[0] + 1
        sizes = {n: blocked.block_size_for(top, n) for n in counts}
        io = {r.block_size: r for r in measures.io_by_blocks(g, sorted(set(sizes.values()))).collect()}
        for n, size in sizes.items():
            rows.append((name, n, _seconds(blocked.apply(g, block_size=size)), float(io[size].read_bytes), float(io[size].written_bytes)))
    return spark.createDataFrame(rows, "graph string, blocks int, seconds double, read_bytes double, written_bytes double")


@query("exp_exchange_by_mode")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Vectors that a layer exchanges in an epoch, by mode and partitions, for width 4."""
    out, pairs = None, partition.prepare(w1(spark, d).edges)
    for parts in (2, 4, 8, 16):
        cloned = layout.clones(partition.random_edge(pairs, parts))
        tree = layout.trees(cloned)
        for mode, bins in (("local_only", 1), ("sync_full", 1), ("delayed", 5)):
            roles = layout.with_roles(cloned, tree, layout.bins(tree, bins) if bins > 1 else None)
            volume = measures.comm_volume(roles, 4, mode, bins).agg(F.coalesce(F.avg("vectors"), F.lit(0.0)).alias("vectors_per_epoch"))
            row = volume.select(F.lit(parts).alias("parts"), F.lit(mode).alias("mode"), "vectors_per_epoch")
            out = row if out is None else out.union(row)
    return out


def _seconds(df: DataFrame) -> float:
    began = time.monotonic()
    df.write.format("noop").mode("overwrite").save()
    return time.monotonic() - began


@query("exp_ablation")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Seconds and modelled traffic of one aggregation as optimisations are added one on the other, by graph.

    The baseline moves every message; partial sums over salted tasks move one vector a task and destination, which
    evens out hubs; blocks of sources bound what a task holds of the features; the kernel reduces runs of arrays.
    """
    rows, blocks = [], 4
    shapes = (("dense", w1(spark, d)), ("sparse", graphs.sparse_part_order(spark, d)), ("skewed", graphs.document_similarity(spark, d, 4)))
    for name, g in shapes:
        g = graphs.PropertyGraph(checkpointed(g.vertices), checkpointed(g.edges), g.width)
        m, top, vector = g.edges.count(), (g.vertices.agg(F.max("vid")).first()[0] or 0) + 1, g.width * 8
        whole, cut = (measures.io_infinite_cache(g, blocked.block_size_for(top, n)).first() for n in (1, blocks))
        gathered = float(m * (16 + vector))
        steps = (
            ("baseline", lambda g=g: aggregate.apply(g, strategy="baseline"), gathered + m * vector, float(m * vector + whole.written_bytes)),
            ("+ dynamic tasks", lambda g=g: aggregate.salted(g, 4), gathered, float(whole.written_bytes)),
            ("+ blocks", lambda g=g: blocked.apply(g, blocks), float(cut.read_bytes), float(cut.written_bytes)),
            ("+ array kernel", lambda g=g: blocked.apply(g, blocks, kernel="arrow"), float(cut.read_bytes), float(cut.written_bytes)),
        )
        rows += [(name, step, _seconds(run()), read, written) for step, run, read, written in steps]
    return spark.createDataFrame(rows, "graph string, step string, seconds double, read_bytes double, written_bytes double")


@query("exp_work_against_sampling")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Operations of the sampled neighbourhoods of all training vertices and of the full neighbourhood on the part-part graph, by hop."""
    g = w1(spark, d)
    seeds = g.vertices.where(graphs.split_of(F.col("vid")) == "train").select("vid")  # all training vertices
    frontiers, _ = sampling.neighbours(g.edges, seeds, (15, 10, 5))
    n, m = g.vertices.count(), g.edges.count()
    rows = []
    for hop, (front, fanout, width) in enumerate(zip(frontiers, (15, 10, 5), (256, 256, 100))):
        rows.append((hop, float(front.count() * fanout * width), float(n * (m / max(1, n)) * width)))
    return spark.createDataFrame(rows, "hop int, sampled_ops double, full_ops double")


@query("exp_sampling_training")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Epoch seconds and loss of the trainer that samples mini-batches and of full-batch training, on the part-part graph."""
    g = w1(spark, d)
    features = g.vertices.select("vid", F.transform("feat", lambda x: x / 50).alias("feat"))
    labels = g.vertices.select("vid", (F.col("vid") % 3).cast("int").alias("y"), graphs.split_of(F.col("vid")).alias("split"))
    graph = graphs.PropertyGraph(features, checkpointed(g.edges), 4)
    rows = [("sampled", h["epoch"], h["seconds"], h["loss"]) for h in sampling.fit(graph, labels, [4, 16, 3], 1000, (15, 10), 2)]
    cut = checkpointed(partition.random_edge(partition.prepare(graph.edges), 2))
    cloned = layout.clones(cut)
    trainer = Trainer(partition.both_ways(cut), layout.with_roles(cloned, layout.trees(cloned)), features, labels, [4, 16, 3], "delayed", delay=1)
    rows += [("full batch, delayed", h["epoch"], h["seconds"], float(h["loss"])) for h in trainer.fit(2)]
    return spark.createDataFrame(rows, "trainer string, epoch int, seconds double, loss double")
