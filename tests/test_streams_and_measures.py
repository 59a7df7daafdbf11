from collections import Counter

import pytest
from pyspark.sql import functions as F

from graphweave.operators import measures, partition, sampling
from graphweave.operators.aggregate import apply
from graphweave.sources import tables
from graphweave.sources.graphs import PropertyGraph
from graphweave.storage import scratch
from graphweave.streaming import streams


@pytest.fixture(scope="module")
def ring(spark):
    pairs = [(i, (i + k) % 60) for i in range(60) for k in (1, 7)]
    return partition.prepare(spark.createDataFrame(pairs, "src long, dst long")).cache()


def test_arriving_edges_are_placed_once_and_retries_agree(spark, ring):
    path = scratch(spark, "arriving")
    ring.repartition(3, "ord").write.parquet(path)
    stream = spark.readStream.schema(ring.schema).option("maxFilesPerTrigger", 1).parquet(path)
    placer = streams.EdgePlacer(spark, 4)
    first = sorted(map(tuple, placer.run(stream).collect()))
    assert sorted((u, v) for u, v, _ in first) == sorted((r.src, r.dst) for r in ring.collect())
    assert max(Counter(p for _, _, p in first).values()) < len(first)
    batch = spark.read.parquet(f"{placer.path}/edges/batch=1").join(ring, ["src", "dst"]).select("src", "dst", "ord")
    before = sorted(map(tuple, spark.read.parquet(f"{placer.path}/edges/batch=1").collect()))
    placer(spark.createDataFrame(batch.collect(), batch.schema), 1)  # the batch comes again
    assert sorted(map(tuple, spark.read.parquet(f"{placer.path}/edges/batch=1").collect())) == before
    again = streams.EdgePlacer(spark, 4, placer.path).run(stream)  # restart from the checkpoint: nothing new
    assert sorted(map(tuple, again.select("src", "dst", "part").collect())) == first


def test_sketches_count_neighbours(spark):
    edges = spark.createDataFrame([(i, i % 3) for i in range(3000)], "src long, dst long")
    for r in edges.groupBy("dst").agg(F.approx_count_distinct("src").alias("near"), F.hll_sketch_estimate(F.hll_sketch_agg("src")).alias("sketch")).collect():
        assert abs(r.near - 1000) < 150 and abs(r.sketch - 1000) < 60


def test_partitioned_sink_keeps_all_rows(spark, ring):
    cut = partition.random_edge(ring, 4)
    stored = tables.write_partitioned(cut, scratch(spark, "sink"))
    assert sorted((r.src, r.dst, int(r.part)) for r in stored.collect()) == sorted(map(tuple, cut.collect()))


def test_simulator_and_peaks(spark, ring, monkeypatch):
    g = PropertyGraph(spark.range(60).selectExpr("id as vid", "array(1.0D) as feat"), ring, 1)
    found = measures.memory_io(g, 4, 1000)
    exact = measures.io_infinite_cache(g, 15, 8).first()
    assert found["read_bytes"] == exact.read_bytes and found["written_bytes"] == exact.written_bytes
    monkeypatch.setattr(measures, "MOST_SIMULATED", 10)
    with pytest.raises(ValueError):
        measures.memory_io(g, 4, 1000)
    peaks = measures.peak_memory(spark)
    assert peaks["heap_peak"] > 1e6


def test_times_of_a_history():
    history = [{"epoch": e, "seconds": 4.0, "local_seconds": 1.0, "remote_seconds": 2.0, "wait_seconds": 0.5} for e in range(12)]
    assert measures.ap_share(history) == 0.75 and measures.local_and_remote(history)["remote_share"] == pytest.approx(2 / 3)
    assert measures.epoch_time(history, "delayed", 5) == 4.0


def test_sampled_edges_of_a_hub_match_brute_force(spark):
    edges = [(i, 0) for i in range(500)] + [(i, 1 + i % 3) for i in range(40)]
    df = spark.createDataFrame(edges, "src long, dst long")
    got = sampling.sampled_edges(df, spark.range(3).withColumnRenamed("id", "vid"), 7, 2).collect()
    want = []
    for v in range(3):
        want += [(u, v) for u, w in sorted((e for e in edges if e[1] == v), key=lambda e: ((e[0] * 1009 + e[1] * 9176 + 662) % 65521, e[0]))[:7]]
    assert sorted((r.src, r.dst) for r in got) == sorted(want)


def test_mini_batches_learn(spark):
    pairs = [(i, j) for i in range(40) for j in range(40) if i != j and i % 2 == j % 2 and (i + j) % 3 == 0]
    g = PropertyGraph(spark.range(40).selectExpr("id as vid", "array(double(id % 2), 1.0D) as feat"), spark.createDataFrame(pairs, "src long, dst long"), 2)
    labels = spark.range(40).selectExpr("id as vid", "int(id % 2) as y", "'train' as split")
    history = sampling.fit(g, labels, [2, 4, 2], 20, (5, 3), 3, lr=0.1)
    assert history[-1]["loss"] < history[0]["loss"] and apply(g).count() == 40


def test_parallel_walk_equals_the_simulator(spark, ring):
    """The parallel form counts what one walk counts, in caches smaller and larger than a block, with no bound on edges."""
    import random

    draw = random.Random(3)
    some = sorted({(draw.randrange(60), draw.randrange(60)) for _ in range(900)})
    edges = spark.createDataFrame(some, "src long, dst long").cache()
    for blocks, cache in ((1, 1), (1, 5), (1, 25), (3, 7), (3, 19), (7, 3), (64, 4)):
        found, want = measures.blocked_walk(edges, 60, blocks, cache).first(), measures.reuse(some, 60, blocks, cache)
        assert (found.touches, found.loads, found.outputs) == (want["touches"], want["loads"], want["outputs"]), (blocks, cache)
    g = PropertyGraph(spark.range(60).selectExpr("id as vid", "array(1.0D) as feat"), edges, 1)
    assert measures.walked_io(g, 3, 7) == measures.memory_io(g, 3, 7)


def test_block_choice_takes_more_edges_than_the_simulator(spark, ring, monkeypatch):
    from graphweave.operators import blocked

    monkeypatch.setattr(measures, "MOST_SIMULATED", 10)
    g = PropertyGraph(spark.range(60).selectExpr("id as vid", "array(1.0D) as feat"), ring, 1)
    assert set(blocked.choose(g, 8, (1, 2))[1]) == {1, 2}
