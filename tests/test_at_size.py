"""Queries that were too slow on large tables: the same results with less work."""

from pathlib import Path

from graphweave import catalog, catalog_experiments
from graphweave.operators import blocked, measures, partition, remote
from graphweave.sources.graphs import PropertyGraph
from graphweave.storage import shared_folder

FOLDER = "/root/testdata/sf0.001"


def test_delayed_sync_of_given_partials_writes_no_slices(spark):
    parted = catalog.Parted(spark, FOLDER, 3, 2)
    fulls = parted.all_full(6)
    assert fulls[0].rdd.getNumPartitions() >= 1 and "cut" not in vars(parted) and "roles" not in vars(parted)  # nothing was dealt to one task a part
    folder = Path(shared_folder(spark).removeprefix("file:"))
    plans, written = remote.DelayedSync(2, 2, 2, given=True), remote.DelayedSync(2, 2, 2)
    before = set(folder.iterdir())
    made = [plans.step(e, full) for e, full in enumerate(fulls)]
    assert set(folder.iterdir()) == before
    for e, full in enumerate(fulls):
        assert sorted(map(str, made[e].collect())) == sorted(map(str, written.step(e, full).collect()))


def test_io_of_several_block_sizes_takes_one_pass(spark):
    edges = spark.createDataFrame([(0, 1), (0, 1), (5, 1), (6, 2), (199, 2), (199, 7), (63, 9), (3, None)], "src long, dst long")
    g = PropertyGraph(spark.range(200).selectExpr("id as vid", "array(1D, 2D) as feat"), edges, 2)
    sizes = [1, 3, 50, 200, 1000]
    got = {r.block_size: tuple(r)[1:] for r in measures.io_by_blocks(g, sizes).collect()}
    assert got == {size: tuple(measures.io_infinite_cache(g, size).first()) for size in sizes}


def test_blocks_time_and_io_deals_its_edges_once(spark, monkeypatch):
    plans = []
    monkeypatch.setattr(catalog_experiments, "_seconds", lambda df: plans.append(df._jdf.queryExecution().executedPlan().toString()) or 0.0)
    threshold = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")  # as large tables are joined
    try:
        rows = {(r.graph, r.blocks): r for r in catalog.QUERIES["exp_blocks_time_and_io"](spark, FOLDER).collect()}
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", threshold)
    assert len(rows) == len(plans) == 14
    assert not any("Exchange hashpartitioning(src" in p or "Sort [src" in p for p in plans)
    g = catalog.w1(spark, FOLDER)
    top = g.vertices.agg({"vid": "max"}).first()[0] + 1
    for n in (1, 16, 64):
        want = measures.io_infinite_cache(g, blocked.block_size_for(top, n)).first()
        assert (rows["dense", n].read_bytes, rows["dense", n].written_bytes) == (want.read_bytes, want.written_bytes)


def test_arriving_edges_are_sorted_by_a_leading_number_after_their_state(spark):
    edges = spark.createDataFrame([(1, 2, 5), (2, 3, None), (1, 3, 5), (4, 5, -7), (1, 4, 2)], "src long, dst long, ord int")
    held = spark.createDataFrame([(1, [2]), (5, [0, 3]), (9, [1])], "vid long, parts array<int>")
    placed = partition.place_batch(edges, held, [0.0, 0.0, 7.0, 0.0], 4)
    state = partition.Greedy(4, loads=[0.0, 0.0, 7.0, 0.0], held={1: 4, 5: 9})
    assert [tuple(r) for r in placed.collect()] == [(u, v, state.place(u, v)) for u, v in ((2, 3), (4, 5), (1, 4), (1, 2), (1, 3))]
    assert "isnotnull(dst" not in placed._jdf.queryExecution().executedPlan().toString().split("Sort [")[1].split("]")[0]
