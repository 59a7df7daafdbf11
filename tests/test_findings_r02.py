"""Queries of the second round's findings, on small tables."""

from pyspark.sql import functions as F

from graphweave import catalog, catalog_tables

FOLDER = "/root/testdata/sf0.001"


def test_model_queries_follow_the_tables(spark, tmp_path):
    rows = [(i, [0.5] * 3, i % 2) for i in range(4)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {r.name: r.value for r in catalog.QUERIES["param_sync"](spark, str(tmp_path)).collect()}
    assert got["1"] == 4 * (3 * 256 + 256 + 256 * 256 + 256 + 256 * 2 + 2) and got["64"] == 64 * got["1"]
    spark.createDataFrame([(1, 10), (1, 11), (2, 11), (2, 12)], "l_orderkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(10,), (11,), (12,)], "p_partkey long").write.parquet(f"{tmp_path}/part.parquet")
    work = {r.name: r.value for r in catalog.QUERIES["work_full"](spark, str(tmp_path)).collect()}
    assert work["1_hop2"] == 400.0 and work["1_hop1"] == 1024.0  # three vertices, four directed edges
    model = {r.name: r.value for r in catalog.QUERIES["memory_model"](spark, str(tmp_path)).collect()}
    clones = len({(v, (u * 7919 + w * 104729) % 32) for u, w in ((10, 11), (11, 12)) for v in (u, w)})
    assert round(model["32"] - 4.0 * (4 * 256 + 256 * 256 + 256 * 3), 3) == round(8 * clones / 32 * (8 + 4 * 256 + 3), 3)
    sampled = {r.name: r.value for r in catalog.QUERIES["work_sampled"](spark, str(tmp_path)).collect()}
    assert set(sampled) == {"hop2", "hop1", "hop0", "batches_1", "batches_16"} and sampled["hop1"] >= sampled["hop0"] * 256 * 10 / (15 * 256)


def test_peak_memory_is_of_an_aggregation(spark, monkeypatch):
    seen = []
    whole = catalog.aggregate.apply
    monkeypatch.setattr(catalog.aggregate, "apply", lambda g, **o: seen.append(g) or whole(g, **o))
    assert {r.name for r in catalog.QUERIES["peak_memory"](spark, FOLDER).collect()} == {"heap_peak", "resident_peak"} and seen


def test_large_table_is_not_broadcast(spark, monkeypatch):
    plan = lambda: catalog_tables._hinted(spark.range(10), "broadcast")._jdf.queryExecution().analyzed().toString().lower()
    assert "broadcast" in plan()
    monkeypatch.setattr(catalog_tables, "MOST_BROADCAST", 0)
    assert "broadcast" not in plan() and "shuffle_hash" in plan()


def test_all_epochs_in_one_pass(spark):
    parted = catalog.Parted(spark, FOLDER, 2)
    for e, full in enumerate(parted.all_full(3)):
        want = parted.full(e)
        assert want.exceptAll(full).count() == 0 and full.count() == want.count()
    assert full.agg(F.max(F.size("vec"))).first()[0] == parted.width


def test_blank_lines_are_told_by_their_first_character(spark):
    from graphweave.llm import line_dedup

    lines = ["", " ", "\t \r", " ", "one two three four five six", "one two three four five six", " \tx", " \tx", "\r"]
    docs = spark.createDataFrame([(1, "\n".join(lines))], "doc_id long, text string")
    gone = line_dedup.dropped_lines(docs)
    assert [r.dropped for r in gone.collect()] == [[5, 7]]
    assert "translate(" not in line_dedup.dropped_lines(docs)._jdf.queryExecution().optimizedPlan().toString()


def test_freed_memory_goes_back(spark):
    import psutil

    from graphweave.llm.common import trimmed

    held = [bytes(2000) for _ in range(100_000)]
    kept = held[::500]
    full = psutil.Process().memory_info().rss
    del held
    trimmed()
    assert psutil.Process().memory_info().rss < full - 100e6 and len(kept) == 200


def test_arrays_of_the_document_graph_make_no_rows(spark, monkeypatch):
    import numpy as np

    from graphweave import catalog_experiments
    from graphweave.operators import partition
    from graphweave.sources import graphs

    g = graphs.document_similarity(spark, FOLDER)
    want = sorted((r.src, r.dst) for r in g.edges.collect())
    ids = sorted(r.vid for r in g.vertices.collect())
    langs = {r.vid: (r.y, r.split) for r in graphs.language_labels(spark, FOLDER).collect()}
    collect = type(g.edges).collect
    monkeypatch.setattr(type(g.edges), "collect", lambda df: [] if df.columns == ["src", "dst"] else collect(df))
    src, dst, x, y, split = catalog_experiments._arrays(spark, FOLDER)
    assert sorted((ids[u], ids[v]) for u, v in zip(src, dst)) == want and x.shape == (len(ids), 16)
    assert [(int(a), b) for a, b in zip(y, split)] == [langs[v] for v in ids]
    placed, state = {}, partition.Greedy(3)
    for u, v in sorted({(min(p), max(p)) for p in zip(src.tolist(), dst.tolist())}, key=lambda p: ((p[0] * 7919 + p[1] * 104729) % 1000003, p)):
        placed[u, v] = state.place(u, v)
    assert catalog_experiments._greedy_parts(src, dst, 3).tolist() == [placed[min(p), max(p)] for p in zip(src.tolist(), dst.tolist())]
    assert catalog_experiments._greedy_parts(np.zeros(0, int), np.zeros(0, int), 3).tolist() == []


def test_profiles_of_all_cuts_equal_those_of_each(spark, monkeypatch):
    from graphweave import catalog_experiments  # noqa: F401  registers its queries
    from graphweave.operators import layout, measures, partition
    from graphweave.sources import graphs

    jobs, counts = [], (2, 4, 8, 16, 32, 64, 128)
    for f in ("greedy", "random_edge"):
        whole = getattr(partition, f)
        monkeypatch.setattr(partition, f, lambda *a, whole=whole: jobs.append(a) or whole(*a))
    got = {(r.graph, r.parts, r.method): r for r in catalog.QUERIES["exp_replication_sweep"](spark, FOLDER).collect()}
    assert len(got) == 42 and not jobs  # one pass over a graph's pairs for all cuts, not one for each
    pairs = partition.prepare(graphs.customer_supplier(spark, FOLDER).edges).cache()
    for parts in (4, 128):
        for method, cut in (("greedy", partition.greedy), ("random", partition.random_edge)):
            placed = cut(pairs, parts).cache()
            cloned, row = layout.clones(placed), got["customer_supplier", parts, method]
            want = (measures.replication_factor(cloned).first()[0], measures.edge_balance(placed, parts).first()[0], measures.split_share(cloned).first()[0])
            assert all(abs(x - y) < 1e-9 for x, y in zip(want, (row.replication, row.edge_balance, row.split_share)))


def test_complete_streams_end_in_files(spark):
    from graphweave.streaming import streams

    made = catalog.QUERIES["stream_session"](spark, FOLDER)
    assert made.inputFiles() and made.agg(F.sum("n")).first()[0] == 1000
    none = streams.drain(streams.windowed(streams.events_stream(spark, FOLDER).where("event_id < 0"), "1 day"), "complete")
    assert none.count() == 0 and none.columns == ["start", "event_type", "n", "total"]


def test_all_batches_sampled_together_are_as_each_alone(spark):
    from graphweave.operators import sampling

    edges = spark.range(400).select((F.col("id") * 37 % 61).alias("src"), (F.col("id") * F.col("id") % 53).alias("dst")).distinct()
    seeds = spark.range(20).select((F.col("id") % 3).cast("int").alias("batch"), (F.col("id") * 2).alias("vid"))
    for most in (8192, 2):  # in one list, and as hubs in groups
        used, found = sampling.neighbours_of_batches(sampling.adjacency(edges, most), seeds, (3, 2), 5)
        got = {(r.batch, r.src, r.dst) for r in found.collect()}
        vertices = {(r.batch, r.vid) for r in used.collect()}
        for batch in range(3):
            frontiers, samples = sampling.neighbours(edges, seeds.where(F.col("batch") == batch).select("vid"), (3, 2), 5 + batch)
            assert {(s, d) for b, s, d in got if b == batch} == {(r.src, r.dst) for s in samples for r in s.collect()}
            assert {v for b, v in vertices if b == batch} == {r.vid for r in frontiers[-1].collect()}
