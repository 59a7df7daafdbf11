import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from graphweave.experiments import ArrayTrainer
from graphweave.operators import layout, measures, partition, remote
from graphweave.operators.train import Model, Optimiser, Trainer
from graphweave.storage import checkpointed

PARTS = 3


@pytest.fixture(scope="module")
def graph(spark):
    rng = random.Random(2)
    pairs = {tuple(sorted(rng.sample(range(30), 2))) for _ in range(90)}
    edges = partition.prepare(spark.createDataFrame(sorted(pairs), "src long, dst long")).cache()
    return edges, sorted(pairs)


def placed_by_hand(order, parts, slack=None):
    """The least-loaded rule in plain sets, independent of the library."""
    load, where, out = [0] * parts, {}, {}
    for n, (u, v) in enumerate(order):
        a, b = where.setdefault(u, set()), where.setdefault(v, set())
        options = a & b or a | b or set(range(parts))
        if slack is not None:
            free = {q for q in range(parts) if load[q] < (1 + slack) * (n + 1) / parts}
            options = options & free or free or set(range(parts))
        q = sorted(options, key=lambda q: (load[q], q))[0]
        load[q] += 1
        a.add(q)
        b.add(q)
        out[u, v] = q
    return out


def mixed(pairs):
    return sorted(pairs, key=lambda p: ((p[0] * 7919 + p[1] * 104729) % 1000003, p))


def test_greedy_follows_the_rule(graph):
    edges, pairs = graph
    for parts, order, slack in ((PARTS, "hash", None), (64, "hash", None), (128, "hash", 0.1), (PARTS, "sorted", None), (PARTS, "sorted", 0.05)):
        got = {(r.src, r.dst): r.part for r in partition.greedy(edges, parts, order, slack).collect()}
        assert got == placed_by_hand(mixed(pairs) if order == "hash" else sorted(pairs), parts, slack), (parts, order, slack)


def test_greedy_needs_mixed_order(spark):
    pairs = [(i, i + 1) for i in range(200)]  # in sorted order each edge meets the last one's partition
    path = partition.prepare(spark.createDataFrame(pairs, "src long, dst long"))
    loads = lambda order, slack=None: sorted(r["count"] for r in partition.greedy(path, 4, order, slack).groupBy("part").count().collect())
    assert loads("sorted") == [200]
    assert len(loads("hash")) == 4 and loads("hash")[-1] <= 60
    assert len(loads("sorted", 0.05)) == 4 and loads("sorted", 0.05)[-1] <= 54


def test_parallel_greedy_places_every_edge(graph):
    edges, pairs = graph
    cut = partition.greedy_parallel(edges, PARTS, rounds=3, tasks=2, chunk_edges=20)
    rows = cut.collect()
    assert sorted((r.src, r.dst) for r in rows) == pairs and all(0 <= r.part < PARTS for r in rows)
    factor = lambda c: measures.replication_factor(layout.clones(c)).first()[0]
    assert 1 <= factor(cut) <= factor(partition.random_edge(edges, PARTS)) + 0.2


@pytest.mark.parametrize("parts", [64, 128])
def test_parallel_greedy_keeps_states_of_many_parts(spark, parts):
    pairs = [(10 * i + k, 10 * i + k + 1) for i in range(300) for k in range(3)]  # paths apart from each other
    edges = partition.prepare(spark.createDataFrame(pairs, "src long, dst long"))
    cut = checkpointed(partition.greedy_parallel(edges, parts, rounds=4, tasks=1))
    rows = cut.collect()
    assert sorted((r.src, r.dst) for r in rows) == pairs and {r.part for r in rows} == set(range(parts))
    assert measures.replication_factor(layout.clones(cut)).first()[0] < 1.25  # by chance it is near 1.5


def test_greedy_beats_random(graph):
    edges, _ = graph
    factor = lambda c: measures.replication_factor(layout.clones(c)).first()[0]
    assert 1 <= factor(partition.greedy(edges, PARTS)) < factor(partition.random_edge(edges, PARTS)) <= PARTS


def test_three_way_cut_of_the_example(spark):
    """Seven vertices and nine edges in three partitions, worked out by hand."""
    rows = [(0, 1, 0), (1, 2, 0), (0, 2, 0), (2, 3, 1), (3, 4, 1), (2, 4, 1), (4, 5, 2), (5, 6, 2), (2, 6, 2)]
    cut = spark.createDataFrame(rows, "src long, dst long, part int")
    cloned = layout.clones(cut)
    held = {(r.vid, r.part): r.copies for r in cloned.collect()}
    assert held == {(0, 0): 1, (1, 0): 1, (2, 0): 3, (2, 1): 3, (2, 2): 3, (3, 1): 1, (4, 1): 2, (4, 2): 2, (5, 2): 1, (6, 2): 1}
    assert measures.replication_factor(cloned).first()[0] == 10 / 7 and measures.replication_factor(cloned, "split").first()[0] == 2.5
    assert measures.edge_balance(cut, 3).first()[0] == 1.0
    assert sorted(tuple(r) for r in layout.vertex_map(cloned).collect()) == [(0, 0, 3), (1, 3, 6), (2, 6, 10)]
    lists = {r.vid: r.local_ids for r in layout.clone_lists(layout.local_ids(cloned)).collect()}
    assert lists == {2: [2, 3, 6], 4: [5, 7]}
    features = cloned.select("vid", "part", F.array(F.col("vid").cast("double")).alias("feat"))
    for kernel in ("columns", "csr"):
        partials = {(r.vid, r.part): r.vec[0] for r in remote.local_aggregate(cut, features, 1, kernel=kernel).collect()}
        assert partials == {(1, 0): 0.0, (2, 0): 1.0, (3, 1): 2.0, (4, 1): 5.0, (5, 2): 4.0, (6, 2): 7.0}
    roles = layout.with_roles(cloned, layout.trees(cloned))
    full = remote.complete(remote.local_aggregate(cut, features, 1), roles, 1)
    synced = {(r.vid, r.part): r.vec[0] for r in remote.sync_full(full, 1).collect()}
    assert synced[2, 0] == synced[2, 1] == synced[2, 2] == 1.0 and synced[4, 1] == synced[4, 2] == 5.0
    assert sum(r.vectors for r in measures.comm_volume(roles, 1, "sync_full").collect()) == 6


def test_local_aggregation_moves_no_rows(spark, graph):
    edges, _ = graph
    cut = remote.dealt(partition.both_ways(partition.random_edge(edges, PARTS)), PARTS)
    cloned = layout.clones(partition.random_edge(edges, PARTS))
    features = remote.dealt(cloned.select("vid", "part", F.array(F.col("vid") * 1.0, F.lit(2.0)).alias("feat")), PARTS)
    threshold = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")  # as for frames too large to broadcast
    for kernel in ("columns", "csr"):
        for direction in ("forward", "backward"):
            sums = remote.local_aggregate(cut, features, 2, direction=direction, kernel=kernel)
            plan = sums._jdf.queryExecution().executedPlan().toString()
            assert "Exchange" not in plan, plan
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", threshold)
    forms = [sorted((r.vid, r.part, tuple(r.vec)) for r in remote.local_aggregate(cut, features, 2, kernel=k).collect()) for k in ("columns", "csr")]
    assert forms[0] == forms[1]


def test_csr_kernel_in_small_blocks(graph):
    edges, _ = graph
    cut = partition.both_ways(partition.random_edge(edges, PARTS))
    features = layout.clones(cut).select("vid", "part", F.array(F.col("vid") * 1.0, F.lit(2.0)).alias("feat"))
    for reduce in ("sum", "max", "min"):
        forms = [sorted((r.vid, r.part, tuple(r.vec)) for r in remote.local_aggregate(cut, features, 2, reduce, kernel=k, block=b).collect()) for k, b in (("columns", 0), ("csr", 1), ("csr", 7))]
        assert forms[0] == forms[1] == forms[2]


def test_layout_is_consistent(graph):
    edges, _ = graph
    cloned = layout.clones(partition.random_edge(edges, PARTS))
    numbered = layout.local_ids(cloned).collect()
    assert sorted(r.local_id for r in numbered) == list(range(len(numbered)))
    found = {r.local_id: r.part for r in layout.locate(layout.local_ids(cloned).select("local_id"), layout.vertex_map(cloned)).collect()}
    assert found == {r.local_id: r.part for r in numbered}
    for tree in layout.trees(cloned).collect():
        held = sorted(r.part for r in numbered if r.vid == tree.vid)
        assert sorted([tree.root_part, *tree.leaf_parts]) == held


def test_exchange_counts(graph):
    edges, _ = graph
    cloned = layout.clones(partition.random_edge(edges, PARTS))
    tree = layout.trees(cloned)
    roles = layout.with_roles(cloned, tree, layout.bins(tree, 2))
    full = measures.comm_volume(roles, 4, "sync_full").collect()
    split = measures.comm_volume(roles, 4, "delayed", 2).collect()
    assert [tuple(r) for r in measures.comm_volume(roles, 4, "local_only").collect()] == [(0, 0, 0)]
    assert sum(r.vectors for r in split) == full[0].vectors == 2 * cloned.selectExpr("count(*) - count(distinct vid) as n").first().n


def test_published_work_and_memory():
    assert [round(x / 1e9, 2) for x in measures.full_work(measures.FULL_VERTICES[1])] == [12.61, 32.29, 32.29]
    assert [round(x / 1e9, 2) for x in measures.full_work(measures.FULL_VERTICES[16])] == [3.07, 7.86, 7.86]
    assert round(sum(measures.sampled_work()) / 1e9, 3) == 0.202
    assert [measures.batches_per_socket(measures.TRAIN_VERTICES, measures.BATCH, s) for s in (1, 16)] == [99, 7]
    for parts, rf, gigabytes in ((32, 4.63, 180), (64, 5.63, 112), (128, 6.62, 70)):
        model = measures.memory_model(measures.DATASETS["citations"][0] * rf / parts, 128, 256, 256, 172)["total"] / 1e9
        assert abs(model / gigabytes - 1) < 0.06


def arrays(pairs, seed=0):
    rng = np.random.default_rng(seed)
    src = np.array([p[0] for p in pairs] + [p[1] for p in pairs])
    dst = np.array([p[1] for p in pairs] + [p[0] for p in pairs])
    low, high = np.minimum(src, dst), np.maximum(src, dst)
    part = (low * 7919 + high * 104729) % PARTS
    x, y = rng.normal(size=(30, 2)), rng.integers(0, 3, 30)
    split = np.where(np.arange(30) % 10 < 6, "train", "test").astype(object)
    return src, dst, part, x, y, split


def test_gradients_by_finite_differences(graph):
    data = arrays(graph[1])
    trainer = ArrayTrainer(*data, [2, 4, 3], "local_only")
    grads, _ = trainer.gradients()
    for layer, cell in ((0, (1, 2)), (1, (3, 1))):
        w = trainer.model.layers[layer][0]
        w[cell] += 1e-5
        up = trainer.gradients()[1]["loss"]
        w[cell] -= 2e-5
        down = trainer.gradients()[1]["loss"]
        w[cell] += 1e-5
        assert abs((up - down) / 2e-5 - grads[layer][0][cell]) < 1e-6


def test_full_sync_equals_one_partition(graph):
    src, dst, part, x, y, split = arrays(graph[1])
    whole = ArrayTrainer(src, dst, 0 * part, x, y, split, [2, 4, 3], "sync_full")
    cut = ArrayTrainer(src, dst, part, x, y, split, [2, 4, 3], "sync_full")
    for (a, _), (b, _) in zip(whole.gradients()[0], cut.gradients()[0]):
        assert np.allclose(a, b, atol=1e-10)


@pytest.mark.parametrize("mode", ["sync_full", "local_only", "delayed"])
def test_distributed_training_equals_arrays(spark, graph, mode):
    edges, pairs = graph
    src, dst, part, x, y, split = arrays(pairs)
    pairs_cut = partition.random_edge(edges, PARTS)
    cloned = layout.clones(pairs_cut)
    tree = layout.trees(cloned)
    roles = layout.with_roles(cloned, tree)
    features = spark.createDataFrame([(i, [float(v) for v in row]) for i, row in enumerate(x)], "vid long, feat array<double>")
    labels = spark.createDataFrame([(i, int(y[i]), split[i]) for i in range(30)], "vid long, y int, split string")
    epochs = 3 if mode == "delayed" else 2
    spark_side = Trainer(partition.both_ways(pairs_cut), roles, features, labels, [2, 4, 3], mode, delay=1, optimiser=Optimiser("sgd", 0.5))
    root_of = np.zeros(30, int)
    for r in tree.collect():
        root_of[r.vid] = r.root_part
    array_side = ArrayTrainer(src, dst, part, x, y, split, [2, 4, 3], mode, delay=1, optimiser=Optimiser("sgd", 0.5), root_of=root_of)
    array_side.model = Model([(w.copy(), b.copy()) for w, b in spark_side.model.layers])
    isolated = set(range(30)) - {v for p in pairs for v in p}
    assert not isolated & {i for i in range(30) if split[i] == "train"}
    a, b = spark_side.fit(epochs), array_side.fit(epochs)
    assert np.allclose([h["loss"] for h in a], [h["loss"] for h in b])
    for (w, c), (v, d) in zip(spark_side.model.layers, array_side.model.layers):
        assert np.allclose(w, v) and np.allclose(c, d)


def test_delay_must_fit_bins():
    with pytest.raises(ValueError):
        remote.DelayedSync(2, 3, 2)


def test_greedy_streams_its_edges(spark):
    """Edges come to the rule in several batches, none of which is the whole table, and the state left behind fits the cut."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "50")
    try:
        pairs = sorted({(i, (i * i + k) % 300 + 300) for i in range(300) for k in range(3)})
        edges = partition.prepare(spark.createDataFrame(pairs, "src long, dst long"))
        cut = {(r.src, r.dst): r.part for r in partition.greedy(edges, 5).collect()}
        assert cut == placed_by_hand(mixed(pairs), 5)
        slack = {(r.src, r.dst): r.part for r in partition.greedy(edges, 5, "sorted", 0.05).collect()}
        assert slack == placed_by_hand(sorted(pairs), 5, 0.05)
        left = partition.greedy_state(edges, 5).collect()
        held = {}
        for (u, v), part in cut.items():
            held.setdefault(u, set()).add(part), held.setdefault(v, set()).add(part)
        assert {r.vid: set(r.parts) for r in left if r.vid is not None} == held
        assert {r.parts[0]: r.edges for r in left if r.vid is None} == {q: list(cut.values()).count(q) for q in range(5)}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert not hasattr(partition, "MOST_ORDERED")


def test_trainer_sums_small_partitions_as_arrays_and_large_ones_as_columns(spark, monkeypatch):
    from graphweave.operators import layout, partition, remote, train

    pairs = partition.numbered(spark.createDataFrame([(i, i + k) for i in range(12) for k in (1, 3)], "src long, dst long"))
    cut = partition.random_edge(pairs, 2)
    cloned = layout.clones(cut)
    vertices = cloned.select("vid").distinct()
    features = vertices.selectExpr("vid", "array(vid / 10D, 1D) as feat")
    labels = vertices.selectExpr("vid", "cast(vid % 2 as int) as y", "'train' as split")
    used, sums = [], remote.local_aggregate
    monkeypatch.setattr(remote, "local_aggregate", lambda *a, kernel="columns", **k: used.append(kernel) or sums(*a, kernel=kernel, **k))
    losses = {}
    for most, kernel in ((4_000_000, "csr"), (1, "columns")):
        monkeypatch.setattr(train, "MOST_ARRAY_EDGES", most)
        used.clear()
        made = train.Trainer(partition.both_ways(cut), layout.with_roles(cloned, layout.trees(cloned)), features, labels, [2, 3, 2], "sync_full")
        losses[kernel] = [h["loss"] for h in made.fit(1)]
        assert set(used) == {kernel}
    assert abs(losses["csr"][0] - losses["columns"][0]) < 1e-9
