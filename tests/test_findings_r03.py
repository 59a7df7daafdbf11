"""Queries of the third round's findings, on small tables."""

from itertools import combinations

from graphweave.operators import relational, wedges


def _brute(pairs):
    near = {}
    for u, v in pairs:
        if u is not None and v is not None and u != v:
            near.setdefault(u, set()).add(v)
            near.setdefault(v, set()).add(u)
    count = {v: sum(b in near[a] for a, b in combinations(near[v], 2)) for v in near}
    return {v: n for v, n in count.items() if n}, {v: 2 * n / (len(near[v]) * (len(near[v]) - 1)) for v, n in count.items() if len(near[v]) > 1}


def test_triangles_join_no_wedges(spark, monkeypatch):
    rows = [(i * i % 97 - 40, i * 31 % 89 - 40) for i in range(900)]
    rows += [(2**60, v) for v in range(-40, 30)] + [(2**60 + 1, v) for v in range(-40, 30)] + [(2**60, 2**60 + 1)]  # two hubs, ids beyond 2^53
    rows += [(v, u) for u, v in rows[:50]] + rows[:50] + [(7, 7), (None, 3), (5, None)]
    edges = spark.createDataFrame(rows, "src long, dst long")
    triangles, share = _brute(rows)
    for most, piece, hubs in ((wedges.BLOCK_EDGES, wedges.PIECE, wedges.MOST_HUBS), (40, 7, 30)):  # in as many blocks as slots, and in many
        monkeypatch.setattr(wedges, "BLOCK_EDGES", most)
        monkeypatch.setattr(wedges, "PIECE", piece)
        monkeypatch.setattr(wedges, "MOST_HUBS", hubs)
        found = relational.triangles(edges)
        assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
        assert {r.vid: r.triangles for r in found.collect()} == triangles
        got = {r.vid: r.clustering for r in relational.clustering(edges).collect()}
        assert got.keys() == share.keys() and all(abs(got[v] - share[v]) < 1e-12 for v in share)
    assert relational.triangles(edges.where("src = 7 and dst = 7")).count() == 0


def test_array_trainer_keeps_messages_of_leaves_alone():
    import numpy as np

    from graphweave.experiments import ArrayTrainer

    rng = np.random.default_rng(0)
    n, pairs = 2000, rng.integers(0, 40, (80, 2))
    src, dst = np.concatenate([pairs[:, 0], pairs[:, 1]]), np.concatenate([pairs[:, 1], pairs[:, 0]])
    part, split = np.tile(np.arange(80) % 3, 2), np.where(np.arange(n) % 2, "train", "test").astype(object)
    delay, width = 5, 4
    for mode in ("sync_full", "delayed"):
        trainer = ArrayTrainer(src, dst, part, rng.normal(size=(n, width)), np.arange(n) % 3, split, [width, width, 3], mode, delay)
        largest = []
        whole = trainer._sum
        trainer._sum = lambda values, *a, **k: largest.append(len(values)) or whole(values, *a, **k)
        assert len(trainer.fit(3 * delay)) == 3 * delay
        clones = len(np.unique(np.concatenate([part * n + src, part * n + dst])))
        assert max(largest) == clones  # vertices without an edge are in no sum
        held = sum(a.size for slices in trainer.sent.values() for a in slices)
        assert held <= 2 * 3 * clones * width  # three sums an epoch, and each bin's leaves once among the epochs kept
        assert bool(held) == (mode == "delayed")


def test_cuts_of_a_graph_share_its_ordered_edges(spark):
    from pyspark.sql import functions as F

    from graphweave.operators import partition

    rows = [(g, i * 7 % 50 + base, 1000 + i * i % 90 + base) for g, base in (("a", 0), ("b", 2**40)) for i in range(600)]
    edges = spark.createDataFrame(rows, "graph string, src long, dst long").distinct().withColumn("ord", (F.col("src") * 7919 + F.col("dst") * 104729) % 1000003)
    found = partition.greedy_profiles(edges, (2, 3, 70))
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Generate" not in plan  # no copy of the edges for each number of parts
    got = {(r.graph, r.parts, r.part): (r.vertices, r.clones, r.split, r.edges) for r in found.collect()}
    assert len(got) == 2 * (2 + 3 + 70)
    for graph in ("a", "b"):
        mine = sorted((r.ord, r.src, r.dst) for r in edges.where(F.col("graph") == graph).collect())
        for parts in (2, 3, 70):
            state = partition.Greedy(parts)
            where = {}
            for _, u, v in mine:
                where.setdefault(state.place(u, v), []).append((u, v))
            at = {v: {q for q, es in where.items() for e in es if v in e} for v in state.held}
            for q in range(parts):
                here = [v for v, qs in at.items() if q in qs]
                assert got[graph, parts, q] == (len(at), len(here), sum(len(at[v]) > 1 for v in here), len(where.get(q, [])))
    assert partition.greedy_profiles(edges.where("graph = 'c'"), (2,)).count() == 0
