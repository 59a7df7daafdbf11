import random

import pytest
from pyspark.sql import functions as F

from graphweave.operators import aggregate, blocked, gcn, relational, schedule
from graphweave.plans.spec import AggSpec, choose
from graphweave.sources.graphs import PropertyGraph

OPS = {"add": lambda x, y: x + y, "sub": lambda x, y: x - y, "mul": lambda x, y: x * y, "copy_lhs": lambda x, y: x, "copy_rhs": lambda x, y: y}
REDUCE = {"sum": sum, "max": max, "min": min}


@pytest.fixture(scope="module")
def small(spark):
    """Loops, repeated edges, an isolated vertex, a null end."""
    rng = random.Random(3)
    feats = {v: [float(rng.randint(-9, 9)) for _ in range(3)] for v in range(12)}
    edges = [(rng.randrange(11), rng.randrange(10), [float(rng.randint(-9, 9)) for _ in range(3)]) for _ in range(40)] + [(4, 4, [1.0, 2.0, 3.0])] * 2
    vertices = spark.createDataFrame(list(feats.items()), "vid long, feat array<double>")
    df = spark.createDataFrame([*edges, (None, 3, [0.0] * 3)], "src long, dst long, efeat array<double>")
    return PropertyGraph(vertices.cache(), df.cache(), 3, 3), feats, edges


def brute(feats, edges, binary, reduce, empty=0.0):
    got = {v: [] for v in feats}
    for u, v, e in edges:
        got[v].append([OPS[binary](x, y) for x, y in zip(feats[u], e)])
    return {v: [REDUCE[reduce](c) for c in zip(*ms)] if ms else [empty] * 3 for v, ms in got.items()}


def rows(df):
    return {r.vid: [round(x, 9) + 0.0 for x in r.feat] for r in df.collect()}  # forms agree up to rounding


def test_combinations_match_brute_force(small):
    g, feats, edges = small
    for binary, reduce in (("add", "sum"), ("sub", "max"), ("mul", "min"), ("copy_lhs", "sum"), ("copy_rhs", "max")):
        rhs = None if binary == "copy_lhs" else "edge"
        want = brute(feats, edges, binary, reduce)
        for strategy in ("baseline", "wide", "long", "summarizer", "arrow"):
            assert rows(aggregate.apply(g, binary, reduce, rhs=rhs, strategy=strategy)) == want, (binary, reduce, strategy)


def test_blocks_salts_and_empty_value(small):
    g, feats, edges = small
    want = brute(feats, edges, "copy_lhs", "sum")
    assert rows(blocked.apply(g, 3)) == rows(blocked.apply(g, 4, side="dst")) == rows(aggregate.salted(g, 3)) == want
    assert rows(aggregate.apply(g, "copy_rhs", "min", rhs="edge", empty=7.0))[11] == [7.0] * 3
    total = [sum(c) for c in zip(*(f for u, _, _ in edges for f in [feats[u]]))]
    assert [sum(c) for c in zip(*want.values())] == total  # column sums: out-degrees times features


def test_plans_read_only_their_operands(small):
    g, _, _ = small
    text = aggregate.apply(g, "copy_rhs", "sum", rhs="edge", keep_isolated=False)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in text
    with pytest.raises(ValueError):
        AggSpec("add")
    assert choose(AggSpec(), 256) == "summarizer" and choose(AggSpec(), 16) == "wide"


def test_dense_first_equals_aggregate_first(small):
    g, _, _ = small
    w, b = [[1.0, -2.0], [0.5, 1.0], [2.0, 0.0]], [0.5, -1.0]
    one, two = (rows(gcn.layer(g, w, b, order=o)) for o in ("aggregate_first", "dense_first"))
    assert all(abs(x - y) < 1e-9 for v in one for x, y in zip(one[v], two[v]))


def test_dynamic_handing_is_no_slower():
    rng = random.Random(1)
    for _ in range(50):
        work = [rng.paretovariate(1.2) for _ in range(64)]
        dynamic = schedule.makespan(work, 8, True)
        assert max(max(work), sum(work) / 8) <= dynamic + 1e-9 <= sum(work) / 8 + max(work) + 1e-6
    skewed = [100.0] * 8 + [1.0] * 56
    assert schedule.makespan(skewed, 8, True) < schedule.makespan(skewed, 8, False)


def test_validation_names_dangling_ends(spark):
    g = PropertyGraph(spark.createDataFrame([(1, [1.0])], "vid long, feat array<double>"), spark.createDataFrame([(1, 2)], "src long, dst long"), 1)
    assert [(r.problem, r["count"]) for r in g.validate().collect()] == [("dangling end", 1)]
    assert aggregate.apply(g).where(F.col("vid") == 2).count() == 0


def test_baseline_is_another_plan_and_unknown_forms_raise(small):
    g, _, _ = small
    plans = [aggregate.apply(g, strategy=s)._jdf.queryExecution().optimizedPlan().toString() for s in ("baseline", "wide")]
    assert "collect_list" in plans[0] and "collect_list" not in plans[1]
    means = [rows(aggregate.apply(g, reduce="mean", strategy=s)) for s in ("baseline", "wide")]
    assert means[0] == means[1]
    with pytest.raises(ValueError):
        aggregate.apply(g, strategy="no_such")


def test_ranked_and_nearest_match_brute_force(spark):
    rng = random.Random(5)
    values = [(i, rng.choice([None, 1.0, 2.0, rng.random()])) for i in range(300)]
    df = spark.createDataFrame(values, "id long, x double")
    got = [r.id for r in relational.ranked(df, F.desc_nulls_last("x"), F.col("id")).orderBy("place").collect()]
    assert got == [i for i, _ in sorted(values, key=lambda v: (v[1] is None, -(v[1] or 0), v[0]))]
    vectors = [(i, [float(rng.randint(-3, 3)) for _ in range(4)]) for i in range(120)]
    found = relational.knn(spark.createDataFrame(vectors, "vid long, feat array<double>"), 5, block=17).collect()
    want = []
    for i, x in vectors:
        best = sorted((-sum(a * b for a, b in zip(x, y)), j) for j, y in vectors if j != i)[:5]
        want += [(i, j, r + 1, -s) for r, (s, j) in enumerate(best)]
    assert sorted((r.vid, r.neighbour, r["rank"], r.score) for r in found) == sorted(want)
