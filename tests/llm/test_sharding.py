import math
import zlib
from collections import Counter

from pyspark.sql import functions as F

from graphweave.llm.sharding import Node, even_tree, grown, place, shard_documents


def placed(spark, tree, n=20000):
    return dict(spark.range(n).select("id", place(F.col("id"), tree).alias("s")).collect())


def test_growth_moves_rows_only_into_the_new_shard(spark):
    docs = spark.createDataFrame([(i, f"text {i % 7}") for i in range(12000)] + [(None, None), (5, ""), (5, "")], "doc_id long, text string").withColumn("shard", F.lit("x"))
    rows = shard_documents(docs, even_tree(), grown(even_tree(), 24)).collect()
    assert len(rows) == 12003 and {r.shard for r in rows} == set(range(24))
    assert all(r.grown_shard in (r.shard, 24) for r in rows)
    assert abs(sum(r.grown_shard == 24 for r in rows) / 12003 - 1 / 25) < 0.01
    by = {}
    for r in rows:
        by.setdefault(r.shard, []).append(r.slot)
    assert all(sorted(v) == list(range(len(v))) for v in by.values())
    assert max(map(len, by.values())) < 12003 / 24 * 1.25
    assert all(r.size == 8 + len(f"text {r.doc_id % 7}") and r.text_crc32 == zlib.crc32(f"text {r.doc_id % 7}".encode()) for r in rows if r.doc_id and r.size > 8)
    assert [r.size for r in rows if r.doc_id is None] == [8]


def test_weights_steer_shares_and_confine_movement(spark):
    leaf = lambda n, w: Node(n, (), w)
    tree = lambda w: Node(0, (Node(0, (Node(0, (leaf(0, 1.0), leaf(1, 3.0))),)), Node(1, (Node(1, (leaf(2, w), leaf(3, 2.0), leaf(4, 0.0))),))))
    before, after = placed(spark, tree(2.0)), placed(spark, tree(4.0))
    share = Counter(before.values())
    assert 4 not in share and all(math.isclose(share[s] / 20000, w / 8, rel_tol=0.1) for s, w in ((0, 1), (1, 3), (2, 2), (3, 2)))
    assert all(after[i] in (2, 3) for i in before if before[i] != after[i])  # into the subtree that grew, or inside it


def test_empty_table(spark):
    assert shard_documents(spark.createDataFrame([], "doc_id long, text string")).count() == 0
