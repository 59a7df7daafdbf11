import math
import random

from pyspark.sql import functions as F

from graphweave.llm.topk import top_k


def brute(rows, k, every):
    fine = [(i, [math.floor(64 * x) for x in v]) for i, v in rows if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v)]
    out = []
    for at, (i, v) in enumerate(fine):
        if i % every == 0 and (i, v) not in fine[:at]:
            scored = sorted((-sum(a * b for a, b in zip(v, w)), j) for n, (j, w) in enumerate(fine) if n != at and len(w) == len(v))
            out += [(i, r + 1, j, -s) for r, (s, j) in enumerate(scored[:k])]
    return sorted(out)


def test_matches_brute_force(spark):
    rng = random.Random(2)
    rows = [(i, [rng.choice([-1.0, -0.5, 0.01, 0.3, 1.0]) for _ in range(5)]) for i in range(300)]
    rows += [(0, rows[0][1]), (0, rows[0][1]), (5, rows[7][1]), (None, rows[1][1]), (301, None), (302, [1.0, None, 0.0, 0.0, 0.0]), (303, [float("nan")] * 5), (304, [float("inf")] * 5), (320, [1e7] * 5), (340, [1.0, 2.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("rank", F.lit("x"))
    got = top_k(df, F.col("vec_id") % 20 == 0, 7, tile_rows=6, shard_rows=20, fan_in=3)
    assert sorted(map(tuple, got.collect())) == brute(rows, 7, 20)
    assert top_k(df.limit(0), F.col("vec_id") % 20 == 0, 7).count() == 0
    few = df.where("vec_id in (20, 21, 22)")
    assert sorted(map(tuple, top_k(few, F.col("vec_id") % 20 == 0, 7).collect())) == brute([r for r in rows if r[0] in (20, 21, 22)], 7, 20)
