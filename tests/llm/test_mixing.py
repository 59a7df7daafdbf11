from collections import defaultdict
from fractions import Fraction

from pyspark.sql import functions as F

from graphweave.llm.mixing import cycle_weights, first_positions, integral, mix, positions, share, word_count

SIZES = {"a": 40, "b": 3, "c": 500, "d": 7, None: 60}


def docs(spark):
    rows, i = [], 0
    for source, n in SIZES.items():
        for k in range(n):
            rows.append((i, " ".join(["w"] * (k % 17)) if k % 19 else None, source, "en"))
            i += 1
    return spark.createDataFrame(rows, "doc_id long, text string, source string, target string")


def test_shares():
    assert share([10, 10], [Fraction(1), Fraction(1)]) == [10, 10]
    assert share([10, 1000, 1000], [Fraction(5), Fraction(1), Fraction(1)]) == [30, 990, 990]
    assert sum(share([3, 0, 900], [Fraction(5), Fraction(2), Fraction(1)])) == 903
    assert share([], []) == [] and integral(((0.0, 1.0), (1.0, 3.0)))[-1] == 2


def test_takes_meet_targets(spark):
    df = docs(spark)
    got = mix(df).collect()
    again = {r.doc_id: r.taken for r in mix(df.repartition(7)).collect()}
    assert len(got) == df.count() and {r.doc_id: r.taken for r in got} == again
    by = defaultdict(lambda: [0, 0, 0.0])
    for r in got:
        assert r["size"] == len((r.text or "").split()) and 0 <= r.taken <= 3 * r["size"]
        by[r.source][0] += r.taken
        by[r.source][1] += r["size"]
        by[r.source][2] = r["target"]
        assert r.source_size == sum(x["size"] for x in got if x.source == r.source)
    assert abs(sum(t for _, _, t in by.values()) - sum(s for _, s, _ in by.values())) < 1e-6
    for taken, size, target in by.values():
        assert abs(taken - target) <= 1 and target <= 3 * size


def test_positions_follow_the_schedule(spark):
    df = docs(spark)
    rows = positions(mix(df)).select("source", "size", "position", "copy", "taken", F.spark_partition_id().alias("p")).collect()
    places = [r.position for r in rows]
    assert all(0 <= p <= 1 for p in places)
    ordered = sorted(rows, key=lambda r: r.p)
    ends = [(min(q), max(q)) for k in sorted({r.p for r in rows}) if (q := [r.position for r in ordered if r.p == k])]
    assert all(a[1] <= b[0] for a, b in zip(ends, ends[1:]))
    early = lambda s: sum(r["size"] for r in rows if r.source == s and r.position < 0.5) / sum(r["size"] for r in rows if r.source == s)
    assert early("a") > 0.55  # the largest weight fades
    assert early("c") < 0.45  # the smallest grows


def test_empty_and_counts(spark):
    assert mix(docs(spark).limit(0)).count() == 0
    df = spark.createDataFrame([("a\x0bb\x1cc  d\n",), ("",), (None,), (" \t",)], "t string")
    assert [r[0] for r in df.select(word_count(F.col("t"))).collect()] == [3, 0, 0, 0]
    none = mix(df.select(F.lit(1).alias("doc_id"), F.lit(None).cast("string").alias("text"), F.lit("s").alias("source")))
    assert [r.taken for r in none.collect()] == [0] * 4


def brute(rows, most_repeats=3):
    """(doc, taken, first position) by sequential sums in hash order, positions by bisection of the integral."""
    sources = sorted({r.source for r in rows}, key=lambda x: (x is None, x or ""))
    schedules = [cycle_weights()(i) for i in range(len(sources))]
    sizes = [sum(r["size"] for r in rows if r.source == s) for s in sources]
    targets, capped = {}, {}
    while len(capped) < len(sources):
        free = [i for i in range(len(sources)) if i not in capped]
        unit = Fraction(sum(sizes) - sum(capped.values())) / sum(integral(schedules[i])[-1] for i in free)
        targets = capped | {i: unit * integral(schedules[i])[-1] for i in free}
        over = [i for i in free if targets[i] > most_repeats * sizes[i]]
        if not over:
            break
        capped |= {i: Fraction(most_repeats * sizes[i]) for i in over}
    out = []
    for i, s in enumerate(sources):
        wanted, before = int(targets[i] + Fraction(1, 2)), 0
        (t0, w0), (t1, w1) = schedules[i]
        demand = lambda t: (w0 * t + (w1 - w0) * t * t / 2) / integral(schedules[i])[-1] * wanted  # noqa: B023, E731
        for r in sorted((r for r in rows if r.source == s), key=lambda r: (r.h, r.doc_id)):
            taken = sum(max(0, min(r["size"], wanted - copy * sizes[i] - before)) for copy in range(most_repeats))
            low, high = 0.0, 1.0
            for _ in range(60):
                middle = (low + high) / 2
                low, high = (middle, high) if demand(middle) < before + r["size"] / 2 else (low, middle)
            out.append((r.doc_id, taken, round(low, 6) if taken else None))
            before += r["size"]
    return sorted(out)


def test_mix_matches_brute_force(spark):
    df = docs(spark).union(docs(spark).where("doc_id between 100 and 130"))  # repeated rows
    long = spark.createDataFrame([(5000, "w " * 200_000, "e", "en"), (5001, "w", "e", "en"), (5002, None, "f", "en")], df.schema)
    df = df.union(long)
    hashed = df.select("doc_id", "source", word_count(F.col("text")).alias("size")).withColumn("h", F.xxhash64(F.lit(0), "doc_id", "size"))
    rows = first_positions(mix(df)).select("doc_id", "taken", "first_position", F.spark_partition_id().alias("p")).collect()
    assert sorted((r.doc_id, r.taken, r.first_position and round(r.first_position, 6)) for r in rows) == brute(hashed.collect())
    places = [-1.0 if r.first_position is None else r.first_position for r in sorted(rows, key=lambda r: r.p)]
    assert places == sorted(places) and len({r.p for r in rows}) > 1
