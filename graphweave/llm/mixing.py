"""Mixing sources to target weights under a time-varying curriculum.

Each source has a weight schedule over training time 0 to 1, piecewise linear. Its integral is the source's
weight; the weights share the words of all documents, no source gives more than ``most_repeats`` times its own
size, and the excess goes to the others by weight. A source's stream repeats its documents in hash order. The
integral of its schedule, scaled to its target, is its cumulative token demand; inverting it at a document's
place in the stream gives the training position of that copy, and a range sort by position gives the mixture.

Places in a stream are prefix sums in two levels, so a source with a third of all rows costs no task more than a
bucket of it. Sources are a dimension of the mixture's configuration (a schedule is given for each); one total a
source reaches the driver, and Spark broadcasts the plan of sources only while it is under its threshold.

Defined results: a null text has size 0 and is never taken; null is a source of its own, the last one; ties of
the hash order break by id; repeated rows are documents of their own, next to each other in the stream; a very
long text is one document, cut only where its source's demand ends in it; an empty table gives no rows; columns
of the input that clash with a result column are replaced by it.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from fractions import Fraction

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window as W

from graphweave.llm.common import fresh, materialize, slots

Knots = Sequence[tuple[float, float]]


def word_count(text: Column) -> Column:
    """Maximal runs of characters other than ASCII white space; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def cycle_weights(weights: Sequence[int] = (5, 2, 1)) -> Callable[[int], Knots]:
    """Schedules by a source's place in order: the largest weight fades, the smallest grows, others stay."""

    def schedule(i: int) -> Knots:
        w = weights[i % len(weights)]
        slope = {max(weights): 0.5, min(weights): -0.5}.get(w, 0.0)
        return ((0.0, w * (1 + slope)), (1.0, w * (1 - slope)))

    return schedule


def integral(knots: Knots) -> list[Fraction]:
    """The schedule's integral from the first knot up to each knot."""
    sums = [Fraction(0)]
    for (t0, w0), (t1, w1) in zip(knots, knots[1:]):
        sums.append(sums[-1] + (Fraction(t1) - Fraction(t0)) * (Fraction(w0) + Fraction(w1)) / 2)
    return sums


def share(sizes: Sequence[int], weights: Sequence[Fraction], most_repeats: int = 3) -> list[Fraction]:
    """Targets that sum to all sizes, by weight, none above most_repeats times its size."""
    targets: list[Fraction] = [Fraction(0)] * len(sizes)
    left, rest = {i for i in range(len(sizes)) if weights[i] > 0}, Fraction(sum(sizes))
    while left:
        unit = rest / sum(weights[i] for i in left)
        full = {i for i in left if unit * weights[i] > most_repeats * sizes[i]}
        if not full:
            for i in left:
                targets[i] = unit * weights[i]
            break
        for i in full:
            targets[i] = Fraction(most_repeats * sizes[i])
            rest -= targets[i]
        left -= full
    return targets


def mix(
    docs: DataFrame,
    schedule: Callable[[int], Knots] | None = None,
    most_repeats: int = 3,
    id_col: str = "doc_id",
    source_col: str = "source",
    size_col: str | None = None,
    text_col: str = "text",
    seed: int = 0,
) -> DataFrame:
    """docs with size, source_size, target, taken, and the plan's columns for ``positions``.

    taken counts words over all repeats; the document at a source's end of demand is cut to the words wanted.
    """
    schedule = schedule or cycle_weights()
    size = F.col(size_col) if size_col else word_count(F.col(text_col))
    docs = docs.withColumn("size", F.coalesce(size, F.lit(0)).cast("long"))
    totals = [(r[0], r[1] or 0) for r in docs.groupBy(source_col).agg(F.sum("size")).collect()]
    totals.sort(key=lambda x: (x[0] is None, x[0] if x[0] is None else [ord(c) for c in str(x[0])]))
    knots = [[(float(t), float(w)) for t, w in schedule(i)] for i in range(len(totals))]
    targets = share([n for _, n in totals], [integral(k)[-1] for k in knots], most_repeats)
    rows = [(s, n, float(t), int(t + Fraction(1, 2)), i, k) for i, ((s, n), t, k) in enumerate(zip(totals, targets, knots))]
    plan = docs.sparkSession.createDataFrame(
        rows,
        T.StructType(
            [
                T.StructField("__source", docs.schema[source_col].dataType),
                T.StructField("source_size", T.LongType()),
                T.StructField("target", T.DoubleType()),
                T.StructField("__wanted", T.LongType()),
                T.StructField("__rank", T.IntegerType()),
                T.StructField("__knots", T.ArrayType(T.ArrayType(T.DoubleType()))),
            ]
        ),
    )
    docs = docs.drop("source_size", "target", "taken")
    docs = docs.join(plan, docs[source_col].eqNullSafe(plan["__source"])).drop("__source")
    # Place in the source's hash order: prefix sums over buckets of the hash, then inside each bucket.
    buckets = max(64, 4 * slots(docs.sparkSession))
    docs = docs.withColumn("__h", F.xxhash64(F.lit(seed), id_col, "size"))
    docs = docs.withColumn("__bucket", F.floor((F.col("__h") / 2.0**64 + 0.5) * buckets).cast("int"))
    sums = materialize(docs.groupBy("__rank", "__bucket").agg(F.sum("size").alias("n")))
    up_to = W.partitionBy("__rank").orderBy("__bucket").rowsBetween(W.unboundedPreceding, -1)
    sums = sums.select("__rank", "__bucket", F.coalesce(F.sum("n").over(up_to), F.lit(0)).alias("__before"))
    docs = docs.join(sums, ["__rank", "__bucket"])
    inside = W.partitionBy("__rank", "__bucket").orderBy("__h", id_col).rowsBetween(W.unboundedPreceding, -1)
    docs = docs.withColumn("__before", F.col("__before") + F.coalesce(F.sum("size").over(inside), F.lit(0)))
    whole = F.when(F.col("source_size") > 0, F.expr("__wanted div source_size")).otherwise(F.lit(0))
    rest = F.col("__wanted") - whole * F.col("source_size") - F.col("__before")
    docs = docs.withColumn("taken", whole * F.col("size") + F.greatest(F.lit(0), F.least(rest, F.col("size"))))
    return docs.drop("__bucket", "__h", "__rank")


def position(place: Column, wanted: Column, knots: Column) -> Column:
    """Training time at which a source's cumulative demand reaches place words, by inverting its integral."""
    pairs = F.zip_with(F.slice(knots, 1, F.size(knots) - 1), F.slice(knots, 2, F.size(knots) - 1), lambda a, b: F.struct(a.alias("a"), b.alias("b")))
    area = lambda p: (p.b[0] - p.a[0]) * (p.a[1] + p.b[1]) / 2
    total = F.aggregate(pairs, F.lit(0.0), lambda s, p: s + area(p))
    goal = place / F.greatest(wanted, F.lit(1)) * total

    def inside(p: Column, left: Column) -> Column:
        slope = (p.b[1] - p.a[1]) / (p.b[0] - p.a[0])
        root = F.sqrt(F.greatest(F.lit(0.0), p.a[1] * p.a[1] + 2 * slope * left))
        return p.a[0] + F.coalesce(F.try_divide(2 * left, p.a[1] + root), F.lit(0.0))

    start = F.struct(goal.alias("left"), F.lit(None).cast("double").alias("t"))
    found = F.aggregate(
        pairs,
        start,
        lambda s, p: F.struct(
            (s.left - area(p)).alias("left"),
            F.coalesce(s.t, F.when(s.left <= area(p), inside(p, s.left))).alias("t"),
        ),
    )
    return F.coalesce(found.t, F.element_at(knots, -1)[0])


def first_positions(mixed: DataFrame) -> DataFrame:
    """mixed with first_position, where the first copy of each document goes, range-sorted by it; null without a copy, at the front."""
    place = position(F.col("__before") + F.col("size") / 2, F.col("__wanted"), F.col("__knots"))
    rows = mixed.withColumn("first_position", F.when(F.col("taken") > 0, place)).drop("__knots", "__wanted", "__before")
    return _range_sorted(rows, "first_position")


def _range_sorted(rows: DataFrame, by: str) -> DataFrame:
    """rows in order of a column; ties, and rows without a value, are dealt over partitions by what else they hold."""
    others = [c for c in rows.columns if c != by]
    tie = fresh(rows, "__tie")
    rows = rows.withColumn(tie, F.xxhash64(*(F.col(f"`{c}`") for c in others)))
    return rows.repartitionByRange(slots(rows.sparkSession), by, tie).sortWithinPartitions(by, tie).drop(tie)


def positions(mixed: DataFrame) -> DataFrame:
    """A row for every copy that the mix takes, whole, with copy (from 0) and its training position, range-sorted."""
    copies = F.expr("cast(ceil(taken / size) as int)")
    rows = mixed.where("taken > 0").withColumn("copy", F.explode(F.sequence(F.lit(0), copies - 1)))
    place = F.col("copy") * F.col("source_size") + F.col("__before") + F.col("size") / 2
    rows = rows.withColumn("position", position(place, F.col("__wanted"), F.col("__knots")))
    rows = rows.drop("__knots", "__wanted", "__before")
    return _range_sorted(rows, "position")
