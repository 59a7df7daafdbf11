"""The aggregation primitive: combine operands along in-edges, reduce at the destination.

All forms give one row per vertex. Baseline is the unoptimised pull: each destination gathers the vectors of all
its in-edges and folds them one by one, so every message crosses the shuffle and a hub's list meets in one task;
it is there to be compared with. Wide keeps d aggregate columns (partial sums on the map side, one row per
vertex and task in the shuffle); long explodes dimensions; summarizer keeps one state vector; arrow reduces
sorted runs of a batch in numpy before the shuffle. A copy of the left operand reads no edge features, a copy of
edge features joins no vertices. Null components are skipped; a vertex without in-edges gets ``empty``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphweave.functions.vectors import REDUCE, combine
from graphweave.plans.spec import STRATEGIES, AggSpec, choose
from graphweave.sources.graphs import PropertyGraph
from graphweave.storage import checkpointed

_KERNEL = {"sum": np.add, "max": np.maximum, "min": np.minimum}


def messages(g: PropertyGraph, spec: AggSpec, keep: tuple[str, ...] = ()) -> DataFrame:
    """(dst, *keep, m): the combined vector of every edge, joining only the operands that are read."""
    used = spec.operands
    rows = g.edges.select("src", "dst", *keep, *(["efeat"] if "edge" in used else [])).where("src is not null and dst is not null")
    for end in ("src", "dst"):
        if end in used:
            rows = rows.join(g.vertices.select(F.col("vid").alias(end), F.col("feat").alias(f"{end}_feat")), end)
    column = {"src": "src_feat", "dst": "dst_feat", "edge": "efeat"}
    y = F.col(column[spec.rhs]) if spec.rhs and spec.rhs in used else None
    x = F.col(column[spec.lhs]) if spec.lhs in used else None
    return rows.select("dst", *keep, combine(spec.binary, x, y).alias("m"))


def width_of(g: PropertyGraph, spec: AggSpec) -> int:
    return g.edge_width if set(spec.operands) == {"edge"} else g.width


def reduce_wide(rows: DataFrame, keys: list[str], reduce: str, width: int, vector: str = "m", out: str = "feat") -> DataFrame:
    """One aggregate column per dimension; the array is put together after the shuffle."""
    columns = [REDUCE[reduce](F.col(vector)[j]).alias(f"__{j}") for j in range(width)]
    return rows.groupBy(*keys).agg(*columns).select(*keys, F.array(*(F.col(f"__{j}") for j in range(width))).alias(out))


def reduce_long(rows: DataFrame, keys: list[str], reduce, vector: str = "m") -> DataFrame:
    """(keys, dim, val)."""
    function = REDUCE[reduce] if isinstance(reduce, str) else reduce
    flat = rows.select(*keys, F.posexplode(vector).alias("dim", "x"))
    return flat.groupBy(*keys, "dim").agg(function(F.col("x")).alias("val"))


def _gather(flat: DataFrame, keys: list[str], width: int, out: str) -> DataFrame:
    columns = [F.max(F.when(F.col("dim") == j, F.col("val"))).alias(f"__{j}") for j in range(width)]
    return flat.groupBy(*keys).agg(*columns).select(*keys, F.array(*(F.col(f"__{j}") for j in range(width))).alias(out))


def reduce_summarizer(rows: DataFrame, keys: list[str], reduce: str, out: str = "feat", vector: str = "m") -> DataFrame:
    """One mergeable state vector per group; components must not be null."""
    from pyspark.ml.functions import array_to_vector, vector_to_array
    from pyspark.ml.stat import Summarizer

    vectors = array_to_vector(vector)
    summary = {"sum": Summarizer.sum, "max": Summarizer.max, "min": Summarizer.min, "mean": Summarizer.mean}[reduce]
    return rows.groupBy(*keys).agg(summary(vectors).alias("__v")).select(*keys, vector_to_array("__v").alias(out))


def reduce_arrow(rows: DataFrame, keys: list[str], reduce: str, width: int, out: str = "feat") -> DataFrame:
    """Runs of equal keys in a batch are reduced in numpy, then once more after the shuffle; for sum, max and min."""
    ufunc = _KERNEL[reduce]
    key_types = ", ".join(f"{k} long" for k in keys)

    def run(batches):
        for batch in batches:
            if not len(batch):
                continue
            names = np.stack([batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in range(len(keys))])
            lists = batch.column(len(keys))
            values = lists.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(batch), -1)
            order = np.lexsort(names[::-1])
            names, values = names[:, order], values[order]
            first = np.flatnonzero(np.concatenate([[True], (names[:, 1:] != names[:, :-1]).any(axis=0)]))
            reduced = ufunc.reduceat(values, first, axis=0)
            arrays = [pa.array(names[i][first]) for i in range(len(keys))]
            offsets = pa.array(np.arange(len(first) + 1, dtype=np.int32) * reduced.shape[1])
            arrays.append(pa.ListArray.from_arrays(offsets, pa.array(reduced.reshape(-1))))
            yield pa.RecordBatch.from_arrays(arrays, names=[*keys, "m"])

    partial = rows.select(*keys, "m").mapInArrow(run, f"{key_types}, m array<double>")
    return reduce_wide(partial, keys, reduce, width, out=out)


def reduce_baseline(rows: DataFrame, keys: list[str], reduce: str, out: str = "feat", vector: str = "m") -> DataFrame:
    """One pass by destination: all vectors of a key in a list, folded in a loop, without partial results."""
    gathered = rows.groupBy(*keys).agg(F.collect_list(vector).alias("__all"))
    pair = {"max": F.greatest, "min": F.least}.get(reduce)
    step = lambda a, b: pair(a, b) if pair else F.coalesce(a + b, a, b)

    def fold(lists: Column) -> Column:
        rest = F.slice(lists, 2, F.greatest(F.size(lists) - 1, F.lit(1)))
        return F.aggregate(rest, lists[0], lambda s, x: F.zip_with(s, x, step))

    total = fold(F.col("__all"))
    if reduce == "mean":
        seen = F.transform("__all", lambda m: F.transform(m, lambda x: F.when(x.isNotNull(), 1.0).otherwise(0.0)))
        total = F.zip_with(total, fold(seen), lambda s, n: F.try_divide(s, n))
    return gathered.select(*keys, total.alias(out))


def reduce_rows(rows: DataFrame, keys: list[str], spec: AggSpec, width: int, strategy: str, out: str = "feat") -> DataFrame:
    if strategy == "long" or callable(spec.reduce):
        return _gather(reduce_long(rows, keys, spec.reduce), keys, width, out)
    if strategy == "summarizer":
        return reduce_summarizer(rows, keys, spec.reduce, out)
    if strategy == "arrow":
        return reduce_arrow(rows, keys, spec.reduce, width, out)
    if strategy == "baseline":
        return reduce_baseline(rows, keys, spec.reduce, out)
    return reduce_wide(rows, keys, spec.reduce, width, out=out)


def completed(g: PropertyGraph, reduced: DataFrame, spec: AggSpec, width: int) -> DataFrame:
    """Every vertex once: those without in-edges, and null components, get the empty value."""
    empty = F.lit(spec.empty).cast("double")
    if not spec.keep_isolated:
        return reduced.select(F.col("dst").alias("vid"), "feat")
    rows = g.vertices.select("vid").join(reduced.withColumnRenamed("dst", "vid"), "vid", "left")
    filled = F.transform("feat", lambda x: F.coalesce(x, empty))
    return rows.select("vid", F.coalesce(filled, F.array_repeat(empty, width)).alias("feat"))


def apply(g: PropertyGraph, binary="copy_lhs", reduce="sum", lhs: str = "src", rhs: str | None = None, empty: float | None = 0.0, strategy: str = "auto", keep_isolated: bool = True) -> DataFrame:
    """(vid, feat) for every vertex, or for destinations alone without keep_isolated."""
    spec = AggSpec(binary, reduce, lhs, rhs, empty, keep_isolated)
    width = width_of(g, spec)
    chosen = choose(spec, width) if strategy == "auto" else strategy
    if chosen not in STRATEGIES:
        raise ValueError(f"strategies are {('auto', *STRATEGIES)}")
    return completed(g, reduce_rows(messages(g, spec), ["dst"], spec, width, chosen), spec, width)


def operator_matrix() -> list[tuple[str, str]]:
    """All pairs of combination and reduction."""
    return [(b, r) for b in ("add", "sub", "mul", "div", "copy_lhs", "copy_rhs") for r in ("sum", "max", "min")]


def long_form(df: DataFrame, as_long: bool = True, vector: str = "feat", keys: tuple[str, ...] = ("vid",), digits: int = 6) -> DataFrame:
    """(keys, dim, val), whole numbers or rounded doubles."""
    val = F.round("val").cast("long") if as_long else F.round("val", digits)
    return df.select(*keys, F.posexplode(vector).alias("dim", "val")).select(*keys, "dim", val.alias("val"))


def k_hop(g: PropertyGraph, k: int, cut_lineage: bool = False, **options) -> DataFrame:
    """The primitive k times, each on the result before; lineage is cut between hops on request."""
    for hop in range(k):
        vertices = apply(g, **options)
        if cut_lineage and hop < k - 1:
            vertices = checkpointed(vertices)
        g = PropertyGraph(vertices, g.edges, g.width, g.edge_width)
    return g.vertices


def salted(g: PropertyGraph, salts: int, **options) -> DataFrame:
    """Two-step reduction for hubs: by destination and a hash of the source, then by destination."""
    spec = AggSpec(**options)
    width = width_of(g, spec)
    salted_edges = g.edges.withColumn("salt", F.pmod(F.xxhash64("src"), F.lit(salts)).cast("int"))
    rows = messages(PropertyGraph(g.vertices, salted_edges, g.width, g.edge_width), spec, ("salt",))
    first = reduce_wide(rows, ["dst", "salt"], spec.reduce, width, out="m")
    return completed(g, reduce_wide(first, ["dst"], spec.reduce, width), spec, width)


def spmm(adjacency: DataFrame, features: DataFrame) -> DataFrame:
    """Sparse times dense: adjacency (src, dst, a), features (vid, feat); (vid, dim, val) of the product."""
    rows = adjacency.join(features.select(F.col("vid").alias("src"), F.posexplode("feat").alias("dim", "x")), "src")
    return rows.groupBy(F.col("dst").alias("vid"), "dim").agg(F.sum(F.col("a") * F.col("x")).alias("val"))


def sddmm(g: PropertyGraph, op: str = "dot") -> DataFrame:
    """A value or vector for each edge from its ends' vectors: (src, dst, val)."""
    from graphweave.functions.vectors import dot

    rows = g.edges.select("src", "dst")
    rows = rows.join(g.vertices.select(F.col("vid").alias("src"), F.col("feat").alias("x")), "src")
    rows = rows.join(g.vertices.select(F.col("vid").alias("dst"), F.col("feat").alias("y")), "dst")
    value: Column = dot(F.col("x"), F.col("y")) if op == "dot" else combine({"copy": "copy_lhs"}.get(op, op), F.col("x"), F.col("y"))
    return rows.select("src", "dst", value.alias("val"))
