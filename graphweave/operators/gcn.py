"""Graph-convolution layers: (neighbour sum + own) over in-degree, a dense map, an activation."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphweave.operators import aggregate
from graphweave.operators.schedule import in_degrees
from graphweave.plans.spec import AggSpec
from graphweave.sources.graphs import PropertyGraph

NORMS = {
    "in_degree": lambda d: F.greatest(d, F.lit(1)),
    "in_degree_plus_one": lambda d: d + 1,
    "none": lambda d: F.lit(1),
}


def normalise(total: Column, own: Column, degree: Column, norm: str = "in_degree") -> Column:
    return F.zip_with(total, own, lambda s, h: (s + h) / NORMS[norm](degree))


def gcn_aggregate(g: PropertyGraph, norm: str = "in_degree") -> DataFrame:
    """(vid, feat): neighbour sum plus own vector, divided by the in-degree (by one without in-edges)."""
    spec = AggSpec()
    rows = aggregate.messages(g, spec)
    if aggregate.choose(spec, g.width) == "wide":  # the degree is one more column of the same pass
        columns = [F.sum(F.col("m")[j]).alias(f"__{j}") for j in range(g.width)]
        sums = rows.groupBy("dst").agg(F.count("*").alias("degree"), *columns)
        sums = sums.select(F.col("dst").alias("vid"), "degree", F.array(*(F.col(f"__{j}") for j in range(g.width))).alias("total"))
    else:
        sums = aggregate.apply(g, keep_isolated=False).withColumnRenamed("feat", "total").join(in_degrees(g), "vid")
    rows = g.vertices.select("vid", "feat").join(sums, "vid", "left")
    total = F.coalesce("total", F.array_repeat(F.lit(0.0), g.width))
    return rows.select("vid", normalise(total, F.col("feat"), F.coalesce("degree", F.lit(0)), norm).alias("feat"))


def dense(rows: DataFrame, weights: np.ndarray, bias: np.ndarray, relu: bool = True, vector: str = "feat", out: str = "feat", keys: tuple[str, ...] = ("vid",)) -> DataFrame:
    """vector times weights plus bias, by matrix products over Arrow batches; the weights travel with the task."""
    weights, bias = np.asarray(weights, float), np.asarray(bias, float)

    def run(batches):
        for batch in batches:
            if len(batch):
                x = batch.column(len(keys)).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(batch), -1)
                z = x @ weights + bias
                z = np.maximum(z, 0) if relu else z
                offsets = pa.array(np.arange(len(batch) + 1, dtype=np.int32) * z.shape[1])
                columns = [batch.column(i) for i in range(len(keys))]
                yield pa.RecordBatch.from_arrays([*columns, pa.ListArray.from_arrays(offsets, pa.array(z.reshape(-1)))], names=[*keys, out])

    types = ", ".join(f"{k} {rows.schema[k].dataType.simpleString()}" for k in keys)
    return rows.select(*keys, vector).mapInArrow(run, f"{types}, {out} array<double>")


def dense_columns(rows: DataFrame, weights: list[list[float]], bias: list[float], relu: bool = True, vector: str = "feat") -> DataFrame:
    """The same inside generated code, for narrow layers."""

    def component(j: int) -> Column:
        z = sum((F.col(vector)[i] * float(w[j]) for i, w in enumerate(weights)), F.lit(float(bias[j])))
        return F.greatest(z, F.lit(0.0)) if relu else z

    return rows.select("vid", F.array(*map(component, range(len(bias)))).alias("feat"))


def layer(g: PropertyGraph, weights: list[list[float]], bias: list[float], relu: bool = True, norm: str = "in_degree", order: str = "aggregate_first") -> DataFrame:
    """One layer. Since the sum is linear, the dense map may come first; that is cheaper where it narrows."""
    if order == "aggregate_first":
        return dense_columns(gcn_aggregate(g, norm), weights, bias, relu)
    narrow = dense_columns(g.vertices, weights, [0.0] * len(bias), False)
    total = gcn_aggregate(PropertyGraph(narrow, g.edges, len(bias)), norm)
    plus = F.zip_with("feat", F.array(*(F.lit(float(b)) for b in bias)), lambda z, b: z + b)
    return total.select("vid", (F.transform(plus, lambda z: F.greatest(z, F.lit(0.0))) if relu else plus).alias("feat"))


def cheaper_order(width: int, hidden: int) -> str:
    return "dense_first" if hidden < width else "aggregate_first"


def forward(g: PropertyGraph, weights: list[tuple[list[list[float]], list[float]]], norm: str = "in_degree") -> DataFrame:
    """All layers, with an activation after each but the last."""
    for i, (w, b) in enumerate(weights):
        vertices = layer(g, w, b, relu=i < len(weights) - 1, norm=norm, order=cheaper_order(g.width, len(b)))
        g = PropertyGraph(vertices, g.edges, len(b))
    return g.vertices


def backward_aggregate(g: PropertyGraph) -> DataFrame:
    """Gradient of the neighbour sum: own vector plus the sum along reversed edges."""
    from graphweave.sources.graphs import reverse

    sums = aggregate.apply(PropertyGraph(g.vertices, reverse(g.edges), g.width)).withColumnRenamed("feat", "total")
    return g.vertices.select("vid", "feat").join(sums, "vid").select("vid", F.zip_with("total", "feat", lambda s, x: s + x).alias("feat"))


def relational_layer(edges: DataFrame, vertices: DataFrame, relation_weights: dict[str, list[list[float]]], self_weights: list[list[float]], relu: bool = True) -> DataFrame:
    """Typed edges (src, dst, rel): mean per relation, a map per relation, summed with the vertex's own map."""
    width, out = len(self_weights), len(self_weights[0])
    rows = edges.join(vertices.select(F.col("vid").alias("src"), "feat"), "src")
    means = aggregate.reduce_wide(rows.select("dst", "rel", F.col("feat").alias("m")), ["dst", "rel"], "mean", width, out="m")

    def mapped(vector: str, w: list[list[float]]) -> Column:
        return F.array(*(sum((F.col(vector)[i] * float(w[i][j]) for i in range(width)), F.lit(0.0)) for j in range(out)))

    per_relation = None
    for rel, w in relation_weights.items():
        per_relation = F.when(F.col("rel") == rel, mapped("m", w)) if per_relation is None else per_relation.when(F.col("rel") == rel, mapped("m", w))
    known = means.where(F.col("rel").isin(*relation_weights)).select("dst", per_relation.alias("m"))
    summed = aggregate.reduce_wide(known, ["dst"], "sum", out, out="total").withColumnRenamed("dst", "vid")
    joined = vertices.select("vid", mapped("feat", self_weights).alias("own")).join(summed, "vid", "left")
    z = F.zip_with("own", F.coalesce("total", F.array_repeat(F.lit(0.0), out)), lambda a, b: a + b)
    return joined.select("vid", (F.transform(z, lambda x: F.greatest(x, F.lit(0.0))) if relu else z).alias("feat"))


def predict(scores: DataFrame) -> DataFrame:
    from graphweave.functions.vectors import argmax

    return scores.select("vid", argmax(F.col("feat")).alias("y"))


def link_scores(g: PropertyGraph) -> DataFrame:
    """Link head: inner product of the ends of each edge."""
    return aggregate.sddmm(g, "dot")


def graph_readout(vertices: DataFrame, graph_of: DataFrame, width: int, reduce: str = "sum") -> DataFrame:
    """Graph head: reduction over the vertices of each graph; graph_of is (vid, gid)."""
    rows = vertices.join(graph_of, "vid").select("gid", F.col("feat").alias("m"))
    return aggregate.reduce_wide(rows, ["gid"], reduce, width)
