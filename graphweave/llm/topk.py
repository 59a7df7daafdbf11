"""Exact top-k search by inner product: tiled matrix products, partial selection, tree merging.

Queries are dealt into tiles and candidates into shards of bounded size, both packed into one block row each. A
block pair is one matrix product; from it every query keeps its k best, and the partial lists of a query meet in
a tree of bounded fan-in, so neither a task nor the driver holds more than a tile, a shard, or a node's lists.

Components are floor(scale * x). Products run in doubles where these are exact (sums below 2^53), otherwise in
integers; scores beyond 64 bits are an error.

Defined results: vectors that are null or hold a null or non-finite component take no part, nor do vectors of
another length than the query's; a query's own row is no candidate of it, other rows with its id are; repeated
rows count each as candidates, and as one query; ties go to smaller ids; fewer candidates than k give all of
them; null ids and extra columns take no part; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphweave.llm.common import materialize

_PARTIAL = "array<struct<rest bigint, vec_id bigint>>"


def quantised(vectors: DataFrame, scale: int, id_col: str, vector_col: str) -> DataFrame:
    """(vec_id, q, n): distinct rows that take part, with how often each occurs."""
    wide = F.transform(vector_col, lambda x: F.floor(F.lit(float(scale)) * x.cast("double")))
    fine = F.forall(vector_col, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < float("inf")))
    rows = vectors.where(F.col(id_col).isNotNull() & F.coalesce(fine, F.lit(False)))
    rows = rows.select(F.col(id_col).cast("long").alias("vec_id"), wide.alias("q"))
    return rows.groupBy("vec_id", "q").agg(F.count("*").alias("n"))


def _packed(rows: DataFrame, blocks: int, name: str) -> DataFrame:
    """One row per block: ids, counts and components of its vectors, in id order; blocks differ in vector length."""
    block = F.pmod(F.xxhash64("vec_id", "q"), F.lit(blocks)).cast("int")
    grouped = rows.withColumn(name, block).groupBy(name, F.size("q").alias("width"))
    packed = grouped.agg(F.sort_array(F.collect_list(F.struct("vec_id", "q", "n"))).alias("rows"))
    return packed.select(
        name,
        "width",
        F.col("rows.vec_id").alias(f"{name}_ids"),
        F.col("rows.n").alias(f"{name}_n"),
        F.flatten("rows.q").alias(f"{name}_q"),
    )


def _products(queries: np.ndarray, candidates: np.ndarray) -> np.ndarray:
    reach = float(np.abs(queries).max(initial=0)) * float(np.abs(candidates).max(initial=0)) * queries.shape[1]
    if reach < 2**53:
        return (queries.astype(float) @ candidates.T.astype(float)).astype(np.int64)
    exact = queries.astype(object) @ candidates.T.astype(object)
    return exact.astype(np.int64)  # raises beyond 64 bits


def _best(scores: np.ndarray, ids: np.ndarray, times: np.ndarray, own: np.ndarray, k: int) -> list[list[dict]]:
    """Of each row the k best, equals by place (ids ascend). own: the column that is the query's row, or -1."""
    n = scores.shape[1]
    line = np.flatnonzero(own >= 0)
    scores[line, own[line]] = np.iinfo(np.int64).min  # kept only where the same row occurs again
    if n > 2 * k:
        bar = np.partition(scores, n - k, axis=1)[:, n - k]
    out = []
    for i, row in enumerate(scores):
        if n > 2 * k:
            over = np.flatnonzero(row > bar[i])
            level = np.flatnonzero(row == bar[i])[: k - len(over)]
            at = np.concatenate([over, level])
        else:
            at = np.arange(n)
        at = at[np.lexsort((at, -row[at]))]
        out.append([(int(row[j]), int(ids[j]), int(times[j])) for j in at if j != own[i]][:k])
    return out


def top_k(
    vectors: DataFrame, is_query: Column, k: int, scale: int = 64, id_col: str = "vec_id", vector_col: str = "embedding",
    tile_rows: int = 4096, shard_rows: int = 8192, fan_in: int = 16,
) -> DataFrame:
    """(query_id, rank, vec_id, score) of the k best candidates of each row that is_query (over vec_id) holds for."""
    rows = materialize(quantised(vectors, scale, id_col, vector_col))
    chosen = rows.where(is_query)
    n_rows, n_queries = rows.count(), chosen.count()
    tiles, shards = max(1, -(-n_queries // tile_rows)), max(1, -(-n_rows // shard_rows))
    packed_queries = materialize(_packed(chosen, tiles, "tile"))
    packed_rows = _packed(rows, shards, "shard").withColumn("tile", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1))))
    pairs = packed_rows.repartition(max(1, min(tiles * shards, 4096)), "tile", "shard").join(F.broadcast(packed_queries) if n_queries <= tile_rows else packed_queries, ["tile", "width"])

    def run(batches):
        for batch in batches:
            for r in range(len(batch)):
                row = {name: batch.column(name).slice(r, 1) for name in batch.schema.names}
                width = max(1, row["width"][0].as_py())
                part = {name: row[name].flatten().to_numpy(zero_copy_only=False) for name in ("tile_ids", "shard_ids", "shard_n", "tile_q", "shard_q")}
                q, c = part["tile_q"].reshape(-1, width), part["shard_q"].reshape(-1, width)
                where = {}
                for j, key in enumerate(zip(part["shard_ids"].tolist(), map(bytes, c))):
                    where[key] = j
                for a in range(0, len(q), 256):
                    own = np.array([where.get(key, -1) for key in zip(part["tile_ids"][a : a + 256].tolist(), map(bytes, q[a : a + 256]))])
                    found = _best(_products(q[a : a + 256], c), part["shard_ids"], part["shard_n"], own, k)
                    for i, best in enumerate(found):
                        if own[i] >= 0 and part["shard_n"][own[i]] > 1:  # copies of the query's row
                            same = int(_products(q[a + i : a + i + 1], c[own[i] : own[i] + 1])[0, 0])
                            best.append((same, int(part["shard_ids"][own[i]]), int(part["shard_n"][own[i]]) - 1))
                            best.sort(key=lambda x: (-x[0], x[1]))
                        best = [x for x in best for _ in range(min(x[2], k))][:k]
                        found[i] = [{"rest": -s, "vec_id": v} for s, v, _ in best]
                    ids = part["tile_ids"][a : a + 256]
                    vector = [bytes(x) for x in q[a : a + 256]]
                    shard = np.full(len(ids), row["shard"][0].as_py(), np.int32)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(ids, pa.int64()), pa.array(vector, pa.binary()), pa.array(shard), pa.array(found, pa.list_(pa.struct([("rest", pa.int64()), ("vec_id", pa.int64())])))],
                        names=["query_id", "query", "node", "best"],
                    )

    lists = pairs.mapInArrow(run, f"query_id long, query binary, node int, best {_PARTIAL}")
    while True:
        lists = lists.withColumn("node", F.expr(f"node div {fan_in}").cast("int"))
        merged = F.slice(F.sort_array(F.flatten(F.collect_list("best"))), 1, k)
        lists = lists.groupBy("query_id", "query", "node").agg(merged.alias("best"))
        if shards <= fan_in:
            break
        shards = -(-shards // fan_in)
    ranked = lists.select("query_id", F.posexplode("best").alias("at", "x"))
    return ranked.select("query_id", (F.col("at") + 1).cast("int").alias("rank"), F.col("x.vec_id").alias("vec_id"), (-F.col("x.rest")).alias("score"))
