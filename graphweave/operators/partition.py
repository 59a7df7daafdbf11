"""Cuts of a graph: the greedy least-loaded vertex-cut, its parallel form, and hash cuts to compare with.

The greedy rule is sequential: an edge goes to the least loaded partition among those that hold both its ends,
else either end, else all. Edges come in hash order, since in sorted order the rule piles edges up. The parallel
form runs it per chunk on a snapshot and merges states after each round; what a task holds is its own chunk's
part of the state, joined to the chunk's edges before the pass, so no table of vertices is broadcast.
"""

from __future__ import annotations

from collections import Counter
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweave.functions.vectors import part_of
from graphweave.storage import checkpointed, released


def prepare(edges: DataFrame, undirected: bool = True) -> DataFrame:
    """Each pair once: ordered ends if undirected, no loops, no nulls; with a well-mixed order."""
    a, b = (F.least("src", "dst"), F.greatest("src", "dst")) if undirected else (F.col("src"), F.col("dst"))
    return numbered(edges.where("src is not null and dst is not null and src <> dst").select(a.alias("src"), b.alias("dst")).distinct())


def numbered(pairs: DataFrame) -> DataFrame:
    """Pairs that are ordered and distinct already, with the well-mixed order."""
    return pairs.select("src", "dst").withColumn("ord", (F.col("src") * 7919 + F.col("dst") * 104729) % 1000003)


def both_ways(cut: DataFrame) -> DataFrame:
    """A cut of unordered pairs as directed edges, both of a pair in one partition."""
    return cut.select("src", "dst", "part").union(cut.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "part"))


class Greedy:
    """State of the sequential rule: loads of partitions, and for vertices the set of partitions as bits."""

    def __init__(self, parts: int, slack: float | None = None, loads: list[float] | None = None, held: dict[int, int] | None = None):
        self.parts, self.slack = parts, slack
        self.loads = list(loads) if loads else [0.0] * parts
        self.held = dict(held) if held else {}
        self.everywhere = (1 << parts) - 1
        self.ranked = sorted(range(parts), key=lambda q: (self.loads[q], q))

    def place(self, u: int, v: int) -> int:
        return self.place_all([u], [v])[0]

    def place_all(self, us: list[int], vs: list[int]) -> list[int]:
        """Partitions of edges that come in this order. Partitions are kept ranked by load, so the least loaded is the first that fits."""
        held, loads, ranked, parts, slack, everywhere = self.held, self.loads, self.ranked, self.parts, self.slack, self.everywhere
        out, last = [], parts - 1
        for u, v in zip(us, vs):
            a, b = held.get(u, 0), held.get(v, 0)
            options = a & b or a | b or everywhere
            i = 0
            while not options >> ranked[i] & 1:
                i += 1
            if i and slack is not None and loads[ranked[i]] >= (1 + slack) * (sum(loads) + 1) / parts:
                i = 0  # the least loaded option is at the cap, so all options are
            part = ranked[i]
            load = loads[part] = loads[part] + 1
            while i < last:
                after = ranked[i + 1]
                if loads[after] > load or loads[after] == load and after > part:
                    break
                ranked[i] = after
                i += 1
            ranked[i] = part
            bit = 1 << part
            held[u], held[v] = a | bit, b | bit
            out.append(part)
        return out


def _ids(column: pa.Array) -> list:
    """to_pylist of whole numbers; by way of numpy, which is several times faster, where none is null."""
    return column.to_pylist() if column.null_count else column.to_numpy(zero_copy_only=False).tolist()


def _in_order(edges: DataFrame, *order: str) -> DataFrame:
    """All rows in one task, sorted outside its Python worker, which gets them as a stream of batches."""
    return edges.repartition(1).sortWithinPartitions(*order)


def greedy(edges: DataFrame, parts: int, order: str = "hash", slack: float | None = None) -> DataFrame:
    """(src, dst, part) by the exact sequential rule, in one ordered task that holds the vertices' states, not the edges."""

    def run(batches):
        state = Greedy(parts, slack)
        for batch in batches:
            part = state.place_all(_ids(batch.column(0)), _ids(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(part, pa.int32())], names=["src", "dst", "part"])

    rows = _in_order(edges.select("src", "dst", "ord"), "ord", "src", "dst") if order == "hash" else _in_order(edges.select("src", "dst"), "src", "dst")
    return rows.select("src", "dst").mapInArrow(run, "src long, dst long, part int")


def greedy_state(edges: DataFrame, parts: int) -> DataFrame:
    """(vid, parts, edges): what the exact rule leaves behind: each vertex with its partitions, and, without a vertex, each partition with its edges."""

    def run(batches):
        state = Greedy(parts)
        for batch in batches:
            state.place_all(_ids(batch.column(0)), _ids(batch.column(1)))
        ids = list(state.held)
        for i in range(0, len(ids), 50_000):
            some = ids[i : i + 50_000]
            held = [[q for q in range(parts) if state.held[v] >> q & 1] for v in some]
            yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array(held, pa.list_(pa.int32())), pa.nulls(len(some), pa.int64())], names=["vid", "parts", "edges"])
        loads = [int(x) for x in state.loads]
        yield pa.RecordBatch.from_arrays([pa.nulls(parts, pa.int64()), pa.array([[q] for q in range(parts)], pa.list_(pa.int32())), pa.array(loads, pa.int64())], names=["vid", "parts", "edges"])

    return _in_order(edges.select("src", "dst", "ord"), "ord", "src", "dst").select("src", "dst").mapInArrow(run, "vid long, parts array<int>, edges long")


def greedy_profiles(edges: DataFrame, counts: tuple[int, ...]) -> DataFrame:
    """(graph, parts, part, vertices, clones, split, edges) of the exact rule's cuts of several graphs into several numbers of parts.

    edges is (graph, src, dst, ord). A graph's edges are put in order once; each of its cuts reads them from there in
    one ordered task, which holds its vertices' states, not the edges. The cuts run side by side.
    """
    names = ["graph", "parts", "part", "vertices", "clones", "split", "edges"]

    def left(graph: str, parts: int, state: Greedy) -> pa.RecordBatch:
        clones, split = [0] * parts, [0] * parts
        for held, n in Counter(state.held.values()).items():
            for q in range(parts):
                if held >> q & 1:
                    clones[q] += n
                    split[q] += n * (held & (held - 1) > 0)
        columns = [[graph] * parts, [parts] * parts, list(range(parts)), [len(state.held)] * parts, clones, split, [int(x) for x in state.loads]]
        return pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(columns, (pa.string(), pa.int32(), pa.int32(), *[pa.int64()] * 4))], names=names)

    def cut(graph: str, parts: int):
        def run(batches):
            state, before = Greedy(parts), None
            for batch in batches:
                for i in range(len(batch)):
                    first = tuple(batch.column(c)[i].as_py() for c in range(3))
                    if before is not None and first < before:
                        raise RuntimeError("stored edges were read out of their order")
                    before = first
                    kind = np.dtype(batch.column(3)[i].as_py())
                    state.place_all(*(np.frombuffer(batch.column(c)[i].as_buffer(), kind).tolist() for c in (4, 5)))
            if before is not None:
                yield left(graph, parts, state)

        return run

    spark, found = edges.sparkSession, []
    slots = int(spark.conf.get("spark.sql.shuffle.partitions"))
    for graph in sorted(r.graph for r in edges.select("graph").distinct().collect()):
        rows = edges.where(F.col("graph") == graph).select("ord", "src", "dst").repartitionByRange(slots, "ord", "src", "dst").sortWithinPartitions("ord", "src", "dst")
        packed = checkpointed(rows.mapInArrow(_packed, "ord long, first_src long, first_dst long, kind string, src binary, dst binary"))
        released(spark)
        found += [packed.coalesce(1).mapInArrow(cut(graph, p), "graph string, parts int, part int, vertices long, clones long, split long, edges long") for p in sorted(counts, reverse=True)]
    if not found:
        return spark.createDataFrame([], "graph string, parts int, part int, vertices long, clones long, split long, edges long")
    return reduce(DataFrame.union, found)


def _packed(batches):
    """Each batch of ordered edges as one row: its first edge, and its ends as bytes, in four each where they fit."""
    for batch in batches:
        if len(batch):
            src, dst = (batch.column(c).to_numpy().astype(np.int64) for c in (1, 2))
            small = np.iinfo(np.int32)
            fits = all(small.min <= x.min() and x.max() <= small.max for x in (src, dst))
            kind = "int32" if fits else "int64"
            first = [pa.array([int(batch.column(0)[0].as_py())], pa.int64()), pa.array(src[:1]), pa.array(dst[:1]), pa.array([kind])]
            yield pa.RecordBatch.from_arrays([*first, *(pa.array([x.astype(kind).tobytes()], pa.binary()) for x in (src, dst))], names=["ord", "first_src", "first_dst", "kind", "src", "dst"])


def random_profiles(edges: DataFrame, counts: tuple[int, ...]) -> DataFrame:
    """The same for random_edge: each vertex's partitions as bits, for all numbers of parts in one pass over the ends."""
    bits = 62  # of a long
    words = [(p, w) for p in counts for w in range(-(-p // bits))]
    of = {p: part_of(F.col("src"), F.col("dst"), p) for p in counts}
    bit = lambda p, w: F.when(F.floor(of[p] / bits) == w, F.call_function("shiftleft", F.lit(1).cast("long"), (of[p] % bits).cast("int"))).otherwise(F.lit(0).cast("long"))
    ends = edges.select("graph", F.explode(F.array("src", "dst")).alias("vid"), *(bit(p, w).alias(f"b{p}_{w}") for p, w in words))
    held = ends.groupBy("graph", "vid").agg(*(F.bit_or(f"b{p}_{w}").alias(f"b{p}_{w}") for p, w in words))

    def places(p: int):
        masks = F.array(*(F.col(f"b{p}_{w}") for w in range(-(-p // bits))))
        copies = sum((F.bit_count(F.col(f"b{p}_{w}")) for w in range(-(-p // bits))), F.lit(0))
        word = lambda q: F.element_at(masks, (F.floor(q / bits) + 1).cast("int"))
        is_held = lambda q: F.call_function("shiftright", word(q), (q % bits).cast("int")).bitwiseAND(F.lit(1).cast("long")) == 1
        found = F.filter(F.sequence(F.lit(0), F.lit(p - 1)), is_held)
        return F.transform(found, lambda q: F.struct(F.lit(p).alias("parts"), q.alias("part"), (copies > 1).cast("long").alias("is_split")))

    cloned = held.select("graph", F.inline(F.concat(*map(places, counts)))).groupBy("graph", "parts", "part").agg(F.count("*").alias("clones"), F.sum("is_split").alias("split"))
    cut = edges.select("graph", F.inline(F.array(*(F.struct(F.lit(p).alias("parts"), of[p].alias("part")) for p in counts))))
    loads = cut.groupBy("graph", "parts", "part").agg(F.count("*").alias("edges"))
    vertices = held.groupBy("graph").agg(F.count("*").alias("vertices"))
    return cloned.join(loads, ["graph", "parts", "part"]).join(vertices, "graph").select("graph", "parts", "part", "vertices", "clones", "split", "edges")


def _chunk_pass(parts: int, slack: float | None, shares: list[float]):
    """The rule over one chunk, from the vertex states that its rows carry."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        known = {}
        for end in ("src", "dst"):
            for vid, held in zip(pdf[end].tolist(), pdf[f"{end}_parts"]):
                if held is not None and vid not in known:
                    known[vid] = sum(1 << int(q) for q in held)
        state = Greedy(parts, slack, shares, known)
        pdf = pdf.sort_values(["ord", "src", "dst"])
        return pdf.assign(part=state.place_all(pdf["src"].tolist(), pdf["dst"].tolist()))[["src", "dst", "part"]]

    return run


def greedy_parallel(edges: DataFrame, parts: int, rounds: int = 4, tasks: int = 8, slack: float | None = None, chunk_edges: int = 500_000) -> DataFrame:
    """The rule on rounds x tasks chunks of hash order; vertex states are united and loads summed after a round.

    A state is the set of partitions that hold a vertex, for any number of partitions. Tasks grow in number with
    the edges, so that a chunk holds about ``chunk_edges`` at most.
    """
    edges = checkpointed(edges)
    tasks = max(tasks, -(-edges.count() // (rounds * chunk_edges)))
    edges = edges.withColumn("chunk", F.pmod(F.xxhash64("src", "dst"), F.lit(rounds * tasks)).cast("int"))
    held = edges.sparkSession.createDataFrame([], "vid long, parts array<int>")
    loads, placed = [0.0] * parts, None
    for r in range(rounds):
        mine = edges.where(F.col("chunk").between(r * tasks, r * tasks + tasks - 1))
        for end in ("src", "dst"):
            mine = mine.join(held.select(F.col("vid").alias(end), F.col("parts").alias(f"{end}_parts")), end, "left")
        shares = [x / tasks for x in loads]

        done = checkpointed(mine.groupBy("chunk").applyInPandas(_chunk_pass(parts, slack, shares), "src long, dst long, part int"))
        placed = done if placed is None else placed.union(done)
        counts = dict(done.groupBy("part").count().collect())
        loads = [x + counts.get(q, 0) for q, x in enumerate(loads)]
        held = checkpointed(merged_state(held, done))
    return placed


def place_batch(edges: DataFrame, held: DataFrame, loads: list[float], parts: int, slack: float | None = None) -> DataFrame:
    """(src, dst, part): one batch of arriving edges placed in order on the state (vid, parts) and loads so far.

    The batch goes to one task, after the state of its own ends alone; edges pass through it as a stream.
    """

    def run(batches):
        known, state = {}, None
        for batch in batches:
            first = batch.column(1).null_count  # the state comes before the edges
            if first:
                vid, held = (batch.column(i).slice(0, first).to_pylist() for i in (0, 2))
                known.update((v, sum(1 << q for q in some)) for v, some in zip(vid, held))
            if first < len(batch):
                state = state or Greedy(parts, slack, loads, known)
                src, dst = batch.column(0).slice(first), batch.column(1).slice(first)
                yield pa.RecordBatch.from_arrays([src, dst, pa.array(state.place_all(_ids(src), _ids(dst)), pa.int32())], names=["src", "dst", "part"])

    ends = edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()
    least = -(1 << 63)  # sorts the state before all edges; as the leading key is a long, most comparisons need no other
    mine = held.join(ends, "vid", "left_semi").select(F.col("vid").alias("src"), F.lit(None).cast("long").alias("dst"), F.lit(least).cast("long").alias("ord"), "parts")
    rows = mine.union(edges.select("src", "dst", F.coalesce(F.col("ord").cast("long"), F.lit(least + 1)), F.lit(None).cast("array<int>")))
    rows = _in_order(rows, "ord", "src", "dst")
    return rows.select("src", "dst", "parts").mapInArrow(run, "src long, dst long, part int")


def merged_state(held: DataFrame, placed: DataFrame) -> DataFrame:
    """The state (vid, parts) with the placed edges' partitions united in."""
    ends = placed.select(F.explode(F.array("src", "dst")).alias("vid"), "part")
    return ends.union(held.select("vid", F.explode("parts").alias("part"))).groupBy("vid").agg(F.collect_set("part").alias("parts"))


def random_edge(edges: DataFrame, parts: int) -> DataFrame:
    return edges.select("src", "dst", part_of(F.col("src"), F.col("dst"), parts).alias("part"))


def source_hash(edges: DataFrame, parts: int) -> DataFrame:
    return edges.select("src", "dst", (F.col("src") * 7919 % parts).cast("int").alias("part"))


def grid2d(edges: DataFrame, side: int) -> DataFrame:
    """A vertex meets at most 2 side - 1 of the side x side partitions."""
    row, column = F.col("src") * 7919 % side, F.col("dst") * 104729 % side
    return edges.select("src", "dst", (row * side + column).cast("int").alias("part"))


def degree_hash(edges: DataFrame, parts: int) -> DataFrame:
    """By the hash of the end of lower degree (the smaller id of equals): hubs are cut, others stay whole."""
    degrees = edges.select(F.explode(F.array("src", "dst")).alias("vid")).groupBy("vid").agg(F.count("*").alias("d"))
    rows = edges.select("src", "dst")
    for end in ("src", "dst"):
        rows = rows.join(degrees.select(F.col("vid").alias(end), F.col("d").alias(f"{end}_d")), end)
    lower = F.when(F.col("src_d") < F.col("dst_d"), F.col("src")).when(F.col("src_d") > F.col("dst_d"), F.col("dst")).otherwise(F.least("src", "dst"))
    return rows.select("src", "dst", (lower * 7919 % parts).cast("int").alias("part"))


def edge_cut(edges: DataFrame, parts: int) -> DataFrame:
    """Vertices hashed to partitions: (src, dst, src_part, dst_part, cut)."""
    a, b = F.col("src") * 7919 % parts, F.col("dst") * 7919 % parts
    return edges.select("src", "dst", a.cast("int").alias("src_part"), b.cast("int").alias("dst_part"), (a != b).alias("cut"))


def expected_replication(edges: DataFrame, parts: int) -> DataFrame:
    """Expected copies of a vertex under a random vertex-cut: parts/n times the sum of 1 - (1 - 1/parts)^degree."""
    degrees = edges.select(F.explode(F.array("src", "dst")).alias("vid")).groupBy("vid").agg(F.count("*").alias("d"))
    return degrees.agg((parts * F.sum(1 - F.pow(F.lit(1 - 1 / parts), F.col("d"))) / F.count("*")).alias("expected"))
