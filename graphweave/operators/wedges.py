"""Triangles without a table of wedges: adjacency lists in blocks, and every pair of blocks compared in one task.

Pairs are directed by a total order in which vertices of high degree come last, so that lists are short. A wedge
u -> v -> w is opened and closed inside the task that has the lists of u and of v; what leaves it is a count a vertex.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweave.storage import checkpointed, released

#: A block holds about so many edges, four bytes each and eight for each name.
BLOCK_EDGES = 2_000_000
#: So many vertices of highest degree, at most, are ordered by degree; the others come before them, by id.
MOST_HUBS = 131_072
#: Ends of wedges that are looked at together.
PIECE = 1 << 18

_LISTS = ("us", "counts", "names", "codes")


def _lists(batches):
    """One block: vertices, lengths of their lists, the names of all ends, and the lists, sorted, as places in the names."""
    some = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches if len(b)]
    if not some:
        return
    u, v = (np.concatenate(x) for x in zip(*some))
    del some
    us, u = np.unique(u, return_inverse=True)
    names, v = np.unique(v, return_inverse=True)
    keys = np.unique(u * len(names) + v)
    del u, v
    counts, codes = np.bincount(keys // len(names), minlength=len(us)), (keys % len(names)).astype(np.int32)
    columns = [us.astype(np.int64), counts.astype(np.int32), names.astype(np.int64), codes]
    yield pa.RecordBatch.from_arrays([pa.array([us[0]], pa.int64()), *(pa.array([c.tobytes()], pa.binary()) for c in columns)], names=["block", *_LISTS])


def _read(batch: pa.RecordBatch, row: int, first: int) -> list[np.ndarray]:
    return [np.frombuffer(batch.column(first + i)[row].as_buffer(), kind) for i, kind in enumerate((np.int64, np.int32, np.int64, np.int32))]


def blocks(edges: DataFrame) -> DataFrame:
    """(block, us, counts, names, codes): each pair of different vertices once, from its lower end, in lists; a block in a partition of its own."""
    spark = edges.sparkSession
    pairs = edges.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).where("a <> b")
    m = pairs.count()
    n = max(spark.sparkContext.defaultParallelism, -(-m // BLOCK_EDGES))
    # At most 2 m / least vertices have a degree of least or more, whatever the graph; a pair that comes twice counts twice here, which only changes the order.
    degree = pairs.select(F.explode(F.array("a", "b")).alias("vid")).groupBy("vid").agg(F.count("*").alias("d"))
    hubs = checkpointed(degree.where(F.col("d") >= max(1, -(-2 * m // MOST_HUBS))))
    for end in ("a", "b"):
        pairs = pairs.join(F.broadcast(hubs.select(F.col("vid").alias(end), F.col("d").alias(f"d{end}"))), end, "left")
    forward = F.struct(F.coalesce("da", F.lit(0)), "a") < F.struct(F.coalesce("db", F.lit(0)), "b")
    directed = pairs.select(F.when(forward, F.col("a")).otherwise(F.col("b")).cast("long").alias("u"), F.when(forward, F.col("b")).otherwise(F.col("a")).cast("long").alias("v"))
    packed = checkpointed(directed.repartition(n, "u").mapInArrow(_lists, "block long, us binary, counts binary, names binary, codes binary"))
    released(spark)
    return packed


def degrees(packed: DataFrame) -> DataFrame:
    """(vid, degree) of every vertex, from blocks."""

    def run(batches):
        for batch in batches:
            for row in range(len(batch)):
                us, counts, names, codes = _read(batch, row, 0)
                yield _counted(us, counts)
                yield _counted(names, np.bincount(codes, minlength=len(names)))

    return packed.select(*_LISTS).mapInArrow(run, "vid long, n long").groupBy("vid").agg(F.sum("n").alias("degree"))


def _counted(ids: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
    some = np.flatnonzero(n)
    return pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(n[some].astype(np.int64))], names=["vid", "n"])


class _Block:
    """One block's lists with the triangles found at its vertices and their ends."""

    def __init__(self, us: np.ndarray, counts: np.ndarray, names: np.ndarray, codes: np.ndarray):
        self.us, self.names, self.codes, self.n = us, names, codes, len(names)
        self.row = np.repeat(np.arange(len(us), dtype=np.int32), counts)
        self.start = np.append(0, np.cumsum(counts, dtype=np.int64))
        self.at_us, self.at_names = np.zeros(len(us), np.int64), np.zeros(len(names), np.int64)

    def _places(self, ids: np.ndarray) -> np.ndarray:
        """Places of sorted ids in the names, n where there is none."""
        at = np.searchsorted(self.names, ids)
        return np.where(self.names[np.minimum(at, self.n - 1)] == ids, at, self.n).astype(np.int32)

    def meet(self, us: np.ndarray, counts: np.ndarray, names: np.ndarray, codes: np.ndarray) -> None:
        """Count the triangles u, v, w with u here and the list of v in the other block."""
        middle = self._places(us)
        lists = np.full(self.n + 1, -1, np.int32)  # of each name as a vertex of the other block
        lists[middle] = np.arange(len(us))
        lists[self.n] = -1
        edges = np.flatnonzero(lists[self.codes] >= 0)
        ends = self._places(names)[codes]
        known = ends < self.n
        ends, of = ends[known], np.repeat(np.arange(len(us), dtype=np.int32), counts)[known]
        sizes = np.bincount(of, minlength=len(us))
        firsts = np.cumsum(sizes) - sizes
        mine = lists[self.codes[edges]]
        total = np.cumsum(sizes[mine])
        lo, done = 0, 0
        while lo < len(edges):
            hi = max(lo + 1, int(np.searchsorted(total, done + PIECE, side="right")))
            self._close(edges[lo:hi], firsts[mine[lo:hi]], sizes[mine[lo:hi]], ends)
            lo, done = hi, int(total[hi - 1])

    def _close(self, edges: np.ndarray, firsts: np.ndarray, sizes: np.ndarray, ends: np.ndarray) -> None:
        """Wedges of some edges in order: most are ruled out by a table of hashes, the others are looked up."""
        stop = np.cumsum(sizes)
        if not len(stop) or not stop[-1]:
            return
        row = self.row[edges]
        a, b = self.start[row[0]], self.start[row[-1] + 1]
        keys = self.row[a:b].astype(np.int64) * self.n + self.codes[a:b]  # sorted, each once
        bits = max(16, int(8 * len(keys)).bit_length())
        table = np.zeros(1 << bits, bool)
        place = lambda k: (k.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - bits)).view(np.int64)
        table[place(keys)] = True
        w = ends[np.repeat(firsts - (stop - sizes), sizes) + np.arange(stop[-1])]
        wedges = np.repeat(row.astype(np.int64) * self.n, sizes) + w
        maybe = np.flatnonzero(table[place(wedges)])
        wanted = wedges[maybe]
        at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
        closed = maybe[keys[at] == wanted]
        edge = edges[np.searchsorted(stop, closed, side="right")]
        np.add.at(self.at_us, self.row[edge], 1)
        np.add.at(self.at_names, self.codes[edge], 1)
        np.add.at(self.at_names, w[closed], 1)

    def found(self):
        yield _counted(self.us, self.at_us)
        yield _counted(self.names, self.at_names)


def counts(packed: DataFrame) -> DataFrame:
    """(vid, triangles) of the vertices in triangles, from blocks.

    All pairs of blocks are read from where they are stored. Pairs of one first block come in a row, so its counts
    are sent on once; in any other order they are right too.
    """

    def run(batches):
        now, block = None, None
        for batch in batches:
            for row in range(len(batch)):
                if (name := batch.column(0)[row].as_py()) != now:
                    if block:
                        yield from block.found()
                    now, block = name, _Block(*(x.copy() for x in _read(batch, row, 1)))
                block.meet(*_read(batch, row, 5))
        if block:
            yield from block.found()

    others = packed.select(*(F.col(c).alias(f"other_{c}") for c in _LISTS))
    tiles = packed.hint("shuffle_replicate_nl").crossJoin(others).coalesce(max(1, packed.rdd.getNumPartitions()))
    conf, most = packed.sparkSession.conf, "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = conf.get(most)
    conf.set(most, "1")  # a pair of blocks is large enough
    try:
        found = checkpointed(tiles.mapInArrow(run, "vid long, n long"))
    finally:
        conf.set(most, before)
    return found.groupBy("vid").agg(F.sum("n").alias("triangles"))
