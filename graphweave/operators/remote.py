"""Synchronisation of partial aggregates between partitions: not at all, in full, or delayed by some epochs.

A split vertex has a root and leaves. Leaves send their partials up, the root reduces and sends the total down.
Delayed by r epochs, a root at epoch e adds what its leaves sent at e - r, and a leaf takes, from epoch 2r on,
the total that its root sent at e - r; split vertices are dealt to bins, and a bin takes part in one epoch of
each round. Vertices that are not split always keep their own partial.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark import InheritableThread
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphweave.operators.aggregate import reduce_wide
from graphweave.session import prepare
from graphweave.storage import checkpointed, checkpointed_as_dealt

_PAIR = {"sum": lambda a, b: a + b, "max": F.greatest, "min": F.least}


def dealt(df: DataFrame, parts: int) -> DataFrame:
    """df dealt once by its column part, and stored so; joins and sums by (part, vid) of frames dealt alike move no rows."""
    return checkpointed_as_dealt(df.repartition(parts, "part"))


def _csr(reduce: str, a: str, b: str, block: int):
    """The kernel of one partition: edges sorted by destination, sources' vectors gathered in blocks, runs reduced."""
    ufunc = {"sum": np.add, "max": np.maximum, "min": np.minimum}[reduce]

    def run(edges: pa.Table, vectors: pa.Table) -> pa.Table:
        ids = vectors["vid"].to_numpy()
        order = np.argsort(ids)
        lists = vectors["feat"].combine_chunks()
        feat = lists.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(ids), -1) if len(ids) else np.zeros((0, 0))
        src, dst = edges[a].to_numpy(), edges[b].to_numpy()
        at = np.minimum(np.searchsorted(ids[order], src), max(0, len(ids) - 1))
        known = ids[order][at] == src if len(ids) else np.zeros(len(src), bool)
        at, dst = order[at[known]] if len(ids) else at[:0], dst[known]
        by_dst = np.argsort(dst, kind="stable")
        at, dst = at[by_dst], dst[by_dst]
        named, first = np.unique(dst, return_index=True)
        out = np.empty((len(named), feat.shape[1]))
        ends = np.append(first[1:], len(dst))
        row = 0
        while row < len(named):  # destinations in runs of about ``block`` edges, so that gathered vectors stay in cache
            stop = max(row + 1, int(np.searchsorted(ends, first[row] + block, side="right")))
            piece = at[first[row] : ends[stop - 1]]
            out[row:stop] = ufunc.reduceat(feat[piece], first[row:stop] - first[row], axis=0)
            row = stop
        part = edges["part"][0].as_py() if len(edges) else 0
        vec = pa.ListArray.from_arrays(pa.array(np.arange(len(named) + 1, dtype=np.int32) * out.shape[1]), pa.array(out.reshape(-1)))
        return pa.table({"part": pa.array(np.full(len(named), part, np.int32)), "vid": pa.array(named), "vec": vec})

    return run


def local_aggregate(cut: DataFrame, features: DataFrame, width: int, reduce: str = "sum", direction: str = "forward", kernel: str = "columns", block: int = 65_536) -> DataFrame:
    """(vid, part, vec) for every clone with an in-edge in its partition.

    features is (vid, part, feat), one row a clone. With edges and clones both ``dealt`` by part, neither the join
    nor the aggregation moves rows: the session's settings for that are applied here. Backward sums along reversed
    edges. Kernel "columns" keeps one aggregate column a dimension; "csr" holds one partition's edges and vectors
    as arrays in a task, for wide vectors.
    """
    prepare(cut.sparkSession)
    a, b = ("src", "dst") if direction == "forward" else ("dst", "src")
    if kernel == "csr":
        clones = features.select(F.col("part").alias("clone_part"), "vid", "feat").groupBy("clone_part")
        groups = cut.select("part", "src", "dst").groupBy("part").cogroup(clones)
        return groups.applyInArrow(_csr(reduce, a, b, block), "part int, vid long, vec array<double>").select("part", "vid", "vec")
    rows = cut.join(features.select(F.col("vid").alias(a), "part", "feat"), ["part", a])
    return reduce_wide(rows.select("part", F.col(b).alias("vid"), F.col("feat").alias("m")), ["part", "vid"], reduce, width, out="vec")


def complete(partials: DataFrame, roles: DataFrame, width: int, empty: float = 0.0) -> DataFrame:
    """One partial for every clone, the empty vector where it has no in-edge, with the clone's role."""
    zero = F.array_repeat(F.lit(empty), width)
    rows = roles.join(partials, ["part", "vid"], "left")
    return rows.select("vid", "part", "root_part", "is_root", "is_split", "bin", F.coalesce("vec", zero).alias("vec"))


def gather_leaves(full: DataFrame) -> DataFrame:
    """What leaves send: (vid, from_part, to_part, vec)."""
    leaves = full.where("is_split and not is_root")
    return leaves.select("vid", F.col("part").alias("from_part"), F.col("root_part").alias("to_part"), "vec")


def reduce_roots(full: DataFrame, sent: DataFrame, width: int, reduce: str = "sum") -> DataFrame:
    """Root clones with their own partial and the leaves' reduced: (vid, part, vec)."""
    roots = full.where("is_split and is_root").select("vid", "part", "vec")
    rows = roots.union(sent.join(roots.select("vid"), "vid", "left_semi").select("vid", F.col("to_part").alias("part"), "vec"))
    return reduce_wide(rows, ["vid", "part"], reduce, width, vector="vec", out="vec")


def gather_roots(full: DataFrame, totals: DataFrame) -> DataFrame:
    """What roots send: their totals to every leaf."""
    leaves = full.where("is_split and not is_root").select("vid", F.col("part").alias("to_part"))
    return totals.join(leaves, "vid").select("vid", F.col("part").alias("from_part"), "to_part", "vec")


def scatter_leaves(full: DataFrame, sent: DataFrame) -> DataFrame:
    """Leaf clones overwritten by what their root sent."""
    return sent.select("vid", F.col("to_part").alias("part"), "vec")


def sync_full(full: DataFrame, width: int, reduce: str = "sum") -> DataFrame:
    """(vid, part, vec): every clone of a vertex gets the reduction over all its clones; only split vertices move."""
    split = full.where("is_split")
    totals = reduce_wide(split, ["vid"], reduce, width, vector="vec", out="total")
    back = split.select("vid", "part").join(totals, "vid")
    rows = full.join(back, ["part", "vid"], "left")
    return rows.select("vid", "part", F.coalesce("total", "vec").alias("vec"))


def local_only(full: DataFrame) -> DataFrame:
    return full.select("vid", "part", "vec")


class AsyncExchange:
    """Materialises a slice in a second driver thread, so that its job may overlap the next epoch's."""

    def __init__(self, df: DataFrame):
        self._done: list = []
        self._thread = InheritableThread(target=self._run, args=(df,))
        self._thread.start()

    def _run(self, df: DataFrame) -> None:
        try:
            self._done.append(checkpointed(df))
        except Exception as error:
            self._done.append(error)

    def result(self) -> DataFrame:
        began = time.monotonic()
        self._thread.join()
        self.waited = time.monotonic() - began
        if isinstance(self._done[0], Exception):
            raise self._done[0]
        return self._done[0]


class Ledger:
    """Messages in flight, by epoch and phase; slices are checkpointed, unless planned only, and dropped once nothing reads them."""

    def __init__(self, delay: int, overlap: bool = False, planned: bool = False):
        self.delay, self.overlap, self.planned, self.waited = delay, overlap, planned, 0.0
        self._slices: dict[tuple[int, str], object] = {}

    def put(self, epoch: int, phase: str, df: DataFrame) -> None:
        self._slices[epoch, phase] = AsyncExchange(df) if self.overlap else df if self.planned else checkpointed(df)

    def get(self, epoch: int, phase: str) -> DataFrame | None:
        found = self._slices.get((epoch, phase))
        if not isinstance(found, AsyncExchange):
            return found
        result = found.result()
        self.waited += found.waited
        return result

    def forget(self, before: int) -> None:
        self._slices = {key: df for key, df in self._slices.items() if key[0] >= before}


class DelayedSync:
    """Delayed synchronisation over epochs: call step(epoch, full) in order from epoch 0.

    With ``given``, what step gets is stored and does not depend on earlier results. Then an epoch's result reads the
    partials of epochs e, e - r and e - 2r alone, so its lineage is short and messages and results stay plans, which
    Spark runs together; else, and where a second thread writes or idle bins keep parts, they are checkpointed.
    """

    def __init__(self, width: int, delay: int, bins: int | None = None, idle: str = "local", reduce: str = "sum", overlap: bool = False, given: bool = False):
        self.width, self.delay, self.bins, self.idle, self.reduce = width, delay, bins or max(delay, 1), idle, reduce
        if delay and delay % self.bins:
            raise ValueError("the delay must be a multiple of the bins, so that a bin meets what it sent")
        if idle == "cached" and reduce != "sum":
            raise ValueError("remote parts can be kept for sums only")
        self.planned = given and not overlap and idle != "cached"
        self.ledger = Ledger(delay, overlap, self.planned)
        self.remote: dict[int, DataFrame] = {}
        self.history: dict[int, DataFrame] = {}

    def step(self, epoch: int, full: DataFrame) -> DataFrame:
        if self.delay == 0:
            return sync_full(full, self.width, self.reduce)
        active = epoch % self.bins
        now = full.where(F.col("bin") == active)
        up = self.ledger.get(epoch - self.delay, "up")
        down = self.ledger.get(epoch - self.delay, "down") if epoch >= 2 * self.delay else None
        roots = now.where("is_split and is_root").select("vid", "part", "vec")
        totals = reduce_roots(now, up, self.width, self.reduce) if up is not None else roots
        cut = (lambda df: df) if self.planned else checkpointed
        totals = cut(totals)
        self.ledger.put(epoch, "up", gather_leaves(now))
        self.ledger.put(epoch, "down", gather_roots(now, totals))
        changed = totals if down is None else totals.union(scatter_leaves(now, down))
        rows = full.join(changed.withColumnRenamed("vec", "synced"), ["part", "vid"], "left")
        result = cut(rows.select("vid", "part", F.coalesce("synced", "vec").alias("vec")))
        if self.idle == "cached":
            result = self._with_kept(epoch, active, full, result)
        self.ledger.forget(epoch - self.delay + 1)
        return result

    def _with_kept(self, epoch: int, active: int, full: DataFrame, result: DataFrame) -> DataFrame:
        """Idle bins add the remote part of their last active epoch; a leaf's excludes the part it sent itself."""
        own = full.where((F.col("bin") == active) & F.col("is_split"))
        pair = lambda f: F.zip_with("vec", "other", f)
        at_root = result.join(own.where("is_root").select("vid", "part", F.col("vec").alias("other")), ["vid", "part"])
        parts = at_root.select("vid", "part", pair(lambda a, b: a - b).alias("kept"))
        if epoch >= 2 * self.delay:
            old = self.history.get(epoch - 2 * self.delay)
            leaves = own.where("not is_root").select("vid", "part")
            at_leaf = result.join(leaves, ["vid", "part"]).join(old.select("vid", "part", F.col("vec").alias("other")), ["vid", "part"])
            parts = parts.union(at_leaf.select("vid", "part", pair(lambda a, b: a - b).alias("kept")))
        self.remote[active] = checkpointed(parts)
        self.history[epoch] = checkpointed(own.select("vid", "part", "vec"))
        self.history = {e: df for e, df in self.history.items() if e > epoch - 2 * self.delay}
        for bin_, kept in self.remote.items():
            if bin_ != active:
                rows = result.join(kept, ["vid", "part"], "left")
                result = rows.select("vid", "part", F.when(F.col("kept").isNotNull(), F.zip_with("vec", "kept", lambda a, b: a + b)).otherwise(F.col("vec")).alias("vec"))
        return result



def sync(full: DataFrame, width: int, mode: str, reduce: str = "sum") -> DataFrame:
    return local_only(full) if mode == "local_only" else sync_full(full, width, reduce)


def exchange_matrix(full: DataFrame, width: int, bytes_per_value: int = 4) -> DataFrame:
    """(from_part, to_part, vectors, bytes) of one full exchange, both phases."""
    leaves = full.where("is_split and not is_root")
    up = leaves.select(F.col("part").alias("from_part"), F.col("root_part").alias("to_part"))
    down = leaves.select(F.col("root_part").alias("from_part"), F.col("part").alias("to_part"))
    rows = up.union(down).groupBy("from_part", "to_part").agg(F.count("*").alias("vectors"))
    return rows.withColumn("bytes", F.col("vectors") * width * bytes_per_value)


def quantize(vec: Column, bits: int = 16) -> Column:
    """Components rounded to a significand of bits - 8 binary digits, as a message of that width would carry."""
    digits = bits - 8

    def cut(x: Column) -> Column:
        exponent = F.floor(F.log2(F.abs(x)))
        unit = F.pow(F.lit(2.0), exponent - digits + 1)
        return F.when(x == 0, 0.0).otherwise(F.round(x / unit) * unit)

    return F.transform(vec, cut)


def combine_pairwise(a: Column, b: Column, reduce: str = "sum") -> Column:
    return F.zip_with(a, b, _PAIR[reduce])


