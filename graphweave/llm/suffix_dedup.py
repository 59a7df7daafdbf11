"""Removal of repeated passages by a suffix array over synchronised positions.

Every window of ``span`` bytes names one anchor in it: the place of the least hash among its ``lead``-byte
strings, the leftmost of equals. Equal windows name anchors at the same offset, so the suffix array is sparse
(suffixes are taken relative to anchors, about one in 170 bytes) and still loses no pair of equal windows.

A row of the array stands for the windows of one anchor whose offsets fall into one block of ``size`` offsets.
Its suffix begins where the block's windows all are (their common part, the core) and goes on to all that they
cover (the hull). Rows are ordered by the suffix's leading tokens: its first sixteen bytes, the rest of the core,
then the hull, the last two as fingerprints. Sampled splitters range-partition the rows by these tokens; a group
of equal suffixes, however large, is cut at splitters of its own by text and place. Buckets sort by multikey
quicksort and compare neighbours; the first and last rows of buckets are compared across the boundaries.

* A neighbour with the same core and hull: all windows of the row are repeated.
* A neighbour with the same core and another hull: some may be; the row goes on, cut into smaller blocks. Of a
  run of equal hulls only the first and the last row go on, as witnesses for the others of the core.
* No neighbour with the same core: none of its windows is repeated.

At blocks of one offset core and hull are the window itself and nothing is left open, so the result is exact up
to collisions of two independent 64-bit fingerprints and sixteen plain bytes.

The same works on words in place of bytes (``words``): passages of that many words that occur elsewhere are found
whatever their length in bytes.

Defined results: null and empty texts have nothing to remove; repeated rows are copies of each other and lose
all windows; windows never cross texts; texts of any length are compared whole; an empty table gives no rows; of
the input's columns only the id and the text take part.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.window import Window as W
from xxhash import xxh64_intdigest

from graphweave.llm.common import map_texts, materialize, maybe_in, released, settled, slots

_LETTERS = np.random.Generator(np.random.PCG64(7)).integers(1, 2**63, (2, 256), dtype=np.uint64) | np.uint64(1)
_BASES = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)
_HEAD = 16  # bytes; two words
#: Rows that a bucket of the suffix array holds on average.
ROWS_PER_BUCKET = 200_000
_powers: dict[int, np.ndarray] = {}


def _power(base: int, n: int) -> np.ndarray:
    """base to the powers 0 to n, modulo 2^64."""
    known = _powers.get(base)
    if known is None or len(known) <= n:
        table = np.full(max(n + 1, 1 << 16), base, np.uint64)
        table[0] = 1
        known = _powers[base] = np.multiply.accumulate(table)
    return known


def tokens_of(raws: list[bytes], words: bool) -> list[np.ndarray]:
    """The bytes of every text, or a number for each of its words."""
    if not words:
        return [np.frombuffer(r, np.uint8) for r in raws]
    numbers: dict[bytes, int] = {}
    split = [r.split() for r in raws]
    for w in {w for ws in split for w in ws}:
        numbers[w] = xxh64_intdigest(w)
    return [np.array([numbers[w] for w in ws], np.uint64) for ws in split]


def _finish(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


class Fingerprints:
    """Fingerprints of any runs of tokens, by prefix sums of a polynomial; two kinds are independent."""

    def __init__(self, data: np.ndarray, kind: int = 0):
        base = _BASES[kind]
        self.up = np.zeros(len(data) + 1, np.uint64)
        letters = _LETTERS[kind][data] if data.dtype == np.uint8 else _finish(data + _LETTERS[kind][0])
        np.cumsum(letters * _power(base, len(data))[: len(data)], out=self.up[1:])
        self.down = _power(pow(base, -1, 1 << 64), len(data))

    def of(self, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        return _finish((self.up[end] - self.up[begin]) * self.down[begin] + (end - begin).astype(np.uint64))

    def fixed(self, length: int) -> np.ndarray:
        n = len(self.up) - length
        return _finish((self.up[length:] - self.up[:n]) * self.down[:n]) if n > 0 else np.zeros(0, np.uint64)


def anchors(data: np.ndarray, ends: np.ndarray, prints: Fingerprints, span: int, lead: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of texts that lie end to end in data: places of anchors, and the first and last window start that names each."""
    none = np.zeros(0, np.int64)
    if len(data) < span:
        return none, none, none
    reach = span - lead + 1
    leads = prints.fixed(lead)
    keys = (leads & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(leads), dtype=np.uint64)
    width = -(-len(keys) // reach)
    grid = np.full(width * reach, np.iinfo(np.uint64).max, np.uint64)
    grid[: len(keys)] = keys
    grid = grid.reshape(width, reach)
    ahead = np.minimum.accumulate(grid, axis=1).reshape(-1)
    behind = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].reshape(-1)
    n = len(data) - span + 1
    named = (np.minimum(behind[:n], ahead[reach - 1 : reach - 1 + n]) & np.uint64(0xFFFFFFFF)).astype(np.int64)
    inside = np.ones(n, bool)  # windows that do not cross the end of a text
    for end in ends.tolist():
        inside[max(0, end - span + 1) : end] = False
    starts = np.flatnonzero(inside)
    if not len(starts):
        return none, none, none
    named = named[starts]
    first = np.flatnonzero(np.concatenate([[True], (named[1:] != named[:-1]) | (starts[1:] != starts[:-1] + 1)]))
    last = np.concatenate([first[1:] - 1, [len(starts) - 1]])
    return named[first], starts[first], starts[last]


def suffix_rows(data: np.ndarray, prints: Fingerprints, at: np.ndarray, low: np.ndarray, high: np.ndarray, size: int, span: int, lead: int):
    """Rows of blocks of ``size`` offsets, for anchors at places ``at`` with windows at offsets low to high before them.

    Returns the number of the anchor, the row's offsets, and the tokens of its suffix.
    """
    first = low // size
    count = high // size - first + 1
    who = np.repeat(np.arange(len(at)), count)
    block = (first[who] + np.arange(len(who)) - np.repeat(np.cumsum(count) - count, count)) * size
    place, lo, hi = at[who], np.maximum(low[who], block), np.minimum(high[who], block + size - 1)
    begin = place - block
    core = _finish(prints.of(begin, begin - (size - 1) + span) + _finish(prints.of(place, place + lead) + block.astype(np.uint64)))
    hull = _finish(Fingerprints(data, 1).of(place - hi, place - lo + span) + (lo * span + hi).astype(np.uint64))
    head = np.ascontiguousarray(data[begin[:, None] + np.arange(_HEAD // data.itemsize)])
    head = (head.view(">u8").astype(np.uint64) if data.itemsize == 1 else head) ^ np.uint64(1 << 63)
    return who, lo, hi, *(x.view(np.int64) for x in (np.ascontiguousarray(head[:, 0]), np.ascontiguousarray(head[:, 1]), core, hull))


def multikey_order(columns: list[np.ndarray]) -> np.ndarray:
    """The order of rows by their columns: each round sorts only runs that are tied so far."""
    order = np.argsort(columns[0], kind="stable")
    tied = columns[0][order][1:] == columns[0][order][:-1]
    for column in columns[1:]:
        if not tied.any():
            break
        open_at = np.flatnonzero(np.concatenate([[False], tied]) | np.concatenate([tied, [False]]))
        run = np.cumsum(np.concatenate([[True], ~tied]))[open_at]
        order[open_at] = order[open_at][np.lexsort((column[order[open_at]], run))]
        tied &= column[order][1:] == column[order][:-1]
    return order


_KEYS = ("h1", "h2", "core", "hull")
_ROW = ("t1", "t2", "at", "lo", "hi")


def _sorted_bucket(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One bucket in suffix order, its neighbours compared: rows that a neighbour resembles, and both ends."""
    table = pa.Table.from_batches(held) if (held := list(batches)) else None
    if table is None or not len(table):
        return
    keys = [table[k].to_numpy() for k in _KEYS]
    order = multikey_order(keys)
    keys = [k[order] for k in keys]
    core = np.logical_and.reduce([k[1:] == k[:-1] for k in keys[:3]])
    hull = core & (keys[3][1:] == keys[3][:-1])
    shared, mixed = np.zeros(len(order), bool), np.zeros(len(order), bool)
    for flag, pair in ((shared, hull), (mixed, core & ~hull)):
        flag[1:] |= pair
        flag[:-1] |= pair
    edge = np.zeros(len(order), np.int32)
    edge[-1] = 2
    edge[0] = 1
    out = np.flatnonzero(shared | mixed | (edge > 0))
    rows = table.select(list(_ROW)).take(pa.array(order[out]))
    made = {"shared": pa.array(shared[out]), "mixed": pa.array(mixed[out]), "edge": pa.array(edge[out])}
    made["bucket"] = pa.array(np.full(len(out), TaskContext.get().partitionId(), np.int32))
    for name, column in [*made.items(), *((k, pa.array(x[out])) for k, x in zip(_KEYS, keys))]:
        rows = rows.append_column(name, column)
    yield from rows.combine_chunks().to_batches(max_chunksize=50_000)


def compared(rows: DataFrame) -> DataFrame:
    """(t1, t2, at, lo, hi, shared, mixed): rows of the suffix array that a neighbour resembles."""
    buckets = max(slots(rows.sparkSession), -(-rows.count() // ROWS_PER_BUCKET))
    dealt = rows.repartitionByRange(buckets, *_KEYS, "t1", "at")
    schema = "t1 long, t2 long, at int, lo int, hi int, shared boolean, mixed boolean, edge int, bucket int, h1 long, h2 long, core long, hull long"
    judged = materialize(dealt.mapInArrow(_sorted_bucket, schema))
    # Across boundaries: two rows a bucket.
    order, key = W.orderBy("bucket", "edge"), F.struct(*_KEYS)
    ends = judged.where("edge > 0").select("*", F.lag(key).over(order).alias("before"), F.lead(key).over(order).alias("after"))

    def same(other: str, keys: tuple[str, ...]) -> Column:
        equal = F.lit(True)
        for k in keys:
            equal = equal & (F.col(f"{other}.{k}") == F.col(k))
        return F.coalesce(equal, F.lit(False))

    core = {o: same(o, _KEYS[:3]) for o in ("before", "after")}
    hull = {o: same(o, _KEYS) for o in core}
    shared = F.col("shared") | hull["before"] | hull["after"]
    mixed = F.col("mixed") | (core["before"] & ~hull["before"]) | (core["after"] & ~hull["after"])
    ends = ends.select(*_ROW, shared.alias("shared"), mixed.alias("mixed"))
    return materialize(judged.where("edge = 0").select(*_ROW, "shared", "mixed").union(ends).where("shared or mixed"))


def _block_sizes(span: int, head: int) -> list[int]:
    """Offsets in a block, from the widest whose windows have a head in common down to one."""
    sizes = [1 << (span - head).bit_length() - 1]
    while sizes[-1] > 1:
        sizes.append(max(1, sizes[-1] // 16))
    return sizes


@dataclass(frozen=True)
class Windows:
    """What counts as a repeat: runs of ``span`` bytes or words; ``lead`` of them choose the anchors."""

    span: int = 400
    lead: int = 64
    words: bool = False

    def __post_init__(self) -> None:
        if not 0 < self.lead <= self.span - self.head:
            raise ValueError("the lead must leave room for a head in the span")

    @property
    def head(self) -> int:
        return _HEAD // (8 if self.words else 1)

    @property
    def block_sizes(self) -> list[int]:
        """Offsets in a block, from the widest whose windows have a head in common down to one."""
        sizes = [1 << (self.span - self.head).bit_length() - 1]
        while sizes[-1] > 1:
            sizes.append(max(1, sizes[-1] // 16))
        return sizes


def repeated_spans(docs: DataFrame, kinds: Sequence[Windows] = (Windows(),), text_col: str = "text") -> list[DataFrame]:
    """For each kind (t1, t2, whole, spans): texts (by two hashes) with repeated windows, and the tokens (b, e) these cover.

    whole: the text occurs more than once, so all of it goes. Spans may overlap and come in no order. All kinds
    share the scan of the texts and the one that fetches the windows left open.
    """
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col), F.lit(""))
    least = min(2 * k.span - 1 if k.words else k.span for k in kinds)
    texts = docs.select(text.alias("text"), F.xxhash64(text).alias("t1"), F.xxhash64(F.lit(1), text).alias("t2")).where(F.octet_length("text") >= least)

    def first_rows(batch: list[str]) -> list:
        raws = [t.encode("utf-8", "surrogatepass") for t in batch]
        return [column for kind in kinds for column in _first_rows(tokens_of(raws, kind.words), kind)]

    columns, integers, longs = (*_ROW[2:], *_KEYS), T.ArrayType(T.IntegerType()), T.ArrayType(T.LongType())
    fields = [(f"{n}_{i}", longs if n in _KEYS else integers) for i in range(len(kinds)) for n in columns]
    found = map_texts(texts, lambda: first_rows, fields, ("t1", "t2"), chars_per_call=1_000_000)
    found = found.groupBy("t1", "t2").agg((F.count("*") > 1).alias("copied"), F.any_value(F.struct(*(n for n, _ in fields))).alias("x"))
    # Checkpoints, unlike stored tables, go as soon as nothing reads them.
    distinct = materialize(found.select("t1", "t2", "copied", "x.*"))
    released(spark)
    copied = [settled(distinct.where(F.col("copied") & (F.size(f"at_{i}") > 0)).select("t1", "t2"), "t1", "t2") for i in range(len(kinds))]
    # The widest blocks of every kind, then the texts of what is left open, then ever narrower blocks.
    judged = []
    for i in range(len(kinds)):
        rows = distinct.select("t1", "t2", F.inline(F.arrays_zip(*(f"{n}_{i}" for n in columns)))).toDF("t1", "t2", *columns)
        judged.append(compared(rows))
        released(spark)
    del distinct, rows
    left = [j.where("mixed").select(*_ROW, F.lit(i).alias("kind")) for i, j in enumerate(judged)]
    wanted = reduce(DataFrame.union, left).groupBy("t1", "t2").agg(F.collect_list(F.struct("at", "lo", "hi", "kind")).alias("xs"))
    wanted = settled(wanted, "t1", "t2")
    whole = maybe_in(texts, "t1", wanted.select("t1")).groupBy("t1", "t2").agg(F.any_value("text").alias("text"))
    whole = whole.join(wanted, ["t1", "t2"]).select("t1", "t2", F.encode("text", "UTF-8").alias("raw"), "xs")
    pieces = materialize(_pieces(whole, kinds))
    del whole, wanted
    released(spark)
    out = []
    for i, kind in enumerate(kinds):
        spans = [_covered(judged[i], kind.span)]
        block = lambda: F.floor(F.col("lo") / kind.block_sizes[0]).cast("int").alias("block")  # noqa: B023, E731
        outer = pieces.where(F.col("kind") == i).select("t1", "t2", "at", block(), "piece", "before")
        for size in kind.block_sizes[1:]:
            left = judged[i].where("mixed").select(*_ROW, block()).join(outer, ["t1", "t2", "at", "block"])
            judged[i] = compared(materialize(_narrower(left, size, kind)))
            released(spark)
            spans.append(_covered(judged[i], kind.span))
        spans = reduce(DataFrame.union, spans).join(copied[i], ["t1", "t2"], "left_anti")
        spans = spans.groupBy("t1", "t2").agg(F.lit(False).alias("whole"), F.collect_list(F.struct("b", "e")).alias("spans"))
        out.append(spans.union(copied[i].select("t1", "t2", F.lit(True), F.array().cast("array<struct<b:int,e:int>>"))))
    return out


def _first_rows(raws: list[np.ndarray], kind: Windows) -> list[list[np.ndarray]]:
    """Rows of the widest blocks: one array a text for each column."""
    data = np.concatenate(raws)
    ends = np.cumsum([len(r) for r in raws])
    prints = Fingerprints(data)
    at, first, last = anchors(data, ends, prints, kind.span, kind.lead)
    who, lo, hi, *tokens = suffix_rows(data, prints, at, at - last, at - first, kind.block_sizes[0], kind.span, kind.lead)
    owner = np.searchsorted(ends, at, side="right")[who]
    cut = np.searchsorted(owner, np.arange(len(raws) + 1))
    columns = [at[who] - np.concatenate([[0], ends])[owner], lo, hi, *tokens]
    return [[c[a:b] for a, b in zip(cut, cut[1:])] for c in columns]


def _covered(judged: DataFrame, span: int) -> DataFrame:
    """(t1, t2, b, e): what the windows of repeated rows cover."""
    return judged.where("shared").select("t1", "t2", (F.col("at") - F.col("hi")).alias("b"), (F.col("at") - F.col("lo") + span).alias("e"))


def _pieces(found: DataFrame, kinds: Sequence[Windows]) -> DataFrame:
    """Rows of the array with the tokens of their windows; the anchor is ``before`` tokens into a piece."""
    types = (*(pa.int64(),) * 2, *(pa.int32(),) * 5, pa.binary())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, len(batch), 64):
                t1, t2, raws, lists = (batch.column(i).slice(a, 64).to_pylist() for i in range(4))
                rows = []
                for i, kind in enumerate(kinds):
                    for k, l, data, xs in zip(t1, t2, tokens_of(raws, kind.words), lists):
                        rows += [(k, l, x["at"], x["lo"], x["hi"], i, x["hi"], data[x["at"] - x["hi"] : x["at"] - x["lo"] + kind.span].tobytes()) for x in xs if x["kind"] == i]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names=[*_ROW, "kind", "before", "piece"])

    return found.mapInArrow(run, "t1 long, t2 long, at int, lo int, hi int, kind int, before int, piece binary")


def _narrower(left: DataFrame, size: int, kind: Windows) -> DataFrame:
    """Suffix rows of narrower blocks, from the pieces that hold their windows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, len(batch), 1024):
                part = batch.slice(a, 1024)
                pieces = part.column(6).to_pylist()
                data = np.frombuffer(b"".join(pieces), np.uint64 if kind.words else np.uint8)
                begin = np.cumsum([0, *map(len, pieces)])[:-1] // data.itemsize
                at, low, high, before = (part.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in (2, 3, 4, 5))
                who, lo, hi, *tokens = suffix_rows(data, Fingerprints(data), begin + before, low, high, size, kind.span, kind.lead)
                rows = [part.column(i).take(pa.array(who)) for i in (0, 1, 2)]
                made = [pa.array(x.astype(np.int32)) for x in (lo, hi)]
                yield pa.RecordBatch.from_arrays([*rows, *made, *map(pa.array, tokens)], names=[*_ROW, *_KEYS])

    schema = "t1 long, t2 long, at int, lo int, hi int, h1 long, h2 long, core long, hull long"
    return left.select(*_ROW, "before", "piece").mapInArrow(run, schema)


def merged(spans: list[dict]) -> tuple[list[int], list[int]]:
    """Begins and ends of maximal runs of bytes under the spans."""
    begins: list[int] = []
    ends: list[int] = []
    for b, e in sorted((s["b"], s["e"]) for s in spans):
        if ends and b <= ends[-1]:
            ends[-1] = max(ends[-1], e)
        else:
            begins.append(b)
            ends.append(e)
    return begins, ends


def remove_repeats(docs: DataFrame, span: int = 400, lead: int = 64, id_col: str = "doc_id", text_col: str = "text", passage_words: int = 50) -> DataFrame:
    """(id_col, n_bytes, n_removed, n_spans, kept_sha256, n_passage_words), and begins and ends of the removed runs of bytes.

    n_passage_words counts words in passages of at least ``passage_words`` words that start elsewhere too; they stay
    in the text unless the byte windows cover them.
    """
    kinds = (Windows(span, lead), Windows(passage_words, max(1, passage_words // 6), True))
    found, passages = repeated_spans(docs, kinds, text_col)
    found = found.join(passages.select("t1", "t2", F.col("whole").alias("all_words"), F.col("spans").alias("passages")), ["t1", "t2"], "full")
    found = settled(found, "t1", "t2")
    del passages
    released(docs.sparkSession)
    text = F.coalesce(F.col(text_col), F.lit(""))
    every = docs.select(F.col(id_col).alias("id"), text.alias("text"), F.xxhash64(text).alias("t1"), F.xxhash64(F.lit(1), text).alias("t2"))
    rows = every.join(found, ["t1", "t2"], "left")
    long, ints = T.LongType(), T.ArrayType(T.IntegerType())
    fields = [("n_bytes", long), ("n_removed", long), ("n_spans", long), ("kept_sha256", T.StringType()), ("n_passage_words", long), ("begins", ints), ("ends", ints)]
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), *(T.StructField(n, t) for n, t in fields)])
    arrow = to_arrow_schema(schema)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, len(batch), 256):
                part = batch.slice(a, 256)
                out: list[list] = [[] for _ in fields]
                for raw, whole, spans, all_words, shared in zip(*(part.column(i).to_pylist() for i in range(1, 6))):
                    begins, ends = ([0], [len(raw)]) if whole else merged(spans or [])
                    sha, kept = hashlib.sha256(), 0
                    for b, e in zip([0, *ends], [*begins, len(raw)]):
                        sha.update(raw[b:e])
                        kept += e - b
                    n_shared = len(raw.split()) if all_words else sum(e - b for b, e in zip(*merged(shared or [])))
                    for column, value in zip(out, (len(raw), len(raw) - kept, len(begins), sha.hexdigest(), n_shared, begins, ends)):
                        column.append(value)
                arrays = [pa.array(x, type=f.type) for x, f in zip(out, list(arrow)[1:])]
                yield pa.RecordBatch.from_arrays([part.column(0).cast(arrow.field(0).type), *arrays], schema=arrow)

    flag = lambda c: F.coalesce(c, F.lit(False)).alias(c)
    return rows.select("id", F.encode("text", "UTF-8").alias("raw"), flag("whole"), "spans", flag("all_words"), "passages").mapInArrow(cut, schema)
