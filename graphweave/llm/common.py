"""Helpers that the training-data operators share: table access, text kernels, checkpoints, two-level ranks."""

from __future__ import annotations

import contextlib
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator, Sequence

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

#: Characters that one kernel call gets at most, unless one text alone is longer.
CHARS_PER_CALL = 2_000_000
#: Longs of the broadcast filter of ``maybe_in`` at most, of 64 bits each: a proven bound of what is broadcast.
MOST_FILTER_WORDS = 1 << 18


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share: the session's ``spark.checkpoint.dir``.

    Only where that is unset and Spark runs on one machine (tests), a temporary one is taken.
    """
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder:
            if not context.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
            folder = tempfile.mkdtemp(prefix="checkpoints")
        context.setCheckpointDir(folder)
    return context._jsc.sc().getCheckpointDir().get()


def materialize(df: DataFrame) -> DataFrame:
    """Checkpoint df in the shared folder and cut its lineage, so that lost executors cost no recomputation."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


def stored(df: DataFrame) -> DataFrame:
    """df written as Parquet to the shared folder and read again, for tables that hold whole texts."""
    path = f"{shared_folder(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.parquet(path)


def released(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of finished steps now: it does so once the driver's objects for them are collected.

    Memory that the driver's Python has freed goes back to the system too.
    """
    trimmed()
    spark.sparkContext._jvm.System.gc()


def settled(df: DataFrame, *keys: str) -> DataFrame:
    """The materialised df as one side of a join on keys that may be skewed on the other side.

    The keys are rebuilt by an expression, so Spark deals both sides out anew for the join; adaptive execution
    splits large partitions only in that case, not where an aggregation's own exchange feeds the join.
    """
    return rekeyed(materialize(df), *keys)


def rekeyed(df: DataFrame, *keys: str) -> DataFrame:
    """The same for a df that is materialised or stored already."""
    rebuilt = {k: F.when(F.col(k).isNotNull(), F.col(k)) for k in keys}
    return df.select(*(rebuilt[c].alias(c) if c in rebuilt else c for c in df.columns))


def maybe_in(rows: DataFrame, hashed: str, keys: DataFrame) -> DataFrame:
    """The rows whose hash may be among keys (one column), which some join decides later; a filter of 16 bits a key.

    Keys that would fill more than half of the largest bit table get none: it would let most rows through.
    """
    n = keys.count()
    if n > MOST_FILTER_WORDS * 32:
        return rows
    words = min(MOST_FILTER_WORDS, max(1 << 10, 1 << (n // 4).bit_length()))
    word = lambda c: F.pmod(F.shiftright(c, 6), F.lit(words)).cast("int")
    bit = lambda c: F.call_function("shiftleft", F.lit(1).cast("long"), c.bitwiseAND(F.lit(63)).cast("int"))
    key = F.col(keys.columns[0])
    bits = materialize(keys.groupBy(word(key).alias("__word")).agg(F.bit_or(bit(key)).alias("__bits")))
    at = F.col(hashed)
    hit = F.col("__bits").bitwiseAND(bit(at)) != 0
    return rows.join(F.broadcast(bits), (word(at) == F.col("__word")) & hit, "left_semi")


def slots(spark: SparkSession) -> int:
    """Partitions that a wide step of this session is cut into."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def _runs(lengths: Sequence[int], most: int) -> Iterator[tuple[int, int]]:
    start, total = 0, 0
    for i, n in enumerate(lengths):
        if total and total + n > most:
            yield start, i
            start, total = i, 0
        total += n
    if start < len(lengths):
        yield start, len(lengths)


def trimmed() -> None:
    """Give memory that a task has freed back to the system: its Python worker stays idle beside the next steps of the executor."""
    import ctypes

    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError, OSError):  # only some systems can
        ctypes.CDLL(None).malloc_trim(0)


def map_texts(
    df: DataFrame,
    make_kernel: Callable[[], Callable[[list[str]], list]],
    fields: Sequence[tuple[str, T.DataType]],
    keep: Sequence[str],
    text_col: str = "text",
    chars_per_call: int = CHARS_PER_CALL,
) -> DataFrame:
    """Apply a kernel to whole texts in Arrow batches, without a shuffle.

    ``make_kernel`` is called once per task; its result maps a list of texts (null becomes "") to one list
    or array per entry of ``fields``. The columns ``keep`` pass through; a new field replaces a kept column
    of the same name, other columns of df are dropped.
    """
    new = {name for name, _ in fields}
    keep = [c for c in keep if c not in new]
    schema = T.StructType([*(df.schema[c] for c in keep), *(T.StructField(n, t) for n, t in fields)])
    arrow = to_arrow_schema(schema)
    alias = "__text"
    while alias in keep:
        alias += "_"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel = make_kernel()
        for batch in batches:
            column = batch.column(len(keep))
            lengths = pa.compute.fill_null(pa.compute.binary_length(column), 0).to_pylist()
            for a, b in _runs(lengths, chars_per_call):
                texts = [t if t is not None else "" for t in column.slice(a, b - a).to_pylist()]
                made = kernel(texts)
                kept = [batch.column(i).slice(a, b - a).cast(arrow.field(i).type) for i in range(len(keep))]
                made = [pa.array(x, type=f.type) for x, f in zip(made, list(arrow)[len(keep) :], strict=True)]
                yield pa.RecordBatch.from_arrays([*kept, *made], schema=arrow)
        del kernel
        trimmed()

    import pyarrow.compute  # noqa: F401

    return df.select(*(F.col(f"`{c}`") for c in keep), F.col(f"`{text_col}`").alias(alias)).mapInArrow(run, schema)


def ascii_words(text: Column) -> Column:
    """Maximal runs of characters other than ASCII white space; an empty array for a null text."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+"), lambda w: w != "")


def fresh(df: DataFrame, stem: str) -> str:
    """A column name that df does not use."""
    while stem in df.columns:
        stem += "_"
    return stem
