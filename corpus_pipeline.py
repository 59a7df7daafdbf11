"""A training corpus from raw documents: toxicity, line dedup, near-dedup, source mixing, token ids.

Every stage takes all that its predecessor kept, written as Parquet and read again. Columns of documents pass
through unchanged but for the text, and n_chars with it, where lines go.

Defined results of every stage: a null text is an empty one (it stays null in the column); a null id, language,
source or count is a value like any other; repeated rows are documents of their own until near-dedup, which keeps
one of each group; ties go to the smaller id, then the smaller text hash, then the smaller row; texts of any
length are worked on whole; further columns pass through, under any name; an empty table gives no rows.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphweave.llm.byte_bpe import encode_documents
from graphweave.llm.common import fresh, released, settled, stored, table
from graphweave.llm.line_dedup import deduplicate_lines
from graphweave.llm.mixing import mix, positions, word_count
from graphweave.llm.queries import RANKS, TOXIC_FROM
from graphweave.llm.simhash import near_copies
from graphweave.llm.toxicity import score_documents


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose restored text scores as toxic go."""
    learnable = F.crc32(F.col("doc_id").cast("string")) % 3 != 1
    score = fresh(docs, "score")
    scored = score_documents(docs, table(spark, sf_dir, "labels"), tuple(docs.columns), learnable=learnable, score_col=score)
    return scored.where(F.col(score) < TOXIC_FROM).drop(score)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that an earlier line equals or nearly equals go, and documents that have no other line."""
    kept = deduplicate_lines(docs)
    return kept.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else kept


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies, by five-word shingles, one document stays: that of least id, then of least text hash.

    A row is one of its text, not of its id: different texts under one id, or under none, are different documents.
    """
    node = fresh(docs, "__node")
    rows = docs.withColumn(node, F.xxhash64(F.coalesce("text", F.lit(""))))
    found = settled(near_copies(rows, node), "node")
    grouped = rows.select("doc_id", F.col(node).alias("text")).join(found, F.col("text") == F.col("node"), "left")
    grouped = grouped.select("doc_id", F.col("text").alias(node), F.coalesce("root", "text").alias("root"))
    keeper = F.min(F.struct(F.col("doc_id").isNull().alias("null"), F.col("doc_id").alias("id"), F.col(node).alias("text")))
    keeper = grouped.groupBy("root").agg(keeper.alias("keeper")).select(F.col("keeper.id").alias("__id"), F.col("keeper.text").alias("__kept"))
    # Rows of one id and text differ in other columns only: the least of them stays. One exchange of texts serves both steps.
    key = lambda c: (F.coalesce(c, F.lit(0).cast(docs.schema["doc_id"].dataType)).alias("__id"), c.isNull().alias("__null"))
    least = rows.groupBy(*key(F.col("doc_id")), node).agg(F.min(F.struct(*(F.col(f"`{c}`") for c in docs.columns))).alias("row"))
    keeper = settled(keeper.select(*key(F.col("__id")), F.col("__kept").alias(node)))
    released(spark)
    return least.join(keeper, ["__id", "__null", node], "left_semi").select("row.*")


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Copies of whole documents by their sources' schedules, in the order of training."""
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), "doc_id", "source", word_count(F.col("text")).alias("size"))
    return positions(mix(rows, size_col="size")).select("row.*")


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every copy, and a digest of the bytes that they decode to."""
    decoded = encode_documents(docs, public_tokenizers.path(RANKS), ("doc_id",), with_offsets=False, with_decoded=True)
    digest = F.sha2(F.concat_ws(",", F.col("ids").cast("array<string>")), 256)
    return decoded.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), digest.alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"), "ids")


STAGES = [
    ("toxicity", toxicity),
    ("line dedup", line_dedup),
    ("SimHash near-dedup", near_dedup),
    ("source mixing", source_mix),
    ("byte-level BPE", token_ids),
]

#: Viterbi restoration, trained scores and BPE merges have no SQL form; the tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
