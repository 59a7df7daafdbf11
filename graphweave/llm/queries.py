"""The registered queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphweave.llm.common import table

#: The rank file of op4 and of the pipeline's last stage.
RANKS = "byte_bpe_multi_50k.tiktoken"
#: A document of this score or more counts as toxic.
TOXIC_FROM = 0.7


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphweave.llm.toxicity import score_documents

    remainder = F.crc32(F.col("doc_id").cast("string")) % 3
    labels = table(spark, sf_dir, "labels")
    scored = score_documents(table(spark, sf_dir, "documents"), labels, learnable=remainder != 1)
    return scored.select(
        "doc_id",
        F.coalesce(remainder == 1, F.lit(False)).alias("held_out"),
        "score",
        (F.col("score") >= TOXIC_FROM).cast("int").alias("predicted"),
    )


def op2_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphweave.llm.topk import top_k

    vectors = table(spark, sf_dir, "embeddings")
    return top_k(vectors, F.col("vec_id") % 20 == 0, 20)


def op3_hash_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphweave.llm.sharding import even_tree, grown, shard_documents

    tree = even_tree(3, 2, 4)
    return shard_documents(table(spark, sf_dir, "documents"), tree, grown(tree, 24)).select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard"
    )


def op4_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from graphweave.llm.byte_bpe import decode_documents, encode_documents

    path = public_tokenizers.path(RANKS)
    encoded = encode_documents(table(spark, sf_dir, "documents"), path, ("doc_id",), with_offsets=False)
    return decode_documents(encoded, path, ("doc_id", "ids")).select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.concat_ws(",", F.col("ids").cast("array<string>")), 256).alias("ids_sha256"),
        F.sha2(F.col("decoded"), 256).alias("decoded_sha256"),
    )


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphweave.llm.simhash import fingerprints, near_duplicates

    found = near_duplicates(fingerprints(table(spark, sf_dir, "documents")))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fingerprint"), 16, "0")).alias("fingerprint"), "component_id")


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphweave.llm.pii import KINDS, find_personal_data

    found = find_personal_data(table(spark, sf_dir, "documents"))
    text = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s.kind, s.start, s.end)), ",")
    of_kind = lambda kind: F.filter("base_spans", lambda s: s.kind == kind)
    counts = [F.size(of_kind(kind)).cast("long").alias(f"n_{kind}") for kind in KINDS]
    return found.select("doc_id", *counts, F.sha2(text("base_spans"), 256).alias("base_sha256"), text("all_spans").alias("spans"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphweave.llm.quality import judge

    return judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphweave.llm.suffix_dedup import remove_repeats

    found = remove_repeats(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "n_passage_words")


def op9_curriculum_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphweave.llm.common import materialize
    from graphweave.llm.mixing import first_positions, mix, word_count

    docs = table(spark, sf_dir, "documents")
    sized = materialize(docs.select("doc_id", "source", word_count(F.col("text")).alias("size")))
    mixed = materialize(mix(sized, size_col="size"))
    return first_positions(mixed).select("doc_id", "source", "size", "source_size", "target", F.col("taken").cast("long").alias("taken"), "first_position")


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphweave.llm.line_dedup import dropped_lines

    docs = table(spark, sf_dir, "documents")
    text = F.coalesce("text", F.lit(""))
    lines = docs.select("doc_id", F.xxhash64(text).alias("t"), F.size(F.split(text, "\n")).cast("long").alias("n_lines"))
    gone = dropped_lines(docs)
    return lines.join(gone, lines["doc_id"].eqNullSafe(gone["d"]) & (lines["t"] == gone["t"]), "left").select(
        "doc_id",
        "n_lines",
        F.coalesce(F.size("dropped"), F.lit(0)).cast("long").alias("n_dropped"),
        F.coalesce(F.concat_ws(",", F.col("dropped").cast("array<string>")), F.lit("")).alias("dropped_lines"),
    )


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_toxicity": op1_toxicity,
    "op2_topk": op2_topk,
    "op3_hash_tree": op3_hash_tree,
    "op4_byte_bpe": op4_byte_bpe,
    "op5_simhash": op5_simhash,
    "op6_pii": op6_pii,
    "op7_quality": op7_quality,
    "op8_suffix_dedup": op8_suffix_dedup,
    "op9_curriculum_mix": op9_curriculum_mix,
    "op10_line_dedup": op10_line_dedup,
}

ORACLE_SQL: dict[str, str] = {
    "op2_topk": """
        WITH v AS (
            SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT)) AS q
            FROM embeddings
            WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
        ), s AS (
            SELECT a.vec_id AS query_id, b.vec_id AS vec_id,
                   CAST(list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2])) AS BIGINT) AS score
            FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE a.vec_id % 20 = 0
        ), r AS (
            SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s
        )
        SELECT * FROM r WHERE rank <= 20
    """,
}
