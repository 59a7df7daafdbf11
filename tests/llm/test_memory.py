"""What the tokenizer's Python workers hold: an executor has several of them beside its heap."""

import tracemalloc

import corpus_pipeline
import public_tokenizers

from graphweave.llm import byte_bpe
from graphweave.llm.queries import RANKS

PATH = public_tokenizers.path(RANKS)


def test_token_ids_take_one_python_worker_a_task(spark):
    docs = spark.createDataFrame([(1, "two words\n"), (2, None), (None, "é 中 it's"), (3, "")], "doc_id long, text string")
    made = corpus_pipeline.token_ids(spark, docs, "")
    assert made._jdf.queryExecution().optimizedPlan().toString().count("MapInArrow") == 1
    apart = byte_bpe.decode_documents(byte_bpe.encode_documents(docs, PATH, with_offsets=False), PATH)
    want = apart.selectExpr("doc_id", "size(ids) as n", "sha2(decoded, 256) as d", "ids").collect()
    assert sorted(map(str, made.selectExpr("doc_id", "int(n_tokens) as n", "decoded_sha256 as d", "ids").collect())) == sorted(map(str, want))


def test_tables_are_built_in_little_memory():
    byte_bpe.codepoint_classes.cache_clear()
    tracemalloc.start()
    try:
        byte_bpe.codepoint_classes()
        classes = tracemalloc.get_traced_memory()[1]
        tracemalloc.reset_peak()
        held = byte_bpe.Vocabulary(PATH)
        now, peak = tracemalloc.get_traced_memory()
    finally:
        tracemalloc.stop()
    assert held and classes < 40e6 and peak - now < 15e6, (classes, peak - now)
