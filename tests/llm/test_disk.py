"""What operators keep on disk beside their results."""

from pathlib import Path

import corpus_pipeline
from graphweave.llm.suffix_dedup import remove_repeats


def test_suffix_dedup_leaves_no_tables_behind(spark):
    from graphweave.llm.common import shared_folder

    folder = Path(shared_folder(spark).removeprefix("file:"))
    before = set(folder.glob("table-*"))
    passage = " ".join(f"p{i}" for i in range(150))
    rows = [(k, f"{' '.join(f'w{k}x{i}' for i in range(90))} {passage if k < 3 else ''}") for k in range(6)]
    got = {r.doc_id: r.n_removed for r in remove_repeats(spark.createDataFrame([*rows, (9, rows[5][1])], "doc_id long, text string")).collect()}
    assert all(got[k] >= len(passage) for k in range(3)) and got[3] == got[4] == 0 and got[5] == got[9] == len(rows[5][1])
    assert folder.exists() and set(folder.glob("table-*")) == before


def test_near_dedup_exchanges_whole_rows_once(spark):
    docs = spark.createDataFrame([(1, "a b c d e f", "s"), (1, "a b c d e f", "r"), (None, "g", "s"), (None, "g", None)], "doc_id long, text string, source string")
    made = corpus_pipeline.near_dedup(spark, docs, "")
    assert sorted(map(str, made.collect())) == sorted(map(str, [docs.collect()[1], docs.collect()[3]]))
    assert made._jdf.queryExecution().optimizedPlan().toString().count("Join") == 1
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        plan = corpus_pipeline.near_dedup(spark, docs, "")._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")
    assert plan.count("Exchange hashpartitioning") <= 2  # of the rows and, unless broadcast, of the keepers
