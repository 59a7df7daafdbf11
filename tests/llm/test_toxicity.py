import itertools
import random
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from graphweave.llm.toxicity import Restorer, count_grams, letter_costs, score_documents

CLEAN = ["the meadow lies under a quiet sky", "people walk along the river and talk", "bread and butter on the table", "a letter came from the city", "rain fell over the hills all day", "children read a book about ships"]
FOUL = ["you worthless idiot go away", "what a pathetic clown you are", "shut up you idiot", "worthless people like you", "that clown is a pathetic liar"]


@pytest.fixture(scope="module")
def corpus(spark):
    rows = [(i, f"{CLEAN[i % 6]} number {i % 5}", i % 2) for i in range(240)] + [(1000 + i, f"{FOUL[i % 5]} number {i % 4}", 0) for i in range(80)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score long")
    labels = spark.createDataFrame([(i, int(i >= 1000)) for i, _, _ in rows] + [(1, None), (9999, 1)], "doc_id long, toxic int")
    return docs, labels


def test_restores_disguised_words(corpus):
    restorer = Restorer(letter_costs(count_grams(corpus[0])))
    for token, word in (("1d10t", "idiot"), ("i-d-i-o-t", "idiot"), ("idioooot", "idiot"), ("p@thetic", "pathetic"), ("cl0wn!!!", "clown"), ("w0rthless", "worthless"), ("river,", "river")):
        assert word in restorer.word(token), token
    assert "idiot" in restorer.words("you I D I O T there")
    assert restorer.words("") == set() and restorer.words("12345 --- !!!") <= {"12345"}


def test_counts_cover_the_corpus(spark):
    df = spark.createDataFrame([("abc",), (None,), ("",)], "text string")
    counts = count_grams(df)
    assert counts.sum() >= 4 and counts[((1 * 27 + 2) * 27 + 3) * 27] == 1
    assert np.isfinite(letter_costs(count_grams(df.limit(0)))).all()


def test_scores(spark, corpus):
    docs, labels = corpus
    more = spark.createDataFrame([(5000, "you are a w0rthless 1d10t", 0), (5001, "bread over the river", 0), (5002, None, 0), (5003, "", 0)], docs.schema)
    got = {r.doc_id: r.score for r in score_documents(docs.union(more), labels).collect()}
    assert len(got) == 324 and all(0 <= s <= 1 for s in got.values())
    assert min(got[i] for i in got if 1000 <= i < 2000) > 0.7 > max(got[i] for i in got if i < 1000)
    assert got[5000] > 0.7 > got[5001] and got[5002] == got[5003] < 0.7


def test_no_labels(spark, corpus):
    docs, labels = corpus
    got = score_documents(docs, labels.limit(0)).collect()
    assert len({r.score for r in got}) == 1
    assert score_documents(docs.limit(0), labels).count() == 0


def test_viterbi_finds_the_cheapest_of_all_paths(corpus):
    restorer = Restorer(letter_costs(count_grams(corpus[0])))
    cost_of = np.array(restorer.costs).reshape((27,) * 4)
    rng = random.Random(2)
    tokens = ["1d10t", "iidioott", "a$$", "i-d", "y o u", "wor th", "cl0wn", "!!", "a.b_c", "ßé1", "жa0"]
    tokens += ["".join(rng.choice("aio01$!. -tt") for _ in range(rng.randint(1, 6))) for _ in range(60)]
    for token in tokens:
        cheapest = []
        for path in itertools.product(*restorer.steps(token)):
            context, cost, written = (0, 0, 0), 0.0, ""
            for letter, sign, step in path:
                cost += step
                if letter > 0 or (letter == 0 and context[-1]):
                    cost += cost_of[(*context, letter)]
                    context = (*context[1:], letter)
                written += sign
            cheapest.append((cost + (cost_of[(*context, 0)] if context[-1] else 0.0), written.split()))
        found = restorer.best(token)
        assert abs(found[0] - min(c for c, _ in cheapest)) < 1e-6, token
        assert any(abs(c - found[0]) < 1e-6 and w == found[1].split() for c, w in cheapest)


def test_spacing_repetition_and_trailing_signs(corpus):
    restorer = Restorer(letter_costs(count_grams(corpus[0])))
    assert "idiot" in restorer.words("you idiiot") and "idiot" in restorer.words("iidioott")
    assert {"worthless", "idiot"} <= restorer.words("w o r t h l e s s i d i o t")
    assert {"you", "pathetic"} <= set(restorer.words("y0u_p@thetic"))
    assert "idiot" in restorer.words("id iot") and "worthless" in restorer.words("wor th less")
    assert "idiot" in restorer.words("x" * 70 + "-1d10t") and "idiot" in restorer.words("i d i o t " * 40)
    assert "number" in restorer.words("number 12345") and "12345" in restorer.words("number 12345")
    assert restorer.words("the meadow lies under a quiet sky") == set("the meadow lies under a quiet sky".split())


def test_very_long_tokens_and_runs_are_decoded_in_linear_time(corpus):
    restorer = Restorer(letter_costs(count_grams(corpus[0])))
    for text in ("1d10t" * 4000, "i d i o t " * 4000, "a" * 20_000, "-1d" * 7000):
        began = time.process_time()
        assert restorer.words(text)
        assert time.process_time() - began < 20


def test_repeated_rows_clashing_columns_and_very_long_texts(spark, corpus):
    docs, labels = corpus
    more = spark.createDataFrame([(6000, "bread and butter " * 20_000 + " you worthless idiot clown", 1), (1000, "zz other text of a labelled id", 1), (3, docs.first().text, 1), (None, "you idiot", 2)], docs.schema)
    every = docs.union(more).withColumn("__id", F.lit(1)).withColumn("toxic", F.lit("x"))
    rows = score_documents(every, labels, ("doc_id", "score", "toxic")).collect()
    assert len(rows) == 324 and rows[0].asDict().keys() == {"doc_id", "score", "toxic"}
    got = {r.doc_id: r.score for r in rows if r.doc_id != 1000}
    assert got[6000] > 0.5 and got[None] > 0.5 > got[3]
