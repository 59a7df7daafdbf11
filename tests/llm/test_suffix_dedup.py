import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest

from graphweave.llm import suffix_dedup
from graphweave.llm.suffix_dedup import Fingerprints, anchors, multikey_order, remove_repeats


def brute(docs, span):
    raws = [(i, (t or "").encode()) for i, t in docs]
    seen = Counter(r[p : p + span] for _, r in raws for p in range(len(r) - span + 1))
    out = []
    for i, r in raws:
        gone = bytearray(len(r))
        for p in range(len(r) - span + 1):
            if seen[r[p : p + span]] > 1:
                gone[p : p + span] = b"\1" * span
        spans = sum(1 for p in range(len(r)) if gone[p] and not (p and gone[p - 1]))
        kept = bytes(b for b, g in zip(r, gone) if not g)
        out.append((i, len(r), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def corpus(rng):
    word = lambda: "".join(rng.choice("abcdé") for _ in range(rng.randint(1, 7)))
    prose = lambda n: " ".join(word() for _ in range(n))
    passages = [prose(n) for n in (8, 14, 20, 40, 90)]
    docs = []
    for i in range(60):
        parts = [prose(rng.randint(0, 30)) if rng.random() < 0.6 else rng.choice(passages) for _ in range(rng.randint(0, 6))]
        docs.append((i, " ".join(parts)))
    docs += [(60 + i, docs[i % 7][1]) for i in range(10)]
    docs += [(80, "ab" * 300), (81, "x" * 150), (82, "x" * 61), (83, "ab" * 31), (84, None), (85, ""), (85, docs[3][1]), (85, docs[3][1])]
    return docs


@pytest.mark.parametrize("rows_per_bucket", [200_000, 60])
def test_matches_brute_force(spark, monkeypatch, rows_per_bucket):
    monkeypatch.setattr(suffix_dedup, "ROWS_PER_BUCKET", rows_per_bucket)
    docs = corpus(random.Random(9))
    df = spark.createDataFrame(docs, "doc_id long, text string").selectExpr("*", "'x' as k", "1 as begins")
    got = remove_repeats(df, span=60, lead=12).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
    assert sorted(map(tuple, got.collect()), key=str) == brute(docs, 60)


def test_empty_table(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert remove_repeats(df).count() == 0


def test_equal_windows_name_equal_anchors():
    rng = random.Random(1)
    shared = bytes(rng.randrange(256) for _ in range(900))
    named = []
    for raw in (b"left" * 50 + shared, shared + b"right" * 90):
        data = np.frombuffer(raw, np.uint8)
        at, _, _ = anchors(data, np.array([len(raw)]), Fingerprints(data), 400, 64)
        named.append({raw[p : p + 64] for p in at.tolist()})
    assert len(named[0] & named[1]) >= 2


def test_multikey_order_is_the_order_of_the_rows():
    rng = np.random.default_rng(2)
    columns = [rng.integers(0, 4, 3000) for _ in range(5)]
    order = multikey_order(columns)
    rows = list(zip(*columns))
    assert [rows[i] for i in order] == sorted(rows)
    assert multikey_order([np.zeros(0, int)] * 3).tolist() == []


def test_hot_passage_and_very_long_texts(spark):
    rng = random.Random(4)
    prose = lambda n: " ".join("".join(rng.choice("abcdef") for _ in range(5)) for _ in range(n))
    passage, long = prose(120), prose(30_000)
    docs = [(i, f"{prose(rng.randint(0, 80))} {passage[rng.randint(0, 90):]} {prose(rng.randint(0, 80))}") for i in range(300)]
    docs += [(1000, long), (1001, "z" * 40_000), (1002, long[50_000:90_000] + prose(50)), (1003, "z" * 399), (1004, "z" * 400)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = remove_repeats(df).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
    assert sorted(map(tuple, got.collect()), key=str) == brute(docs, 400)


def test_passages_are_counted_in_words(spark):
    docs = corpus(random.Random(3))
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = remove_repeats(df, passage_words=9).select("doc_id", "n_passage_words").collect()
    split = [(i, re.findall(rb"[^\x20\x09-\x0D]+", (t or "").encode())) for i, t in docs]
    seen = Counter(tuple(w[p : p + 9]) for _, w in split for p in range(len(w) - 8))
    want = [(i, len({k for p in range(len(w) - 8) if seen[tuple(w[p : p + 9])] > 1 for k in range(p, p + 9)})) for i, w in split]
    assert sorted(map(tuple, got)) == sorted(want) and sum(n for _, n in want) > 500
