import random
import re

import numpy as np
import pytest
import xxhash

from graphweave.llm import simhash
from graphweave.llm.simhash import fingerprint, fingerprints, links, near_copies, near_duplicates


def brute_print(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), text or ""))
    grams = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or ([" ".join(words)] if words else [])
    hashes = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_components(prints):
    ids = sorted(prints)
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in ids:
        for j in ids:
            if j < i and (prints[i] ^ prints[j]).bit_count() <= 2:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_fingerprint_matches_brute_force():
    texts = ["", "  \n", "One", "one two", "A b C d e\tf", "É È é\x1c x y z", "w " * 500, "a b c " * 70_000]
    for text in texts:
        assert fingerprint(text) & (1 << 64) - 1 == brute_print(text)


def test_components_match_brute_force(spark):
    rng = random.Random(5)
    prints, base = {}, [rng.getrandbits(64) for _ in range(12)]
    for i in range(500):
        p = rng.choice(base)
        for _ in range(rng.choice([0, 0, 1, 1, 2, 3, 5])):
            p ^= 1 << rng.randrange(64)
        prints[i] = p
    for i in range(500, 530):  # a chain, each two bits from the last
        prints[i] = ((1 << 2 * (i - 500)) - 1) & (1 << 64) - 1
    rows = [(i, p - (1 << 64) if p >> 63 else p) for i, p in prints.items()]
    df = spark.createDataFrame(rows, "doc_id long, fingerprint long")
    got = {r.doc_id: r.component_id for r in near_duplicates(df).collect()}
    assert got == brute_components(prints)
    for bound in (1, 1000):
        got = {r.doc_id: r.component_id for r in near_duplicates(df, list_bound=bound).collect()}
        assert got == brute_components(prints)


def test_edge_cases(spark):
    docs = spark.createDataFrame(
        [(1, None, "x"), (2, "", "y"), (3, "a b c d", None), (3, "a b c d", None), (4, "q r s t u v", "z")],
        "doc_id long, text string, component_id string",
    )
    got = near_duplicates(fingerprints(docs)).collect()
    assert sorted((r.doc_id, r.component_id) for r in got) == [(1, 1), (2, 1), (3, 3), (3, 3), (4, 4)]
    assert near_duplicates(fingerprints(docs.limit(0))).count() == 0
    assert links(docs.limit(0).selectExpr("doc_id as f")).count() == 0


@pytest.mark.parametrize(("least", "most"), [(16, 1 << 18), (2, 1 << 18), (2, 50)])
def test_near_copies_are_all_pairs_of_similarity_four_fifths(spark, monkeypatch, least, most):
    monkeypatch.setattr(simhash, "FREQUENT_FROM", least)
    monkeypatch.setattr(simhash, "MOST_FREQUENT", most)
    rng = random.Random(5)
    texts = ["", " ", "one", "one two", "One  two"]
    for base in range(12):
        words = [f"w{rng.randint(0, 400)}" for _ in range(rng.choice((12, 60, 150, 300)))]
        for k in range(6):
            copy = list(words)
            for _ in range(rng.choice((0, 1, 1, 2, 3, 5, 8))):
                copy[rng.randrange(len(copy))] = f"n{rng.randint(0, 10**6)}"
            texts.append(" ".join(copy[: len(copy) - rng.choice((0, 0, 1, 7))]))
    shared = " ".join(f"p{i}" for i in range(80))  # a passage in texts that are not similar
    texts += [f"{shared} {' '.join(f'q{k}x{i}' for i in range(100))}" for k in range(20)]
    texts = sorted(set(texts))

    def shingles(text):
        words = text.lower().split()
        return {" ".join(words[i : i + 5]) for i in range(len(words) - 4)} or {" ".join(words)}

    sets, root = [shingles(t) for t in texts], list(range(len(texts)))
    far = 0
    for i in range(len(texts)):
        for j in range(i):
            if 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]):
                far += (fingerprint(texts[i], 5) ^ fingerprint(texts[j], 5)).bit_count() > 2
                a, b = root[i], root[j]
                root = [min(a, b) if r in (a, b) else r for r in root]
    assert far > 10 and len(set(root)) > 20
    docs = spark.createDataFrame(list(enumerate(texts)), "node long, text string")
    found = {r.node: r.root for r in near_copies(docs, "node").collect()}
    assert [found.get(i, i) for i in range(len(texts))] == root


def test_texts_that_share_much_without_being_similar_leave_the_join_as_few_pairs(spark, monkeypatch):
    rng = random.Random(3)
    texts = []
    for base in range(3):
        words = [f"b{base}w{i}" for i in range(200)]
        for k in range(30):
            copy = list(words)
            for at in rng.sample(range(200), 7):
                copy[at] = f"n{rng.randint(0, 10**9)}"
            texts.append(" ".join(copy))
    rows = []

    def counted(posted, made=simhash.candidates):
        found = made(posted)
        rows.append(found.count())
        return found

    monkeypatch.setattr(simhash, "candidates", counted)
    sets = [{*simhash.shingle_hashes(t, 5).tolist()} for t in texts]
    similar = {(i, j) for j in range(90) for i in range(j) if 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j])}
    found = {r.node: r.root for r in near_copies(spark.createDataFrame(list(enumerate(texts)), "node long, text string"), "node").collect()}
    assert all(found[i] == found[j] for i, j in similar)
    assert rows[0] < 90  # 30 * 29 / 2 pairs share keys in each of three groups, most under many keys


def test_sketches_differ_in_no_more_bits_than_sets_in_shingles():
    rng = random.Random(4)
    for n in (0, 3, 40, 700, 5000):
        one = {rng.getrandbits(64) for _ in range(n)}
        for changed in (0, 1, n // 9, n // 2):
            other = set(list(one)[changed:]) | {rng.getrandbits(64) for _ in range(changed)}
            for words in (simhash.SKETCH_WORDS, simhash.wide_words(n)):
                a, b = (simhash.parity_sketch(np.array(sorted(s), np.uint64), words) for s in (one, other))
                assert len(a) == words and sum(int(x).bit_count() for x in (a ^ b).view(np.uint64)) <= len(one ^ other)
        folded = simhash.parity_sketch(np.array(sorted(one), np.uint64), 16)
        assert ((folded[:8] ^ folded[8:]) == simhash.parity_sketch(np.array(sorted(one), np.uint64), 8)).all()
