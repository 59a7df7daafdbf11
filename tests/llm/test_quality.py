import math
import random
import re
import zlib
from collections import Counter

from graphweave.llm.quality import WIDTH, judge, measure, train


def brute(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    windows = Counter(tuple(words[i : i + 5]) for i in range(len(words) - 4))
    covered = {k for i in range(len(words) - 4) if windows[tuple(words[i : i + 5])] > 1 for k in range(i, i + 5)}
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return {"n_words": len(words), "word_chars": sum(map(len, words)), "n_symbols": len(re.findall(r"[#*$%&|<>]", text)), "n_dup_lines": len(lines) - len(set(lines)), "n_repeat_words": len(covered)}


def test_counts_match_brute_force():
    rng = random.Random(4)
    texts = ["", " \n", "é\x1c b\x85c", "a b c d e a b c d e f", "x " * 3000]
    texts += ["".join(rng.choice("ab é\n\t#|") for _ in range(rng.randint(0, 200))) for _ in range(500)]
    for text in texts:
        assert measure(text)[0] == brute(text)


def test_verdicts(spark):
    rng = random.Random(6)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 8)))
    good = [(i, " ".join(word() for _ in range(60))) for i in range(150)]
    bad = [(1000 + i, " ".join(word() + "$$$" for _ in range(60))) for i in range(100)]
    labels = spark.createDataFrame([(i, int(i < 1000)) for i, _ in good + bad if i % 3] + [(0, None), (7777, 1)], "doc_id long, quality int")
    docs = spark.createDataFrame(good + bad + [(2000, None), (2001, ""), (2002, "a b c d e " * 20)], "doc_id long, text string").selectExpr("*", "1 as kept", "'x' as score")
    got = {r.doc_id: r for r in judge(docs, labels).collect()}
    assert all(got[i].kept for i, _ in good) and not any(got[i].kept for i, _ in bad)
    assert all(got[i].base_failed and not got[i].kept for i in (2000, 2001, 2002))
    assert judge(docs.limit(0), labels).count() == 0
    same = judge(docs.where("doc_id < 1000"), labels.limit(0)).collect()
    assert len({r.score for r in same}) == 1 and all(r.kept for r in same)  # an even chance reaches the threshold


def slow_features(text):
    """Every word, pair of words and three characters, in plain loops, as (feature, value)."""
    mask, a, b = (1 << 64) - 1, 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F
    words = [zlib.crc32(w.lower()) for w in re.findall(rb"[^\x20\x09-\x0D]+", text.encode())]
    mixed = lambda g, shift, m, bits: ((g ^ g >> shift) * m & mask) >> (64 - bits)
    of_words = Counter(mixed(w * a & mask, 29, b, 18) for w in words)
    of_words += Counter(mixed((((u * b + v) & mask) * a + 1) & mask, 29, b, 18) for u, v in zip(words, words[1:]))
    p = list(map(ord, text))
    of_chars = Counter((1 << 18) + mixed((((x * a & mask) ^ y) * b + z) & mask, 31, a, 15) for x, y, z in zip(p, p[1:], p[2:]))
    out = {(1 << 18) + (1 << 15) + int(math.log2(len(words) + 1)): 1.0}
    for counts in (of_words, of_chars):
        norm = math.sqrt(sum(math.log1p(n) ** 2 for n in counts.values()))
        out |= {k: math.log1p(n) / norm for k, n in counts.items()}
    return out


def test_features_and_verdicts_match_brute_force(spark):
    rng = random.Random(9)
    texts = ["", "a", "one two", "È é\x1c b", "distinct words of a text count each once", *(" ".join(rng.choice("abcdefg") * rng.randint(1, 3) for _ in range(rng.randint(1, 60))) for _ in range(80))]
    for text in texts:
        at, values = measure(text)[1]
        want = slow_features(text)
        assert set(at.tolist()) == set(want) and len(at) == len(want)
        assert all(abs(want[k] - v) < 1e-9 for k, v in zip(at.tolist(), values.tolist()))
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)] + [(3, "repeated id"), (7, texts[7]), (7, texts[7])], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(len(t) % 5 > 0)) for i, t in enumerate(texts)], "doc_id long, quality int")
    weights, bias = train(docs, labels)
    rows = judge(docs, labels).collect()
    assert len(rows) == len(texts) + 3 and {(r.score, r.kept) for r in rows if r.doc_id == 7}.__len__() == 1
    for r in rows:
        if r.doc_id != 3:
            score = 1 / (1 + math.exp(-bias - sum(weights[k] * v for k, v in slow_features(texts[r.doc_id]).items())))
            counts = brute(texts[r.doc_id])
            failed = counts["n_words"] < 10 or 100 * counts["n_repeat_words"] > 20 * counts["n_words"]
            assert abs(r.score - score) < 1e-4 and r.base_failed == failed and (r.kept == (not failed and r.score >= 0.5))


def test_very_long_texts_are_measured_whole():
    clean = " ".join(f"w{i % 977}" for i in range(200_000))
    at, values = measure(clean + " last#word")[1]
    assert set(measure("last#word")[1][0].tolist()) - {WIDTH - 32 + 1} <= set(at.tolist()) and abs((values**2).sum() - 3) < 1e-6
