import random

from graphweave.llm import line_dedup
from graphweave.llm.line_dedup import deduplicate_lines, dropped_lines


def one_edit(a, b):
    if abs(len(a) - len(b)) > 1:
        return False
    if len(a) == len(b):
        return sum(x != y for x, y in zip(a, b)) <= 1
    long, short = (a, b) if len(a) > len(b) else (b, a)
    return any(long[:i] + long[i + 1 :] == short for i in range(len(long)))


def brute(docs, near_words=6):
    seen, gone = [], {}
    for i, text in sorted(docs, key=lambda d: d[0]):
        for no, line in enumerate((text or "").split("\n")):
            words = line.split()
            if not words:
                continue
            if any(line == s or (min(len(words), len(w)) >= near_words and one_edit(words, w)) for s, w in seen):
                gone.setdefault(i, []).append(no)
            seen.append((line, words))
    return gone


def corpus(n, seed):
    rng = random.Random(seed)
    base = [[rng.choice("abcdefg") * rng.randint(1, 2) for _ in range(rng.choice([1, 3, 6, 7, 8, 9, 15]))] for _ in range(25)]
    docs = []
    for i in range(n):
        lines = []
        for _ in range(rng.randint(0, 6)):
            words = list(rng.choice(base))
            for _ in range(rng.choice([0, 1, 1, 2])):
                at, kind = rng.randrange(len(words) + 1), rng.random()
                words[at : at + (kind > 0.3)] = [] if kind > 0.7 and len(words) > 1 else [rng.choice("hijklmnop")]
            lines.append(" ".join(words))
        docs.append((i, "\n".join(lines)))
    return docs


def test_matches_brute_force(spark, monkeypatch):
    docs = corpus(150, 3)
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = {r.d: r.dropped for r in dropped_lines(df).collect()}
    assert got == brute(docs)
    monkeypatch.setattr(line_dedup, "_IN_ROW", 6)  # windows for the longer lines
    assert {r.d: r.dropped for r in dropped_lines(df).collect()} == got


def test_rebuilt_texts_and_edge_cases(spark):
    long = " ".join(map(str, range(3000)))
    docs = [
        (1, "one two three four five six seven\n\nshort line", "k", None),
        (2, "one two three four FIVE six seven\nown line here", "k", 1),
        (3, "short line", "k", 2),
        (4, None, None, 3),
        (5, "", "k", 4),
        (6, long, "k", 5),
        (7, long + " x\n" + long.replace(" 7 ", " 8 "), "k", 6),
        (8, "same\nsame", "k", 7),
        (8, "same\nsame", "k", 7),
    ]
    df = spark.createDataFrame(docs, "doc_id long, text string, dropped string, h long")
    got = sorted((r.doc_id, r.text) for r in deduplicate_lines(df).where("text is not null").collect())
    assert got == [(1, docs[0][1]), (2, "own line here"), (5, ""), (6, long), (8, "same"), (8, "same")]
    out = deduplicate_lines(df)
    assert out.columns == df.columns and out.where("doc_id = 4").count() == 1
    assert dropped_lines(df.limit(0)).count() == 0


def test_main_path_is_native(spark):
    df = spark.createDataFrame(corpus(5, 1), "doc_id long, text string")
    plan = deduplicate_lines(df)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan
