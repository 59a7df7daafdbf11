import random
import re
import time

from graphweave.llm import pii

BASE = {
    "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
    "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(x) <= 255 for x in m.split("."))),
    "card": (r"[0-9]([\x20-]?[0-9])+", lambda m: 16 <= len(d := re.sub(r"\D", "", m)) <= 19 and pii.passes_luhn(d)),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 8 <= len(re.sub(r"\D", "", m)) <= 15),
}


def brute(text):
    return {kind: [m.span() for m in re.finditer(p, text) if fine(m.group())] for kind, (p, fine) in BASE.items()}


def test_plain_scan_matches_the_patterns():
    rng = random.Random(3)
    for alphabet in ("a1.@+- (9)0.5", "0123456789 -+", "ab@.c-"):
        for _ in range(8000):
            text = "".join(rng.choice(alphabet) for _ in range(rng.randint(0, 45)))
            assert brute(text) == pii.plain_spans(text), text
    assert pii.plain_spans("4111 1111-1111 1111")["card"] == [(0, 19)]
    assert pii.plain_spans("1" * 200_000 + "." + "a@" * 50_000)["email"] == []


def test_disguises_map_back_to_the_source():
    for text, kind, span in (
        ("write to john.doe [at] example [dot] com now", "email", "john.doe [at] example [dot] com"),
        ("john at example dot com", "email", "john at example dot com"),
        ("jоhn@exаmple.com!", "email", "jоhn@exаmple.com"),
        ("call plus one two three four five five five six seven eight nine.", "phone", "plus one two three four five five five six seven eight nine"),
        ("ip 192[.]168[.]1[.]1 here", "ip", "192[.]168[.]1[.]1"),
        ("card ４１１１ １１１１ １１１１ １１１１ x", "card", "４１１１ １１１１ １１１１ １１１１"),
        ("a@b.com and x (at) y.org", "email", "x (at) y.org"),
    ):
        found = pii.disguised_spans(text, pii.plain_spans(text))
        assert [text[a:b] for a, b in found[kind]] == [span], text
    for text in ("look at this. dot the i at home", "seven at a time, one two three four", "at noon, dot by dot", ""):
        assert not any(pii.disguised_spans(text, pii.plain_spans(text)).values()), text


def test_documents(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (3, "é a@b.co x at y dot org"), (3, "é a@b.co x at y dot org")], "doc_id long, text string").selectExpr("*", "1 as base_spans")
    got = sorted((r.doc_id, [tuple(s) for s in r.base_spans], [tuple(s) for s in r.all_spans]) for r in pii.find_personal_data(docs).collect())
    three = (3, [("email", 2, 8)], [("email", 2, 8), ("email", 9, 23)])
    assert got == [(1, [], []), (2, [], []), three, three]
    assert pii.find_personal_data(docs.limit(0)).count() == 0
    assert pii.redact("call a@b.co now", [(5, 11)]) == "call [removed] now"


def test_disguises_need_no_other_sign_in_the_text():
    for text, kind, span in (
        ("mail john at example.com", "email", "john at example.com"),
        ("john [аt] example [dоt] com", "email", "john [аt] example [dоt] com"),
        ("john [at] example [d​ot] com", "email", "john [at] example [d​ot] com"),
        ("john {at} example.com", "email", "john {at} example.com"),
        ("john <at> example.com", "email", "john <at> example.com"),
        ("john@example{ . }com", "email", "john@example{ . }com"),
        ("plus оne two thrеe fоur five five five six sevеn", "phone", "plus оne two thrеe fоur five five five six sevеn"),
        ("ring plus 4 4 oh 2 0 7 9 4 6", "phone", "plus 4 4 oh 2 0 7 9 4 6"),
    ):
        found = pii.disguised_spans(text, pii.plain_spans(text))
        assert [text[a:b] for a, b in found[kind]] == [span], text


def test_every_test_before_a_transducer_holds_where_its_pattern_matches():
    rng = random.Random(4)
    parts = ("at", "AT", "аt", "dot", "d​ot", "dоt", " ", "  ", "[", "]", "(", ")", "{", "}", "<", ">", ".", "@", "john", "x", "com", "oh", "one", "plus", "five", "7", "-")
    plain = (pii._ODD, lambda s: [(pii._plain_letter(s), 0, 1)])
    at, dot = (lambda s: [("@", 0, len(s))]), (lambda s: [(".", 0, len(s))])
    for _ in range(8000):
        text = "".join(rng.choice(parts) for _ in range(rng.randint(1, 14)))
        seen = pii.Rewritten(text)
        for pattern, rewrite in (plain, (pii._AT, at), (pii._SPACED_AT, at), (pii._DOT, dot), (pii._SPELLED, pii._spell_out)):
            seen.apply(pattern, rewrite)
        spans = {k: [seen.source(s) for s in v if k != "email" or seen.text[s[0] : s[1]].rpartition(".")[2].isalpha()] for k, v in pii.plain_spans(seen.text).items()}
        known = pii.plain_spans(text)
        want = {k: [s for s in v if not any(s[0] < e and b < s[1] for b, e in known[k])] for k, v in spans.items()}
        assert pii.disguised_spans(text, known) == want, text


def test_very_long_disguised_texts_are_read_in_linear_time():
    n = 100_000
    blanks = "x at y.org" + " " * n + "dot"
    texts = [blanks, "[" + " " * n + "at ] x", "( " * (n // 2) + "at", "john [at] " + "a." * (n // 2), "0" * n + "1.1.1.1", "1." * (n // 2), "plus " * (n // 5), "plus" + " " * n + "one", "one " * (n // 4), "1 " * (n // 2) + "x", "at" * (n // 2) + " dot", "a at b dot c " * (n // 13), "ａ@b.co " * (n // 7), "1.2.3.4 " * (n // 8) + "five", "5" * n + "a", "one-" * (n // 4), ". " * (n // 2) + "]", "@" * n, "+1 " * (n // 3), "а" * n]
    for text in texts:
        began = time.process_time()
        pii.disguised_spans(text, pii.plain_spans(text))
        assert time.process_time() - began < 2, text[:20]
    found = pii.plain_spans("0" * 5000 + "1.1.1.1 " + "9" * 5000 + ".1.1.1")["ip"]
    assert found == [(0, 5007)]


def test_added_spans_touch_no_plain_ones():
    rng = random.Random(8)
    for _ in range(2000):
        cuts = sorted(rng.sample(range(60), 8))
        known = list(zip(cuts[::2], cuts[1::2]))
        spans = [(a, a + rng.randint(1, 12)) for a in rng.sample(range(60), 6)]
        assert pii.without_overlaps(spans, known) == [s for s in spans if not any(s[0] < e and b < s[1] for b, e in known)]
