import base64
import random

import public_tokenizers
import pytest
import tiktoken

from graphweave.llm.byte_bpe import Vocabulary, decode_documents, encode_documents, piece_starts

PATH = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


@pytest.fixture(scope="module")
def reference():
    with open(PATH, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_matches_the_library(reference):
    rng = random.Random(1)
    texts = ["".join(rng.choice("ab'sremdlvtST  \n\t\r 12é.,!Ä中　 '") for _ in range(rng.randint(0, 60))) for _ in range(5000)]
    texts += ["", " ", "\n", "a" * 5000, "ab" * 3000, "!?" * 400, "'s'll're  've", "it's they'll I'm''s", "x" * 64 + " " + "y" * 65, "<|endoftext|>"]
    small = Vocabulary(PATH, most=50)  # the cache is emptied again and again
    for vocabulary in (Vocabulary(PATH), small):
        for a in range(0, len(texts), 700):
            part = texts[a : a + 700]
            assert vocabulary.encode(part)[0] == [reference.encode_ordinary(t) for t in part]


def test_offsets_cut_the_text_into_its_pieces():
    ids, offsets = (v := Vocabulary(PATH)).encode(["Hello there, it's 42 élan  vital\n"])
    text = "Hello there, it's 42 élan  vital\n"
    ends = [*offsets[0].tolist()[1:], len(text)]
    pieces = [text[a:b] for a, b in zip(offsets[0], ends)]
    assert pieces == ["Hello", " there", ",", " it", "'s", " 42", " élan", " ", " vital", "\n"]
    assert v.decode(ids[0]).decode() == text


def test_scan_does_not_depend_on_neighbours():
    joined, starts = piece_starts(["a b", "", "'s"])
    assert joined == "a b\n\n's\n" and starts.tolist() == [0, 1, 3, 4, 5, 7]


def test_documents(spark, reference):
    rows = [(1, None, "x"), (2, "", "y"), (3, "two words", "z"), (3, "two words", "z"), (None, "é" * 3000, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, ids string")
    encoded = encode_documents(docs, PATH)
    out = decode_documents(encoded, PATH).collect()
    want = sorted((str(i), reference.encode_ordinary(t or "")) for i, t, _ in rows)
    assert sorted((str(r.doc_id), list(r.ids)) for r in out) == want
    assert sorted(bytes(r.decoded).decode() for r in out) == sorted((t or "") for _, t, _ in rows)
    assert decode_documents(encode_documents(docs.limit(0), PATH), PATH).count() == 0
