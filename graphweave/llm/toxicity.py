"""Toxicity of noisy text: a noisy channel is decoded before the restored words are scored.

Every token opens a lattice of the characters it may stand for: a sign or figure is a look-alike letter or
noise, a repeated character is written once or as often as it stands there, a separator inside a token and a
blank between fragments is a word boundary or noise. A Viterbi search over the lattice, under a character
language model of order four with counts from the whole corpus and costs of the channel's steps, gives the
likeliest words. A lattice of one path (letters without repeats) is its own reading and is not searched. Blanks
are open where letters stand apart in a run, and between a word of at most three letters and its neighbour where
the language model prefers the two as one. Tokens and runs of any length are decoded whole, in linear time.

A logistic regression on restored words and their beginnings, trained and calibrated on labelled documents,
scores each whole text. A token of figures alone is a number and not decoded; plain readings of a token count
beside the decoded ones.

Training takes at most ``most_labelled`` labelled documents, those of least id hash. Counts of the language
model and scores cover all documents. Label, language, source and id are no inputs of a score.

Defined results: null and empty texts score as texts without words; very long texts are scored whole; repeated
rows score alike, and a labelled id with several texts is learned from its least text alone; labels that are
null or lack a document are not learned from, an id with several labels counts as the largest; without labels of
both kinds all scores are constant; an empty table gives no rows; columns that are not kept are dropped, a kept
one that clashes with the score is replaced.
"""

from __future__ import annotations

import re
import unicodedata
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphweave.llm import logistic
from graphweave.llm.common import map_texts

# What a sign may stand for in disguised words.
LOOKALIKES = {
    "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "gb", "7": "t", "8": "b", "9": "g",
    "@": "a", "$": "s", "!": "il", "|": "il", "+": "t", "(": "c", "€": "e", "£": "l", "¥": "y",
}

_LETTERS = 27  # a to z and the word boundary 0
_SWAP, _SKIP_SIGN, _SKIP_SECOND, _SKIP_MORE, _LOSE = 0.7, 1.2, 3.0, 0.3, 5.0
#: Costs of dropping a separator or blank between fragments, and between longer parts; of a boundary among single letters.
_DROP, _JOIN, _BREAK = 0.1, 3.0, 0.5
_EDGES = "".join(map(chr, [*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)])) + "«»“”‘’…–—¡¿"


@lru_cache(maxsize=1)
def _folded() -> np.ndarray:
    """Number of the base letter of every codepoint, 0 if it has none."""
    fold = np.zeros(0x110000, np.int32)
    for cp in range(0x2000):
        base = unicodedata.normalize("NFKD", chr(cp))[:1].lower()
        if "a" <= base <= "z":
            fold[cp] = ord(base) - 96
    fold[ord("ß")] = 19
    return fold


def _gram_counts(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    codes = _folded()[np.frombuffer((" ".join(["", *texts]) + "   ").encode("utf-32-le", "surrogatepass"), np.uint32)]
    grams = ((codes[:-3] * _LETTERS + codes[1:-2]) * _LETTERS + codes[2:-1]) * _LETTERS + codes[3:]
    counts = np.bincount(grams, minlength=_LETTERS**4)
    at = np.flatnonzero(counts)
    return at, counts[at]


def count_grams(docs: DataFrame, text_col: str = "text") -> np.ndarray:
    """Counts of all four-letter windows of the corpus; what reaches the driver is bounded by the alphabet."""

    def run(batches):
        total = np.zeros(_LETTERS**4, np.int64)
        for batch in batches:
            texts = [t for t in batch.column(0).to_pylist() if t]
            while texts:
                part, size = [], 0
                while texts and size < 2_000_000:
                    part.append(texts.pop())
                    size += len(part[-1])
                at, counts = _gram_counts(part)
                total[at] += counts
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], names=["gram", "n"])

    rows = docs.select(text_col).mapInArrow(run, "gram int, n long").groupBy("gram").agg(F.sum("n").alias("n"))
    made = rows.toArrow()
    counts = np.zeros(_LETTERS**4)
    counts[made["gram"].to_numpy()] = made["n"].to_numpy()
    return counts


def letter_costs(counts: np.ndarray, weight: float = 4.0) -> np.ndarray:
    """-log P(letter | three before), each order backed by the next lower one; indexed by the window's number."""
    n = counts.reshape((_LETTERS,) * 4)
    p = np.full(_LETTERS, 1 / _LETTERS)
    for order in range(4):
        c = n.sum(axis=tuple(range(3 - order))) if order < 3 else n
        p = (c + weight * p) / (c.sum(axis=-1, keepdims=True) + weight)
    return (-np.log(p)).astype(np.float32).reshape(-1)


@lru_cache(maxsize=100_000)
def _readings(ch: str) -> tuple[tuple[int, str, float], ...] | None:
    """What a character may be, wherever it stands; None for a separator."""
    if _APART.match(ch) and ch not in LOOKALIKES:
        return None
    if letter := int(_folded()[ord(ch)]):
        return ((letter, ch, 0.0),)
    if ch.isalpha():
        return ((-1, ch, 0.0),)
    swaps = tuple((ord(x) - 96, x, _SWAP) for x in LOOKALIKES.get(ch, ""))
    return (*swaps, (-1, "", _LOSE if ch.isdigit() else _SKIP_SIGN if ch in LOOKALIKES else _DROP))


class Restorer:
    """Restores words of one text at a time; tokens are looked up in a bounded cache."""

    def __init__(self, costs: np.ndarray, most: int = 300_000):
        self.table, self.costs, self.most = costs, costs.tolist(), most
        self.cache, self.decoded = {}, {}

    @staticmethod
    def steps(token: str) -> list[tuple[tuple[int, str, float], ...]]:
        """For each character the (letter, what is written, cost) it may be; letter 0 is a boundary, -1 changes no context."""
        out = list(map(_readings, token))
        if None in out:
            sizes = [len(p) for p in _APART.split(token)]
            part, inside = 0, False
            for i, known in enumerate(out):
                if known is None:
                    part += inside
                    longest = max(sizes[max(0, part - 1) : part + 1], default=0)
                    drop, broken = (_DROP, _BREAK) if longest <= 1 else (_DROP, _DROP) if longest <= 2 and token[i] != " " else (_JOIN, 0.0)
                    out[i] = ((-1, "", drop), (0, " ", broken))
                inside = known is not None
        for twice in _TWICE.finditer(token):
            i = twice.start() + 1
            while i < len(token) and token[i] == token[i - 1]:
                if _readings(token[i]):
                    out[i] = (*out[i], (-1, "", _SKIP_MORE if i > 1 and token[i - 2] == token[i] else _SKIP_SECOND))
                i += 1
        return out

    def best(self, token: str) -> tuple[float, str]:
        """Cost and reading of the cheapest path; states are the last three letters, as one number."""
        costs, square = self.costs, _LETTERS**2
        states: dict[int, tuple[float, tuple | None]] = {0: (0.0, None)}
        for steps in self.steps(token):
            if len(states) == 1 and len(steps) == 1 and steps[0][0] > 0:  # the common case of the loop below
                head, (cost, path) = states.popitem()
                letter, written, step = steps[0]
                states[head % square * _LETTERS + letter] = cost + step + costs[head * _LETTERS + letter], (path, written)
                continue
            after: dict[int, tuple[float, tuple | None]] = {}
            for head, (cost, path) in states.items():
                row, kept = head * _LETTERS, head % square * _LETTERS
                for letter, written, step in steps:
                    if letter > 0 or letter == 0 and head % _LETTERS:
                        total, key = cost + step + costs[row + letter], kept + letter
                    else:
                        total, key = cost + step, head
                    known = after.get(key)
                    if known is None or total < known[0]:
                        after[key] = (total, (path, written) if written else path)
            states = after
        cost, path = min(((c + (costs[head * _LETTERS] if head % _LETTERS else 0.0), path) for head, (c, path) in states.items()), key=lambda x: x[0])
        written = []
        while path:
            path, last = path
            written.append(last)
        return cost, "".join(reversed(written))

    def decode(self, token: str) -> tuple[str, ...]:
        """The likeliest words behind a token, or behind tokens with blanks between them."""
        found = self.decoded.get(token)
        if found is None:
            if len(self.decoded) >= self.most:
                self.decoded.clear()
            found = self.decoded[token] = tuple(self.best(token)[1].split())
        return found

    def word(self, token: str) -> tuple[str, ...]:
        """Restored words of a token without white space, in lower case."""
        if token.isalpha():
            return (token,) if not _TWICE.search(token) else tuple({token, *self.decode(token)})
        core = token.strip(_EDGES)
        inner = token.strip(_PLAIN_EDGES)
        if core.isalpha() and not _TWICE.search(core):
            return (core,) if core == inner else tuple(dict.fromkeys([core, *self.decode(inner)]))
        parts = [p for p in _APART.split(core) if p]
        if all(p.isdigit() for p in parts) and all(c.isdigit() or c not in LOOKALIKES for c in inner):
            return tuple(parts)
        plain = [p for p in parts if p.isalpha()]
        if core == inner and len(plain) == len(parts) and min(map(len, parts), default=3) > 2 and not _TWICE.search(core):
            return tuple(plain)
        return tuple(dict.fromkeys([*plain, *self.decode(inner)]))

    def open_blanks(self, text: str) -> np.ndarray:
        """Places of single blanks between letters, a word of at most three of them on one side, that the language model would rather drop.

        Whether it does depends on three letters on either side, so all blanks of a text are judged at once.
        """
        points = np.frombuffer(f"   {text}   ".encode("utf-32-le", "surrogatepass"), np.uint32)
        c = _folded()[points]
        at = np.flatnonzero((c[3:-3] == 0) & (c[2:-4] > 0) & (c[4:-2] > 0)) + 3
        at = at[(points[at] == 32) | (points[at] == 10) | (points[at] == 9)]
        x, y, z, u, v, w = (c[at + k].astype(np.int64) for k in (-3, -2, -1, 1, 2, 3))
        before, after = np.minimum(at, 4), np.minimum(len(c) - 1 - at, 4)
        short = (x == 0) | (y == 0) | (c[at - before] == 0) | (v == 0) | (w == 0) | (c[at + after] == 0)
        at, x, y, z, u, v, w = (a[short] for a in (at, x, y, z, u, v, w))
        x = np.where(y == 0, 0, x)
        cost = lambda a, b, c, d: self.table[((a * _LETTERS + b) * _LETTERS + c) * _LETTERS + d]
        rest = np.where(v > 0, 1.0, 0.0)  # what follows the end of the right word is the same either way
        apart = cost(x, y, z, 0) + cost(y, z, 0, u) + cost(z, 0, u, v) + rest * cost(0, u, v, w)
        joined = cost(x, y, z, u) + cost(y, z, u, v) + rest * cost(z, u, v, w)
        return at[joined + _JOIN < apart] - 3

    def _fragments(self, text: str) -> list[str]:
        """Runs of tokens, joined by blanks, whose blanks are open: letters set apart, and fragments of words."""
        runs = []
        for found in _SET_APART.finditer(text):
            run: list[str] = []
            for t in [*found.group().split(), ""]:
                if t and (t.isalpha() or t in LOOKALIKES):
                    run.append(t)
                else:
                    if len(run) >= 3:
                        runs.append(" ".join(run))
                    run = []
        end = -1
        places = self.open_blanks(text).tolist()
        for i, place in enumerate(places):
            if place < end:
                continue
            begin, end, k = place, place, i
            while begin and not text[begin - 1].isspace():
                begin -= 1
            while k < len(places) and places[k] == end:
                end += 1
                while end < len(text) and not text[end].isspace():
                    end += 1
                k += 1
            runs.append(" ".join(text[begin:end].split()))
        return runs

    def words(self, text: str) -> set[str]:
        """All restored words of a text."""
        text = text.lower()
        out: set[str] = set()
        cache = self.cache
        for token in set(text.split()).union(self._fragments(text)):
            found = cache.get(token)
            if found is None:
                if len(cache) >= self.most:
                    cache.clear()
                found = cache[token] = self.decode(token) if " " in token else self.word(token)
            out.update(found)
        return out


_SET_APART = re.compile(r"(?<!\S)\S(?:\s+\S){2,}(?!\S)")
_TWICE = re.compile(r"(.)\1+")
_APART = re.compile(r"[\s.\-_*,;:/\\'\"~#%&<>\[\]{}=?]+")
_PLAIN_EDGES = "".join(c for c in _EDGES if c not in LOOKALIKES)


def features(word: str) -> list[int]:
    """Hashes of a word and of its beginnings."""
    raw = word.encode("utf-8", "surrogatepass")
    return [zlib.crc32(b"=" + raw), *(zlib.crc32(b"^" + word[:k].encode("utf-8", "surrogatepass")) for k in range(4, min(9, len(word))))]


class Scorer:
    def __init__(self, costs: np.ndarray, chosen: np.ndarray, weights: np.ndarray, bias: float):
        self.restorer = Restorer(costs)
        self.weights = dict(zip(chosen.tolist(), weights.tolist()))
        self.bias, self.cache = bias, {}

    def score(self, text: str) -> float:
        hit: set[int] = set()
        cache = self.cache
        for word in self.restorer.words(text):
            found = cache.get(word)
            if found is None:
                if len(cache) >= 300_000:
                    cache.clear()
                found = cache[word] = tuple(f for f in features(word) if f in self.weights)
            if found:
                hit.update(found)
        return float(logistic.sigmoid(self.bias + sum(sorted(self.weights[f] for f in hit))))


def train(docs: DataFrame, labels: DataFrame, costs: np.ndarray, id_col: str = "doc_id", label_col: str = "toxic", text_col: str = "text", learnable: Column | None = None, most_labelled: int = 4000):
    """The model's chosen features, weights and bias."""
    known = labels.where(F.col(label_col).isNotNull())
    known = known.where(learnable) if learnable is not None else known
    known = known.groupBy(F.col(id_col).alias("__id")).agg(F.max(label_col).cast("double").alias("__label"))
    known = known.orderBy(F.xxhash64("__id"), "__id").limit(most_labelled)  # a documented bound of the training set
    texts = docs.select(F.col(id_col).alias("__id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).join(F.broadcast(known), "__id")
    texts = texts.groupBy("__id", "__label").agg(F.min("text").alias("text"))

    def make():
        restorer = Restorer(costs)

        def kernel(texts: list[str]) -> list:
            return [[sorted({f for w in restorer.words(t) for f in features(w)}) for t in texts]]

        return kernel

    rows = map_texts(texts, make, [("features", T.ArrayType(T.LongType()))], ("__id", "__label")).toArrow()
    rows = rows.sort_by("__id")
    lists = [np.array(x, np.int64) for x in rows["features"].to_pylist()]
    return logistic.train(lists, rows["__label"].to_numpy(), least_df=3, most=3000)


def score_documents(docs: DataFrame, labels: DataFrame, keep: tuple[str, ...] = ("doc_id",), id_col: str = "doc_id", text_col: str = "text", learnable: Column | None = None, score_col: str = "score") -> DataFrame:
    """Columns ``keep`` with the score: the chance, from 0 to 1, that a document is toxic."""
    costs = letter_costs(count_grams(docs, text_col))
    chosen, weights, bias = train(docs, labels, costs, id_col, "toxic", text_col, learnable)

    def make():
        scorer = Scorer(costs, chosen, weights, bias)
        return lambda texts: [[scorer.score(t) for t in texts]]

    return map_texts(docs, make, [(score_col, T.DoubleType())], keep, text_col)
