"""Quality rules: counts of each whole text, and a calibrated logistic regression on hashed n-grams.

The regression sees every word, every pair of neighbouring words and every run of three characters of a text,
hashed into fixed ranges. A feature weighs the logarithm of its count, and the features of words and those of
characters are scaled to length one each, so texts of any length are comparable. It is trained on at most
``most_labelled`` labelled documents, those of least id hash, and calibrated on folds left out; scoring runs in
Arrow batches and keeps documents whose chance of good quality reaches a fixed threshold.

Defined results: null and empty texts have no words and fail the base rules; very long texts are measured whole;
repeated rows are scored alike, and a labelled id with several texts is learned from its least text alone;
labels that are null or lack a document are not learned from, an id with several labels counts as the least;
without labels of both kinds the score is constant; an empty table gives no rows; columns that are not kept are
dropped, a kept one that clashes with a result column is replaced.
"""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphweave.llm import logistic
from graphweave.llm.common import map_texts

_SYMBOLS = "#*$%&|<>"
_WHITE = " \t\n\x0b\x0c\r"
#: Bits of the ranges that n-grams of words and of characters are hashed into.
_WORD_BITS, _CHAR_BITS = 18, 15
WIDTH = (1 << _WORD_BITS) + (1 << _CHAR_BITS) + 32
_A, _B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)
#: Base rules: fewest words, and the largest share (in hundredths) of words in repeated windows.
FEWEST_WORDS, MOST_REPEATED, WINDOW = 10, 20, 5


def repeated_words(ids: np.ndarray, window: int = WINDOW) -> int:
    """Words inside windows that occur at least twice, the first occurrence included."""
    n = len(ids) - window + 1
    if n < 2:
        return 0
    code = np.zeros(n, np.uint64)
    for k in range(window):  # a polynomial over mixed 64-bit word numbers
        code = code * np.uint64(0x9E3779B97F4A7C15) + (ids[k : k + n].astype(np.uint64) + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93)
        code ^= code >> np.uint64(29)
    order = np.argsort(code, kind="stable")
    same = code[order][1:] == code[order][:-1]
    twice = np.zeros(n, bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    if not twice.any():
        return 0
    edges = np.zeros(len(ids) + 1, np.int64)
    at = np.flatnonzero(twice)
    np.add.at(edges, at, 1)
    np.add.at(edges, at + window, -1)
    return int((np.cumsum(edges)[:-1] > 0).sum())


def _scaled(counts: np.ndarray) -> np.ndarray:
    values = np.log1p(counts)
    return values / max(1e-9, np.sqrt((values * values).sum()))


def measure(text: str) -> tuple[dict[str, int], tuple[np.ndarray, np.ndarray]]:
    """Counts of a text, and the hashed features of the regression with their values."""
    words = text.encode("utf-8", "surrogatepass").split()
    numbers: dict[bytes, int] = {}
    ids = np.array([numbers.setdefault(w, len(numbers)) for w in words], np.int64)
    lines = [line for line in text.split("\n") if line.strip(_WHITE)]
    counts = {
        "n_words": len(words),
        "word_chars": len(text) - sum(map(text.count, _WHITE)),
        "n_symbols": sum(map(text.count, _SYMBOLS)),
        "n_dup_lines": len(lines) - len(set(lines)),
        "n_repeat_words": repeated_words(ids),
    }
    found, values = [np.array([WIDTH - 32 + min(31, int(np.log2(len(words) + 1)))])], [np.ones(1)]
    if words:
        hashes = np.array([zlib.crc32(w.lower()) for w in numbers], np.uint64)[ids]
        grams = np.concatenate([hashes * _A, (hashes[:-1] * _B + hashes[1:]) * _A + np.uint64(1)])
        at, n = np.unique((grams ^ grams >> np.uint64(29)) * _B >> np.uint64(64 - _WORD_BITS), return_counts=True)
        found.append(at.astype(np.int64))
        values.append(_scaled(n))
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    if len(points) >= 3:
        grams = (points[:-2] * _A ^ points[1:-1]) * _B + points[2:]
        share = np.bincount(((grams ^ grams >> np.uint64(31)) * _A >> np.uint64(64 - _CHAR_BITS)).astype(np.int64), minlength=1 << _CHAR_BITS)
        at = np.flatnonzero(share)
        found.append(at + (1 << _WORD_BITS))
        values.append(_scaled(share[at]))
    return counts, (np.concatenate(found), np.concatenate(values))


def fails(counts: dict[str, int]) -> bool:
    return counts["n_words"] < FEWEST_WORDS or 100 * counts["n_repeat_words"] > MOST_REPEATED * counts["n_words"]


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", label_col: str = "quality", text_col: str = "text", most_labelled: int = 4000) -> tuple[np.ndarray, float]:
    """Weights of the hashed features and bias of the chance of good quality."""
    known = labels.where(F.col(label_col).isNotNull()).groupBy(F.col(id_col).alias("__id")).agg(F.min(label_col).cast("double").alias("__label"))
    known = known.orderBy(F.xxhash64("__id"), "__id").limit(most_labelled)  # a documented bound of the training set
    texts = docs.select(F.col(id_col).alias("__id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).join(F.broadcast(known), "__id")
    texts = texts.groupBy("__id", "__label").agg(F.min("text").alias("text"))
    fields = [("at", T.ArrayType(T.IntegerType())), ("value", T.ArrayType(T.FloatType()))]

    def kernel(batch: list[str]) -> list:
        found = [measure(t)[1] for t in batch]
        return [[at for at, _ in found], [value for _, value in found]]

    rows = map_texts(texts, lambda: kernel, fields, ("__id", "__label")).toArrow().sort_by("__id")
    lists = [rows[c].combine_chunks() for c in ("at", "value")]
    ends = lists[0].offsets.to_numpy() if len(rows) else np.zeros(1, np.int64)
    at, value = (x.values.to_numpy() if len(rows) else np.zeros(0) for x in lists)
    features = [(at[a:b], value[a:b].astype(float)) for a, b in zip(ends, ends[1:])]
    return logistic.train_weighted(features, rows["__label"].to_numpy(), WIDTH)


def judge(docs: DataFrame, labels: DataFrame, keep: tuple[str, ...] = ("doc_id",), id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """Columns ``keep`` with the counts, base_failed, the regression's score and kept."""
    weights, bias = train(docs, labels, id_col, "quality", text_col)
    weights = weights.astype(np.float32)
    columns = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")

    def kernel(texts: list[str]) -> list:
        out: list[list] = [[] for _ in range(len(columns) + 3)]
        for text in texts:
            counts, (at, values) = measure(text)
            score = float(logistic.sigmoid(bias + weights[at] @ values))
            failed = fails(counts)
            for column, value in zip(out, [*(counts[c] for c in columns), failed, score, not failed and score >= threshold]):
                column.append(value)
        return out

    fields = [*((c, T.LongType()) for c in columns), ("base_failed", T.BooleanType()), ("score", T.DoubleType()), ("kept", T.BooleanType())]
    return map_texts(docs, lambda: kernel, fields, keep, text_col)
