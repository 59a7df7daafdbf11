"""Personal data in plain and in disguised form, with spans that point into the source text.

The plain scan finds identifiers as written. A second scan sees the text through transducers: look-alike letters
and digits become ASCII, runs of spelled digits become figures, bracketed or spelled "at" and "dot" become their
signs. Each transducer writes, for every character it makes, the source characters it came from; identifiers
found in the rewritten text are mapped back by that and added where no plain span of their kind overlaps.

Both scans are linear in the text. Defined results: null and empty texts have no spans; repeated rows are
scanned each; texts of any length are scanned whole; a clashing column is replaced, columns not kept are dropped.
"""

from __future__ import annotations

import re
import unicodedata
from bisect import bisect_left
from functools import lru_cache

from pyspark.sql import DataFrame
from pyspark.sql import types as T

from graphweave.llm.common import map_texts

KINDS = ("email", "ip", "card", "phone")

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_DOTTED = re.compile(r"[0-9]+(?:\.[0-9]+)*")
_FIGURES = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PLUS = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")

Span = tuple[int, int]


def emails(text: str) -> list[Span]:
    out, floor, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > floor and text[start - 1] in _LOCAL:
            start -= 1
        match = _DOMAIN.match(text, at) if start < at else None
        if match:
            floor = match.end()
            out.append((start, floor))
        else:
            floor = max(floor, at + 1)  # no match starts before this sign any more
        at = text.find("@", floor)
    return out


def addresses(text: str) -> list[Span]:
    """Chains of dotted numbers are read four at a time, as a scan from the left does."""
    out = []
    for chain in _DOTTED.finditer(text):
        if chain.end() - chain.start() < 7:
            continue
        parts, at = chain.group().split("."), chain.start()
        for i in range(0, len(parts) - 3, 4):
            four = parts[i : i + 4]
            length = sum(map(len, four)) + 3
            if all(len(n := p.lstrip("0")) <= 3 and int(n or "0") <= 255 for p in four):
                out.append((at, at + length))
            at += length + 1
    return out


def passes_luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 if n > 9 else n
    return total % 10 == 0


def cards(text: str) -> list[Span]:
    out = []
    for match in _FIGURES.finditer(text):
        if match.end() - match.start() >= 16:
            digits = match.group().replace(" ", "").replace("-", "")
            if 16 <= len(digits) <= 19 and passes_luhn(digits):
                out.append(match.span())
    return out


def phones(text: str) -> list[Span]:
    if "+" not in text:
        return []
    return [m.span() for m in _PLUS.finditer(text) if 8 <= sum("0" <= c <= "9" for c in m.group()) <= 15]


_SCANS = dict(zip(KINDS, (emails, addresses, cards, phones)))


def plain_spans(text: str) -> dict[str, list[Span]]:
    return {kind: scan(text) for kind, scan in _SCANS.items()}


# Cyrillic and Greek letters that look like ASCII ones.
_LOOKALIKES = dict(zip("асеорхуіјѕԁһӏԛԝАВЕКМНОРСТХУІЈЅαορνκιεΑΒΕΖΗΙΚΜΝΟΡΤΥΧ", "aceopxyijsdhlqwABEKMHOPCTXYIJSaopvkieABEZHIKMNOPTYX"))
_DIGITS = ("zero", "one", "two", "three", "four", "five", "six", "seven", "eight", "nine")
_SPOKEN = (*_DIGITS, "oh", "plus")
_VALUE = {w: str(i) for i, w in enumerate(_DIGITS)} | {"oh": "0", "plus": "+"}

_ODD = re.compile("[­Ͱ-֏٠-٩۰-۹०-९​-‏‐-―․⁠−。﹒﹫﻿！-～\U0001d400-\U0001d7ff]")
_SPELLED = re.compile(r"(?i)(?<![a-z0-9])(?:plus[ -]+)?(?:(?:zero|oh|one|two|three|four|five|six|seven|eight|nine|[0-9]+)(?:[ .-]+(?=[a-z0-9+])|(?![a-z]))){4,}")
_TOKEN = re.compile(r"(?i)[a-z]+|[0-9]+")
# A run of blanks is entered at its first blank alone, so that runs that lead nowhere are read once.
_AT = re.compile(r"(?i)(?:(?<![ ])[ ]+)?[\[({<][ ]*(?:at|@)[ ]*[\])}>][ ]*")
_SPACED_AT = re.compile(r"(?i)(?<=[a-z0-9])[ ]+at[ ]+(?=[a-z0-9-]+(?:\.|[ ]+dot[ ]+|[ ]*[\[({<][ ]*(?:dot|\.)[ ]*[\])}>])[ ]*[a-z0-9])")
_DOT = re.compile(r"(?i)(?:(?<![ ])[ ]+)?[\[({<][ ]*(?:dot|\.)[ ]*[\])}>][ ]*|(?<=[a-z0-9])[ ]+dot[ ]+(?=[a-z0-9])")
_MARKED_DOT = re.compile(r"\.[ ]*[\])}>]")


@lru_cache(maxsize=100_000)
def _plain_letter(ch: str) -> str:
    if ch in _LOOKALIKES:
        return _LOOKALIKES[ch]
    if unicodedata.category(ch) == "Cf":
        return ""
    if unicodedata.category(ch) == "Pd" or ch == "−":
        return "-"
    if ch in "․。":
        return "."
    if (digit := unicodedata.decimal(ch, None)) is not None:
        return str(digit)
    folded = unicodedata.normalize("NFKC", ch)
    return folded if folded.isascii() else ch


class Rewritten:
    """A text with, for each character, the source range that it stands for."""

    def __init__(self, text: str):
        self.text, self.begin, self.end = text, list(range(len(text))), list(range(1, len(text) + 1))
        self.changed = False

    def apply(self, pattern: re.Pattern, rewrite) -> None:
        out, begin, end, last = [], [], [], 0
        for match in pattern.finditer(self.text):
            a, b = match.span()
            pieces = rewrite(match.group())  # (written, first, last) relative to the match
            if pieces is None or a == b:
                continue
            out.append(self.text[last:a])
            begin += self.begin[last:a]
            end += self.end[last:a]
            for written, i, j in pieces:
                out.append(written)
                begin += [self.begin[a + i]] * len(written)
                end += [self.end[a + j - 1]] * len(written)
            last, self.changed = b, True
        if last:
            self.text = "".join([*out, self.text[last:]])
            self.begin, self.end = begin + self.begin[last:], end + self.end[last:]

    def source(self, span: Span) -> Span:
        return self.begin[span[0]], self.end[span[1] - 1]


def _spell_out(found: str):
    tokens = [(m.group().lower(), *m.span()) for m in _TOKEN.finditer(found)]
    if not any(t in _VALUE for t, _, _ in tokens):
        return None
    gaps = []
    for (token, i, j), following in zip(tokens, [*tokens[1:], None]):
        gaps.append((_VALUE.get(token, token), i, j))
        if following and "." in found[j : following[1]]:
            gaps.append((".", j, following[1]))
    if tokens and tokens[-1][2] < len(found):
        gaps.append((found[tokens[-1][2] :], tokens[-1][2], len(found)))
    return gaps


def disguised_spans(text: str, plain: dict[str, list[Span]]) -> dict[str, list[Span]]:
    """Spans that only the rewritten text shows."""
    none: dict[str, list[Span]] = {kind: [] for kind in KINDS}
    seen = _Lazy(text)
    if not text.isascii():
        seen.apply(_ODD, lambda s: [(_plain_letter(s), 0, 1)])
    # What the other transducers need is looked for in what this one made; each test holds wherever its pattern matches.
    low = seen.text.lower()
    if "at" in low or "@" in low:
        seen.apply(_AT, lambda s: [("@", 0, len(s))])
        if "at" in low:
            seen.apply(_SPACED_AT, lambda s: [("@", 0, len(s))])
    if "dot" in low or _MARKED_DOT.search(low):
        seen.apply(_DOT, lambda s: [(".", 0, len(s))])
    if sum(map(low.count, _SPOKEN)):
        seen.apply(_SPELLED, _spell_out)
    if not seen.changed:
        return none
    out = {}
    for kind, spans in plain_spans(seen.text).items():
        mapped = [seen.source(s) for s in spans if kind != "email" or seen.text[s[0] : s[1]].rpartition(".")[2].isalpha()]
        out[kind] = without_overlaps(mapped, plain[kind])
    return out


def without_overlaps(spans: list[Span], known: list[Span]) -> list[Span]:
    """The spans that touch none of the known ones, which are sorted and apart."""
    starts = [b for b, _ in known]

    def free(span: Span) -> bool:
        at = bisect_left(starts, span[1])
        return at == 0 or known[at - 1][1] <= span[0]

    return [s for s in spans if free(s)]


class _Lazy(Rewritten):
    """Builds the ranges only when a rewrite comes."""

    def __init__(self, text: str):
        self.text, self.changed, self.ready = text, False, False

    def apply(self, pattern: re.Pattern, rewrite) -> None:
        if pattern.search(self.text):
            if not self.ready:
                super().__init__(self.text)
                self.ready = True
            changed = self.changed
            super().apply(pattern, rewrite)
            self.changed |= changed


def joined(spans: dict[str, list[Span]]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for kind in KINDS for a, b in spans[kind])


def find_personal_data(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), text_col: str = "text") -> DataFrame:
    """Columns ``keep`` with base and all spans: arrays of (kind, start, end) in code points, by kind, then start."""
    span = T.StructType([T.StructField("kind", T.StringType()), T.StructField("start", T.LongType()), T.StructField("end", T.LongType())])
    kind = T.ArrayType(span)

    def listed(spans: dict[str, list[Span]]) -> list[dict]:
        return [{"kind": k, "start": a, "end": b} for k in KINDS for a, b in spans[k]]

    def kernel(texts: list[str]) -> list:
        base, every = [], []
        for text in texts:
            plain = plain_spans(text)
            more = disguised_spans(text, plain)
            base.append(listed(plain))
            every.append(listed({k: sorted(plain[k] + more[k]) for k in KINDS}) if any(more.values()) else base[-1])
        return [base, every]

    return map_texts(docs, lambda: kernel, [("base_spans", kind), ("all_spans", kind)], keep, text_col)


def redact(text: str, spans: list[Span], mark: str = "[removed]") -> str:
    """The text with spans replaced; overlapping ones are replaced as one."""
    out, last = [], 0
    for a, b in sorted(spans):
        if b > last:
            out += [text[last:a], mark] if a >= last else []
            last = b
    return "".join([*out, text[last:]])
