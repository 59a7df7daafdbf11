"""Byte-level BPE encoding and decoding with vectorised pre-tokenisation.

Pre-tokenisation uses no regex. Every character gets a symbol from a codepoint-class array (letter, number,
white space, other) and its next two characters; a small automaton over these symbols says where pieces
start. Its run is computed as a scan of transition functions: blocks of characters compose their functions
side by side, the functions of the blocks are chained, and a second sweep with known entry states marks the
starts. Pieces go through a cached pair merge; piece offsets are kept, so ids map back to characters.

Defined results: a null or empty text has no ids and decodes to no bytes; repeated rows are encoded each;
extra columns are dropped unless named in ``keep``; texts of any length are encoded whole.
"""

from __future__ import annotations

import base64
import gc
import heapq
import sys
from functools import lru_cache
from itertools import chain

import numpy as np
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphweave.llm.common import map_texts

# The white space of the Unicode White_Space property.
_SPACES = (*range(0x09, 0x0E), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)

_LETTER, _NUMBER, _OTHER, _SPACE = range(4)

# Symbols of the automaton.
_S_LETTER, _S_NUMBER, _S_OTHER, _S_SHORT, _S_LONG, _S_GAP, _S_BLANK, _S_LAST, _S_CUT = range(9)
# States: the kind of the piece that is open after a character.
_LETTERS, _NUMBERS, _OTHERS, _GAP, _BLANK, _ONE_MORE, _TWO_MORE, _CLOSED = range(8)

_BLOCK = 256
#: Stands for a pair that no token joins.
_NONE = 1 << 40


@lru_cache(maxsize=1)
def codepoint_classes() -> np.ndarray:
    """Class of every codepoint, as one byte each; the Unicode tables are those of the regex library."""
    classes = np.full(sys.maxunicode + 1, _OTHER, np.uint8)
    points = np.concatenate([np.arange(0xD800, dtype="<u4"), np.arange(0xE000, sys.maxunicode + 1, dtype="<u4")])
    every = points.tobytes().decode("utf-32-le")  # not joined from characters: a list of all would take 90 MB
    for found, kind in ((r"\p{L}+", _LETTER), (r"\p{N}+", _NUMBER)):
        for run in regex.finditer(found, every):
            classes[points[run.start() : run.end()]] = kind
    classes[list(_SPACES)] = _SPACE
    return classes


@lru_cache(maxsize=1)
def _automaton() -> tuple[np.ndarray, np.ndarray]:
    """(next state, does a piece start) by symbol and state."""
    goes = np.zeros((9, 8), np.uint8)
    starts = np.ones((9, 8), bool)

    def rule(symbol: int, target: int, inside: dict[int, int]) -> None:
        goes[symbol] = target
        for state, after in inside.items():
            goes[symbol, state] = after
            starts[symbol, state] = False

    rule(_S_LETTER, _LETTERS, {_LETTERS: _LETTERS, _BLANK: _LETTERS, _ONE_MORE: _CLOSED, _TWO_MORE: _ONE_MORE})
    rule(_S_NUMBER, _NUMBERS, {_NUMBERS: _NUMBERS, _BLANK: _NUMBERS})
    rule(_S_OTHER, _OTHERS, {_OTHERS: _OTHERS, _BLANK: _OTHERS})
    rule(_S_SHORT, _ONE_MORE, {_OTHERS: _OTHERS, _BLANK: _OTHERS})
    rule(_S_LONG, _TWO_MORE, {_OTHERS: _OTHERS, _BLANK: _OTHERS})
    rule(_S_GAP, _GAP, {_GAP: _GAP})
    rule(_S_BLANK, _BLANK, {})
    rule(_S_LAST, _CLOSED, {})
    rule(_S_CUT, _CLOSED, {})
    return goes, starts


def _symbols(points: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """The automaton's symbols. cuts: places of the characters that separate texts."""
    kind = codepoint_classes()[points]
    kind[cuts] = _SPACE  # a text's end counts as white space for what precedes it
    out = np.array([_S_LETTER, _S_NUMBER, _S_OTHER, _S_GAP], np.uint8)[kind]
    space = np.flatnonzero(kind == _SPACE)
    space = space[space + 1 < len(kind)]
    last = space[kind[space + 1] != _SPACE]
    out[last] = np.where(points[last] == 0x20, _S_BLANK, _S_LAST)
    quote = np.flatnonzero(points == 0x27)
    if len(quote):
        padded = np.append(points, np.zeros(2, points.dtype))
        padded[cuts] = 0
        one, two = padded[quote + 1], padded[quote + 2]
        out[quote[np.isin(one, [ord(c) for c in "stmd"])]] = _S_SHORT
        pairs = [(ord(a), ord(b)) for a, b in ("re", "ve", "ll")]
        out[quote[np.logical_or.reduce([(one == a) & (two == b) for a, b in pairs])]] = _S_LONG
    out[cuts] = _S_CUT
    return out


def _scan(symbols: np.ndarray) -> np.ndarray:
    """Places where pieces start, by an associative scan of transition functions over blocks."""
    goes, starts = _automaton()
    step = (goes | starts.astype(np.uint8) << 3).reshape(-1)
    n = len(symbols)
    width = -(-n // _BLOCK)
    grid = np.full(width * _BLOCK, _S_CUT, np.uint8)
    grid[:n] = symbols
    rows = np.ascontiguousarray(grid.reshape(width, _BLOCK).T) << 3  # row i: the i-th character of every block
    # Functions of all blocks at once. Most become constant within a word; only the others stay eight wide.
    constant = np.zeros(width, np.uint8)
    open_at, open_functions = np.arange(width), np.tile(np.arange(8, dtype=np.uint8), (width, 1))
    known = np.zeros(width, bool)
    for i, row in enumerate(rows):
        constant = step.take(row | constant) & 7
        if len(open_at):
            open_functions = step.take(row[open_at][:, None] | open_functions) & 7
            if i % 8 == 7 or i == _BLOCK - 1:
                done = (open_functions == open_functions[:, :1]).all(axis=1)
                constant[open_at[done]] = open_functions[done, 0]
                known[open_at[done]] = True
                open_at, open_functions = open_at[~done], open_functions[~done]
    entry = np.empty(width, np.uint8)
    entry[0] = _CLOSED
    entry[1:] = constant[:-1]
    for at, function in zip(open_at.tolist(), open_functions):  # in order, so that an entry is known by then
        if at + 1 < width:
            entry[at + 1] = function[entry[at]]
    marks = np.empty(rows.shape, np.uint8)
    for i, row in enumerate(rows):
        marks[i] = step.take(row | entry)
        entry = marks[i] & 7
    return np.flatnonzero((marks >> 3).T.reshape(-1)[:n])


def piece_starts(texts: list[str]) -> tuple[str, np.ndarray]:
    """The texts joined by one separator each, and where pieces (and separators) start in that."""
    joined = "\n".join(texts) + "\n"
    points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    cuts = np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)) + 1) - 1
    return joined, _scan(_symbols(points, cuts))


class Vocabulary:
    """Ids of pieces, by piece. Missing pieces are merged in batches and cached; at ``most`` entries the cache is emptied."""

    def __init__(self, path: str, most: int = 500_000):
        self.cache: dict[str, tuple[int, ...]] = {}
        with open(path, "rb") as lines:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        size = max(self.ranks.values()) + 1
        self.bytes_of = [b""] * size
        for token, rank in self.ranks.items():
            self.bytes_of[rank] = token
        self.ints = list(range(size))  # one object for each id, however often it is used
        self.byte_ids = np.array([self.ranks[bytes([i])] for i in range(256)], np.int64)
        self.most = most
        self._index_pairs()

    def _index_pairs(self) -> None:
        """An open-addressing table from pairs of ids to the id of their join."""
        ranks = self.ranks
        found = (x for t, r in ranks.items() for i in range(1, len(t)) if t[:i] in ranks and t[i:] in ranks for x in (ranks[t[:i]], ranks[t[i:]], r))
        a, b, r = np.fromiter(found, np.int64).reshape(-1, 3).T
        keys = a << 32 | b
        self.shift = 64 - 20
        self.pair_keys, self.pair_ranks = np.full((1 << 20) + 64, -1, np.int64), np.full((1 << 20) + 64, _NONE, np.int64)
        left, probe = np.arange(len(keys)), self._slot(keys)
        self.probes = 0
        while len(left):
            self.probes += 1
            free = self.pair_keys[probe[left]] == -1
            first = np.unique(probe[left][free], return_index=True)[1]
            put = left[free][first]
            self.pair_keys[probe[put]], self.pair_ranks[probe[put]] = keys[put], r[put]
            left = left[~np.isin(left, put)]
            probe[left] += 1

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(self.shift)).astype(np.int64)

    def _pair_rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        shape = left.shape
        keys = (left << 32 | right).reshape(-1)
        slot = self._slot(keys)
        out = np.where(self.pair_keys[slot] == keys, self.pair_ranks[slot], _NONE)
        open_at = np.flatnonzero((self.pair_keys[slot] != keys) & (self.pair_keys[slot] != -1))
        for _ in range(self.probes):
            if not len(open_at):
                break
            slot[open_at] += 1
            seen = self.pair_keys[slot[open_at]]
            hit = seen == keys[open_at]
            out[open_at[hit]] = self.pair_ranks[slot[open_at[hit]]]
            open_at = open_at[~hit & (seen != -1)]
        return out.reshape(shape)

    def add(self, pieces: list[str]) -> None:
        """Merge pieces, those of like length side by side, and cache them."""
        by_width: dict[int, list[tuple[str, bytes]]] = {}
        for piece in pieces:
            raw = piece.encode("utf-8", "surrogatepass")
            if (rank := self.ranks.get(raw)) is not None:
                self.cache[piece] = (rank,)
            elif len(raw) > 64:
                self.cache[piece] = self._merge_long(raw)
            else:
                by_width.setdefault(-(-len(raw) // 4) * 4, []).append((piece, raw))
        for width, group in by_width.items():
            for a in range(0, len(group), 8192):
                part = group[a : a + 8192]
                for (piece, _), ids in zip(part, self._merge_short([raw for _, raw in part], width)):
                    self.cache[piece] = ids

    def _merge_short(self, raws: list[bytes], width: int) -> list[tuple[int, ...]]:
        """In each round every piece joins its pair of least rank, the leftmost of equals."""
        sizes = np.fromiter(map(len, raws), np.int64, len(raws))
        grid = np.frombuffer(b"".join(r.ljust(width, b"\0") for r in raws), np.uint8).reshape(len(raws), width)
        ids = self.byte_ids[grid]
        costs = np.full((len(raws), width), _NONE, np.int64)
        costs[:, :-1] = np.where(np.arange(1, width) < sizes[:, None], self._pair_rank(ids[:, :-1], ids[:, 1:]), _NONE)
        result: list[tuple[int, ...]] = [()] * len(raws)
        names, columns, ints = np.arange(len(raws)), np.arange(width), self.ints
        while len(names):
            at = costs.argmin(axis=1)
            line = np.arange(len(names))
            best = costs[line, at]
            ended = best == _NONE
            if ended.any():
                for name, row, size in zip(names[ended].tolist(), ids[ended].tolist(), sizes[ended].tolist()):
                    result[name] = tuple([ints[i] for i in row[:size]])
                live = ~ended
                names, ids, costs, sizes, at, best = names[live], ids[live], costs[live], sizes[live], at[live], best[live]
                line = np.arange(len(names))
                if not len(names):
                    break
            ids[line, at] = best
            source = columns + (columns > at[:, None])
            source[:, -1] = np.minimum(source[:, -1], width - 1)
            ids = np.take_along_axis(ids, source, axis=1)
            source = columns + (columns >= at[:, None])
            source[:, -1] = width - 1
            costs = np.take_along_axis(costs, source, axis=1)
            sizes = sizes - 1
            right = at + 1 < sizes
            costs[line, at] = _NONE
            costs[line[right], at[right]] = self._pair_rank(ids[line[right], at[right]], ids[line[right], at[right] + 1])
            left = at > 0
            costs[line[left], at[left] - 1] = self._pair_rank(ids[line[left], at[left] - 1], ids[line[left], at[left]])
        return result

    def _merge_long(self, raw: bytes) -> tuple[int, ...]:
        """The same with a heap and a linked list, for pieces of any length in n log n."""
        ranks, n = self.ranks, len(raw)
        end = list(range(1, n + 1))  # end of the part that starts here; 0 once it was joined to its left
        before = list(range(-1, n - 1))
        heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(raw[i : i + 2])) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, stop = heapq.heappop(heap)
            if not end[i] or (j := end[i]) >= n or end[j] != stop:
                continue
            end[i], end[j] = stop, 0
            if stop < n:
                before[stop] = i
                if (r := ranks.get(raw[i : end[stop]])) is not None:
                    heapq.heappush(heap, (r, i, end[stop]))
            if (h := before[i]) >= 0 and (r := ranks.get(raw[h:stop])) is not None:
                heapq.heappush(heap, (r, h, stop))
        out, i = [], 0
        while i < n:
            out.append(ranks[raw[i : end[i]]])
            i = end[i]
        return tuple(out)

    def encode(self, texts: list[str]) -> tuple[list[list[int]], list[list[int]]]:
        """Ids of every text, and for every piece of it the place of its first character."""
        joined, starts = piece_starts(texts)
        at = starts.tolist()
        pieces = [joined[a:b] for a, b in zip(at, [*at[1:], len(joined)])]
        ids = list(map(self.cache.get, pieces))
        if None in ids:
            missing = {piece for piece, known in zip(pieces, ids) if known is None}
            if len(self.cache) + len(missing) > self.most:
                self.cache.clear()
                missing = set(pieces)
            self.add(list(missing))
            ids = list(map(self.cache.__getitem__, pieces))
        begin = np.concatenate([[0], np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)) + 1)])
        first = np.searchsorted(starts, begin)
        out, offsets = [], []
        for k in range(len(texts)):
            a, b = first[k], first[k + 1] - 1
            out.append(list(chain.from_iterable(ids[a:b])))
            offsets.append((starts[a:b] - begin[k]))
        return out, offsets

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


def encode_documents(
    docs: DataFrame, vocabulary_path: str, keep: tuple[str, ...] = ("doc_id",), text_col: str = "text", with_offsets: bool = True, with_decoded: bool = False
) -> DataFrame:
    """Columns ``keep`` with ids (array<int>) and, if asked, offsets (array<int>: first character of each piece) and decoded (binary).

    Decoding here takes the ids in the worker that made them; ``decode_documents`` has a second worker beside it, with a vocabulary of its own.
    """
    fields = [("ids", T.ArrayType(T.IntegerType()))]
    if with_offsets:
        fields.append(("offsets", T.ArrayType(T.IntegerType())))
    if with_decoded:
        fields.append(("decoded", T.BinaryType()))

    def make():
        vocabulary = Vocabulary(vocabulary_path)
        gc.set_threshold(200_000, 50, 50)  # the cache holds many small tuples without cycles

        def kernel(texts: list[str]) -> list:
            ids, offsets = vocabulary.encode(texts)
            made = [ids, offsets] if with_offsets else [ids]
            return [*made, list(map(vocabulary.decode, ids))] if with_decoded else made

        return kernel

    return map_texts(docs, make, fields, keep, text_col, chars_per_call=1_000_000)


def decode_documents(encoded: DataFrame, vocabulary_path: str, keep: tuple[str, ...] = ("doc_id", "ids")) -> DataFrame:
    """Columns ``keep`` with decoded (binary), from the column ids; null ids decode to no bytes."""
    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_schema

    keep = [c for c in keep if c != "decoded"]
    schema = T.StructType([*(encoded.schema[c] for c in keep), T.StructField("decoded", T.BinaryType())])
    arrow = to_arrow_schema(schema)

    def run(batches):
        vocabulary = Vocabulary(vocabulary_path)
        lookup = np.array(vocabulary.bytes_of, dtype=object)
        for batch in batches:
            for a in range(0, len(batch), 256):
                part = batch.slice(a, 256)
                lists = part.column(len(keep))
                flat = lookup[lists.flatten().to_numpy()]
                ends = np.cumsum([0, *((n or 0) for n in pa.compute.list_value_length(lists).to_pylist())]).tolist()
                decoded = [b"".join(flat[i:j]) for i, j in zip(ends, ends[1:])]
                kept = [part.column(i).cast(arrow.field(i).type) for i in range(len(keep))]
                yield pa.RecordBatch.from_arrays([*kept, pa.array(decoded, pa.binary()).cast(arrow.field(len(keep)).type)], schema=arrow)

    import pyarrow.compute  # noqa: F401

    return encoded.select(*keep, F.col("ids").alias("__ids")).mapInArrow(run, schema)
