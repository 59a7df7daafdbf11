"""Near-duplicates by SimHash, found through a byte-position inverted index with count filtering.

A fingerprint is eight bytes. Two that differ in at most two bits differ in at most two byte positions, so at
least six positional bytes agree. A posting list of one positional byte holds a 256th of all fingerprints, so
lists are keyed by four positional bytes at once: the eight positions form four blocks, six shared bytes leave
two whole blocks at least, and the six pairs of blocks are the index. In a short list the shared positional
bytes of each pair are tallied, pairs under the guaranteed count are dropped, the rest is verified by Hamming
distance. A list of more than ``list_bound`` fingerprints (one of a large group of near copies) makes no pairs:
its fingerprints are posted under themselves and their 64 one-bit neighbours, and all postings of one value lie
within two bits of each other, so linking each to the least one loses no connection. Both ways are exact.

Defined results: null and empty texts have fingerprint zero, which links like any other; repeated rows share a
component; an empty table gives no rows; columns other than the id and the text take no part.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphweave.llm.common import map_texts, materialize, maybe_in, rekeyed, released, settled, stored
from graphweave.llm.components import components

_SEED = 42
#: Frequent shingles that prefixes leave to the end: how many are told apart at most, and from how many texts on.
#: They only order the shingles of a text; the result is the same for any numbers here.
MOST_FREQUENT, FREQUENT_FROM = 1 << 18, 16
_BLOCKS = ((0, 1), (2, 3), (4, 5), (6, 7))
#: Longs of the small parity sketch. Fewer let more pairs through to the exact comparison; the result is the same for any power of two.
SKETCH_WORDS = 8


def shingle_hashes(text: str, shingle: int) -> np.ndarray:
    """Hashes of all runs of ``shingle`` words; of a shorter text, one of its words."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if len(words) < shingle:
        grams = [b" ".join(words)]
    else:
        grams = map(b" ".join, zip(*(words[i:] for i in range(shingle))))
    digest = xxhash.xxh64_intdigest
    return np.array([digest(g, _SEED) for g in grams], np.uint64)


def majority(hashes: np.ndarray) -> int:
    counts = np.zeros(64, np.int64)
    for a in range(0, len(hashes), 65536):
        part = hashes[a : a + 65536].astype(">u8")
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(counts * 2 > len(hashes)).view(">i8")[0])


def parity_sketch(shingles: np.ndarray, words: int = SKETCH_WORDS) -> np.ndarray:
    """Bits by hash, each 1 if an odd number of the distinct shingles falls on it.

    Sketches of two sets differ in at most as many bits as the sets have shingles that are not in both.
    """
    odd = np.bincount((shingles.view(np.uint64) % np.uint64(64 * words)).astype(np.int64), minlength=64 * words) & 1
    return np.packbits(odd.astype(np.uint8)).view(">i8").astype(np.int64)


def wide_words(n: int) -> int:
    """Longs of the wide sketch of n shingles, a power of two: two bits a shingle at least."""
    return max(SKETCH_WORDS, 1 << (2 * n // 64).bit_length())


def _close(x: Column, y: Column, both: Column) -> Column:
    """Whether sketches of x and y differ in at most a ninth of both sizes; of sketches of two lengths the longer one is folded."""

    def folded(of: Column, other: Column) -> Column:
        half = F.size(other)
        return F.when(F.size(of) > half, F.zip_with(F.slice(of, 1, half), F.slice(of, half + 1, half), lambda a, b: a.bitwiseXOR(b))).otherwise(of)

    bits = F.zip_with(folded(x, y), folded(y, x), lambda a, b: F.bit_count(a.bitwiseXOR(b)))
    return 9 * F.aggregate(bits, F.lit(0), lambda a, b: a + b) <= both


def fingerprint(text: str, shingle: int = 3) -> int:
    """The 64 majority bits over the hashes of all shingles, as a signed long."""
    return majority(shingle_hashes(text, shingle)) if text.strip(" \t\n\x0b\x0c\r") else 0


def fingerprints(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), text_col: str = "text", shingle: int = 3) -> DataFrame:
    """Columns ``keep`` with fingerprint (long)."""

    def make():
        return lambda texts: [[fingerprint(t, shingle) for t in texts]]

    return map_texts(docs, make, [("fingerprint", T.LongType())], keep, text_col)


def _byte(value: Column, position: int) -> Column:
    return F.shiftrightunsigned(value, 56 - 8 * position).bitwiseAND(F.lit(255))


def _key(index: int, blocks: tuple[tuple[int, int], ...]) -> Column:
    """Number of the index and the positional bytes of its blocks, in one long."""
    key = F.lit(index).cast("long")
    for first, _ in blocks:
        block = F.shiftrightunsigned(F.col("f"), 48 - 8 * first).bitwiseAND(F.lit(65535))
        key = F.shiftleft(key, 16).bitwiseOR(block)
    return key


def links(distinct: DataFrame, list_bound: int = 8) -> DataFrame:
    """(a, b): links between distinct fingerprints (column f) that connect all within two differing bits."""
    keys = [_key(i, pair) for i, pair in enumerate(combinations(_BLOCKS, 2))]
    postings = distinct.select("f", F.explode(F.array(*keys)).alias("key"))
    sizes = postings.groupBy("key").agg(F.count("*").alias("n"))
    listed = materialize(postings.join(settled(sizes.where("n > 1"), "key"), "key"))
    # Short lists: a tally of the shared positional bytes, then the exact distance.
    short = listed.where(F.col("n") <= list_bound).select("key", "f")
    pairs = short.alias("x").join(short.alias("y"), (F.col("x.key") == F.col("y.key")) & (F.col("x.f") < F.col("y.f")))
    pairs = pairs.select(F.col("x.f").alias("a"), F.col("y.f").alias("b"))
    shared = sum((F.when(_byte(F.col("a"), p) == _byte(F.col("b"), p), 1).otherwise(0) for p in range(8)), F.lit(0))
    pairs = pairs.where(shared >= 6).where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= 2)
    # Long lists: values within one bit, each linked to the least fingerprint posted under it.
    long = listed.where(F.col("n") > list_bound).select("f").distinct()
    flips = F.array(F.lit(0).cast("long"), *(F.lit(1 << i if i < 63 else -(1 << 63)).cast("long") for i in range(64)))
    near = long.select("f", F.explode(F.transform(flips, lambda bit: F.col("f").bitwiseXOR(bit))).alias("value"))
    near = near.groupBy("value").agg(F.collect_list("f").alias("fs")).where("size(fs) > 1")  # 65 at most
    near = near.select(F.array_min("fs").alias("a"), F.explode("fs").alias("b")).where("a <> b")
    return pairs.union(near).distinct()


def near_duplicates(prints: DataFrame, id_col: str = "doc_id", list_bound: int = 8) -> DataFrame:
    """prints (id_col, fingerprint) with component_id: the least id that links reach."""
    prints = materialize(prints)
    first = materialize(prints.groupBy(F.col("fingerprint").alias("f")).agg(F.min(id_col).alias("first_id")))
    found = components(links(first.select("f"), list_bound))
    rooted = first.join(found.select(F.col("node").alias("f"), "root"), "f")
    least = settled(rooted.groupBy("root").agg(F.min("first_id").alias("least_id")), "root")
    moved = rooted.join(least, "root").select("f", F.col("least_id"))
    every = first.join(moved, "f", "left").select("f", F.coalesce("least_id", "first_id").alias("component_id"))
    every = settled(every, "f")
    return prints.join(every, F.col("fingerprint") == F.col("f"), "left").drop("f")


def _shingle_sets(docs: DataFrame, node_col: str, text_col: str, shingle: int) -> DataFrame:
    make = lambda: lambda texts: [[np.unique(shingle_hashes(t, shingle).view(np.int64)) for t in texts]]
    return map_texts(docs, make, [("shingles", T.ArrayType(T.LongType()))], (node_col,), text_col)


def _verified(docs: DataFrame, pairs: DataFrame, node_col: str, text_col: str, shingle: int) -> DataFrame:
    """The pairs (a, b) whose exact shingle sets have a similarity of 0.8 or more."""
    pairs = stored(pairs)
    needed = materialize(pairs.select(F.col("a").alias(node_col)).union(pairs.select("b")).distinct())
    released(docs.sparkSession)
    # One row of each text, before its shingles are made.
    texts = maybe_in(docs.select(node_col, text_col), node_col, needed).dropDuplicates([node_col]).join(needed, node_col, "left_semi")
    sets = materialize(_shingle_sets(texts, node_col, text_col, shingle))
    released(docs.sparkSession)
    for end in ("a", "b"):
        pairs = pairs.join(rekeyed(sets.select(F.col(node_col).alias(end), F.col("shingles").alias(f"of_{end}")), end), end)
    return materialize(pairs.where(9 * F.size(F.array_intersect("of_a", "of_b")) >= 4 * (F.size("of_a") + F.size("of_b"))).select("a", "b"))


def frequent_shingles(docs: DataFrame, text_col: str, shingle: int) -> np.ndarray:
    """Sorted hashes of the most frequent shingles, MOST_FREQUENT at most (two megabytes), counted over all texts.

    Only the lower half of the hashes is counted, as prefixes seldom reach further.
    """

    def make():
        def kernel(texts: list[str]) -> list:
            sets = (np.unique(shingle_hashes(t, shingle).view(np.int64)) for t in texts)
            return [[s[: np.searchsorted(s, 0)] for s in sets]]

        return kernel

    posted = map_texts(docs, make, [("keys", T.ArrayType(T.LongType()))], (), text_col).select(F.explode("keys").alias("key"))
    counts = posted.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") >= FREQUENT_FROM)
    return np.sort(counts.orderBy(F.desc("n"), "key").limit(MOST_FREQUENT).select("key").toArrow()["key"].to_numpy())


def candidates(posted: DataFrame) -> DataFrame:
    """(a, b), some repeated: nodes of postings (key, node, root, n, pos, sketch) under one key that may be similar and have two roots."""
    x, y = posted.alias("x"), rekeyed(posted, "key").alias("y")
    both = F.col("x.n") + F.col("y.n")
    apart = (F.col("x.node") < F.col("y.node")) & (F.col("x.root") != F.col("y.root"))
    # Of similar texts at least four ninths of both sizes are shared, all of them from the first shared key on.
    early_enough = (9 * (F.col("x.n") - F.col("x.pos")) >= 4 * both) & (9 * (F.col("y.n") - F.col("y.pos")) >= 4 * both)
    pairs = x.join(y, (F.col("x.key") == F.col("y.key")) & apart & early_enough & _close(F.col("x.sketch"), F.col("y.sketch"), both))
    return pairs.select(F.col("x.node").alias("a"), F.col("y.node").alias("b"))


def near_copies(docs: DataFrame, node_col: str, text_col: str = "text", shingle: int = 5, list_bound: int = 8) -> DataFrame:
    """(node, root) of texts that chains of shingle similarity 0.8 or more connect; node_col is a hash of the text.

    No bit bound of a 64-bit fingerprint is both sure to hold at similarity 0.8 and selective, so fingerprints and
    first entries of posting lists only join most groups early. The search that decides is complete: of n
    shingles in one order for all texts, two such texts share one of the first n // 5 + 1 at least, and the first
    shared one comes early enough in both. Frequent shingles come last in the order, so a passage that
    many texts share makes no pairs of them. Pairs are made of texts that are not yet connected, so groups of
    copies do not cost the square of their size. Texts that share much without being similar are told apart by
    parity sketches inside the join, which let few of their pairs out and drop no similar one; the comparisons
    themselves may grow as the square of such a group. All links are verified.
    """
    spark = docs.sparkSession
    frequent = spark.sparkContext.broadcast(frequent_shingles(docs, text_col, shingle))
    released(spark)

    def make():
        late = np.append(frequent.value, np.iinfo(np.int64).max)

        def kernel(texts: list[str]) -> list:
            out: list[list] = [[], [], [], [], []]
            for text in texts:
                hashes = shingle_hashes(text, shingle)
                found = np.unique(hashes.view(np.int64))
                is_late = late[np.searchsorted(late, found)] == found
                first = np.concatenate([found[~is_late], found[is_late]])[: len(found) // 5 + 1]
                for column, value in zip(out, (majority(hashes), len(found), first, parity_sketch(found), parity_sketch(found, wide_words(len(found))))):
                    column.append(value)
            return out

        return kernel

    fields = [*((c, T.LongType()) for c in ("f", "n")), *((c, T.ArrayType(T.LongType())) for c in ("keys", "sketch", "wide"))]
    prints = map_texts(docs, make, fields, (node_col,), text_col).withColumnRenamed(node_col, "node")
    prints = stored(prints.dropDuplicates(["node"]))
    released(spark)
    posted = prints.select("node", "n", F.posexplode("keys").alias("pos", "key"))
    shared = settled(posted.groupBy("key").agg(F.count("*").alias("size")).where("size > 1").select("key"), "key")
    released(spark)
    posted = stored(posted.join(shared, "key"))
    del shared
    released(spark)
    heads = settled(posted.groupBy("key").agg(F.min(F.struct("node", "n")).alias("head")), "key")
    alike = lambda n, m: (5 * n >= 4 * m) & (5 * m >= 4 * n)
    # Early links: fingerprints within two bits, and the head of every posting list.
    groups = materialize(prints.groupBy("f").agg(F.min("node").alias("head")))
    close = links(groups.select("f"), list_bound)
    for end in ("a", "b"):
        close = close.join(groups.select(F.col("f").alias(end), F.col("head").alias(f"head_{end}")), end)
    early = close.select(F.col("head_a").alias("a"), F.col("head_b").alias("b"))
    early = early.union(prints.select("node", "f").join(rekeyed(groups, "f"), "f").select("head", "node"))
    early = early.union(posted.join(heads, "key").where(alike(F.col("n"), F.col("head.n"))).select("head.node", "node")).where("a <> b")
    early = early.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    early = _verified(docs, early, node_col, text_col, shingle)
    del groups, close, heads
    released(spark)
    # The complete search, over pairs that early links leave apart.
    root = components(early)
    rooted = prints.select("node").join(rekeyed(root, "node"), "node", "left")
    rooted = settled(rooted.withColumn("root", F.coalesce("root", "node")), "node")
    posted = stored(posted.join(rooted, "node"))
    mixed = settled(posted.groupBy("key").agg(F.min("root").alias("x"), F.max("root").alias("y")).where("x <> y").select("key"), "key")
    released(spark)
    posted = stored(posted.join(mixed, "key").join(rekeyed(prints.select("node", "sketch"), "node"), "node"))
    released(spark)
    pairs = materialize(candidates(posted).distinct())
    for end in ("a", "b"):
        of = prints.select(F.col("node").alias(end), F.col("n").alias(f"n_{end}"), F.col("wide").alias(f"wide_{end}"))
        pairs = pairs.join(rekeyed(of, end), end)
    pairs = pairs.where(_close(F.col("wide_a"), F.col("wide_b"), F.col("n_a") + F.col("n_b"))).select("a", "b")
    found = components(early.union(_verified(docs, pairs, node_col, text_col, shingle)))
    released(spark)
    return found
