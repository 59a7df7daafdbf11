"""Line deduplication by a deletion-neighbourhood join, with DataFrame functions only.

A line goes if an earlier line of the corpus, in the order of document id and line number, equals it or is
within one word edit (a word inserted, deleted or replaced) of it. Lines of fewer than ``near_words`` words match
only exactly; blank lines stay and match nothing.

Equal lines meet by a 128-bit hash. For the edit bound, a line that has a partner shares its first or its last
half with it (as many words as half the longer line, rounded down); only lines that share such a half with a
different line go on. They emit their deletion neighbourhood: the line itself and the line without each of its
words, as hashed keys, in time linear in its words. Lines with an equal key of the same place differ by a
replacement, a line that equals another's variant by an insertion. Each line of a key is compared with the
key's earliest line alone, so a key shared by any number of lines makes no pairs; the edit is verified on words.

Defined results: a null text is one blank line; repeated rows with the same id and text count as one document;
null ids come first; lines of any length are compared whole; an empty table gives no rows; of the input's
columns only the id and the text take part.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from graphweave.llm.common import materialize, maybe_in, settled, stored

#: Words of the longest line whose neighbourhood is made inside its row, where the cost is quadratic.
_IN_ROW = 64


def lines_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(d, t, no, line): the lines of each document, t a hash of its text."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).alias("d"), F.xxhash64(text).alias("t"), F.posexplode(F.split(text, "\n")).alias("no", "line"))
    return rows.withColumn("h", F.xxhash64("line")).withColumn("g", F.xxhash64(F.lit(1), "line"))


def _words(line: Column) -> Column:
    """Pieces between blanks; two blanks in a row have an empty word between them."""
    return F.split(line, " ")


def _halves(words: Column) -> Column:
    """Hashes of the leading and trailing halves that a line within one word edit may share."""
    n = F.size(words)
    made = []
    for tag, length in ((0, F.floor((n - 1) / 2).cast("int")), (1, F.floor(n / 2).cast("int"))):
        length = F.greatest(length, F.lit(1))
        made += [F.xxhash64(F.lit("head"), F.slice(words, 1, length)), F.xxhash64(F.lit("tail"), F.slice(words, n - length + 1, length))]
    return F.array_distinct(F.array(*made))


def _neighbourhood(words: Column) -> Column:
    """Array of (place, key): place 0 the whole line, place i the line without its i-th word.

    A key is the xor of hashes of (index, word); leaving a word out lowers the index of those after it.
    """
    places = F.transform(words, lambda w, i: F.struct(F.xxhash64(i, w).alias("own"), F.xxhash64(i - 1, w).alias("moved")))
    zero = F.lit(0).cast("long")
    start = F.struct(zero.alias("x"), zero.alias("whole"), zero.alias("moved"), F.array().cast("array<bigint>").alias("out"))
    return F.aggregate(
        places,
        start,
        lambda s, p: F.struct(
            s.x.bitwiseXOR(p.own).bitwiseXOR(p.moved).alias("x"),
            s.whole.bitwiseXOR(p.own).alias("whole"),
            s.moved.bitwiseXOR(p.moved).alias("moved"),
            F.concat(s.out, F.array(s.x.bitwiseXOR(p.moved))).alias("out"),
        ),
        lambda s: F.concat(
            F.array(F.struct(F.lit(0).alias("place"), s.whole.alias("key"))),
            F.transform(s.out, lambda x, i: F.struct((i + 1).alias("place"), x.bitwiseXOR(s.moved).alias("key"))),
        ),
    )


def _neighbourhoods(found: DataFrame) -> DataFrame:
    """(h, g, first, size, place, key) of all lines: in the row for short ones, by windows over words for long ones."""
    sized = found.withColumn("size", F.size("words"))
    short = sized.where(F.col("size") <= _IN_ROW).select("h", "g", "first", "size", F.inline(_neighbourhood(F.col("words"))))
    long = sized.where(F.col("size") > _IN_ROW).select("h", "g", "first", "size", F.posexplode("words").alias("i", "w"))
    long = long.select("h", "g", "first", "size", "i", F.xxhash64("i", "w").alias("own"), F.xxhash64(F.col("i") - 1, "w").alias("moved"))
    line = W.partitionBy("h", "g")
    before = F.bit_xor(F.col("own").bitwiseXOR(F.col("moved"))).over(line.orderBy("i").rowsBetween(W.unboundedPreceding, -1))
    key = F.coalesce(before, F.lit(0)).bitwiseXOR(F.col("moved")).bitwiseXOR(F.bit_xor("moved").over(line))
    without = long.select("h", "g", "first", "size", (F.col("i") + 1).alias("place"), key.alias("key"))
    whole = long.groupBy("h", "g", "first", "size").agg(F.bit_xor("own").alias("key"))
    return short.union(without).union(whole.select("h", "g", "first", "size", F.lit(0).alias("place"), "key"))


def _within_one_edit(a: Column, b: Column) -> Column:
    """Do the word arrays differ by at most one word inserted, deleted or replaced?"""
    longer, shorter = F.greatest(F.size(a), F.size(b)), F.least(F.size(a), F.size(b))
    differs = F.zip_with(F.slice(a, 1, shorter), F.slice(b, 1, shorter), lambda x, y: ~x.eqNullSafe(y))
    head = F.array_position(differs, True)
    head = F.when(head == 0, shorter).otherwise(head - 1).cast("int")
    rest = lambda x: F.when(F.size(x) - head - 1 > 0, F.slice(x, head + 2, F.size(x) - head - 1)).otherwise(F.array().cast("array<string>"))
    kept = lambda x: F.when(F.size(x) - head > 0, F.slice(x, head + 1, F.size(x) - head)).otherwise(F.array().cast("array<string>"))
    return (
        F.when(longer - shorter > 1, False)
        .when(F.size(a) == F.size(b), rest(a) == rest(b))
        .when(F.size(a) > F.size(b), rest(a) == kept(b))
        .otherwise(kept(a) == rest(b))
    )


def dropped_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", near_words: int = 6) -> DataFrame:
    """(d, t, dropped): for documents that lose lines, by id and text hash, the sorted numbers of those lines."""
    lines = lines_of(docs, id_col, text_col).where(F.ltrim("line", F.lit(" \t\r")) != "")
    place = F.struct("d", "t", "no")
    worded = lines.select("h", "g", place.alias("place"), _words(F.col("line")).alias("words"))
    halves = F.when(F.size("words") >= near_words, _halves(F.col("words")))
    distinct = worded.groupBy("h", "g").agg(F.min("place").alias("first"), F.count("*").alias("n"), F.any_value(halves).alias("halves"))
    distinct = stored(distinct)
    # Lines that share a half with a different line.
    halves = distinct.select("h", F.explode("halves").alias("half"))
    shared = halves.groupBy("half").agg(F.min("h").alias("a"), F.max("h").alias("b")).where("a <> b")
    shared = settled(shared.select("half"), "half")
    flagged = materialize(maybe_in(halves, "half", shared).join(shared, "half").select("h").distinct())
    # Their deletion neighbourhoods.
    found = maybe_in(lines, "h", flagged).join(settled(flagged, "h"), "h")
    found = found.groupBy("h", "g").agg(F.min(place).alias("first"), F.any_value("line").alias("line"))
    found = stored(found.select("h", "g", "first", _words(F.col("line")).alias("words")))
    variants = stored(_neighbourhoods(found))
    replaced = variants.where("place > 0").groupBy("key", "place", "size").agg(F.min("first").alias("other"), F.count("*").alias("n"))
    replaced = settled(replaced.where("n > 1").drop("n"), "key", "place", "size")
    inserted = variants.groupBy("key").agg(
        F.min(F.when(F.col("place") == 0, F.col("first"))).alias("whole"), F.min(F.when(F.col("place") > 0, F.col("first"))).alias("longer")
    )
    inserted = settled(inserted.where("whole is not null and longer is not null"), "key")
    pairs = variants.where("place > 0").join(replaced, ["key", "place", "size"]).select("h", "g", "first", "other")
    other = F.when(F.col("place") == 0, F.col("longer")).otherwise(F.col("whole"))
    pairs = pairs.union(variants.join(inserted, "key").select("h", "g", "first", other.alias("other")))
    pairs = pairs.where("other < first").distinct()
    # Verify on words.
    later = pairs.join(found.select("h", "g", F.col("words").alias("a")), ["h", "g"])
    earlier = found.select(F.col("first").alias("other"), F.col("words").alias("b"))
    near = later.join(earlier, "other").where(_within_one_edit(F.col("a"), F.col("b"))).select("h", "g").distinct()
    # Every line but the first of its kind goes, the first too if it is near an earlier one.
    near = near.withColumn("near", F.lit(True))
    gone = distinct.join(near, ["h", "g"], "left").where("n > 1 or near")
    gone = settled(gone.select("h", "g", "first", F.coalesce("near", F.lit(False)).alias("near")), "h", "g")
    rows = maybe_in(lines.select("d", "t", "no", "h", "g"), "h", gone.select("h")).join(gone, ["h", "g"])
    rows = rows.where(F.col("near") | (F.col("first") != place)).select("d", "t", "no").distinct()
    return rows.groupBy("d", "t").agg(F.sort_array(F.collect_list("no")).alias("dropped"))


def deduplicate_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", near_words: int = 6, drop_empty: bool = True) -> DataFrame:
    """docs without the lines that ``dropped_lines`` names; documents left without a word go, if drop_empty."""
    gone = dropped_lines(docs, id_col, text_col, near_words).toDF("__d", "__t", "__dropped")
    # Lines take the place of the text, cut before the join, so that taking one by its number costs no new cut.
    text = F.col(f"`{text_col}`")
    rows = docs.withColumn("__hash", F.xxhash64(F.coalesce(text, F.lit("")))).withColumn(text_col, F.split(text, "\n"))
    rows = rows.join(gone, F.col(f"`{id_col}`").eqNullSafe(F.col("__d")) & (F.col("__hash") == F.col("__t")), "left")
    numbers = F.array_except(F.sequence(F.lit(0), F.size(text) - 1), "__dropped")
    kept = F.array_join(F.transform(numbers, lambda i: F.get(text, i)), "\n")
    rows = rows.withColumn("__kept", F.when(F.col("__dropped").isNull() | text.isNull(), F.array_join(text, "\n")).otherwise(kept))
    if drop_empty:
        rows = rows.where(F.col("__dropped").isNull() | F.col("__kept").rlike(r"[^\x20\x09-\x0D]"))
    return rows.select(*(F.col("__kept").alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns))
