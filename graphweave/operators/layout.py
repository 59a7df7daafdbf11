"""Partition setup of a cut: clones, consecutive local ids and their range map, clone lists, trees, bins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def clones(cut: DataFrame) -> DataFrame:
    """(vid, part, copies, is_split): the partitions that each vertex meets an edge in."""
    pairs = cut.select("part", F.explode(F.array("src", "dst")).alias("vid")).distinct()
    counts = pairs.groupBy("vid").agg(F.count("*").alias("copies"))
    return pairs.join(counts, "vid").select("vid", "part", "copies", (F.col("copies") > 1).alias("is_split"))


def vertex_map(cloned: DataFrame) -> DataFrame:
    """(part, lo, hi): the range of local ids of each partition; one row a partition."""
    sizes = cloned.groupBy("part").agg(F.count("*").alias("n"))
    hi = F.sum("n").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, 0))
    return sizes.select("part", (hi - F.col("n")).alias("lo"), hi.alias("hi"))


def local_ids(cloned: DataFrame, block: int = 1024) -> DataFrame:
    """Clones with local_id: consecutive over partitions, by vertex id inside one.

    Ranks are taken in blocks of ids and over blocks, so no task sorts a whole partition.
    """
    rows = cloned.select("vid", "part", "copies", "is_split", F.floor(F.col("vid") / block).cast("long").alias("block"))
    before = W.partitionBy("part").orderBy("block").rowsBetween(W.unboundedPreceding, -1)
    sizes = rows.groupBy("part", "block").agg(F.count("*").alias("n"))
    first = sizes.select("part", "block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first"))
    first = first.join(F.broadcast(vertex_map(cloned).select("part", "lo")), "part")
    rank = F.row_number().over(W.partitionBy("part", "block").orderBy("vid")) - 1
    return rows.join(first, ["part", "block"]).select("vid", "part", "copies", "is_split", (F.col("lo") + F.col("first") + rank).alias("local_id"))


def locate(ids: DataFrame, mapping: DataFrame) -> DataFrame:
    """(local_id, part, place): the partition whose range holds an id, by a join with the range map (a row a part)."""
    held = (F.col("local_id") >= F.col("lo")) & (F.col("local_id") < F.col("hi"))
    return ids.join(F.broadcast(mapping), held).select("local_id", "part", (F.col("local_id") - F.col("lo")).alias("place"))


def clone_lists(numbered: DataFrame) -> DataFrame:
    """(vid, local_ids): the sorted local ids of each split vertex, at most one a partition."""
    return numbered.where("is_split").groupBy("vid").agg(F.sort_array(F.collect_list("local_id")).alias("local_ids"))


def trees(cloned: DataFrame, seed: int = 0) -> DataFrame:
    """(vid, root_part, leaf_parts): a pseudo-random root, all other clones its leaves."""
    draw = (F.col("vid") * 1009 + F.col("part") * 9176 + seed) % 65521
    ranked = cloned.groupBy("vid").agg(F.sort_array(F.collect_list(F.struct(draw.alias("draw"), "part"))).alias("c"))
    parts = F.transform("c", lambda x: x.part)
    return ranked.select("vid", parts[0].alias("root_part"), F.sort_array(F.slice(parts, 2, F.greatest(F.size("c") - 1, F.lit(1)))).alias("leaf_parts"))


def bins(tree: DataFrame, count: int, block: int = 1024) -> DataFrame:
    """(vid, bin) of split vertices: ranks in id order, modulo the count; ranked in blocks, then over blocks."""
    split = tree.where("size(leaf_parts) > 0").select("vid", F.floor(F.col("vid") / block).cast("long").alias("block"))
    sizes = split.groupBy("block").agg(F.count("*").alias("n"))
    first = F.coalesce(F.sum("n").over(W.orderBy("block").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    rank = F.col("first") + F.row_number().over(W.partitionBy("block").orderBy("vid")) - 1
    return split.join(sizes.select("block", first.alias("first")), "block").select("vid", (rank % count).cast("int").alias("bin"))


def with_roles(cloned: DataFrame, tree: DataFrame, binned: DataFrame | None = None) -> DataFrame:
    """Clones with root_part, is_root, and bin (0 for whole vertices)."""
    rows = cloned.join(tree.select("vid", "root_part"), "vid").withColumn("is_root", F.col("part") == F.col("root_part"))
    if binned is None:
        return rows.withColumn("bin", F.lit(0))
    return rows.join(binned, "vid", "left").withColumn("bin", F.coalesce("bin", F.lit(0)))
