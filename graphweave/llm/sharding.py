"""Sharding by a hierarchical weighted hash tree of regions, racks and shards.

A document descends from the root: at each level every child draws an exponential variate from a hash of the
document's id and the child's name, divided by the child's weight (the sum of its leaves), and the least draw
wins. A child whose weight stays keeps its draw, so a change of weights moves rows only into or out of the
subtrees whose weights change. A new shard that must take rows only into itself gets a subtree of its own.
Nothing but the id decides, so placement needs no shuffle and survives any repartitioning.

Slots number a shard's rows without gaps, in two levels: counts of hash buckets, then ranks inside a bucket.

Defined results: a null id draws like any id; a null text has size 8 (its frame) and no checksum but that of an
empty text; repeated rows get slots of their own; an empty table gives no rows; clashing columns are replaced.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from graphweave.llm.common import materialize, slots


@dataclass(frozen=True)
class Node:
    """A region, rack or (without children) shard. Weights of inner nodes are those of their leaves together."""

    name: int
    children: tuple[Node, ...] = ()
    leaf_weight: float = 1.0

    @property
    def weight(self) -> float:
        return sum(c.weight for c in self.children) if self.children else self.leaf_weight


def even_tree(regions: int = 3, racks: int = 2, shards: int = 4) -> Node:
    """A tree of equal shards, numbered from 0; inner names differ from all others of their level."""
    region_nodes = []
    for r in range(regions):
        first = r * racks
        rack_nodes = [Node(k, tuple(Node(k * shards + s) for s in range(shards))) for k in range(first, first + racks)]
        region_nodes.append(Node(r, tuple(rack_nodes)))
    return Node(0, tuple(region_nodes))


def grown(tree: Node, shard: int, weight: float = 1.0) -> Node:
    """The tree with one more shard, in a region of its own, so that rows move only into it."""
    region = 1 + max(c.name for c in tree.children)
    rack = 1 + max(k.name for c in tree.children for k in c.children)
    return Node(tree.name, (*tree.children, Node(region, (Node(rack, (Node(shard, (), weight),)),))))


def place(key: Column, tree: Node, level: int = 0) -> Column:
    """The shard of a key: nested choices, one per level; nodes without weight are never chosen."""
    if not tree.children:
        return F.lit(tree.name)
    children = [c for c in tree.children if c.weight > 0]
    if len(children) == 1:
        return place(key, children[0], level + 1)

    def draw(child: Node) -> Column:
        uniform = (F.shiftrightunsigned(F.xxhash64(key, F.lit(level), F.lit(child.name)), 11) + 0.5) * 2.0**-53
        return F.struct((-F.ln(uniform) / child.weight).alias("draw"), F.lit(child.name).alias("name"))

    chosen = F.array_min(F.array(*map(draw, children)))["name"]
    if not any(c.children for c in children):
        return chosen
    below = F.transform(
        F.array(chosen),
        lambda name: F.coalesce(*(F.when(name == c.name, place(key, c, level + 1)) for c in children)),
    )
    return below[0]


def with_slots(placed: DataFrame, by: str, order: tuple[str, ...]) -> DataFrame:
    """placed with slot: 0, 1, ... inside each value of by, whatever its share of the rows."""
    buckets = max(64, 4 * slots(placed.sparkSession))
    placed = placed.withColumn("__bucket", F.pmod(F.xxhash64(*order), F.lit(buckets)).cast("int"))
    counts = materialize(placed.groupBy(by, "__bucket").agg(F.count("*").alias("__n")))
    before = W.partitionBy(by).orderBy("__bucket").rowsBetween(W.unboundedPreceding, -1)
    counts = counts.select(by, "__bucket", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__first"))
    inside = W.partitionBy(by, "__bucket").orderBy(*order)
    ranked = placed.join(counts, [by, "__bucket"]).withColumn("slot", F.col("__first") + F.row_number().over(inside) - 1)
    return ranked.drop("__bucket", "__first")


def shard_documents(docs: DataFrame, tree: Node | None = None, wider: Node | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id_col, size, text_crc32, shard, slot, grown_shard), the last by the tree ``wider`` (null without one)."""
    tree = tree or even_tree()
    text = F.coalesce(F.col(text_col), F.lit(""))
    placed = docs.select(
        id_col,
        (F.octet_length(text) + 8).cast("long").alias("size"),
        F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"),
        place(F.col(id_col), tree).cast("int").alias("shard"),
        (place(F.col(id_col), wider) if wider else F.lit(None)).cast("int").alias("grown_shard"),
    )
    return with_slots(materialize(placed), "shard", (id_col, "text_crc32", "size"))
