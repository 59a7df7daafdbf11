"""Graphs over the given tables, with integer features so that sums are exact in any order."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphweave.sources.tables import scan


@dataclass(frozen=True)
class PropertyGraph:
    """vertices (vid, feat array<double>), edges (src, dst[, efeat array<double>, ...]) and the vector widths."""

    vertices: DataFrame
    edges: DataFrame
    width: int
    edge_width: int = 0

    def validate(self) -> DataFrame:
        """Violations by kind: null ids, edges whose ends are no vertices, vectors of another width."""
        ids = self.vertices.select(F.col("vid").alias("end"))
        ends = self.edges.select(F.explode(F.array("src", "dst")).alias("end"))
        dangling = ends.where("end is not null").join(ids, "end", "left_anti").select(F.lit("dangling end").alias("problem"))
        null_end = ends.where("end is null").select(F.lit("null end").alias("problem"))
        narrow = self.vertices.where(F.size("feat") != self.width).select(F.lit("width").alias("problem"))
        null_id = self.vertices.where("vid is null").select(F.lit("null id").alias("problem"))
        return dangling.union(null_end).union(narrow).union(null_id).groupBy("problem").count()


def integer_feature(vid: Column, j: int) -> Column:
    return ((vid * 31 + j * 17 + 7) % 101 - 50).cast("double")


def integer_features(vid: Column, width: int) -> Column:
    return F.array(*(integer_feature(vid, j) for j in range(width)))


def random_features(vid: Column, width: int, seed: int = 0) -> Column:
    """Pseudo-random components in [-1, 1) by an arithmetic hash that any engine can repeat."""
    mixed = lambda j: ((vid % 65521) * ((j * 7919 + seed * 104729 + 12345) % 65521) + (vid % 8191) * (j * j + 31 * j + 17) + j * 271) % 65521
    return F.array(*((mixed(j) * 2 / 65521.0 - 1.0) for j in range(width)))


def vertex_id_feature(vid: Column) -> Column:
    return F.array(vid.cast("double"))


def symmetrize(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def reverse(edges: DataFrame) -> DataFrame:
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *rest)


def simplify(edges: DataFrame) -> DataFrame:
    """Without loops and repeated edges."""
    return edges.where("src <> dst").select("src", "dst").distinct()


def co_occurring(pairs: DataFrame, group: str, item: str) -> DataFrame:
    """(src, dst) with src < dst: each pair of different items of one group once; a heavy group splits by AQE's skew join."""
    pairs = pairs.select(group, item).distinct()
    other = pairs.select(F.col(group), F.col(item).alias("dst"))
    return pairs.join(other, group).where(F.col(item) < F.col("dst")).select(F.col(item).alias("src"), "dst").distinct()


def co_occurrence(pairs: DataFrame, group: str, item: str) -> DataFrame:
    """Directed edges both ways between different items of one group; only one way is shuffled to be made distinct."""
    both = F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return co_occurring(pairs, group, item).select(F.inline(both))


def co_purchase(spark: SparkSession, folder: str, width: int = 4) -> PropertyGraph:
    """Parts joined by a common order, both ways."""
    edges = co_occurrence(scan(spark, folder, "lineitem", ["l_orderkey", "l_partkey"]), "l_orderkey", "l_partkey")
    parts = scan(spark, folder, "part", ["p_partkey"])
    return PropertyGraph(parts.select(F.col("p_partkey").alias("vid"), integer_features(F.col("p_partkey"), width).alias("feat")), edges, width)


def co_purchase_pairs(spark: SparkSession, folder: str) -> DataFrame:
    """(src, dst) with src < dst: the edges of co_purchase, each pair once."""
    return co_occurring(scan(spark, folder, "lineitem", ["l_orderkey", "l_partkey"]), "l_orderkey", "l_partkey")


def customer_supplier(spark: SparkSession, folder: str, width: int = 4) -> PropertyGraph:
    """Hub side: customers and suppliers by orders, both ways; supplier ids follow those of customers."""
    customers, suppliers = scan(spark, folder, "customer", ["c_custkey"]), scan(spark, folder, "supplier", ["s_suppkey"])
    offset = 1_000_000_000
    orders, lines = scan(spark, folder, "orders", ["o_orderkey", "o_custkey"]), scan(spark, folder, "lineitem", ["l_orderkey", "l_suppkey"])
    pairs = orders.join(lines, orders["o_orderkey"] == lines["l_orderkey"])
    edges = symmetrize(pairs.select(F.col("o_custkey").alias("src"), (F.col("l_suppkey") + offset).alias("dst")).distinct())
    ids = customers.select(F.col("c_custkey").alias("vid")).union(suppliers.select((F.col("s_suppkey") + offset).alias("vid")))
    return PropertyGraph(ids.select("vid", integer_features(F.col("vid") % 1_000_003, width).alias("feat")), edges, width)


def document_similarity(spark: SparkSession, folder: str, width: int = 16, least: int = 2, df_range: tuple[int, int] = (2, 12)) -> PropertyGraph:
    """Documents that share at least ``least`` rare words (three letters or more, in 2 to 12 documents)."""
    docs = scan(spark, folder, "documents", ["doc_id", "text"])
    words = docs.select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]{3,})"), 1))).alias("word"))
    counts = words.groupBy("word").agg(F.count("*").alias("df")).where(F.col("df").between(*df_range))
    rare = words.join(counts, "word").select("word", "doc_id")
    other = rare.select("word", F.col("doc_id").alias("dst"))
    shared = rare.join(other, "word").where("doc_id <> dst").groupBy(F.col("doc_id").alias("src"), "dst").count().where(F.col("count") >= least)
    vertices = docs.select(F.col("doc_id").alias("vid"), random_features(F.col("doc_id"), width).alias("feat"))
    return PropertyGraph(vertices, shared.select("src", "dst"), width)


def part_order(spark: SparkSession, folder: str) -> PropertyGraph:
    """Multigraph of one edge a line item, part to order, with three integer edge features."""
    lines = scan(spark, folder, "lineitem", ["l_orderkey", "l_partkey", "l_quantity", "l_discount", "l_tax"])
    whole = lambda c: F.round(F.col(c) * 100).cast("double")
    edges = lines.select(F.col("l_partkey").alias("src"), F.col("l_orderkey").alias("dst"), F.array(F.col("l_quantity").cast("double"), whole("l_discount"), whole("l_tax")).alias("efeat"))
    ids = scan(spark, folder, "part", ["p_partkey"]).select(F.col("p_partkey").alias("vid")).union(scan(spark, folder, "orders", ["o_orderkey"])).distinct()
    return PropertyGraph(ids.select("vid", integer_features(F.col("vid"), 3).alias("feat")), edges, 3, 3)


def sparse_part_order(spark: SparkSession, folder: str, width: int = 4) -> PropertyGraph:
    """Sparse bipartite counterpart: distinct order-part pairs both ways; part ids are offset."""
    offset = 1_000_000_000
    lines = scan(spark, folder, "lineitem", ["l_orderkey", "l_partkey"])
    edges = symmetrize(lines.select(F.col("l_orderkey").alias("src"), (F.col("l_partkey") + offset).alias("dst")).distinct())
    ids = edges.select(F.col("src").alias("vid")).distinct()
    return PropertyGraph(ids.select("vid", integer_features(F.col("vid") % 1_000_003, width).alias("feat")), edges, width)


#: Offsets that keep the ids of vertex types apart.
TYPE_OFFSET = {"region": 0, "nation": 1_000, "supplier": 10_000_000, "part": 1_000_000_000, "customer": 2_000_000_000, "orders": 3_000_000_000}


def typed(spark: SparkSession, folder: str) -> PropertyGraph:
    """Typed graph of all relations and their inverses; vertices carry vtype, the id is the feature."""
    load = lambda name, *columns: scan(spark, folder, name, list(columns))
    at = TYPE_OFFSET
    link = lambda df, rel, a, ta, b, tb: df.select((F.col(a).cast("long") + at[ta]).alias("src"), (F.col(b).cast("long") + at[tb]).alias("dst"), F.lit(rel).alias("rel"))
    lines = load("lineitem", "l_orderkey", "l_partkey", "l_suppkey")
    edges = link(load("nation", "n_nationkey", "n_regionkey"), "in_region", "n_nationkey", "nation", "n_regionkey", "region")
    edges = edges.union(link(load("customer", "c_custkey", "c_nationkey"), "customer_nation", "c_custkey", "customer", "c_nationkey", "nation"))
    edges = edges.union(link(load("supplier", "s_suppkey", "s_nationkey"), "supplier_nation", "s_suppkey", "supplier", "s_nationkey", "nation"))
    edges = edges.union(link(load("orders", "o_orderkey", "o_custkey"), "ordered_by", "o_orderkey", "orders", "o_custkey", "customer"))
    edges = edges.union(link(lines, "contains", "l_orderkey", "orders", "l_partkey", "part").distinct())
    edges = edges.union(link(lines, "supplied_by", "l_partkey", "part", "l_suppkey", "supplier").distinct())
    edges = edges.union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.concat(F.lit("inverse_"), "rel").alias("rel")))
    keys = {"region": "r_regionkey", "nation": "n_nationkey", "supplier": "s_suppkey", "part": "p_partkey", "customer": "c_custkey", "orders": "o_orderkey"}
    vertices = None
    for vtype, key in keys.items():
        rows = load(vtype, key).select((F.col(key).cast("long") + at[vtype]).alias("vid"), F.lit(vtype).alias("vtype"))
        vertices = rows if vertices is None else vertices.union(rows)
    return PropertyGraph(vertices.select("vid", vertex_id_feature(F.col("vid")).alias("feat"), "vtype"), edges, 1)


def nearest(spark: SparkSession, folder: str, k: int = 10) -> PropertyGraph:
    """Edges from each vector's k nearest (largest inner product of quantised components) to it."""
    from graphweave.operators.relational import knn

    vectors = scan(spark, folder, "embeddings").select(F.col("vec_id").alias("vid"), quantised(F.col("embedding")).alias("feat"))
    return PropertyGraph(vectors, knn(vectors, k).select(F.col("neighbour").alias("src"), F.col("vid").alias("dst")), 64)


def quantised(vector: Column, by: int = 1000) -> Column:
    return F.transform(vector, lambda x: F.round(x.cast("double") * by).cast("double"))


def conversation_chain(spark: SparkSession, folder: str) -> DataFrame:
    """Edges (conv_id, src turn, dst turn) from each turn to the next."""
    turns = scan(spark, folder, "conversations", ["conv_id", "turn"]).distinct()
    following = turns.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("turn").alias("dst"))
    return turns.join(following, ["conv_id", "turn"]).select("conv_id", F.col("turn").alias("src"), "dst")


def page_links(spark: SparkSession, folder: str) -> DataFrame:
    """Edges (host, path) from the hosts of pages to the targets of their links."""
    pages = scan(spark, folder, "pages", ["url", "html"])
    host = F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)
    return pages.select(host.alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("path")).distinct()


def split_of(vid: Column) -> Column:
    """train for six tenths of the ids, then validation and test for two each."""
    bucket = (vid * 31 + 7) % 10
    return F.when(bucket < 6, "train").when(bucket < 8, "validation").otherwise("test")


def language_labels(spark: SparkSession, folder: str) -> DataFrame:
    """(vid, y, split): the language of each document as a class from 0, by name."""
    docs = scan(spark, folder, "documents", ["doc_id", "lang"])
    names = [r[0] for r in docs.select("lang").where("lang is not null").distinct().orderBy("lang").collect()]
    y = (F.array_position(F.array(*map(F.lit, names)), F.col("lang")) - 1).cast("int")
    return docs.select(F.col("doc_id").alias("vid"), y.alias("y"), split_of(F.col("doc_id")).alias("split"))


def quality_labels(spark: SparkSession, folder: str) -> DataFrame:
    return scan(spark, folder, "labels").select(F.col("doc_id").alias("vid"), F.col("quality").alias("y"), split_of(F.col("doc_id")).alias("split"))
