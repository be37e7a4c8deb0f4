"""Vertices with the same edges, solved once.

Twins have equal outgoing and equal incoming edges, labels included.  A walk of one edge or more from u to v
stays one, with the same word, when u or v is replaced by a twin.  So the least vertex of each class stands for all: facts
of the graph induced on these are the facts of the whole graph, each pair for the rectangle of two classes.  Rectangles
are written out last, array by array, and nothing of their size is shuffled, sorted or kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..graph import EDGE, LabeledGraph
from ..runtime import Stage
from .kron import meet_tiles


def reduced(graph: LabeledGraph) -> tuple[LabeledGraph, DataFrame]:
    """The graph on one vertex of each class, and (id, twin) of all vertices with edges.

    Classes are proposed by hashes of the edges and proved by counting: between two classes there are either all
    edges of a label or none.  A class that fails is taken apart, so a collision of hashes changes no answer."""
    stage = Stage(graph.edges.sparkSession)
    e, _ = stage.put(graph.edges.select(*EDGE).distinct())
    ends = e.select(F.col("src").alias("id"), F.xxhash64(F.lit(0), "label", "dst").alias("h"), F.xxhash64(F.lit(1), "dst", "label").alias("k"))
    ends = ends.union(e.select("dst", F.xxhash64(F.lit(2), "label", "src"), F.xxhash64(F.lit(3), "src", "label")))
    sign = ends.groupBy("id").agg(F.bit_xor("h").alias("h"), F.bit_xor("k").alias("k"), F.count("*").alias("n"))
    w = Window.partitionBy("h", "k", "n")
    members, _ = stage.put(sign.select("id", F.min("id").over(w).alias("twin"), F.count("*").over(w).alias("size")))
    a = members.select(F.col("id").alias("src"), F.col("twin").alias("a"), F.col("size").alias("n_a"))
    b = members.select(F.col("id").alias("dst"), F.col("twin").alias("b"), F.col("size").alias("n_b"))
    cells, _ = stage.put(e.join(a, "src").join(b, "dst").groupBy("a", "label", "b", "n_a", "n_b").agg(F.count("*").alias("n")))
    torn = cells.where(F.col("n") != F.col("n_a") * F.col("n_b"))
    torn, n = stage.put(torn.select(F.col("a").alias("twin")).union(torn.select("b")).distinct())
    members = members.select("id", "twin")
    edges = cells.select(F.col("a").alias("src"), "label", F.col("b").alias("dst"))
    if n:
        alone = torn.withColumn("torn", F.lit(True))
        members, _ = stage.put(members.join(alone, "twin", "left").select("id", F.when(F.col("torn"), F.col("id")).otherwise(F.col("twin")).alias("twin")))
        edges, _ = stage.put(e.join(members.select(F.col("id").alias("src")).where("id = twin"), "src", "left_semi").join(members.where("id = twin").select(F.col("id").alias("dst")), "dst", "left_semi").select(*EDGE))
    return LabeledGraph(edges, members.where("id = twin").select("id")), members


def expand(pairs: DataFrame, members: DataFrame) -> DataFrame:
    """Rows (src, dst, ...) of the reduced graph for all members of the classes of src and dst."""
    rest = [c for c in pairs.columns if c not in ("src", "dst")]
    left = pairs.join(members.select(F.col("twin").alias("src"), F.col("id").alias("u")), "src")
    right = members.select(F.col("twin").alias("dst"), F.col("id").alias("v"))
    return meet_tiles(left, right, "dst").select(F.col("u").alias("src"), F.col("v").alias("dst"), *rest)
