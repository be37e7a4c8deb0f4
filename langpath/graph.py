"""Edge-labelled directed graphs as relations."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

EDGE = ["src", "label", "dst"]


@dataclass
class LabeledGraph:
    """edges (src long, label string, dst long), distinct; vertices (id long, ...), isolated ones included.

    ``pieces`` (id long, piece long) is an optional hint: it maps each vertex to a part of the graph that
    no edge leaves.  Builders that know such parts (the events of a user) give it."""

    edges: DataFrame
    vertices: DataFrame
    pieces: DataFrame | None = None

    @classmethod
    def of(cls, edges: DataFrame, vertices: DataFrame | None = None, pieces: DataFrame | None = None) -> LabeledGraph:
        e = edges.select(F.col("src").cast("long"), F.col("label").cast("string"), F.col("dst").cast("long")).distinct()
        if vertices is None:
            vertices = e.select(F.col("src").alias("id")).union(e.select("dst")).distinct()
        return cls(e, vertices.select(F.col("id").cast("long")), pieces)

    # ---- matrix views
    def decompose(self) -> dict[str, DataFrame]:
        """One Boolean matrix, as coordinates, per label."""
        return {r[0]: self.edges.where(F.col("label") == r[0]).select("src", "dst") for r in self.edges.select("label").distinct().orderBy("label").collect()}

    def label_sets(self) -> DataFrame:
        """Adjacency matrix of label sets: src, dst, labels."""
        return self.edges.groupBy("src", "dst").agg(F.array_sort(F.collect_set("label")).alias("labels"))

    @classmethod
    def compose(cls, label_sets: DataFrame, vertices: DataFrame | None = None) -> LabeledGraph:
        return cls.of(label_sets.select("src", F.explode("labels").alias("label"), "dst"), vertices)

    # ---- derived graphs
    def with_inverses(self, labels: list[str] | None = None) -> LabeledGraph:
        """Add ``x~`` edges, all labels or some."""
        e = self.edges if labels is None else self.edges.where(F.col("label").isin(labels))
        back = e.select(F.col("dst").alias("src"), F.concat("label", F.lit("~")).alias("label"), F.col("src").alias("dst"))
        return LabeledGraph(self.edges.union(back), self.vertices, self.pieces)

    def undirected(self) -> LabeledGraph:
        """Each edge also backwards, under the same label."""
        back = self.edges.select(F.col("dst").alias("src"), "label", F.col("src").alias("dst"))
        return LabeledGraph(self.edges.union(back).distinct(), self.vertices, self.pieces)

    def reversed(self) -> LabeledGraph:
        return LabeledGraph(self.edges.select(F.col("dst").alias("src"), "label", F.col("src").alias("dst")), self.vertices, self.pieces)

    def select_labels(self, labels: set[str]) -> LabeledGraph:
        return LabeledGraph(self.edges.where(F.col("label").isin(sorted(labels))), self.vertices, self.pieces)

    def subgraph(self, keep: Column) -> LabeledGraph:
        """Vertices for which ``keep`` (over ``id``) holds, and the edges among them."""
        v = self.vertices.where(keep)
        e = self.edges.join(v.select(F.col("id").alias("src")), "src", "left_semi").join(v.select(F.col("id").alias("dst")), "dst", "left_semi")
        return LabeledGraph(e.select(*EDGE), v, self.pieces)

    def as_fsm(self):
        """The graph as an automaton whose states are all start and final (small graphs)."""
        from .language.fsm import Fsm

        ids = {r[0]: k for k, r in enumerate(self.vertices.orderBy("id").collect())}
        rows = frozenset((ids[r[0]], r[1], ids[r[2]]) for r in self.edges.collect())
        every = frozenset(range(len(ids)))
        return Fsm(len(ids), rows, every, every)

    # ---- measures
    def label_frequency(self) -> DataFrame:
        from pyspark.sql import Window

        n = self.edges.groupBy("label").agg(F.count("*").alias("n"))
        return n.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n"), "label")))

    def stats(self) -> DataFrame:
        """One row per measure: vertices, edges, and edges of each label."""
        one = lambda name, n: F.struct(F.lit(name).alias("measure"), n.alias("n"))
        v = self.vertices.agg(F.count("*").alias("n")).select(one("vertices", F.col("n")).alias("r"))
        e = self.edges.agg(F.count("*").alias("n")).select(one("edges", F.col("n")).alias("r"))
        lab = self.edges.groupBy("label").agg(F.count("*").alias("n")).select(F.struct(F.concat(F.lit("label "), "label").alias("measure"), "n").alias("r"))
        return v.union(e).union(lab).select("r.*")
