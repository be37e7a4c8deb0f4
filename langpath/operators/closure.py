"""Transitive closure of product graphs, in the variants that the experiments compare.

A product vertex (q, u) is one number ``u * Q + q``: the graph vertex leads, so rows of one graph
vertex stay together.  Edges and closures are relations (x, y); packed rows are (x, block, word)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..runtime import Grown, Stage, local_table

XY = ["x", "y"]


def pack(q: Column | str, u: Column | str, n_states: int) -> Column:
    q, u = (F.col(c) if isinstance(c, str) else c for c in (q, u))
    return (u.cast("long") * n_states + q).cast("long")


def unpack(x: Column | str, n_states: int) -> tuple[Column, Column]:
    x = F.col(x) if isinstance(x, str) else x
    return F.pmod(x, F.lit(n_states)).cast("int"), F.floor(x / n_states).cast("long")


def _then(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("x", F.col("y").alias("m")).join(b.select(F.col("x").alias("m"), "y"), "m").select("x", "y")


def scratch(edges: DataFrame, stage: Stage, strategy: str = "squaring") -> tuple[DataFrame, int]:
    """Closure of all edges.  ``linear`` extends new pairs by an edge, ``squaring`` joins new pairs
    with all pairs on either side, so its rounds grow with the logarithm of the longest way."""
    edges, n = stage.put(edges.select(*XY).distinct())
    known, fresh, total = Grown(stage, edges), edges, n
    while n:
        step = _then(fresh, edges) if strategy == "linear" else _then(fresh, known.df).union(_then(known.df, fresh))
        fresh, n = stage.put(step.distinct().join(known.df, XY, "left_anti"))
        if n:
            known.add(fresh)
            total += n
    return known.df, total


def insert(closure: DataFrame | None, new_edges: DataFrame, stage: Stage) -> tuple[DataFrame, DataFrame, int]:
    """Add a batch of edges to a closed relation: (closure, added pairs, their number).

    Pairs that end in a new edge or begin with one, the edge's own ends included, and so on with
    the pairs that this adds; what is known is never derived again."""
    if closure is None:
        known, total = scratch(new_edges, stage)
        return known, known, total
    fresh, n = stage.put(new_edges.select(*XY).distinct().join(closure, XY, "left_anti"))
    known, added, total = Grown(stage, closure), None, 0
    while n:
        added = fresh if added is None else added.union(fresh)
        total += n
        known.add(fresh)
        step = _then(fresh, known.df).union(_then(known.df, fresh)).distinct()
        fresh, n = stage.put(step.join(known.df, XY, "left_anti"))
    return known.df, added if added is not None else closure.limit(0), total


# --------------------------------------------------------------------------- packed rows
def to_rows(pairs: DataFrame) -> DataFrame:
    """(x, block, word): bit y % 64 of block y div 64."""
    bit = F.expr("shiftleft(1L, cast(pmod(y, 64) as int))")
    return pairs.select("x", F.expr("y div 64").alias("block"), bit.alias("w")).groupBy("x", "block").agg(F.bit_or("w").alias("word"))


def to_pairs(rows: DataFrame) -> DataFrame:
    bit = rows.select("x", "block", "word", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("k")).where(F.expr("(shiftright(word, k) & 1) = 1"))
    return bit.select("x", (F.col("block") * 64 + F.col("k")).alias("y"))


def block_table(spark: SparkSession, width: int = 4) -> DataFrame:
    """a AND NOT b of all pairs of ``width``-bit blocks; 4**width rows."""
    n = 1 << width
    return spark.range(n).select(F.col("id").cast("int").alias("a")).crossJoin(spark.range(n).select(F.col("id").cast("int").alias("b"))).select("a", "b", F.col("a").bitwiseAND(F.bitwise_not("b")).alias("c"))


def and_not(new: DataFrame, known: DataFrame, table: DataFrame | None = None, width: int = 4) -> DataFrame:
    """New bits of rows: in ``new`` and not in ``known``.  With a table, block by block by look-up."""
    both = new.join(known.select("x", "block", F.col("word").alias("old")), ["x", "block"], "left").withColumn("old", F.coalesce("old", F.lit(0).cast("long")))
    if table is None:
        return both.select("x", "block", F.col("word").bitwiseAND(F.bitwise_not("old")).alias("word")).where("word <> 0")
    mask = (1 << width) - 1
    part = lambda c: F.expr(f"cast(shiftrightunsigned({c}, k * {width}) & {mask} as int)")
    cut = both.select("x", "block", "word", "old", F.explode(F.sequence(F.lit(0), F.lit(64 // width - 1))).alias("k")).select("x", "block", "k", part("word").alias("a"), part("old").alias("b"))
    hit = cut.where("a <> 0").join(F.broadcast(table), ["a", "b"]).where("c <> 0")
    return hit.groupBy("x", "block").agg(F.bit_or(F.expr(f"shiftleft(cast(c as bigint), k * {width})")).alias("word"))


def _either(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("x", "block", "word").union(b.select("x", "block", "word")).groupBy("x", "block").agg(F.bit_or("word").alias("word"))


def insert_packed(rows: DataFrame | None, new_edges: DataFrame, stage: Stage, table: DataFrame | None = None) -> tuple[DataFrame, DataFrame, int]:
    """:func:`insert` on packed rows: (rows, added rows, number of added pairs).

    Whole words travel: the row of j is joined to all x that reach j, OR-ed per word, and what
    x has already is taken out."""
    empty = local_table(new_edges.sparkSession, [], "x long, block long, word long")
    known = rows if rows is not None else empty
    fresh, n = stage.put(and_not(to_rows(new_edges), known, table))
    added, total = empty, 0
    while n:
        total += fresh.agg(F.sum(F.bit_count("word"))).first()[0]
        added = _either(added, fresh)
        known, _ = stage.put(_either(known, fresh))
        walk = lambda a, b: to_pairs(a).select("x", F.col("y").alias("m")).join(b.select(F.col("x").alias("m"), "block", "word"), "m").select("x", "block", "word")
        step = walk(fresh, known).union(walk(known, fresh)).groupBy("x", "block").agg(F.bit_or("word").alias("word"))
        fresh, n = stage.put(and_not(step, known, table))
    added, _ = stage.put(added)
    return known, added, total
