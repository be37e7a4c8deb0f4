"""Kronecker products, over coordinates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..graph import LabeledGraph
from ..runtime import Stage, small

#: Right sides of up to this many rows are broadcast.
HELD_ROWS = 1_500_000
#: Rows of one key that are kept as one array, on either side.
TILE_ROWS = 256


def matrix(a: DataFrame, b: DataFrame, rows_b: int, cols_b: int, b_is_small: bool = False) -> DataFrame:
    """Product of numeric coordinate matrices (i, j, x): block (i, j) of the result is x times b."""
    right = b.select(F.col("i").alias("k"), F.col("j").alias("l"), F.col("x").alias("y"))
    pairs = a.crossJoin(F.broadcast(right) if b_is_small else right)
    return pairs.select((F.col("i") * rows_b + F.col("k")).alias("i"), (F.col("j") * cols_b + F.col("l")).alias("j"), (F.col("x") * F.col("y")).alias("x"))


def _tasks(df: DataFrame) -> int:
    spark = df.sparkSession
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)


def meet(left: DataFrame, right: DataFrame, key: str, held: int = HELD_ROWS, on: Column | None = None) -> DataFrame:
    """Join on a key of few values, whose result is far larger than its factors: left rows are dealt evenly, and the right
    rows of a key wait in a hash table, so that result rows leave as they are made.  Nothing is sorted or spilled.

    A right side of a checked size (``held`` rows) is broadcast.  Else left rows draw a share and right rows go to each: the
    result has as many rows for a right row as left has for its key, so the copies cost less than the result does.
    ``on``: a further condition, over both sides."""
    n = int(left.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if small(right, held):
        one, each, keys = left.repartition(_tasks(left)), F.broadcast(right), [key]
    else:
        share = F.pmod(F.xxhash64(*left.columns), F.lit(n)).cast("int")
        one = left.withColumn("share", share).repartition(n, key, "share")
        each = right.withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).repartition(n, key, "share").hint("shuffle_hash")
        keys = [key, "share"]
    if on is None:
        return one.join(each, keys).drop("share")
    each = each.withColumnsRenamed({k: f"_{k}" for k in keys})
    same = [F.col(k) == F.col(f"_{k}") for k in keys]
    return one.join(each, [*same, on]).drop("share", *(f"_{k}" for k in keys))


def _tiles(df: DataFrame, key: str, name: str, least: int = TILE_ROWS) -> DataFrame:
    """Arrays of ``TILE_ROWS`` rows of a key; of fewer, but ``least``, while there is not an array for each task."""
    rest = [c for c in df.columns if c != key]
    df, _ = Stage(df.sparkSession).put(df)
    size = F.greatest(F.lit(least), F.least(F.lit(TILE_ROWS), F.ceil(F.count(F.lit(1)) / _tasks(df))))
    many = df.groupBy(key).agg(F.ceil(F.count(F.lit(1)) / size).alias("many"))
    tile = F.pmod(F.xxhash64(*rest), F.col("many")).alias("tile")
    return df.join(many, key).select(key, *rest, tile).groupBy(key, "tile").agg(F.collect_list(F.struct(*rest)).alias(name)).drop("tile")


def meet_tiles(left: DataFrame, right: DataFrame, key: str) -> DataFrame:
    """:func:`meet` with result rows in an order that files of columns hold in few bits: arrays of some ``TILE_ROWS`` rows
    meet, and two arrays are written out together.  So the columns of the left side come in runs and those of the right
    repeat within the reach of a compressor; row by row, both cost a file their full width.

    Arrays are unrolled inside the JVM.  Generated code holds all that one input row gives before it hands on the first of it, so
    the join and the outer unrolling carry a lambda: Spark has no generated code for these, and their rows leave one by one."""
    lc, rc = ([c for c in df.columns if c != key] for df in (left, right))
    pairs = F.exists(F.array(F.size("_a")), lambda n: n + F.size("_b") > 0)
    both = meet(_tiles(left, key, "_a", 16), _tiles(right, key, "_b"), key, HELD_ROWS // TILE_ROWS, pairs)
    outer = both.select(key, F.inline(F.transform("_a", lambda x: x)), "_b")
    return outer.select(key, *lc, F.inline("_b")).select(key, *lc, *rc)


def graphs(g: LabeledGraph, h: LabeledGraph) -> DataFrame:
    """Product edges (src1, src2, label, dst1, dst2): pairs of edges with one label.  Give the larger graph first."""
    left = g.edges.select(F.col("src").alias("src1"), "label", F.col("dst").alias("dst1"))
    right = h.edges.select(F.col("src").alias("src2"), "label", F.col("dst").alias("dst2"))
    return meet_tiles(left, right, "label").select("src1", "src2", "label", "dst1", "dst2")


def label_sets(g: LabeledGraph, h: LabeledGraph, sep: str | None = None) -> DataFrame:
    """The same on adjacency matrices of label sets: cells intersect, empty cells vanish.  ``sep``: labels as one text.

    Sets are few and cells many: sets meet first, each pair of sets is intersected once, and cells follow by the name of their set."""
    name = lambda labels: F.array_join(labels, "\x00")
    left = g.label_sets().select(F.col("src").alias("src1"), F.col("dst").alias("dst1"), name("labels").alias("l1"), "labels")
    right = h.label_sets().select(F.col("src").alias("src2"), F.col("dst").alias("dst2"), name("labels").alias("l2"), "labels")
    stage = Stage(g.edges.sparkSession)
    (left, _), (right, _) = stage.put(left), stage.put(right)
    sets = lambda df, k, c: df.select(k, F.col("labels").alias(c)).distinct()
    both = F.array_sort(F.array_intersect("a", "b"))
    met = sets(left, "l1", "a").crossJoin(sets(right, "l2", "b")).where(F.arrays_overlap("a", "b"))
    met, _ = stage.put(met.select("l1", "l2", (F.array_join(both, sep) if sep is not None else both).alias("labels")))
    cells = left.select("src1", "dst1", "l1").join(F.broadcast(met), "l1")
    return meet_tiles(cells, right.select("src2", "dst2", "l2"), "l2").select("src1", "src2", "dst1", "dst2", "labels")


def families(m: dict[str, DataFrame], n: dict[str, DataFrame]) -> dict[str, DataFrame]:
    """Product of Boolean families: per common label the product of its matrices."""
    out = {}
    for label in sorted(m.keys() & n.keys()):
        left = m[label].select(F.col("src").alias("src1"), F.col("dst").alias("dst1"))
        right = n[label].select(F.col("src").alias("src2"), F.col("dst").alias("dst2"))
        out[label] = left.crossJoin(right).select("src1", "src2", "dst1", "dst2")
    return out


def collapse(product: DataFrame) -> DataFrame:
    """Boolean sum over the labels."""
    return product.select("src1", "src2", "dst1", "dst2").distinct()


def machine_product(transitions: DataFrame, edges: DataFrame) -> DataFrame:
    """Index edges (q, u, symbol, p, v, is_call) of a machine and a graph; the machine is a few
    rows and is broadcast, so edges are not moved."""
    t = F.broadcast(transitions)
    return edges.join(t, edges["label"] == t["symbol"]).select("q", F.col("src").alias("u"), "symbol", "p", F.col("dst").alias("v"), "is_call")


def flatten(q: Column, u: Column, n: int) -> Column:
    return (q * n + u).cast("long")


def unflatten(x: Column, n: int) -> tuple[Column, Column]:
    return F.floor(x / n).cast("int"), (x % n).cast("long")


def project_path(path: Column, side: int) -> Column:
    """One component of a walk of the product: array of (src, label, dst)."""
    return F.transform(path, lambda e: F.struct(e[f"src{side}"].alias("src"), e["label"].alias("label"), e[f"dst{side}"].alias("dst")))
