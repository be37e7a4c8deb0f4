"""Baselines: Boolean matrix products over a binary normal form, and level-wise product search."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import EDGE, LabeledGraph
from ..language.fsm import Fsm
from ..language.grammar import Grammar
from ..language.rsm import from_fsm
from ..runtime import Grown, Stage, local_table
from . import blocks as bl
from . import hubs as hb
from . import twins as tw


def _start(graph: LabeledGraph, grammar: Grammar):
    spark = graph.edges.sparkSession
    nf = grammar.to_binary_normal_form()
    units = local_table(spark, sorted(nf.units), "a string, t string")
    pairs = local_table(spark, sorted(nf.pairs), "a string, b string, c string") if nf.pairs else local_table(spark, [], "a string, b string, c string")
    base = graph.edges.join(F.broadcast(units), graph.edges["label"] == units["t"]).select("src", F.col("a").alias("label"), "dst")
    null = sorted(nf.nullable & nf.names)
    loops = graph.vertices.select(F.col("id").alias("src"), F.explode(F.array(*map(F.lit, null))).alias("label"), F.col("id").alias("dst")) if null else None
    return nf, pairs, base, loops


def matrix_reach(graph: LabeledGraph, grammar: Grammar, delta: bool = True, twins: bool = False, blocks: set[str] | None = None) -> DataFrame:
    """Facts (src, label, dst) of the grammar's nonterminals: for A -> B C the product of the matrices of
    B and C is added to A's until nothing changes.  ``delta``: products with a new factor only.  ``twins``: equal rows and
    columns of the label matrices are multiplied once.  ``blocks``: facts of these nonterminals only, and blocks of the matrices
    along labels that the grammar repeats are solved inside tasks.

    Empty words are folded into the rules, so reflexive facts join the answer only."""
    if twins:
        part, members = tw.reduced(graph)
        own = tw.expand(matrix_facts(part, grammar, delta), members).select(*EDGE)
        loops = _start(graph, grammar)[3]
        return own.union(loops).distinct() if loops is not None else own
    loops = _start(graph, grammar)[3]
    if blocks is not None:
        own = bl.facts(graph, grammar, blocks)
        return own.union(loops.where(F.col("label").isin(sorted(blocks)))).distinct() if loops is not None else own
    own = matrix_facts(graph, grammar, delta)
    return own.union(loops).distinct() if loops is not None else own


def matrix_facts(graph: LabeledGraph, grammar: Grammar, delta: bool = True) -> DataFrame:
    """Facts by words of one label or more."""
    nf, pairs, base, _ = _start(graph, grammar)
    stage = Stage(graph.edges.sparkSession)
    fresh, n = stage.put(base.distinct())
    known = Grown(stage, fresh)

    def times(left: DataFrame, right: DataFrame) -> DataFrame:
        head = left.join(F.broadcast(pairs), left["label"] == pairs["b"]).select("src", "a", "c", F.col("dst").alias("m"))
        tail = right.select(F.col("src").alias("m"), F.col("label").alias("c"), "dst")
        return head.join(tail, ["m", "c"]).select("src", F.col("a").alias("label"), "dst")

    while n:
        step = times(fresh, known.df).union(times(known.df, fresh)) if delta else times(known.df, known.df)
        fresh, n = stage.put(step.distinct().join(known.df, EDGE, "left_anti"))
        if n:
            known.add(fresh)
    return known.df.where(F.col("label").isin(sorted(nf.names)))


def matrix_single_path(graph: LabeledGraph, grammar: Grammar) -> DataFrame:
    """Single-path semantics: (src, label, dst, len, mid, left, right) with the length of a shortest word and
    the last split of its derivation; a fact of one edge has no split."""
    nf, pairs, base, loops = _start(graph, grammar)
    stage = Stage(graph.edges.sparkSession)
    none = [F.lit(None).cast("long").alias("mid"), F.lit(None).cast("string").alias("left"), F.lit(None).cast("string").alias("right")]
    known, n = stage.put(base.distinct().select(*EDGE, F.lit(1).alias("len"), *none))
    fresh = known

    def times(left: DataFrame, right: DataFrame) -> DataFrame:
        head = left.join(F.broadcast(pairs), left["label"] == pairs["b"]).select("src", "a", "b", "c", F.col("dst").alias("m"), F.col("len").alias("l1"))
        tail = right.select(F.col("src").alias("m"), F.col("label").alias("c"), "dst", F.col("len").alias("l2"))
        return head.join(tail, ["m", "c"]).select("src", F.col("a").alias("label"), "dst", (F.col("l1") + F.col("l2")).alias("len"), F.col("m").alias("mid"), F.col("b").alias("left"), F.col("c").alias("right"))

    best = lambda df: df.groupBy(*EDGE).agg(F.min(F.struct("len", "mid", "left", "right")).alias("x")).select(*EDGE, "x.*")
    while n:
        step = best(times(fresh, known).union(times(known, fresh)))
        old = known.select(*EDGE, F.col("len").alias("old"))
        fresh, n = stage.put(step.join(old, EDGE, "left").where("old is null or len < old").drop("old"))
        if n:
            known, _ = stage.put(best(known.unionByName(fresh)))
    own = known
    if loops is not None:
        own = best(known.unionByName(loops.select(*EDGE, F.lit(0).alias("len"), *none)))
    return own


def extract_single(single: DataFrame, grammar: Grammar, src: int, label: str, dst: int, graph: LabeledGraph) -> list[tuple[int, str, int]]:
    """The walk of one fact, by following the splits; reads one row per step of the derivation."""
    nf = grammar.to_binary_normal_form()
    r = single.where((F.col("src") == src) & (F.col("label") == label) & (F.col("dst") == dst)).first()
    if r is None:
        raise KeyError((src, label, dst))
    if r["len"] == 0:
        return []
    if r["mid"] is None:
        names = sorted(t for a, t in nf.units if a == label)
        e = graph.edges.where((F.col("src") == src) & (F.col("dst") == dst) & F.col("label").isin(names)).orderBy("label").first()
        return [(src, e["label"], dst)]
    return extract_single(single, grammar, src, r["left"], r["mid"], graph) + extract_single(single, grammar, r["mid"], r["right"], dst, graph)


def bfs(graph: LabeledGraph, machine: Fsm, sources: DataFrame | None = None, by_hubs: bool = False) -> DataFrame:
    """Regular reachability by level-wise search of the product, each level one join.  ``by_hubs``: pairs joined by a hub of the
    product are found by the search of the hub, and the search of a source stops there."""
    if by_hubs:
        return hb.answers(graph, from_fsm(machine), sources)
    spark = graph.edges.sparkSession
    stage = Stage(spark)
    m = machine.determinize()
    step = F.broadcast(m.to_df(spark)) if m.edges else None
    edges, _ = stage.put(graph.select_labels(m.alphabet).edges)
    base = (sources if sources is not None else graph.vertices).select(F.col("id").alias("s"), F.lit(next(iter(m.starts))).alias("q"), F.col("id").alias("v"))
    seen, n = stage.put(base)
    level = seen
    while n and step is not None:
        nxt = level.join(step, "q").select("s", "p", F.col("v").alias("src"), F.col("symbol").alias("label")).join(edges, ["src", "label"]).select("s", F.col("p").alias("q"), F.col("dst").alias("v"))
        level, n = stage.put(nxt.distinct().join(seen, ["s", "q", "v"], "left_anti"))
        seen = seen.union(level)
    return seen.where(F.col("q").isin(sorted(m.finals))).select(F.col("s").alias("src"), F.col("v").alias("dst")).distinct()
