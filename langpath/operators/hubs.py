"""Regular reachability of all pairs by hubs of the product graph.

A hub is a product vertex (q, u) in a cycle of the machine.  What reaches it, B, and what it reaches, F, are found by one level-wise
search each, linear in the edges, and every pair of B x F is an answer.  A few hubs often carry nearly all of a
quadratic answer: each product vertex gets the set of its hubs as bits, and pairs whose bits meet are
written out last, each once, from these two linear tables.  The other pairs are found by level-wise search from every source, which
leaves a vertex out as soon as hubs join it to the source, for then they join all that follows as well."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..graph import EDGE, LabeledGraph
from ..language.rsm import RecursiveMachine
from ..runtime import Grown, Stage, local_table
from .kron import meet_tiles

#: Product graphs of up to this many edges (two longs each) are searched for hubs inside one task.
TASK_EDGES = 8_000_000
MOST = 62


def _knots(machine: RecursiveMachine) -> dict[int, int]:
    """States on cycles of the machine, with the number of their strongly connected part."""
    reach = {q: machine._states(q) for q in range(machine.n)}
    part: dict[int, int] = {}
    for q in range(machine.n):
        ring = {p for p in reach[q] if q in reach[p]}
        if len(ring) > 1 or any(a == b == q for a, _, b in machine.edges):
            part[q] = min(ring)
    return part


def _search(nxt: tuple[np.ndarray, np.ndarray], root: int) -> np.ndarray:
    """Which of the numbered vertices a root reaches, itself included."""
    first, to = nxt
    seen = np.zeros(len(first) - 1, bool)
    seen[root] = True
    level = np.array([root])
    while len(level):
        n = first[level + 1] - first[level]
        at = np.repeat(first[level] - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum())
        fresh = np.unique(to[at])
        level = fresh[~seen[fresh]]
        seen[level] = True
    return seen


def _masks(x: np.ndarray, y: np.ndarray, n_states: int, knots: dict[int, int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(vertex, bits of the hubs that reach it, bits of the hubs it reaches)."""
    names, both = np.unique(np.concatenate((x, y)), return_inverse=True)
    a, b = both[: len(x)].astype(np.int32), both[len(x) :].astype(np.int32)

    def rows(s: np.ndarray, t: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return np.concatenate(([0], np.cumsum(np.bincount(s, minlength=len(names))))), t[np.argsort(s, kind="stable")]

    fore, back = rows(a, b), rows(b, a)
    score = np.minimum(np.diff(fore[0]), np.diff(back[0]))
    score[~np.isin(names % n_states, list(knots))] = 0
    after, before = np.zeros(len(names), np.int64), np.zeros(len(names), np.int64)
    for k in range(MOST):
        root = int(np.argmax(score)) if len(score) else 0
        if not len(score) or score[root] == 0:
            break
        f, g = _search(fore, root), _search(back, root)
        score[f & g] = 0  # their part of the graph has its hub
        if int(f.sum()) * int(g.sum()) < 8 * len(names):
            break  # the search from every source does these pairs as well
        after[f] |= 1 << k
        before[g] |= 1 << k
    return names, after, before


def _in_task(product: DataFrame, n_states: int, knots: dict[int, int]) -> DataFrame:
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        got = [(f["x"].to_numpy(np.int64), f["y"].to_numpy(np.int64)) for f in frames]
        if got:
            x, y = (np.concatenate(c) for c in zip(*got, strict=True))
            names, after, before = _masks(x, y, n_states, knots)
            for k in range(0, len(names), 100_000):
                s = slice(k, k + 100_000)
                yield pd.DataFrame({"x": names[s], "after": after[s], "before": before[s]})

    return product.coalesce(1).mapInPandas(run, "x long, after long, before long")


def _in_rounds(product: DataFrame, n_states: int, knots: dict[int, int], stage: Stage) -> DataFrame:
    """The same by joins: one hub for each part of the machine, both directions in one relation."""
    spark = product.sparkSession
    q = F.pmod("x", F.lit(n_states)).cast("int")
    degree = product.select("x", F.lit(1).alias("o"), F.lit(0).alias("i")).union(product.select("y", F.lit(0), F.lit(1))).groupBy("x").agg(F.least(F.sum("o"), F.sum("i")).alias("score"))
    part = F.broadcast(local_table(spark, sorted(knots.items()), "q int, part int"))
    best = degree.where("score > 0").withColumn("q", q).join(part, "q").groupBy("part").agg(F.max_by("x", F.struct("score", "x")).alias("x")).collect()
    ways = product.select(F.lit(0).alias("dir"), "x", "y").union(product.select(F.lit(1), "y", "x"))
    fresh, n = stage.put(local_table(spark, [(d, r["x"], 1 << k) for k, r in enumerate(best) for d in (0, 1)], "dir int, x long, hub long"))
    known = Grown(stage, fresh)
    while n:
        step = fresh.join(ways, ["dir", "x"]).select("dir", F.col("y").alias("x"), "hub").distinct()
        fresh, n = stage.put(step.join(known.df, ["dir", "x", "hub"], "left_anti"))
        if n:
            known.add(fresh)
    bits = lambda d: F.coalesce(F.bit_or(F.when(F.col("dir") == d, F.col("hub"))), F.lit(0)).cast("long")
    return known.df.groupBy("x").agg(bits(0).alias("after"), bits(1).alias("before"))


def _meet_bits(a: str | Column, b: str | Column) -> Column:
    return (F.col(a) if isinstance(a, str) else a).bitwiseAND(F.col(b) if isinstance(b, str) else b) != 0


def answers(graph: LabeledGraph, machine: RecursiveMachine, sources: DataFrame | None = None, task_edges: int | None = None) -> DataFrame:
    """Distinct pairs (src, dst) of a deterministic machine without calls."""
    spark, n = graph.edges.sparkSession, machine.n
    stage = Stage(spark)
    start, finals = machine.boxes[machine.start_box]
    accepted = F.pmod("x", F.lit(n)).cast("int").isin(sorted(finals))
    vertex = lambda x: F.expr(f"({x} - pmod({x}, {n})) div {n}")
    moves = F.broadcast(machine.transitions_df(spark).select(F.col("symbol").alias("label"), "q", "p"))
    product = graph.edges.select(*EDGE).join(moves, "label").select((F.col("src") * n + F.col("q")).alias("x"), (F.col("dst") * n + F.col("p")).alias("y"))
    product, size = stage.put(product.distinct())
    knots = _knots(machine)
    in_task = size <= (TASK_EDGES if task_edges is None else task_edges)
    masks, _ = stage.put(_in_task(product, n, knots) if in_task else _in_rounds(product, n, knots, stage))
    seeds = (sources if sources is not None else graph.vertices).select(F.col("id").cast("long").alias("src")).distinct()
    seeds = seeds.withColumn("x", F.col("src") * n + start).join(masks.select("x", "after", "before"), "x", "left")
    src, _ = stage.put(seeds.select("src", "x", F.coalesce("before", F.lit(0)).alias("m"), F.coalesce("after", F.lit(0)).alias("after")))
    dst, _ = stage.put(masks.where(accepted & (F.col("after") != 0)).groupBy(vertex("x").alias("dst")).agg(F.bit_or("after").alias("k")))
    # rectangles of classes whose bits meet
    met = src.select("m").distinct().crossJoin(F.broadcast(dst.select("k").distinct())).where(_meet_bits("m", "k"))
    met, _ = stage.put(met)
    square = meet_tiles(src.where("m != 0").select("src", "m").join(F.broadcast(met), "m").select("src", "k"), dst, "k").select("src", "dst")
    # pairs that no hub joins
    links, _ = stage.put(product.join(masks.select(F.col("x").alias("y"), "after"), "y", "left").select("x", "y", F.coalesce("after", F.lit(0)).alias("after")))
    fresh, m = stage.put(src.where(~_meet_bits("m", "after")).select("src", "m", "x"))
    seen = Grown(stage, fresh)
    while m:
        step = fresh.join(links, "x").where(~_meet_bits("m", "after")).select("src", "m", F.col("y").alias("x")).distinct()
        fresh, m = stage.put(step.join(seen.df, ["src", "m", "x"], "left_anti"))
        if m:
            seen.add(fresh)
    single = seen.df.where(accepted).select("src", "m", vertex("x").alias("dst")).distinct().join(dst, "dst", "left")
    return square.union(single.where(~_meet_bits("m", F.coalesce("k", F.lit(0)))).select("src", "dst"))
