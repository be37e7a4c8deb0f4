"""Path plans and their rewrites before execution."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import LabeledGraph
from ..language import rsm
from ..operators import index as ix
from ..operators import paths as pt


@dataclass(frozen=True)
class PathPlan:
    """What is asked: machine, graph, ends, and what is returned."""

    graph: LabeledGraph
    machine: rsm.RecursiveMachine
    sources: DataFrame | None = None  # (id)
    targets: DataFrame | None = None
    mode: str = "reach"  # reach, paths, single
    max_length: int | None = None
    max_paths: int | None = None
    backward: bool = False  # graph and machine are reversed; answers are turned back
    strategy: str = "auto"


def targets_to_sources(plan: PathPlan) -> PathPlan:
    """Only targets given: search backwards from them, so only what reaches them is touched."""
    if plan.targets is None or plan.sources is not None or plan.backward:
        return plan
    return replace(plan, graph=plan.graph.reversed(), machine=plan.machine.reversed(), sources=plan.targets, targets=None, backward=True)


def rarer_end_first(plan: PathPlan) -> PathPlan:
    """No ends given and no calls: begin at the end whose first labels are rarer."""
    m = plan.machine
    if plan.sources is not None or plan.targets is not None or plan.backward or m.has_calls or m.nullable():
        return plan
    start, finals = m.boxes[m.start_box]
    first = {s for q, s, _ in m.edges if q == start}
    last = {s for _, s, p in m.edges if p in finals}
    if first == last:
        return plan
    n = {r["label"]: r["n"] for r in plan.graph.edges.where(F.col("label").isin(sorted(first | last))).groupBy("label").agg(F.count("*").alias("n")).collect()}
    total = lambda xs: sum(n.get(x, 0) for x in xs)
    if 2 * total(last) >= total(first):
        return plan
    return replace(plan, graph=plan.graph.reversed(), machine=m.reversed(), backward=True)


def prune_labels(plan: PathPlan) -> PathPlan:
    """Only labels that the machine reads."""
    return replace(plan, graph=plan.graph.select_labels(plan.machine.terminals))


RULES = (targets_to_sources, rarer_end_first, prune_labels)


def optimize(plan: PathPlan, rules=RULES) -> PathPlan:
    for rule in rules:
        plan = rule(plan)
    return plan


def execute(plan: PathPlan) -> DataFrame:
    """reach: (src, dst); paths and single: (src, dst, len, word).  Without a length bound, ``single`` finds a walk of every
    pair and ``paths`` all walks; if these are infinitely many, a bound must be given."""
    index = ix.build(plan.graph, plan.machine, sources=plan.sources, strategy=plan.strategy)
    if plan.mode == "reach":
        out = index.reachable()
    else:
        length = plan.max_length
        if length is None and plan.mode == "paths" and _infinite(index, plan.sources):
            raise ValueError("some pair is joined by infinitely many walks: give a length bound (UP TO n)")
        if plan.mode == "single":
            rows = pt.single(index, length, plan.sources)
        else:
            rows = pt.union_all(list(pt.levels(index, length, plan.sources)))
        if plan.max_paths is not None:
            rows = pt.top_k(rows, plan.max_paths)
        out = pt.as_words(_turned(rows)) if plan.backward else pt.as_words(rows)
    if plan.backward and plan.mode == "reach":
        out = out.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    if plan.targets is not None:
        end = "src" if plan.backward else "dst"
        out = out.join(plan.targets.select(F.col("id").alias(end)).distinct(), end, "left_semi")
    return out


def _infinite(index: ix.PathIndex, sources: DataFrame | None) -> bool:
    pairs = pt.is_infinite(index).where("infinite")
    if sources is not None:
        pairs = pairs.join(sources.select(F.col("id").alias("src")), "src", "left_semi")
    return not pairs.isEmpty()


def _turned(rows: DataFrame) -> DataFrame:
    """Walks of the reversed graph as walks of the graph."""
    back = F.transform(F.reverse("path"), lambda e: F.struct(e["dst"].alias("src"), e["label"].alias("label"), e["src"].alias("dst")))
    return rows.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "len", back.alias("path"))
