"""Boolean matrix products by blocks.

Labels that a grammar repeats (``A -> b A``) make chains, and a product adds one edge of a chain a round.  Along these labels
a graph often falls apart into small components.  A component is a block: facts with an end in it are brought together, and all
products over its vertices are made inside one task until nothing is new there.  Products over other vertices are joins.
Every fact goes to the blocks of both its ends, so the rounds end with the same facts."""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import EDGE, LabeledGraph
from ..language.grammar import Grammar, NormalForm
from ..runtime import Grown, Stage, local_table, small
from .jumps import TASK_EDGES, _in_rounds, _in_task
from .kron import HELD_ROWS

#: Components with more vertices are left to joins.
BLOCK_VERTICES = 2048
#: Blocks whose facts have more ends are solved fact by fact, not as dense matrices.
DENSE = 6144

Rule = tuple[str, str, str]


def rules_of(nf: NormalForm) -> set[Rule]:
    """Own rules, with all labels that count as their factors.  Facts are kept under the label that made them only."""
    by = defaultdict(set)
    made = {a for a, *_ in nf.own_pairs} | {a for a, _ in nf.own_units}
    for a, m in nf.alone:
        if m in made:
            by[a].add(m)
    return {(a, x, y) for a, b, c in nf.own_pairs for x in by[b] for y in by[c]}


def repeated(nf: NormalForm, rules: set[Rule]) -> set[str]:
    """Terminals t with A -> t A or A -> A t."""
    other = {b for a, b, c in rules if a == c} | {c for a, b, c in rules if a == b}
    return {t for a, t in nf.own_units if a in other}


def facts(graph: LabeledGraph, grammar: Grammar, wanted: set[str], vertices: int | None = None) -> DataFrame:
    """Facts (src, label, dst) of the wanted nonterminals by words of one label or more."""
    nf = grammar.to_binary_normal_form()
    rules = rules_of(nf)
    answer = {(w, m) for w, m in nf.alone if w in wanted}
    spark = graph.edges.sparkSession
    stage = Stage(spark)
    units = local_table(spark, sorted(nf.own_units), "a string, t string")
    base = graph.edges.join(F.broadcast(units), F.col("label") == F.col("t")).select("src", F.col("a").alias("label"), "dst")
    fresh, n = stage.put(base.distinct())
    known, held = Grown(stage, fresh), _labels(fresh)
    new = held
    roots, n_roots = _roots(graph, repeated(nf, rules), stage, BLOCK_VERTICES if vertices is None else vertices)
    while n:
        steps = [_times(fresh, new, known.df, held, rules, roots, n_roots), _times(known.df, held, fresh, new, rules, roots, n_roots)]
        if n_roots:
            steps.append(_blocks(fresh, known.df, rules, {m for _, m in answer}, roots, n_roots, stage))
        steps = [s for s in steps if s is not None]
        if not steps:
            break
        step = steps[0]
        for s in steps[1:]:
            step = step.union(s)
        step, n = stage.put(step.distinct())
        new = _labels(step)
        old = known.df.where(F.col("label").isin(sorted(new)))
        if not new & held:
            fresh = step
        elif n <= HELD_ROWS:
            again, _ = stage.put(old.join(F.broadcast(step), EDGE, "left_semi"))
            fresh, n = stage.put(step.join(F.broadcast(again), EDGE, "left_anti"))
        else:
            fresh, n = stage.put(step.join(old, EDGE, "left_anti"))
        if n:
            new = _labels(fresh)
            held = held | new
            known.add(fresh)
    names = local_table(spark, sorted(answer), "w string, m string")
    out = known.df.join(F.broadcast(names), F.col("label") == F.col("m")).select("src", F.col("w").alias("label"), "dst")
    return out.distinct() if len(answer) > len(wanted) else out


def _labels(df: DataFrame) -> set[str]:
    return {r[0] for r in df.select("label").distinct().collect()}


def _roots(graph: LabeledGraph, labels: set[str], stage: Stage, most: int) -> tuple[DataFrame | None, int]:
    """(v, root) of the vertices in blocks."""
    if not labels:
        return None, 0
    pairs, n = stage.put(graph.select_labels(labels).edges.select(F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y")).distinct())
    if not n:
        return None, 0
    roots, _ = stage.put(_in_task(pairs) if n <= TASK_EDGES else _in_rounds(pairs))
    size = roots.groupBy("root").count().where(F.col("count") <= most).select("root")
    return stage.put(roots.join(size, "root", "left_semi").select("v", "root"))


def _held(df: DataFrame, n: int) -> DataFrame:
    return F.broadcast(df) if n <= HELD_ROWS else df


def _times(left: DataFrame, in_left: set[str], right: DataFrame, in_right: set[str], rules: set[Rule], roots: DataFrame | None, n_roots: int) -> DataFrame | None:
    """Products over vertices outside of blocks."""
    some = sorted(r for r in rules if r[1] in in_left and r[2] in in_right)
    if not some:
        return None
    table = F.broadcast(local_table(left.sparkSession, some, "a string, b string, c string"))
    left = left.where(F.col("label").isin(sorted({b for _, b, _ in some})))
    right = right.where(F.col("label").isin(sorted({c for _, _, c in some})))

    def outside(df: DataFrame, end: str) -> DataFrame:
        return df.join(_held(roots.select(F.col("v").alias(end)), n_roots), end, "left_anti").select(*EDGE) if n_roots else df

    free = outside(right, "src")
    if small(free, HELD_ROWS):
        right = F.broadcast(free)
        if not free.head(1):
            return None
    elif small(ends := outside(left, "dst"), HELD_ROWS):
        left = F.broadcast(ends)
        if not ends.head(1):
            return None
    else:
        right = free
    left = left.select("src", F.col("label").alias("b"), F.col("dst").alias("m"))
    right = right.select(F.col("src").alias("m"), F.col("label").alias("c"), "dst")
    return left.join(right, "m").join(table, ["b", "c"]).select("src", F.col("a").alias("label"), "dst")


def _blocks(fresh: DataFrame, known: DataFrame, rules: set[Rule], answer: set[str], roots: DataFrame, n_roots: int, stage: Stage) -> DataFrame | None:
    """Facts made in the blocks that a fresh fact touches, as far as other vertices or the answer need them."""

    def ends(df: DataFrame) -> DataFrame:
        a, b = _held(roots.toDF("src", "s"), n_roots), _held(roots.toDF("dst", "d"), n_roots)
        at = df.join(a, "src", "left").join(b, "dst", "left").where("s is not null or d is not null")
        return at.withColumn("root", F.explode(F.array_compact(F.array_distinct(F.array("s", "d")))))

    touched, n = stage.put(ends(fresh).select("root").distinct())
    if not n:
        return None
    rows = ends(known).join(touched, "root", "left_semi")
    rows = rows.select("root", *EDGE, F.coalesce(F.col("s") == F.col("root"), F.lit(False)).alias("s"), F.coalesce(F.col("d") == F.col("root"), F.lit(False)).alias("d"))
    left, right = {b for _, b, _ in rules}, {c for _, _, c in rules}

    def run(table: pa.Table) -> pa.Table:
        src, dst, label = table["src"].to_numpy(), table["dst"].to_numpy(), table["label"].to_pylist()
        names, both = np.unique(np.concatenate((src, dst)), return_inverse=True)
        a, b = both[: len(src)], both[len(src) :]
        inner = np.zeros(len(names), bool)
        inner[a[table["s"].to_numpy(zero_copy_only=False)]] = True
        inner[b[table["d"].to_numpy(zero_copy_only=False)]] = True
        xs, ls, ys = [], [], []
        for name, x, y in (_dense if len(names) <= DENSE else _sparse)(a, label, b, inner, rules):
            keep = np.ones(len(x), bool) if name in answer else (name in left) & ~inner[y] | (name in right) & ~inner[x]
            xs.append(names[x[keep]])
            ys.append(names[y[keep]])
            ls.append(pa.array([name], pa.string()).take(pa.array(np.zeros(int(keep.sum()), np.int64))))
        if not xs:
            return pa.table({"src": pa.array([], pa.int64()), "label": pa.array([], pa.string()), "dst": pa.array([], pa.int64())})
        return pa.table({"src": np.concatenate(xs), "label": pa.chunked_array(ls), "dst": np.concatenate(ys)})

    return rows.groupBy("root").applyInArrow(run, "src long, label string, dst long")


def _dense(a: np.ndarray, label: list[str], b: np.ndarray, inner: np.ndarray, rules: set[Rule]):
    """New facts (label, x, y) of a block, by dense products over its vertices."""
    n, at = len(inner), np.flatnonzero(inner)
    name = np.array(label)
    m = {}
    for k in sorted(set(label)):
        m[k] = np.zeros((n, n), bool)
        m[k][a[name == k], b[name == k]] = True
    first = {k: x.copy() for k, x in m.items()}
    times = lambda x, y: x.astype(np.float32) @ y.astype(np.float32) > 0

    def star(x: np.ndarray) -> np.ndarray:
        x = x | np.eye(len(x), dtype=bool)
        while (y := times(x, x)).sum() != x.sum():
            x = y
        return x

    new = set(m)
    while new:
        old, new = new, set()
        for head, p, q in sorted(rules):
            if p not in m or q not in m or not {p, q} & (old | new):
                continue
            x, y = m[p][:, at], m[q][at]
            if head == q != p:  # all repetitions at once
                x = times(x, star(x[at]))
            elif head == p != q:
                y = times(star(y[:, at]), y)
            more = times(x, y)
            had = m.get(head)
            if (more & ~had if had is not None else more).any():
                m[head] = more if had is None else had | more
                new.add(head)
    for k, x in m.items():
        yield k, *np.nonzero(x & ~first[k] if k in first else x)


def _sparse(a: np.ndarray, label: list[str], b: np.ndarray, inner: np.ndarray, rules: set[Rule]):
    """The same fact by fact."""
    first = set(zip(a.tolist(), label, b.tolist(), strict=True))
    seen, todo = set(first), list(first)
    by_left, by_right = defaultdict(list), defaultdict(list)
    for head, p, q in rules:
        by_left[p].append((q, head))
        by_right[q].append((p, head))
    out, into = defaultdict(set), defaultdict(set)
    while todo:
        x, k, y = todo.pop()
        out[x, k].add(y)
        into[y, k].add(x)
        made = [(x, h, z) for q, h in by_left[k] if inner[y] for z in out[y, q]] + [(z, h, y) for p, h in by_right[k] if inner[x] for z in into[x, p]]
        for f in made:
            if f not in seen:
                seen.add(f)
                todo.append(f)
    got = defaultdict(list)
    for x, k, y in seen - first:
        got[k].append((x, y))
    for k, rows in got.items():
        yield k, *np.array(rows, np.int64).T
