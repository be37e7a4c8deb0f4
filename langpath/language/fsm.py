"""Finite automata without empty moves."""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..runtime import local_table

from . import regex as rx

TRANSITIONS = "q int, symbol string, p int"


@dataclass(frozen=True)
class Fsm:
    """States 0..n-1; several start states are allowed (a graph seen as an automaton has them)."""

    n: int
    edges: frozenset[tuple[int, str, int]]
    starts: frozenset[int]
    finals: frozenset[int]

    @property
    def alphabet(self) -> set[str]:
        return {s for _, s, _ in self.edges}

    @property
    def nullable(self) -> bool:
        return bool(self.starts & self.finals)

    def successors(self) -> dict[tuple[int, str], set[int]]:
        out: dict[tuple[int, str], set[int]] = defaultdict(set)
        for q, s, p in self.edges:
            out[q, s].add(p)
        return out

    def accepts(self, word: list[str]) -> bool:
        step, now = self.successors(), set(self.starts)
        for s in word:
            now = set().union(*(step.get((q, s), ()) for q in now), set())
        return bool(now & self.finals)

    def is_finite(self) -> bool:
        """No cycle on a way from a start to a final state: the language is finite."""
        live = self.trim()
        color = [0] * live.n
        nxt = defaultdict(set)
        for q, _, p in live.edges:
            nxt[q].add(p)

        def loops(q: int) -> bool:
            color[q] = 1
            for p in nxt[q]:
                if color[p] == 1 or (color[p] == 0 and loops(p)):
                    return True
            color[q] = 2
            return False

        return not any(color[q] == 0 and loops(q) for q in range(live.n))

    # ---- constructions
    def _renumbered(self, keep: list[int]) -> Fsm:
        new = {q: k for k, q in enumerate(keep)}
        return Fsm(len(keep), frozenset((new[q], s, new[p]) for q, s, p in self.edges if q in new and p in new), frozenset(new[q] for q in self.starts if q in new), frozenset(new[q] for q in self.finals if q in new))

    def trim(self) -> Fsm:
        """Only states on a way from a start to a final state (the starts always stay)."""

        def closure(seed: set[int], nxt: dict[int, set[int]]) -> set[int]:
            seen, todo = set(seed), list(seed)
            while todo:
                for p in nxt[todo.pop()]:
                    if p not in seen:
                        seen.add(p)
                        todo.append(p)
            return seen

        fore, back = defaultdict(set), defaultdict(set)
        for q, _, p in self.edges:
            fore[q].add(p)
            back[p].add(q)
        live = closure(set(self.starts), fore) & closure(set(self.finals), back)
        return self._renumbered(sorted(live | set(self.starts)))

    def determinize(self) -> Fsm:
        step, start = defaultdict(dict), frozenset(self.starts)
        names, todo = {start: 0}, [start]
        symbols = sorted(self.alphabet)
        move = self.successors()
        while todo:
            now = todo.pop()
            for s in symbols:
                nxt = frozenset().union(*(move.get((q, s), ()) for q in now))
                if nxt:
                    if nxt not in names:
                        names[nxt] = len(names)
                        todo.append(nxt)
                    step[names[now]][s] = names[nxt]
        edges = frozenset((q, s, p) for q, row in step.items() for s, p in row.items())
        return Fsm(len(names), edges, frozenset([0]), frozenset(k for x, k in names.items() if x & self.finals))

    def minimize(self) -> Fsm:
        """Smallest deterministic automaton, without a dead state; states in breadth-first order."""
        d = self.determinize().trim()
        if not d.starts:
            return Fsm(1, frozenset(), frozenset([0]), frozenset())
        symbols = sorted(d.alphabet)
        step = {(q, s): p for q, s, p in d.edges}
        block = {q: int(q in d.finals) for q in range(d.n)}
        while True:
            sign = {q: (block[q], *(block.get(step.get((q, s)), -1) for s in symbols)) for q in range(d.n)}
            names = {x: k for k, x in enumerate(sorted(set(sign.values())))}
            new = {q: names[sign[q]] for q in range(d.n)}
            if len(set(new.values())) == len(set(block.values())):
                break
            block = new
        start = block[next(iter(d.starts))]
        rows = {(block[q], s): block[p] for q, s, p in d.edges}
        order, todo = {start: 0}, [start]
        for b in todo:
            for s in symbols:
                if (p := rows.get((b, s))) is not None and p not in order:
                    order[p] = len(order)
                    todo.append(p)
        return Fsm(len(order), frozenset((order[q], s, order[p]) for (q, s), p in rows.items()), frozenset([0]), frozenset(order[block[q]] for q in d.finals))

    def reversed(self) -> Fsm:
        return Fsm(self.n, frozenset((p, s, q) for q, s, p in self.edges), self.finals, self.starts)

    def intersect(self, other: Fsm) -> Fsm:
        """Product automaton: states are pairs, numbered q * other.n + p."""
        edges = frozenset((a * other.n + c, s, b * other.n + d) for a, s, b in self.edges for c, t, d in other.edges if s == t)
        pair = lambda xs, ys: frozenset(x * other.n + y for x in xs for y in ys)
        return Fsm(self.n * other.n, edges, pair(self.starts, other.starts), pair(self.finals, other.finals))

    # ---- relations
    def to_df(self, spark: SparkSession) -> DataFrame:
        return local_table(spark, sorted(self.edges), TRANSITIONS)

    def as_graph(self, spark: SparkSession):
        """The automaton as a labelled graph; start and final states are marked in ``vertices``."""
        from ..graph import LabeledGraph

        edges = local_table(spark, [(q, s, p) for q, s, p in sorted(self.edges)], "src long, label string, dst long")
        vertices = local_table(spark, [(q, q in self.starts, q in self.finals) for q in range(self.n)], "id long, is_start boolean, is_final boolean")
        return LabeledGraph(edges, vertices)

    def matrices(self) -> dict[str, set[tuple[int, int]]]:
        """Coordinates of the ones of each label's Boolean matrix."""
        out: dict[str, set[tuple[int, int]]] = {}
        for q, s, p in self.edges:
            out.setdefault(s, set()).add((q, p))
        return out


def from_regex(r: rx.Regex | str, deterministic: bool = True) -> Fsm:
    """Position automaton of the expression; deterministic: made deterministic and minimal."""
    if isinstance(r, str):
        r = rx.parse(r)
    names: list[str] = [""]
    follow: set[tuple[int, int]] = set()

    def visit(node: rx.Regex) -> tuple[bool, set[int], set[int]]:
        """(nullable, first positions, last positions)"""
        if node.kind == "sym":
            names.append(node.name)
            k = {len(names) - 1}
            return False, k, k
        if node.kind == "eps":
            return True, set(), set()
        if node.kind == "none":
            return False, set(), set()
        if node.kind == "star":
            _, first, last = visit(node.parts[0])
            follow.update((a, b) for a in last for b in first)
            return True, first, last
        got = [visit(p) for p in node.parts]
        if node.kind == "alt":
            return any(g[0] for g in got), set().union(*(g[1] for g in got)), set().union(*(g[2] for g in got))
        null, first, last = True, set(), set()
        for n, f, e in got:
            follow.update((a, b) for a in last for b in f)
            first = first | f if null else first
            last = last | e if n else e
            null = null and n
        return null, first, last

    null, first, last = visit(r)
    edges = {(0, names[k], k) for k in first} | {(a, names[b], b) for a, b in follow}
    m = Fsm(len(names), frozenset(edges), frozenset([0]), frozenset(last | ({0} if null else set())))
    return m.minimize() if deterministic else m
