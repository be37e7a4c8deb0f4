"""Recursive state machines: one automaton (box) per nonterminal, in one numbering of states."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..runtime import local_table

from . import fsm as fa
from . import grammar as gr
from . import regex as rx


@dataclass(frozen=True)
class RecursiveMachine:
    start_box: str
    edges: tuple[tuple[int, str, int], ...]
    boxes: dict[str, tuple[int, frozenset[int]]]  # name -> start state, final states
    n: int

    @property
    def calls(self) -> set[str]:
        return {s for _, s, _ in self.edges if s in self.boxes}

    @property
    def has_calls(self) -> bool:
        return bool(self.calls)

    @property
    def terminals(self) -> set[str]:
        return {s for _, s, _ in self.edges} - set(self.boxes)

    def size(self) -> int:
        """States over all boxes."""
        return self.n

    def nullable(self) -> set[str]:
        """Boxes that accept the empty word, calls of such boxes included."""
        null: set[str] = set()
        while True:
            free = {(q, p) for q, s, p in self.edges if s in null}
            new = set()
            for name, (start, finals) in self.boxes.items():
                seen, todo = {start}, [start]
                for q in todo:
                    for a, b in free:
                        if a == q and b not in seen:
                            seen.add(b)
                            todo.append(b)
                if seen & finals:
                    new.add(name)
            if new == null:
                return null
            null = new

    def with_start(self, box: str) -> RecursiveMachine:
        if box not in self.boxes:
            raise ValueError(f"no box {box}")
        return RecursiveMachine(box, self.edges, self.boxes, self.n)

    def transitions(self) -> list[tuple[int, str, int, bool]]:
        return sorted((q, s, p, s in self.boxes) for q, s, p in self.edges)

    def transitions_df(self, spark: SparkSession) -> DataFrame:
        return local_table(spark, self.transitions(), "q int, symbol string, p int, is_call boolean")

    def boxes_df(self, spark: SparkSession) -> DataFrame:
        rows = [(b, s, f) for b, (s, fs) in sorted(self.boxes.items()) for f in sorted(fs)]
        return local_table(spark, rows, "box string, start int, final int")

    def reversed(self) -> RecursiveMachine:
        """The machine of the reversed words: each box's automaton reversed, calls kept."""
        parts = {}
        for name, (start, finals) in self.boxes.items():
            own = self._states(start)
            number = {q: k for k, q in enumerate(sorted(own))}
            edges = frozenset((number[p], s, number[q]) for q, s, p in self.edges if q in own)
            parts[name] = fa.Fsm(len(own), edges, frozenset(number[f] for f in finals if f in own), frozenset([number[start]])).minimize()
        return assemble(self.start_box, parts)

    def _states(self, start: int) -> set[int]:
        seen, todo = {start}, [start]
        for q in todo:
            for a, _, b in self.edges:
                if a == q and b not in seen:
                    seen.add(b)
                    todo.append(b)
        return seen

    def accepts(self, word: list[str]) -> bool:
        """Run on a word; configurations that share a box and a position are explored once, so
        left recursion ends."""
        from ..operators.solver import solve

        if not word:
            return self.start_box in self.nullable()
        line = [(i, s, i + 1) for i, s in enumerate(word)]
        return (0, len(word)) in solve(line, self, sources=[0]).get(self.start_box, set())


def assemble(start: str, parts: dict[str, fa.Fsm]) -> RecursiveMachine:
    edges: list[tuple[int, str, int]] = []
    boxes: dict[str, tuple[int, frozenset[int]]] = {}
    base = 0
    for name, m in parts.items():
        (first,) = m.starts
        edges += [(q + base, s, p + base) for q, s, p in sorted(m.edges)]
        boxes[name] = (first + base, frozenset(f + base for f in m.finals))
        base += m.n
    return RecursiveMachine(start, tuple(edges), boxes, base)


def from_grammar(g: gr.Grammar | str, start: str | None = None, minimize: bool = True) -> RecursiveMachine:
    if isinstance(g, str):
        g = gr.parse(g, start)
    order = [g.start, *(n for n in g.rules if n != g.start)]
    parts = {}
    for n in order:
        m = fa.from_regex(g.rules[n], deterministic=minimize)
        parts[n] = m
    return assemble(g.start, parts)


def from_regex(r: rx.Regex | str, name: str = "S") -> RecursiveMachine:
    """A single box without calls."""
    return assemble(name, {name: fa.from_regex(r)})


def from_fsm(m: fa.Fsm, name: str = "S") -> RecursiveMachine:
    return assemble(name, {name: m.minimize()})
