"""In-memory solver for one graph piece: used inside tasks (one component of a graph, or a graph
of a checked size) and as the reference in tests.  Works on plain Python tuples."""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterable, Iterator

Edge = tuple[int, str, int]


def solve(edges: Iterable[Edge], machine, sources: Iterable[int] | None = None, vertices: Iterable[int] | None = None, boxes: Iterable[str] | None = None) -> dict[str, set[tuple[int, int]]]:
    """Facts of the wanted boxes (default: the start box) by a demand-driven worklist: a box is
    entered at a vertex only when a walk calls it there.  Without ``sources`` every vertex is one."""
    adj: dict[tuple[str, int], list[int]] = defaultdict(list)
    seen_v: set[int] = set(vertices or ())
    for u, s, v in set(edges):
        adj[s, u].append(v)
        seen_v.update((u, v))
    step: dict[int, list[tuple[str, int, bool]]] = defaultdict(list)
    for q, s, p, call in machine.transitions():
        step[q].append((s, p, call))
    finals = {name: f for name, (_, f) in machine.boxes.items()}
    starts = {name: q for name, (q, _) in machine.boxes.items()}
    facts: dict[str, dict[int, set[int]]] = {name: defaultdict(set) for name in machine.boxes}
    waiting: dict[tuple[str, int], list[tuple[str, int, int]]] = defaultdict(list)
    reach: set[tuple[str, int, int, int]] = set()
    todo: list[tuple[str, int, int, int]] = []

    def add(x: tuple[str, int, int, int]) -> None:
        if x not in reach:
            reach.add(x)
            todo.append(x)

    for name in boxes or (machine.start_box,):
        for u in seen_v if sources is None else sources:
            add((name, u, starts[name], u))
    while todo:
        box, u, q, v = todo.pop()
        if q in finals[box] and v not in facts[box][u]:
            facts[box][u].add(v)
            for b2, u2, p2 in waiting[box, u]:
                add((b2, u2, p2, v))
        for s, p, call in step[q]:
            if call:
                waiting[s, v].append((box, u, p))
                add((s, v, starts[s], v))
                for w in tuple(facts[s][v]):
                    add((box, u, p, w))
            else:
                for w in adj.get((s, v), ()):
                    add((box, u, p, w))
    return {name: {(u, v) for u, vs in rows.items() for v in vs} for name, rows in facts.items()}


def regular_pairs(edges: Iterable[Edge], step: dict[tuple[int, str], int], start: int, finals: set[int], n_states: int, vertices: Iterable[int]) -> Iterator[tuple[int, int]]:
    """Answer pairs of a deterministic automaton on one piece, by rows of bits: the row of product
    vertex (q, u) has a bit per product vertex it reaches, and rows are joined by OR."""
    names = sorted(set(vertices))
    number = {u: k for k, u in enumerate(names)}
    nxt: dict[int, list[int]] = defaultdict(list)
    by_symbol: dict[str, list[tuple[int, int]]] = defaultdict(list)
    for (q, s), p in step.items():
        by_symbol[s].append((q, p))
    for u, s, v in set(edges):
        for q, p in by_symbol.get(s, ()):
            nxt[number[u] * n_states + q].append(number[v] * n_states + p)
    rows = close_rows(nxt)
    final_mask = 0
    for k in range(len(names)):
        for f in finals:
            final_mask |= 1 << (k * n_states + f)
    for k, u in enumerate(names):
        x = k * n_states + start
        bits = rows.get(x, 0) & final_mask
        if start in finals:
            bits |= 1 << x
        seen = set()
        while bits:
            low = bits & -bits
            seen.add((low.bit_length() - 1) // n_states)
            bits ^= low
        for j in seen:
            yield u, names[j]


def close_rows(nxt: dict[int, list[int]]) -> dict[int, int]:
    """Rows of bits of the transitive closure.  Strongly connected parts share one row and are
    finished in reverse topological order (iterative depth-first search)."""
    index: dict[int, int] = {}
    low: dict[int, int] = {}
    rows: dict[int, int] = {}
    on: set[int] = set()
    stack: list[int] = []
    for root in list(nxt):
        if root in index:
            continue
        work = [(root, iter(nxt.get(root, ())))]
        index[root] = low[root] = len(index)
        stack.append(root)
        on.add(root)
        while work:
            x, it = work[-1]
            for y in it:
                if y not in index:
                    index[y] = low[y] = len(index)
                    stack.append(y)
                    on.add(y)
                    work.append((y, iter(nxt.get(y, ()))))
                    break
                if y in on:
                    low[x] = min(low[x], index[y])
            else:
                work.pop()
                if work:
                    low[work[-1][0]] = min(low[work[-1][0]], low[x])
                if low[x] == index[x]:
                    part = []
                    while True:
                        y = stack.pop()
                        on.discard(y)
                        part.append(y)
                        if y == x:
                            break
                    inside = set(part)
                    bits = 0
                    cyclic = len(part) > 1
                    for y in part:
                        for z in nxt.get(y, ()):
                            bits |= 1 << z
                            if z in inside:
                                cyclic = True
                            else:
                                bits |= rows.get(z, 0)
                    if cyclic:
                        for y in part:
                            bits |= 1 << y
                    for y in part:
                        rows[y] = bits
    return rows


def bounded_paths(edges: Iterable[Edge], machine, max_length: int, sources: Iterable[int] | None = None, vertices: Iterable[int] | None = None) -> Iterator[tuple[int, int, tuple[Edge, ...]]]:
    """All walks of at most ``max_length`` edges that the start box accepts, as a least fixpoint
    over bounded sets; ends for left-recursive, ambiguous and nullable machines."""
    adj: dict[tuple[str, int], list[Edge]] = defaultdict(list)
    seen_v: set[int] = set(vertices or ())
    for e in set(edges):
        adj[e[1], e[0]].append(e)
        seen_v.update((e[0], e[2]))
    step: dict[int, list[tuple[str, int, bool]]] = defaultdict(list)
    for q, s, p, call in machine.transitions():
        step[q].append((s, p, call))
    partial: set[tuple] = set()
    done: dict[tuple[str, int], set[tuple[Edge, ...]]] = defaultdict(set)
    waiting: dict[tuple[str, int], list[tuple]] = defaultdict(list)
    todo: list[tuple] = []

    def add(x: tuple) -> None:
        if len(x[4]) <= max_length and x not in partial:
            partial.add(x)
            todo.append(x)

    for u in seen_v if sources is None else sources:
        add((machine.start_box, u, machine.boxes[machine.start_box][0], u, ()))
    while todo:
        box, u, q, v, path = todo.pop()
        if q in machine.boxes[box][1] and path not in done[box, u]:
            done[box, u].add(path)
            for b2, u2, p2, _, before in tuple(waiting[box, u]):
                add((b2, u2, p2, v, before + path))
        for s, p, call in step[q]:
            if call:
                waiting[s, v].append((box, u, p, v, path))
                add((s, v, machine.boxes[s][0], v, ()))
                for more in tuple(done[s, v]):
                    add((box, u, p, more[-1][2] if more else v, path + more))
            else:
                for e in adj.get((s, v), ()):
                    add((box, u, p, e[2], (*path, e)))
    for (box, u), paths in done.items():
        if box == machine.start_box:
            for path in paths:
                yield u, path[-1][2] if path else u, path
