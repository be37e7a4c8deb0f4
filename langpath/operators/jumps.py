"""Runs of labels between two calls, taken at once.

The product of a machine's label moves and the graph often falls apart into small components: calls separate them.  A walk from a
product vertex through its component is found inside one task, for the vertices that are asked for, so a loop takes a round
for each change between calls and labels, not for each edge of a long chain.  Components of more than ``PART_EDGES`` edges are
left to single steps."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import EDGE
from ..runtime import Grown, Stage
from .solver import close_rows

#: Components with more edges are not closed.
PART_EDGES = 50_000
#: Product graphs of up to this many edges (two longs each) are taken apart inside one task.
TASK_EDGES = 8_000_000
PAIRS = 1 << 18


def _roots(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(vertex, smallest vertex of its component)."""
    names, both = np.unique(np.concatenate((x, y)), return_inverse=True)
    a, b = both[: len(x)], both[len(x) :]
    root = np.arange(len(names))
    while True:
        least = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, root[a], least)
        np.minimum.at(new, root[b], least)
        while True:
            far = new[new]
            if (far == new).all():
                break
            new = far
        if (new == root).all():
            return names, names[root]
        root = new


def _in_task(product: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = pa.Table.from_batches(list(batches), schema=pa.schema([("x", pa.int64()), ("y", pa.int64())]))
        names, root = _roots(*(got.column(c).to_numpy() for c in "xy"))
        for a in range(0, len(names), PAIRS):
            yield pa.RecordBatch.from_arrays([pa.array(names[a : a + PAIRS]), pa.array(root[a : a + PAIRS])], ["v", "root"])

    return product.coalesce(1).mapInArrow(run, "v long, root long")


def _in_rounds(product: DataFrame) -> DataFrame:
    from ..llm.components import components

    both = components(product)
    return both.union(product.where("x = y").select("x", F.col("x").alias("root")).join(both.select(F.col("v").alias("x")), "x", "left_anti").distinct())


class Jumps:
    """Walks by labels only, between product vertices x = u * n + q, made when they are asked for."""

    def __init__(self, terminal: DataFrame, moves: DataFrame, n_states: int, stage: Stage, task_edges: int | None = None, part_edges: int | None = None):
        self.stage, self.n = stage, n_states
        step = F.broadcast(moves.where("not is_call").select(F.col("symbol").alias("label"), "q", "p"))
        product = terminal.select(*EDGE).join(step, "label").select((F.col("src") * n_states + F.col("q")).alias("x"), (F.col("dst") * n_states + F.col("p")).alias("y"))
        product, size = stage.put(product.distinct())
        roots, _ = stage.put(_in_task(product) if size <= (TASK_EDGES if task_edges is None else task_edges) else _in_rounds(product))
        edges, _ = stage.put(product.join(roots.select(F.col("v").alias("x"), "root"), "x"))
        large = edges.groupBy("root").count().where(F.col("count") > (PART_EDGES if part_edges is None else part_edges)).select("root")
        large, n = stage.put(large)
        #: Edges of large components, or None.
        self.single = stage.put(edges.join(large, "root", "left_semi").select("x", "y"))[0] if n else None
        self.edges = stage.put(edges.join(large, "root", "left_anti"))[0] if n else edges
        self.roots = roots.join(large, "root", "left_anti") if n else roots
        self.closed: Grown | None = None
        self.asked: Grown | None = None

    def ask(self, at: DataFrame) -> None:
        """Closes the components at these product vertices (x)."""
        at = at.distinct() if self.asked is None else at.distinct().join(self.asked.df, "x", "left_anti")
        at, n = self.stage.put(at)
        if not n:
            return
        want = at.join(self.roots.select(F.col("v").alias("x"), "root"), "x").select("root", "x", F.lit(None).cast("long").alias("y"))
        rows = self.edges.join(want.select("root").distinct(), "root", "left_semi").select("root", "x", "y").union(want)
        made, _ = self.stage.put(rows.repartition("root").sortWithinPartitions("root").mapInArrow(_close, "x long, y long"))
        if self.asked is None:
            self.asked, self.closed = Grown(self.stage, at), Grown(self.stage, made)
        else:
            self.asked.add(at)
            self.closed.add(made)

    def follow(self, rows: DataFrame, by: DataFrame) -> DataFrame:
        """(u, q, v) rows after a walk or an edge (x, y)."""
        n = self.n
        moved = rows.select("u", (F.col("v") * n + F.col("q")).alias("x")).join(by, "x")
        return moved.select("u", F.pmod("y", F.lit(n)).cast("int").alias("q"), F.expr(f"(y - pmod(y, {n})) div {n}").alias("v"))


def _close(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (root, x, y) with the edges of a component and, with null y, the vertices asked for: pairs of these and what they reach."""
    held: list[pa.RecordBatch] = []
    out: list[tuple[np.ndarray, np.ndarray]] = []
    size = 0

    def parts(table: pa.Table) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        root, x, y = (table.column(c) for c in ("root", "x", "y"))
        root, x, is_edge, y = root.to_numpy(), x.to_numpy(), y.is_valid().to_numpy(), y.fill_null(0).to_numpy()
        cut = np.flatnonzero(np.concatenate(([True], root[1:] != root[:-1], [True]))) if len(root) else np.zeros(0, int)
        for a, b in zip(cut[:-1], cut[1:], strict=True):
            e = is_edge[a:b]
            yield from _reached(x[a:b][e], y[a:b][e], x[a:b][~e])

    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        root = batch.column(0).to_numpy()
        begin = int(np.searchsorted(root, root[-1]))  # the last component may go on
        if begin == 0 and (len(held) == 1 or held[-2].column(0)[-1].as_py() == root[-1]):
            continue
        table = pa.Table.from_batches(held)
        whole = len(table) - (len(root) - begin)
        held = [batch.slice(begin)]
        for pair in parts(table.slice(0, whole)):
            out.append(pair)
            size += len(pair[0])
            if size >= PAIRS:
                yield _batch(out)
                out, size = [], 0
    if held:
        out.extend(parts(pa.Table.from_batches(held)))
    if out:
        yield _batch(out)


def _batch(pairs: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*pairs, strict=True)], ["x", "y"])


def _reached(x: np.ndarray, y: np.ndarray, asked: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    if not np.isin(y, x).any():  # no walk is longer than one edge
        keep = np.isin(x, asked)
        yield x[keep], y[keep]
        return
    names, both = np.unique(np.concatenate((x, y)), return_inverse=True)
    nxt: dict[int, list[int]] = {}
    for a, b in zip(both[: len(x)].tolist(), both[len(x) :].tolist(), strict=True):
        nxt.setdefault(a, []).append(b)
    rows = close_rows(nxt)
    size = (len(names) + 7) // 8
    for a in np.searchsorted(names, asked).tolist():
        bits = np.unpackbits(np.frombuffer(rows.get(a, 0).to_bytes(size, "little"), np.uint8), bitorder="little")
        to = names[np.flatnonzero(bits)]
        yield np.full(len(to), names[a]), to
