"""Index creation: saturate a graph with the facts of a recursive machine.

``build`` is the production path.  It keeps rooted reach rows only, (u, q, v): a walk from vertex u, begun at
the start of q's box, may stand in state q at vertex v.  Boxes are entered on demand, so a call at v
seeds (v, start of the called box, v), and sources restrict all that follows.  Seven strategies give the same facts:

- ``unrolled``: a machine without calls and cycles is a fixed number of joins, one plan and no loop;
- ``pieces``: a graph with known parts is solved part by part inside tasks, after one shuffle;
- ``task``: a graph whose size was checked to be small is one part;
- ``loop``: rounds of distributed joins on new rows only;
- ``hubs``: for machines without calls on graphs with large cycles, see :mod:`.hubs`; it keeps no reach rows;
- ``jumps``: the loop, but runs of labels between calls are closed inside tasks, see :mod:`.jumps`;
- ``bits``: rows of bits in one task, see :mod:`.bitrows`, where they fit a checked size; else the loop.

``build_full`` keeps the whole closure of the product graph instead, in the variants that are compared."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import EDGE, LabeledGraph
from ..language.fsm import Fsm
from ..language.rsm import RecursiveMachine, from_fsm
from ..runtime import LOCAL_ROWS, Grown, Stage, local_table, small, union_all
from . import bitrows as br
from . import closure as cl
from . import hubs as hb
from . import jumps as jp
from . import kron
from . import twins as tw
from .solver import regular_pairs, solve

FACTS = "src long, label string, dst long"
#: Parts with more edges than this go through the distributed loop.
PIECE_ROWS = 50_000


@dataclass
class PathIndex:
    graph: LabeledGraph
    machine: RecursiveMachine
    facts: DataFrame  # (src, label = box, dst)
    reach: DataFrame | None = None  # (u, q, v)
    metrics: list[dict] = field(default_factory=list)
    sources: DataFrame | None = None
    members: DataFrame | None = None  # (id, twin): graph and facts are on one vertex of each class
    distinct: bool = False  # facts are those of the given sources, each once

    def reachable(self, box: str | None = None) -> DataFrame:
        if self.distinct:
            return self.facts.where(F.col("label") == (box or self.machine.start_box)).select("src", "dst")
        pairs = self.facts.where(F.col("label") == (box or self.machine.start_box)).select("src", "dst").distinct()
        if self.members is not None:
            return tw.expand(pairs, self.members)
        if self.sources is None:
            return pairs
        # boxes are entered on demand at other vertices too
        return pairs.join(self.sources.select(F.col("id").cast("long").alias("src")).distinct(), "src", "left_semi")

    @property
    def index_edges(self) -> DataFrame:
        """(q, u, symbol, p, v, is_call): the machine with the saturated graph."""
        e = self.graph.select_labels(self.machine.terminals).edges
        rows = e.select(*EDGE).union(self.facts.select(*EDGE)) if self.machine.has_calls else e.select(*EDGE)
        return kron.machine_product(self.machine.transitions_df(e.sparkSession), rows)

    def pruned(self) -> DataFrame:
        """Index edges on some walk from a start to a final state of their box."""
        spark = self.graph.edges.sparkSession
        stage = Stage(spark)
        e, _ = stage.put(self.index_edges)
        starts = {q for q, _ in self.machine.boxes.values()}
        finals = {f for _, fs in self.machine.boxes.values() for f in fs}

        def spread(seed: DataFrame, a: str, b: str) -> DataFrame:
            known, n = stage.put(seed.distinct())
            fresh = known
            while n:
                nxt = e.select(F.struct(*a).alias("here"), F.struct(*b).alias("there")).join(fresh.select(F.col("s").alias("here")), "here").select(F.col("there").alias("s"))
                fresh, n = stage.put(nxt.distinct().join(known, "s", "left_anti"))
                known = known.union(fresh)
            return known

        head, tail = (F.col("q"), F.col("u")), (F.col("p").alias("q"), F.col("v").alias("u"))
        at = lambda c, xs, cols: e.where(F.col(c).isin(sorted(xs))).select(F.struct(*cols).alias("s"))
        fore = spread(at("q", starts, head), head, tail)
        back = spread(at("p", finals, tail), tail, head)
        keep = e.withColumn("h", F.struct(*head)).withColumn("t", F.struct(*tail))
        keep = keep.join(fore.select(F.col("s").alias("h")), "h", "left_semi").join(back.select(F.col("s").alias("t")), "t", "left_semi")
        return keep.select("q", "u", "symbol", "p", "v", "is_call")

    def insert(self, edges: DataFrame, vertices: DataFrame | None = None) -> PathIndex:
        """The index after more data edges: they are one more delta of the loop."""
        if self.reach is None:
            raise ValueError("only an index made by the loop can be extended")
        e = edges.select(*EDGE).distinct().join(self.graph.edges, EDGE, "left_anti")
        v = self.graph.vertices.union(vertices.select("id") if vertices is not None else e.select(F.col("src").alias("id")).union(e.select("dst"))).distinct()
        old = self.graph
        grown = LabeledGraph(old.edges.select(*EDGE).union(e), v)
        return _loop(grown, self.machine, [self.machine.start_box], self.sources, before=self, delta=e)

    def save(self, path: str) -> None:
        self.facts.write.mode("overwrite").partitionBy("label").parquet(f"{path}/facts")
        self.index_edges.write.mode("overwrite").partitionBy("symbol").parquet(f"{path}/index")
        if self.reach is not None:
            self.reach.write.mode("overwrite").parquet(f"{path}/reach")


def load(graph: LabeledGraph, machine: RecursiveMachine, path: str, with_reach: bool = False) -> PathIndex:
    spark = graph.edges.sparkSession
    reach = spark.read.parquet(f"{path}/reach") if with_reach else None
    return PathIndex(graph, machine, spark.read.schema(FACTS).parquet(f"{path}/facts").select(*EDGE), reach)


def build(graph: LabeledGraph, machine: RecursiveMachine | Fsm, sources: DataFrame | None = None, boxes: list[str] | None = None, strategy: str = "auto", max_rounds: int | None = None, twins: bool = False, large: str = "loop") -> PathIndex:
    """Facts of the start box (or of ``boxes``) from all vertices or the given sources (id).  ``twins``: vertices with the
    same edges are solved once; for graphs known to have many, without sources, and boxes without the empty word.  ``large``: what
    ``auto`` takes for graphs without known parts that are too large for one task."""
    if isinstance(machine, Fsm):
        machine = from_fsm(machine)
    wanted = boxes or [machine.start_box]
    if twins:
        if sources is not None or machine.nullable() & set(wanted):
            raise ValueError("twins are for all sources and boxes that do not accept the empty word")
        part, members = tw.reduced(graph.select_labels(machine.terminals))
        out = build(part, machine, boxes=boxes, strategy=strategy, max_rounds=max_rounds)
        out.members = members
        return out
    slim = graph.select_labels(machine.terminals)
    if strategy == "auto":
        if not machine.has_calls and wanted == [machine.start_box] and _box(machine).is_finite():
            strategy = "unrolled"
        elif graph.pieces is not None:
            strategy = "pieces"
        else:
            strategy = "task" if small(slim.edges, LOCAL_ROWS) and small(graph.vertices, LOCAL_ROWS) else large
    if strategy == "unrolled":
        return PathIndex(graph, machine, _unrolled(slim, machine, sources), sources=sources)
    if strategy in ("pieces", "task"):
        return PathIndex(graph, machine, _pieces(slim, machine, wanted, sources, strategy), sources=sources)
    if strategy == "hubs":
        if machine.has_calls:
            raise ValueError("hubs are for machines without calls")
        pairs = hb.answers(slim, machine, sources)
        return PathIndex(graph, machine, pairs.select("src", F.lit(machine.start_box).alias("label"), "dst"), sources=sources, distinct=True)
    if strategy == "bits":
        if sources is not None:
            raise ValueError("rows of bits are for all sources")
        facts = br.facts_of(slim, machine, wanted)
        if facts is not None:
            return PathIndex(graph, machine, facts, distinct=True)
        strategy = "loop"
    if strategy == "jumps":
        return _leap(slim, machine, wanted, sources)
    if strategy != "loop":
        raise ValueError(f"unknown strategy {strategy}")
    return _loop(slim, machine, wanted, sources, max_rounds=max_rounds)


def build_regular(graph: LabeledGraph, machine: Fsm, **options) -> PathIndex:
    """A regular query: one box without calls, so facts are never fed back."""
    return build(graph, from_fsm(machine), **options)


def _box(machine: RecursiveMachine) -> Fsm:
    start, finals = machine.boxes[machine.start_box]
    return Fsm(machine.n, frozenset(machine.edges), frozenset([start]), finals)


# --------------------------------------------------------------------------- unrolled
def _unrolled(graph: LabeledGraph, machine: RecursiveMachine, sources: DataFrame | None) -> DataFrame:
    """One branch per state and depth; Catalyst sees all joins at once."""
    start, finals = machine.boxes[machine.start_box]
    edges = graph.edges if sources is None else graph.edges
    into: dict[int, list[tuple[int, str]]] = {}
    for q, s, p in machine.edges:
        into.setdefault(p, []).append((q, s))
    level: dict[int, DataFrame | None] = {start: None}  # None: every source itself
    out: list[DataFrame] = []
    seeds = sources.select(F.col("id").alias("src")) if sources is not None else None
    if start in finals:
        base = sources if sources is not None else graph.vertices
        out.append(base.select(F.col("id").alias("src"), F.col("id").alias("dst")))
    while level:
        nxt: dict[int, list[DataFrame]] = {}
        groups: dict[tuple[int, int], list[str]] = {}
        for p, ways in into.items():
            for q, s in ways:
                if q in level:
                    groups.setdefault((q, p), []).append(s)
        for (q, p), symbols in groups.items():
            step = edges.where(F.col("label").isin(sorted(symbols)))
            before = level[q]
            if before is None:
                row = step.select("src", "dst")
                row = row.join(seeds, "src", "left_semi") if seeds is not None else row
            else:
                row = before.select("src", F.col("dst").alias("mid")).join(step.select(F.col("src").alias("mid"), "dst"), "mid").select("src", "dst")
            nxt.setdefault(p, []).append(row)
        level = {p: union_all(rows).distinct() for p, rows in nxt.items()}
        out.extend(df for p, df in level.items() if p in finals)
    none = edges.select("src", "dst").limit(0)
    pairs = union_all(out).distinct() if out else none
    return pairs.select("src", F.lit(machine.start_box).alias("label"), "dst")


# --------------------------------------------------------------------------- parts in tasks
def _rows_by_piece(graph: LabeledGraph, strategy: str) -> DataFrame:
    """Edges and vertices (with null label) of all parts, one shuffle, parts in a row."""
    e, v = graph.edges.select(*EDGE), graph.vertices.select(F.col("id").alias("src"), F.lit(None).cast("string").alias("label"), F.lit(None).cast("long").alias("dst"))
    rows = e.union(v)
    if strategy == "task":
        return rows.select(F.lit(0).cast("long").alias("piece"), *EDGE).coalesce(1)
    tagged = rows.join(graph.pieces.select(F.col("id").alias("src"), "piece"), "src").select("piece", *EDGE)
    return tagged.repartition("piece").sortWithinPartitions("piece")  # no fixed number: small partitions are merged at run time


def by_piece(rows: DataFrame, work, schema: str) -> DataFrame:
    """Apply ``work(edges, vertices) -> rows`` to each part; parts are read in a row."""
    names = [c.strip().split()[0] for c in schema.split(",")]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        piece, edges, vertices, out = None, [], [], []

        def flush():
            if edges or vertices:
                out.extend(work(edges, vertices))

        for f in frames:
            for p, s, label, d in zip(f["piece"].tolist(), f["src"].tolist(), f["label"].tolist(), f["dst"].tolist(), strict=True):
                if p != piece:
                    flush()
                    piece, edges, vertices = p, [], []
                if label is None:
                    vertices.append(s)
                else:
                    edges.append((s, label, int(d)))
            if len(out) > 100_000:
                yield pd.DataFrame(out, columns=names)
                out = []
        flush()
        yield pd.DataFrame(out, columns=names)

    return rows.mapInPandas(run, schema)


def _pieces(graph: LabeledGraph, machine: RecursiveMachine, wanted: list[str], sources: DataFrame | None, strategy: str) -> DataFrame:
    rest = None
    if strategy == "pieces":
        sized = graph.edges.join(graph.pieces.select(F.col("id").alias("src"), "piece"), "src").groupBy("piece").count()
        big = sized.where(F.col("count") > PIECE_ROWS).select("piece")
        if big.limit(1).count():
            ids = graph.pieces.join(big, "piece", "left_semi").select("id")
            part = LabeledGraph(graph.edges.join(ids.select(F.col("id").alias("src")), "src", "left_semi").select(*EDGE), graph.vertices.join(ids, "id", "left_semi"))
            rest = _loop(part, machine, wanted, sources).facts
            graph = LabeledGraph(graph.edges.join(ids.select(F.col("id").alias("src")), "src", "left_anti").select(*EDGE), graph.vertices.join(ids, "id", "left_anti"), graph.pieces)
    chosen = None
    rows = _rows_by_piece(graph, strategy)
    if sources is not None:
        # sources travel as vertices with a label no edge can have
        mark = sources.select(F.col("id").cast("long").alias("src"), F.lit("\x00from").alias("label"), F.lit(-1).cast("long").alias("dst")).distinct()
        g = LabeledGraph(graph.edges.select(*EDGE).union(mark.select(*EDGE)), graph.vertices, graph.pieces)
        rows, chosen = _rows_by_piece(g, strategy), "\x00from"
    regular = not machine.has_calls and wanted == [machine.start_box]
    step = {(q, s): p for q, s, p in machine.edges}
    start, finals = machine.boxes[machine.start_box]
    name, n_states = machine.start_box, machine.n

    def work(edges: list, vertices: list) -> list:
        if chosen is not None:
            own = {s for s, label, _ in edges if label == chosen}
            edges = [e for e in edges if e[1] != chosen]
            facts = solve(edges, machine, own, vertices, wanted)
        elif regular:
            every = {*vertices, *(e[0] for e in edges), *(e[2] for e in edges)}
            return [(u, name, v) for u, v in regular_pairs(edges, step, start, set(finals), n_states, every)]
        else:
            facts = solve(edges, machine, None, vertices, wanted)
        return [(u, box, v) for box, pairs in facts.items() for u, v in pairs]

    out = by_piece(rows, work, FACTS)
    return out if rest is None else out.union(rest.select(*EDGE))


# --------------------------------------------------------------------------- distributed loop
def _loop(graph: LabeledGraph, machine: RecursiveMachine, wanted: list[str], sources: DataFrame | None, before: PathIndex | None = None, delta: DataFrame | None = None, max_rounds: int | None = None) -> PathIndex:
    """Semi-naive rounds: each joins the new reach rows with all edges and facts, and the older
    reach rows with the new facts (or new edges) only."""
    spark = graph.edges.sparkSession
    stage = Stage(spark)
    moves = machine.transitions_df(spark)
    step = F.broadcast(moves.select("q", "symbol", "p"))
    starts = {b: q for b, (q, _) in machine.boxes.items()}
    finals = local_table(spark, [(f, b) for b, (_, fs) in machine.boxes.items() for f in fs], "q int, label string")
    entries = local_table(spark, [(b, q) for b, q in starts.items()], "symbol string, entry int")
    terminal, _ = stage.put(graph.select_labels(machine.terminals).edges.select(*EDGE))
    calls = machine.has_calls
    call_step = F.broadcast(moves.where("is_call").select("q", "symbol", "p"))
    one_final = all(len(fs) == 1 for _, fs in machine.boxes.values())

    def follow(rows: DataFrame, by: DataFrame, edges: DataFrame) -> DataFrame:
        move = rows.join(by, "q").select("u", "p", F.col("v").alias("src"), F.col("symbol").alias("label"))
        return move.join(edges, ["src", "label"]).select("u", F.col("p").alias("q"), F.col("dst").alias("v"))

    def demand(rows: DataFrame) -> DataFrame:
        return rows.join(call_step, "q").join(F.broadcast(entries), "symbol").select(F.col("v").alias("u"), F.col("entry").alias("q"), "v")

    def harvest(rows: DataFrame) -> DataFrame:
        return rows.join(F.broadcast(finals), "q").select(F.col("u").alias("src"), "label", F.col("v").alias("dst"))

    metrics: list[dict] = []
    seeds = (sources if sources is not None else graph.vertices).select(F.col("id").cast("long").alias("id")).distinct()
    entry = F.explode(F.array(*[F.lit(starts[b]) for b in wanted]))
    seed_rows = seeds.select(F.col("id").alias("u"), entry.alias("q"), F.col("id").alias("v"))
    accepted = F.count(F.when(F.col("q").isin(sorted({f for _, fs in machine.boxes.values() for f in fs})), 1))
    put = lambda df: stage.observed(df, done=accepted)
    if before is None:
        fresh, seen = put(seed_rows)
        known, facts = Grown(stage, fresh), None
    else:
        old = before.reach
        more = follow(old, step, delta.select(*EDGE)).union(seed_rows).distinct().join(old, ["u", "q", "v"], "left_anti")
        fresh, seen = put(more)
        known, facts = Grown(stage, old.union(fresh)), Grown(stage, before.facts)
    while seen["n"] and (max_rounds is None or len(metrics) < max_rounds):
        m = seen["done"]
        if m and one_final:
            # one final state: a row in it is a fact, and new rows are new facts
            new_facts = harvest(fresh)
        elif m:
            got = harvest(fresh).distinct()
            new_facts, m = stage.put(got if facts is None else got.join(facts.df, EDGE, "left_anti"))
            if facts is None:
                facts = Grown(stage, new_facts)
            else:
                facts.add(new_facts)
        all_facts = harvest(known.df) if one_final else facts.df if facts is not None else None
        if calls:
            step_rows = follow(fresh, step, terminal if all_facts is None else terminal.union(all_facts)).union(demand(fresh))
            if m:
                step_rows = step_rows.union(follow(known.df, call_step, new_facts))
        else:
            step_rows = follow(fresh, step, terminal)
        metrics.append({"round": len(metrics) + 1, "reach_new": seen["n"], "facts_new": m})
        fresh, seen = put(step_rows.distinct().join(known.df, ["u", "q", "v"], "left_anti"))
        if seen["n"]:
            known.add(fresh)
    found = harvest(known.df) if one_final else facts.df if facts is not None else local_table(spark, [], FACTS)
    return PathIndex(graph, machine, found, known.df, metrics, sources)


def _leap(graph: LabeledGraph, machine: RecursiveMachine, wanted: list[str], sources: DataFrame | None) -> PathIndex:
    """The loop with runs of labels as one step.  A round has two parts: rows that a call enters or leaves, then
    all that these reach by labels.  Rows reached by labels are closed, so only calls go on from them."""
    spark = graph.edges.sparkSession
    stage = Stage(spark)
    moves = machine.transitions_df(spark)
    terminal, _ = stage.put(graph.select_labels(machine.terminals).edges.select(*EDGE))
    jumps = jp.Jumps(terminal, moves, machine.n, stage)
    starts = {b: q for b, (q, _) in machine.boxes.items()}
    callers: dict[str, list[tuple[int, int]]] = {}
    for q, s, p, is_call in machine.transitions():
        if is_call:
            callers.setdefault(s, []).append((q, p))
    # states that labels lead to
    labels = tuple(e for e in machine.edges if e[1] not in machine.boxes)
    by_labels = RecursiveMachine(machine.start_box, labels, machine.boxes, machine.n)
    runs = {q: {p for r, _, p in labels if r in by_labels._states(q)} for q in range(machine.n)}
    ends = {b: sorted(fs) for b, (_, fs) in machine.boxes.items()}
    key, total = ["u", "q", "v"], dict.fromkeys(range(machine.n), 0)
    counts = {f"q{q}": F.count(F.when(F.col("q") == q, 1)) for q in range(machine.n)} | {"away": F.count(F.when(F.col("u") != F.col("v"), 1))}
    in_states = lambda df, states: df.where(F.col("q").isin(sorted(states)))

    def put(df: DataFrame) -> tuple[DataFrame, dict[int, int], int]:
        """Written rows, their number for each state, and how many do not stand at their source."""
        out, seen = stage.observed(df, **counts)
        return out, {q: seen[f"q{q}"] for q in range(machine.n) if seen[f"q{q}"]}, seen["away"]

    def unknown(df: DataFrame, states: set[int]) -> DataFrame:
        """Rows not known yet; only known rows of the states that can occur are read."""
        old = {q for q in states if total[q]}
        return df.join(in_states(known.df, old), key, "left_anti") if old else df

    def called(rows: DataFrame, states: set[int], box: str, facts_: DataFrame) -> DataFrame | None:
        """Rows after calls of a box, from rows in some states."""
        ways = [(q, p) for q, p in callers.get(box, ()) if q in states]
        if not ways:
            return None
        to = F.broadcast(local_table(spark, ways, "q int, p int"))
        move = in_states(rows, {q for q, _ in ways}).join(to, "q").select("u", "p", F.col("v").alias("src"))
        begin = facts_.select("src").distinct()
        begin, m = stage.put(begin)
        if m <= LOCAL_ROWS:
            # few facts begin anywhere else, so their size is known before they are joined
            move, _ = stage.put(move.join(F.broadcast(begin), "src", "left_semi"))
        return move.join(facts_.select("src", "dst"), "src").select("u", F.col("p").alias("q"), F.col("dst").alias("v"))

    seeds = (sources if sources is not None else graph.vertices).select(F.col("id").cast("long").alias("id")).distinct()
    entered, n, away = put(seeds.select(F.col("id").alias("u"), F.explode(F.array(*[F.lit(starts[b]) for b in wanted])).alias("q"), F.col("id").alias("v")))
    known: Grown | None = None
    facts: dict[str, Grown] = {}
    metrics: list[dict] = []
    while n:
        jumps.ask(entered.select((F.col("v") * machine.n + F.col("q")).alias("x")))
        if len(n) == 1 and not away:
            # one row for each source, so what it reaches is distinct
            far = jumps.follow(entered, jumps.closed.df.where("x <> y"))
        else:
            by = jumps.closed.df.where(F.pmod("x", F.lit(machine.n)).isin(sorted(n)))
            far = jumps.follow(entered, F.broadcast(by) if small(by, kron.HELD_ROWS) else by).distinct()
            if {p for q in n for p in runs[q]} & n.keys():
                far = far.join(in_states(entered, n), key, "left_anti")
        far, n_far, _ = put(unknown(far, {p for q in n for p in runs[q]}))
        fresh, older, before = entered.union(far), known.df if known is not None else None, {q for q in total if total[q]}
        now = n.keys() | n_far.keys()
        for q in now:
            total[q] += n.get(q, 0) + n_far.get(q, 0)
        if known is None:
            known = Grown(stage, fresh)
        else:
            known.add(fresh)
        step, n_facts = [], 0
        for b, fs in ends.items():
            old = facts[b].df if b in facts else None
            new = None
            if now & set(fs):
                new = in_states(fresh, fs).select(F.col("u").alias("src"), F.col("v").alias("dst"))
                if len(fs) > 1:  # with one final state new rows are new facts
                    new = new.distinct()
                    new, m = stage.put(new if old is None else new.join(old, ["src", "dst"], "left_anti"))
                    new = new if m else None
                else:
                    m = n.get(fs[0], 0) + n_far.get(fs[0], 0)
                n_facts += m
            if new is not None:
                if old is None:
                    facts[b] = Grown(stage, new)
                else:
                    facts[b].add(new)
                if older is not None:
                    step.append(called(older, before, b, new))
            if b in facts:
                step.append(called(fresh, now, b, facts[b].df))
        enter = {(q, starts[b]) for b, ways in callers.items() for q, _ in ways if q in now}
        if enter:
            to = F.broadcast(local_table(spark, sorted(enter), "q int, entry int"))
            step.append(fresh.join(to, "q").select("v", "entry").distinct().select(F.col("v").alias("u"), F.col("entry").alias("q"), "v"))
        if jumps.single is not None:
            step.append(jumps.follow(fresh, jumps.single))
        metrics.append({"round": len(metrics) + 1, "reach_new": sum(n.values()) + sum(n_far.values()), "facts_new": n_facts})
        step = [df for df in step if df is not None]
        if not step:
            break
        after = {p for ways in callers.values() for _, p in ways} | {e for _, e in enter} | ({p for q in now for p in runs[q]} if jumps.single is not None else set())
        entered, n, away = put(unknown(union_all(step).distinct(), after))
    none = local_table(spark, [], FACTS)
    found = union_all([none, *[g.df.select("src", F.lit(b).alias("label"), "dst") for b, g in facts.items()]])
    return PathIndex(graph, machine, found, known.df if known is not None else None, metrics, sources, distinct=sources is None)


# --------------------------------------------------------------------------- whole closures
def build_full(graph: LabeledGraph, machine: RecursiveMachine | Fsm, closure: str = "incremental", delta: bool = True, table_width: int = 4) -> PathIndex:
    """The loop over the whole product graph: product, closure, facts, until no new fact.

    ``delta``: only new edges enter the product; else all of them each round.  ``closure``: ``linear`` or
    ``squaring`` (from scratch each round), ``incremental`` (pairs), ``packed`` (rows of 64-bit
    words), ``table`` (packed, with block look-ups).  ``metrics`` has the work of each round."""
    if isinstance(machine, Fsm):
        machine = from_fsm(machine)
    spark = graph.edges.sparkSession
    stage, n_states = Stage(spark), machine.n
    moves = machine.transitions_df(spark)
    ends = local_table(spark, [(b, s, f) for b, (s, fs) in machine.boxes.items() for f in fs], "label string, start int, final int")
    table = cl.block_table(spark, table_width) if closure == "table" else None
    terminal, _ = stage.put(graph.select_labels(machine.terminals).edges.select(*EDGE))
    null = [b for b, (s, fs) in machine.boxes.items() if s in fs]
    facts, n_facts = stage.put(graph.vertices.select(F.col("id").alias("src"), F.explode(F.array(*map(F.lit, null))).alias("label"), F.col("id").alias("dst"))) if null else stage.put(local_table(spark, [], FACTS))
    new = terminal.union(facts)  # reflexive facts are part of the first delta
    index = closed = None
    metrics: list[dict] = []
    while True:
        used = new if delta else terminal.union(facts)
        product = kron.machine_product(moves, used).select(cl.pack("q", "u", n_states).alias("x"), cl.pack("p", "v", n_states).alias("y")).distinct()
        if index is not None:
            product = product.join(index, cl.XY, "left_anti")
        fresh, n_product = stage.put(product)
        index = fresh if index is None else index.union(fresh)
        if closure in ("linear", "squaring"):
            before = metrics[-1]["closure_total"] if metrics else 0
            closed, total = cl.scratch(index, stage, closure)
            added, n_added = closed, total - before
        elif closure == "incremental":
            closed, added, n_added = cl.insert(closed, fresh, stage)
        elif closure in ("packed", "table"):
            closed, added_rows, n_added = cl.insert_packed(closed, fresh, stage, table)
            added = cl.to_pairs(added_rows)
        else:
            raise ValueError(f"unknown closure {closure}")
        q, u = cl.unpack("x", n_states)
        p, v = cl.unpack("y", n_states)
        hit = added.select(q.alias("start"), u.alias("src"), p.alias("final"), v.alias("dst")).join(F.broadcast(ends), ["start", "final"]).select(*EDGE).distinct()
        new, n_new = stage.put(hit.join(facts, EDGE, "left_anti"))
        total = (metrics[-1]["closure_total"] if metrics else 0) + n_added
        metrics.append({"round": len(metrics) + 1, "product_new": n_product, "closure_new": n_added, "closure_total": total, "facts_new": n_new})
        facts = facts.union(new)
        if not n_new or not machine.has_calls:
            break
    out = PathIndex(graph, machine, facts, None, metrics)
    out.closure = cl.to_pairs(closed) if closure in ("packed", "table") else closed
    return out
