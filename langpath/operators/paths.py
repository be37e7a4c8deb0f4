"""Path extraction from an index: bounded, first-K, single and lazy.

Walks grow by levels of word length.  A partial walk (s, q, v) began at s in q's box and stands in state q at
v; it grows by a terminal edge, or by a whole walk of a called box.  Level l needs only levels below it, and calls that
bring all l labels or none, which are repeated within the level until nothing is new.  So the search ends for left-recursive,
ambiguous and nullable machines, and a lazy reader stops it after any level."""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from ..graph import LabeledGraph
from ..language.rsm import RecursiveMachine
from ..runtime import LOCAL_ROWS, Stage, local_table, small, union_all
from . import closure as cl
from .index import PathIndex, _rows_by_piece, by_piece
from .solver import bounded_paths

STEP = "struct<src:bigint,label:string,dst:bigint>"
PATHS = f"src long, dst long, len int, path array<{STEP}>"


def word(path: Column | str) -> Column:
    path = F.col(path) if isinstance(path, str) else path
    return F.array_join(F.transform(path, lambda e: e["label"]), " ")


def as_words(paths: DataFrame) -> DataFrame:
    """src, dst, len, word."""
    return paths.select("src", "dst", "len", word("path").alias("word"))


def concat(left: DataFrame, right: DataFrame) -> DataFrame:
    """Set concatenation: every left walk with every right walk that begins where it ends."""
    r = right.select(F.col("src").alias("dst"), F.col("dst").alias("end"), F.col("path").alias("tail"))
    both = left.select("src", "dst", "path").join(r, "dst").select("src", F.col("end").alias("dst"), F.concat("path", "tail").alias("path"))
    return both.distinct().select("src", "dst", F.size("path").alias("len"), "path")


def levels(index: PathIndex, max_length: int | None = None, sources: DataFrame | None = None, box: str | None = None, one: bool = False, prune: bool = True) -> Iterator[DataFrame]:
    """Walks of each length 0, 1, 2, ... of a box, up to ``max_length`` or until no longer walk can come.  ``one`` keeps
    the first walk of each partial row only (shortest witnesses), of which there are finitely many always.

    A partial row of level n extends one of level n - 1 by an edge, or joins one of a level j to a walk of length n - j.  So
    after the last level P with partial rows, nothing can come beyond level 2 P."""
    machine, spark = index.machine, index.graph.edges.sparkSession
    box = box or machine.start_box
    stage = Stage(spark)
    e, _ = stage.put(index.pruned() if prune else index.index_edges)
    terms = e.where("not is_call").select("q", F.col("u").alias("v"), "symbol", "p", F.col("v").alias("w"))
    calls = e.where("is_call").select("q", F.col("u").alias("v"), "symbol", "p", F.col("v").alias("w"))
    owner = F.broadcast(local_table(spark, [(f, b) for b, (_, fs) in machine.boxes.items() for f in fs], "q int, box string"))
    key = ["s", "q", "v"]
    empty = F.array().cast(f"array<{STEP}>")
    start = {b: q for b, (q, _) in machine.boxes.items()}
    if index.facts is None:
        if machine.has_calls:
            raise ValueError("walks of a machine with calls need its facts")
        base = index.graph.vertices.select(F.col("id").alias("s")).distinct()
    else:
        base = index.facts.where(F.col("label") == box).select(F.col("src").alias("s")).distinct()
    if sources is not None:
        base = base.join(sources.select(F.col("id").alias("s")), "s", "left_semi")
    seeds = base.select("s", F.lit(start[box]).alias("q"), F.col("s").alias("v"))
    if machine.has_calls:
        entry = F.broadcast(local_table(spark, [(b, q) for b, q in start.items()], "symbol string, entry int"))
        seeds = seeds.union(calls.select("symbol", "v").distinct().join(entry, "symbol").select(F.col("v").alias("s"), F.col("entry").alias("q"), "v")).distinct()
    nullable = bool(machine.nullable())
    opens_with_call = any(is_call and q in start.values() for q, _, _, is_call in machine.transitions())
    partial: list[DataFrame] = []
    done: list[DataFrame] = []
    held: list[tuple[int, int]] = []  # rows of either, by level: empty ones are not joined

    def finished(rows: DataFrame) -> DataFrame:
        return rows.join(owner, "q").select("box", "s", "v", "path").distinct()

    def extend(rows: DataFrame, more: DataFrame) -> DataFrame:
        """Partial rows through a call edge with walks of the called box."""
        call = rows.join(calls, ["q", "v"]).select("s", "p", "v", "symbol", "w", "path")
        tail = more.select(F.col("box").alias("symbol"), F.col("s").alias("v"), F.col("v").alias("w"), F.col("path").alias("tail"))
        return call.join(tail, ["symbol", "v", "w"]).select("s", F.col("p").alias("q"), F.col("w").alias("v"), F.concat("path", "tail").alias("path"))

    def settle(rows: DataFrame, level: int) -> tuple[DataFrame, bool]:
        """Rows of one level, with calls that bring all labels or none, until nothing is new; and whether there are any."""
        fresh, n = stage.put(first_only(rows.distinct(), level))
        known, some = fresh, n > 0
        if not (nullable or level and opens_with_call):
            return known, some
        while n:
            ended = finished(fresh)
            if level:
                step = [extend(partial[0], ended)] * opens_with_call + [extend(fresh, done[0])] * nullable
            else:
                step = [extend(known, ended), extend(fresh, finished(known))]
            new = union_all(step).distinct().join(known, [*key, "path"], "left_anti")
            fresh, n = stage.put(first_only(new.join(known, key, "left_anti") if one else new, level))
            if n:
                known, _ = stage.put(known.union(fresh))
        return known, some

    def first_only(rows: DataFrame, level: int) -> DataFrame:
        if not one:
            return rows
        rows = rows.groupBy(*key).agg(F.min("path").alias("path"))
        for before in partial[:level]:
            rows = rows.join(before, key, "left_anti")
        return rows

    highest = 0
    for level in itertools.count() if max_length is None else range(max_length + 1):
        if level > (2 * highest if machine.has_calls else highest) and level > highest + 1:
            return
        if level == 0:
            rows = seeds.select(*key, empty.alias("path"))
        else:
            last = partial[level - 1]
            edge = F.struct(F.col("v").alias("src"), F.col("symbol").alias("label"), F.col("w").alias("dst"))
            parts = [last.join(terms, ["q", "v"]).select("s", F.col("p").alias("q"), F.col("w").alias("v"), F.concat("path", F.array(edge)).alias("path"))]
            if machine.has_calls:
                parts += [extend(partial[level - k], done[k]) for k in range(1, level) if held[level - k][0] and held[k][1]]
            rows = union_all(parts)
        settled, some = settle(rows, level)
        partial.append(settled)
        highest = level if some else highest
        ended, n = stage.put(finished(settled))
        done.append(ended)
        held.append((int(some), n))
        mine = done[level].where(F.col("box") == box)
        if sources is not None:
            mine = mine.join(base, "s", "left_semi")
        yield mine.select(F.col("s").alias("src"), F.col("v").alias("dst"), F.lit(level).alias("len"), "path").distinct()


def between(index: PathIndex, pairs: DataFrame, max_length: int, box: str | None = None) -> DataFrame:
    """All walks of at most ``max_length`` labels for the given pairs (src, dst)."""
    sources = pairs.select(F.col("src").alias("id")).distinct()
    return union_all(list(levels(index, max_length, sources, box))).join(pairs.select("src", "dst").distinct(), ["src", "dst"], "left_semi").select("src", "dst", "len", "path")


def all_pairs(index: PathIndex, max_length: int, box: str | None = None) -> DataFrame:
    """All walks of at most ``max_length`` labels.  Graphs with known parts, or of a checked size,
    are searched inside tasks."""
    box = box or index.machine.start_box
    graph, machine = index.graph, index.machine.with_start(box)
    slim = graph.select_labels(machine.terminals)
    strategy = "pieces" if graph.pieces is not None else "task" if small(slim.edges, LOCAL_ROWS // 100) else None
    if strategy is None:
        return union_all(list(levels(index, max_length, box=box)))
    rows = _rows_by_piece(slim, strategy)

    def work(edges: list, vertices: list) -> list:
        return [(u, v, len(path), list(path)) for u, v, path in bounded_paths(edges, machine, max_length, None, vertices)]

    names = f"src long, dst long, len int, path array<{STEP}>"
    return _by_piece_paths(rows, work, names)


def _by_piece_paths(rows: DataFrame, work, schema: str) -> DataFrame:
    import json

    text = by_piece(rows, lambda e, v: [(u, w, n, json.dumps([{"src": a, "label": b, "dst": c} for a, b, c in path])) for u, w, n, path in work(e, v)], "src long, dst long, len int, path string")
    return text.select("src", "dst", "len", F.from_json("path", f"array<{STEP}>").alias("path"))


def top_k(paths: DataFrame, k: int) -> DataFrame:
    """First K walks of each pair: by length, then by word, then by vertices."""
    w = Window.partitionBy("src", "dst").orderBy("len", word("path"), "path")
    return paths.withColumn("k", F.row_number().over(w)).where(F.col("k") <= k).drop("k")


def single(index: PathIndex, max_length: int | None = None, sources: DataFrame | None = None, box: str | None = None) -> DataFrame:
    """One shortest walk per pair; stops at the first level that has all pairs, without a bound as well."""
    box = box or index.machine.start_box
    pairs = index.reachable(box)
    if sources is not None:
        pairs = pairs.join(sources.select(F.col("id").alias("src")), "src", "left_semi")
    stage = Stage(index.graph.edges.sparkSession)
    open_, n = stage.put(pairs)
    found: list[DataFrame] = []
    for level in levels(index, max_length, sources, box, one=True):
        hit = level.join(open_, ["src", "dst"], "left_semi").groupBy("src", "dst", "len").agg(F.min("path").alias("path"))
        got, m = stage.put(hit)
        found.append(got)
        if m:
            open_, n = stage.put(open_.join(got, ["src", "dst"], "left_anti"))
        if not n:
            break
    return union_all(found)


def iterate(index: PathIndex, u: int, v: int, box: str | None = None, max_length: int | None = None) -> Iterator[list[tuple[int, str, int]]]:
    """Walks from u to v by growing length; nothing beyond the level in use is computed.  It ends when no partial walk
    from u can grow, and goes on if one always can."""
    spark = index.graph.edges.sparkSession
    start = local_table(spark, [(u,)], "id long")
    for level in levels(index, max_length, start, box):
        rows = level.where((F.col("src") == u) & (F.col("dst") == v)).orderBy(word("path"), "path")
        for r in rows.toLocalIterator():
            yield [(e["src"], e["label"], e["dst"]) for e in r["path"]]


def simple(paths: DataFrame) -> DataFrame:
    """Walks that visit no vertex twice."""
    seen = F.concat(F.array("src"), F.transform("path", lambda e: e["dst"]))
    return paths.where(F.size(F.array_distinct(seen)) == F.size(seen))


def shortest(paths: DataFrame) -> DataFrame:
    """Walks of the least length of their pair."""
    w = Window.partitionBy("src", "dst")
    return paths.withColumn("m", F.min("len").over(w)).where("len = m").drop("m")


def count_by_length(index: PathIndex, max_length: int) -> DataFrame:
    """Number of accepted walks of each pair and length, without making them.  For machines without
    calls whose automaton is deterministic, where a walk has one run."""
    machine = index.machine
    if machine.has_calls:
        raise ValueError("walks are counted for machines without calls only")
    spark = index.graph.edges.sparkSession
    stage = Stage(spark)
    e, _ = stage.put(kron_edges(index))
    start, finals = machine.boxes[machine.start_box]
    rows, _ = stage.put(index.graph.vertices.select(F.col("id").alias("s"), F.lit(start).alias("q"), F.col("id").alias("v"), F.lit(1).cast("decimal(38,0)").alias("n")))
    out = []
    for level in range(max_length + 1):
        out.append(rows.where(F.col("q").isin(sorted(finals))).groupBy(F.col("s").alias("src"), F.col("v").alias("dst")).agg(F.sum("n").cast("decimal(38,0)").alias("n")).select("src", "dst", F.lit(level).alias("len"), "n"))
        if level < max_length:
            step = rows.join(e, ["q", "v"]).groupBy("s", F.col("p").alias("q"), F.col("w").alias("v")).agg(F.sum("n").cast("decimal(38,0)").alias("n"))
            rows, n = stage.put(step)
            if not n:
                break
    return union_all(out)


def is_deterministic(machine: RecursiveMachine) -> bool:
    """Whether the next label always tells the next move, so a word has one run: no box has the empty word or begins with a
    call, moves of a state begin with different labels, and final states have none.  Sufficient, not necessary."""
    first = {b: {s for q, s, _ in machine.edges if q == start} for b, (start, _) in machine.boxes.items()}
    if machine.nullable() or any(labels & set(machine.boxes) for labels in first.values()):
        return False
    if any(q in finals for q, _, _ in machine.edges for _, finals in machine.boxes.values()):
        return False
    begins = [(q, x) for q, s, _ in machine.edges for x in first.get(s, {s})]
    return len(begins) == len(set(begins))


def count_pairs(index: PathIndex, max_length: int) -> DataFrame:
    """Number of walks (src, dst, n) of each pair up to a length, without making them: the levels of :func:`levels` with
    numbers for walks.  For machines of which a word has one run."""
    machine, spark = index.machine, index.graph.edges.sparkSession
    if not is_deterministic(machine):
        raise ValueError("walks are counted for machines with one run for each word only")
    stage = Stage(spark)
    e, _ = stage.put(index.pruned())
    move = e.select("q", F.col("u").alias("v"), "symbol", "p", F.col("v").alias("w"), "is_call")
    terms, calls = move.where("not is_call"), move.where("is_call")
    owner = F.broadcast(local_table(spark, [(f, b) for b, (_, fs) in machine.boxes.items() for f in fs], "q int, box string"))
    start = {b: q for b, (q, _) in machine.boxes.items()}
    entry = F.broadcast(local_table(spark, list(start.items()), "box string, q int"))
    roots = index.facts.where(F.col("label") == machine.start_box).select(F.col("label").alias("box"), F.col("src").alias("s")).union(calls.select("symbol", "v"))
    partial = [stage.put(roots.distinct().join(entry, "box").select("s", "q", F.col("s").alias("v"), F.lit(1).cast("long").alias("n")))]
    done: list[tuple[DataFrame, int]] = [(index.graph.edges.limit(0), 0)]
    for level in range(1, max_length + 1):
        parts = [partial[-1][0].join(terms, ["q", "v"]).select("s", F.col("p").alias("q"), F.col("w").alias("v"), "n")]
        for k in range(1, level):
            if partial[level - k][1] and done[k][1]:
                tail = done[k][0].select(F.col("box").alias("symbol"), F.col("s").alias("v"), F.col("v").alias("w"), F.col("n").alias("m"))
                parts.append(partial[level - k][0].join(calls, ["q", "v"]).join(tail, ["symbol", "v", "w"]).select("s", F.col("p").alias("q"), F.col("w").alias("v"), (F.col("n") * F.col("m")).alias("n")))
        partial.append(stage.put(union_all(parts).groupBy("s", "q", "v").agg(F.sum("n").alias("n"))))
        ended = partial[-1][0].join(owner, "q").groupBy("box", "s", "v").agg(F.sum("n").alias("n"))
        done.append(stage.put(ended) if partial[-1][1] else (ended, 0))
        if level > 2 * max(k for k, (_, n) in enumerate(partial) if n) + 1:
            break
    mine = [d.where(F.col("box") == machine.start_box).select(F.col("s").alias("src"), F.col("v").alias("dst"), "n") for d, n in done if n]
    return union_all(mine).groupBy("src", "dst").agg(F.sum("n").alias("n")) if mine else local_table(spark, [], "src long, dst long, n long")


def kron_edges(index: PathIndex) -> DataFrame:
    return index.index_edges.select("q", F.col("u").alias("v"), "p", F.col("v").alias("w"))


def is_infinite(index: PathIndex, box: str | None = None) -> DataFrame:
    """(src, dst, infinite): whether infinitely many walks join the pair.

    Facts and rooted places (s, q, v) form a graph of what a walk is made of: a fact leads to its last places, a place to
    the place before it and to the fact called in between.  A pair has infinitely many walks iff its fact
    leads to a cycle that adds a label: by a label's own step, by a step over a called fact that has a word, or by entering a
    called fact behind a place that has one."""
    machine, spark = index.machine, index.graph.edges.sparkSession
    box = box or machine.start_box
    stage = Stage(spark)
    e, _ = stage.put(index.pruned())
    place = lambda s, q, v: F.concat_ws(":", F.lit("p"), s, q, v)
    fact = lambda b, s, v: F.concat_ws(":", F.lit("f"), b, s, v)
    starts = local_table(spark, [(q, b) for b, (q, _) in machine.boxes.items()], "q int, box string")
    owners = local_table(spark, [(f, b) for b, (_, fs) in machine.boxes.items() for f in fs], "q int, box string")
    # rooted places reached from the seeds
    seed = index.facts.select(F.col("src").alias("s"), F.col("label").alias("box")).distinct().join(F.broadcast(starts), "box").select("s", "q", F.col("s").alias("v"))
    known, n = stage.put(seed.distinct())
    fresh = known
    move = e.select("q", F.col("u").alias("v"), "p", F.col("v").alias("w"), "symbol", "is_call")
    while n:
        nxt = fresh.join(move, ["q", "v"]).select("s", F.col("p").alias("q"), F.col("w").alias("v")).distinct()
        fresh, n = stage.put(nxt.join(known, ["s", "q", "v"], "left_anti"))
        known = known.union(fresh)
    steps = known.join(move, ["q", "v"])
    id_ = F.xxhash64
    here, there = id_(place(F.col("s"), F.col("q"), F.col("v"))), id_(place(F.col("s"), F.col("p"), F.col("w")))
    called = id_(fact(F.col("symbol"), F.col("v"), F.col("w")))
    ends = known.join(F.broadcast(owners), "q").select(id_(fact(F.col("box"), F.col("s"), F.col("v"))).alias("x"), id_(place(F.col("s"), F.col("q"), F.col("v"))).alias("y"))
    taken, _ = stage.put(steps.select(there.alias("x"), here.alias("y"), F.when(F.col("is_call"), called).alias("call")).distinct())
    calls = taken.where("call is not null")
    links, _ = stage.put(ends.union(taken.select("x", "y")).union(calls.select("x", F.col("call").alias("y"))).distinct())
    seen, _ = cl.scratch(links, stage)
    # nodes some walk of which has a label
    label = taken.where("call is null").select(F.col("x").alias("y")).distinct()
    filled, _ = stage.put(seen.join(label, "y", "left_semi").select("x").union(label.select(F.col("y").alias("x"))).distinct())
    has = lambda c: filled.select(F.col("x").alias(c))
    consuming = union_all([
        taken.where("call is null").select("x", "y"),
        calls.join(has("call"), "call", "left_semi").select("x", "y"),
        calls.join(has("y"), "y", "left_semi").select("x", F.col("call").alias("y")),
    ])
    hot = consuming.distinct().join(seen.select(F.col("x").alias("y"), F.col("y").alias("x")), ["x", "y"], "left_semi").select("x").distinct()
    reach = seen.join(hot.select(F.col("x").alias("y")), "y", "left_semi").select("x").union(hot).distinct().withColumn("infinite", F.lit(True))
    pairs = index.reachable(box).withColumn("x", id_(fact(F.lit(box), F.col("src"), F.col("dst"))))
    return pairs.join(reach, "x", "left").select("src", "dst", F.coalesce("infinite", F.lit(False)).alias("infinite"))


def verify(paths: DataFrame, graph: LabeledGraph, machine: RecursiveMachine) -> DataFrame:
    """The walks that are wrong: not consecutive, not in the graph, or with a word that the machine rejects."""
    accepts = accepts_udf(machine)
    p = paths.withColumn("pid", F.xxhash64("src", "dst", "path"))
    joined = F.forall(F.sequence(F.lit(0), F.size("path") - 2), lambda i: F.get("path", i)["dst"] == F.get("path", i + 1)["src"])
    shape = F.when(F.size("path") == 0, F.col("src") == F.col("dst")).otherwise((F.get("path", F.lit(0))["src"] == F.col("src")) & (F.element_at("path", -1)["dst"] == F.col("dst")) & F.when(F.size("path") > 1, joined).otherwise(True))
    lost = p.select("pid", F.explode("path").alias("e")).select("pid", "e.*").join(graph.edges, ["src", "label", "dst"], "left_anti").select("pid").distinct()
    bad = p.where(~shape | ~accepts(F.transform("path", lambda e: e["label"]))).select("pid").union(lost).distinct()
    return p.join(bad, "pid", "left_semi").drop("pid")


def accepts_udf(machine: RecursiveMachine):
    """Word acceptor over array<string>, in Arrow batches."""
    @pandas_udf("boolean")
    def accepts(words: pd.Series) -> pd.Series:
        memo: dict[tuple, bool] = {}

        def run(w) -> bool:
            k = tuple(w)
            if k not in memo:
                memo[k] = machine.accepts(list(k))
            return memo[k]

        return words.map(run)

    return accepts
