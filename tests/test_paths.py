import itertools

import pytest

from langpath.language import fsm, grammar, rsm
from langpath.operators import baselines
from langpath.operators import index as ix
from langpath.operators import paths as pt
from langpath.operators.solver import bounded_paths
from langpath.plans.optimizer import PathPlan, execute, optimize
from langpath.plans.sqlfront import LangPathSession
from langpath.streaming import dfa_match
from langpath.workloads import example, machine_of

from .oracles import walks
from .test_index import graph_of, pairs

EDGES = [(0, "a", 1), (1, "a", 0), (1, "b", 1), (1, "b", 2), (2, "a", 1)]


def accepted(edges, machine, length):
    return sorted((u, v, " ".join(e[1] for e in p), p) for u, v, p in walks(edges, length) if machine.accepts([e[1] for e in p]))


def rows(df):
    return sorted((r["src"], r["dst"], " ".join(e["label"] for e in r["path"]), tuple((e["src"], e["label"], e["dst"]) for e in r["path"])) for r in df.collect())


@pytest.mark.parametrize("text", ["S -> ε | a S b", "S -> S S | a | b"])
def test_levels_are_all_walks(spark, text):
    m = rsm.from_grammar(text)
    index = ix.build(graph_of(spark, EDGES), m, strategy="loop")
    assert rows(pt.union_all(list(pt.levels(index, 3)))) == accepted(EDGES, m, 3)
    some = index.graph.vertices.where("id = 0")
    assert rows(pt.union_all(list(pt.levels(index, 3, some)))) == [w for w in accepted(EDGES, m, 3) if w[0] == 0]


@pytest.mark.parametrize("text", ["S -> a S b | a b", "S -> ε | a S b", "S -> S S | a | b", "S -> A b\nA -> a A | ε"])
def test_bounded_search_inside_a_task(text):
    m = rsm.from_grammar(text)
    got = sorted((u, v, " ".join(e[1] for e in p), p) for u, v, p in bounded_paths(EDGES, m, 5))
    assert got == accepted(EDGES, m, 5)


def test_all_pairs_inside_tasks(spark):
    m = rsm.from_grammar("S -> S S | a | b")
    assert rows(pt.all_pairs(ix.PathIndex(graph_of(spark, EDGES), m, None), 4)) == accepted(EDGES, m, 4)


def test_between_topk_single_simple(spark):
    m = rsm.from_regex("a (a | b)*")
    index = ix.build(graph_of(spark, EDGES), m, strategy="loop")
    want = accepted(EDGES, m, 4)
    some = spark.createDataFrame([(0, 1)], "src long, dst long")
    assert rows(pt.between(index, some, 4)) == [w for w in want if w[:2] == (0, 1)]
    every = pt.union_all(list(pt.levels(index, 4)))
    best = {k: sorted(g, key=lambda w: (len(w[3]), w[2], w[3]))[:2] for k, g in itertools.groupby(want, key=lambda w: w[:2])}
    assert rows(pt.top_k(every, 2)) == sorted(x for g in best.values() for x in g)
    one = rows(pt.single(index, 6))
    assert {(w[0], w[1]): len(w[3]) for w in one} == {k: len(g[0][3]) for k, g in best.items()} and len(one) == len(best)
    assert rows(pt.simple(every)) == [w for w in want if len({w[0], *(e[2] for e in w[3])}) == len(w[3]) + 1]
    assert {(w[0], w[1], len(w[3])) for w in rows(pt.shortest(every))} == {(*k, len(g[0][3])) for k, g in best.items()}


def test_counts_without_walks(spark):
    m = rsm.from_regex("a (a | b)*")
    index = ix.build(graph_of(spark, EDGES), m, strategy="loop")
    want = {}
    for w in accepted(EDGES, m, 5):
        want[w[0], w[1], len(w[3])] = want.get((w[0], w[1], len(w[3])), 0) + 1
    assert {(r["src"], r["dst"], r["len"]): int(r["n"]) for r in pt.count_by_length(index, 5).collect()} == want


def test_lazy_walks_of_the_example(spark):
    index = ix.build(example(spark), machine_of("anbn"), strategy="loop")
    walk = list(itertools.islice(pt.iterate(index, 1, 1), 2))
    assert [len(w) for w in walk] == [4, 8]
    assert [(e[0], e[2]) for e in walk[0]] == [(1, 0), (0, 1), (1, 1), (1, 1)]


def test_infinite_flags(spark):
    flag = lambda index: {(r[0], r[1]): r[2] for r in pt.is_infinite(index).collect()}
    assert flag(ix.build(example(spark), machine_of("anbn"), strategy="loop")) == {(0, 1): True, (1, 1): True}
    assert flag(ix.build(example(spark), rsm.from_regex("a b*"), strategy="loop")) == {(0, 1): True, (1, 0): False}
    line = graph_of(spark, [(0, "a", 1), (1, "b", 2)])
    assert flag(ix.build(line, rsm.from_grammar("S -> ε | S S | a"), strategy="loop")) == {(0, 0): False, (1, 1): False, (2, 2): False, (0, 1): False}
    loop = graph_of(spark, [(0, "a", 0)])
    assert flag(ix.build(loop, rsm.from_grammar("S -> S S | a"), strategy="loop")) == {(0, 0): True}


def test_verification_finds_wrong_walks(spark):
    g, m = graph_of(spark, EDGES), rsm.from_regex("a b")
    good = pt.all_pairs(ix.PathIndex(g, m, None), 2)
    assert pt.verify(good, g, m).count() == 0
    bad = spark.createDataFrame([(0, 1, 2, [(0, "a", 1), (2, "b", 1)]), (0, 0, 2, [(0, "a", 1), (1, "a", 0)]), (0, 5, 2, [(0, "a", 1), (1, "b", 5)])], pt.PATHS)
    assert pt.verify(bad, g, m).count() == 3


def test_single_path_baseline(spark):
    g = grammar.parse("S -> a S b | a b")
    graph = graph_of(spark, EDGES)
    single = baselines.matrix_single_path(graph, g)
    for r in single.where("label = 'S'").collect():
        walk = baselines.extract_single(single, g, r["src"], "S", r["dst"], graph)
        assert len(walk) == r["len"] and g.derives([e[1] for e in walk]) and walk[0][0] == r["src"] and walk[-1][2] == r["dst"]


def test_rewrites_keep_answers(spark):
    g, m = graph_of(spark, EDGES), rsm.from_regex("a b+")
    to = spark.createDataFrame([(2,)], "id long")
    want = {p for p in pairs(ix.build(g, m, strategy="task").reachable()) if p[1] == 2}
    assert pairs(execute(optimize(PathPlan(g, m, targets=to)))) == want
    walk = execute(optimize(PathPlan(g, m, targets=to, mode="paths", max_length=3)))
    assert sorted((r["src"], r["dst"], r["word"]) for r in walk.collect()) == sorted((u, v, w) for u, v, w, _ in accepted(EDGES, m, 3) if v == 2)


def test_query_text(spark):
    s = LangPathSession(spark)
    s.register("g", graph_of(spark, EDGES))
    assert pairs(s.sql("MATCH a b* ON g FROM (0)")) == {p for p in pairs(ix.build(graph_of(spark, EDGES), fsm.from_regex("a b*")).reachable()) if p[0] == 0}
    assert s.sql("MATCH {S -> a S b | a b} ON g RETURN paths UP TO 2 LIMIT 1 PER PAIR").count() == s.sql("MATCH a b ON g").count()
    with pytest.raises(ValueError):
        s.parse("MATCH a b")
    with pytest.raises(KeyError):
        s.parse("MATCH a ON nowhere")


def test_online_match_equals_batch(spark, tmp_path):
    rows_ = [(1, k, 100 + k, "ab"[k % 2]) for k in range(5)] + [(2, k, 200 + k, "abba"[k]) for k in range(4)]
    ev = spark.createDataFrame(rows_, "user_id long, k int, event_id long, event_type string").selectExpr("user_id", "timestamp_seconds(k * 60) as ts", "event_id", "event_type")
    ev.coalesce(1).write.parquet(str(tmp_path / "in"))
    m = fsm.from_regex("a b")
    stream = spark.readStream.schema(ev.schema).parquet(str(tmp_path / "in"))
    q = dfa_match(stream, m).writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination()
    got = {(r["src"], r["dst"]) for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    edges = [(u + 100 * x, t, u + 1 + 100 * x) for x, seq in ((1, "ababa"), (2, "abba")) for u, t in enumerate(seq[:-1])]
    from langpath.operators.solver import solve

    assert got == solve(edges, rsm.from_fsm(m), None)["S"]


def test_no_bound_is_silent(spark):
    """Without a bound nothing is lost on finite sets, and infinite ones ask for a bound."""
    s = LangPathSession(spark)
    s.register("chain", graph_of(spark, [(i, "a", i + 1) for i in range(12)]))
    s.register("ring", graph_of(spark, [(0, "a", 1), (1, "a", 0)]))
    for mode in ("reach", "single", "paths"):
        assert s.sql(f"MATCH a+ ON chain FROM (0) RETURN {mode}").count() == 12
    assert sorted((r["dst"], r["len"]) for r in s.sql("MATCH a+ ON ring FROM (0) RETURN single").collect()) == [(0, 2), (1, 1)]
    with pytest.raises(ValueError):
        s.sql("MATCH a+ ON ring FROM (0) RETURN paths")
    assert s.sql("MATCH a+ ON ring FROM (0) RETURN paths UP TO 5").count() == 5


def test_lazy_walks_end(spark):
    graph = graph_of(spark, [(0, "a", 1), (1, "a", 2), (2, "b", 3), (3, "b", 4), (0, "c", 4)])
    regular = ix.build(graph, rsm.from_regex("(a | b | c)+"))
    assert [[e[1] for e in w] for w in pt.iterate(regular, 0, 4)] == [["c"], ["a", "a", "b", "b"]]
    nested = ix.build(graph, rsm.from_grammar("S -> a S b | a b"))
    assert [[e[1] for e in w] for w in pt.iterate(nested, 0, 4)] == [["a", "a", "b", "b"]]


def test_walks_without_calls_need_no_facts(spark):
    g, m = graph_of(spark, [(0, "a", 1), (1, "b", 2), (2, "b", 1), (3, "b", 0)]), rsm.from_regex("a b*")
    whole = [(r["src"], r["dst"], r["len"], str(r["path"])) for r in pt.union_all(list(pt.levels(ix.build(g, m, strategy="loop"), 3))).collect()]
    bare = [(r["src"], r["dst"], r["len"], str(r["path"])) for r in pt.union_all(list(pt.levels(ix.PathIndex(g, m, None), 3, prune=False))).collect()]
    assert sorted(bare) == sorted(whole) and len(bare) == 3


def test_counted_pairs_are_the_walks_that_levels_make(spark):
    g = graph_of(spark, [(0, "b", 1), (1, "a", 2), (1, "a", 3), (2, "b", 4), (3, "b", 4), (4, "b", 5), (0, "a", 1)])
    m = rsm.from_grammar("S -> a S b | a b")
    index = ix.build(g, m, strategy="loop")
    made = pt.union_all(list(pt.levels(index, 6))).groupBy("src", "dst").count()
    assert sorted(map(tuple, pt.count_pairs(index, 6).collect())) == sorted(map(tuple, made.collect())) != []
    assert not pt.is_deterministic(rsm.from_grammar("S -> S S | a"))
