import random

import pytest

from langpath.graph import LabeledGraph
from langpath.language import fsm, grammar, rsm
from langpath.operators import baselines, closure, kron
from langpath.operators import index as ix
from langpath.operators.solver import close_rows, regular_pairs, solve
from langpath.runtime import Stage
from langpath.workloads import example, machine_of
from langpath.workloads.templates import GRAMMARS

from .oracles import grammar_facts, walks


def graph_of(spark, edges, vertices=()):
    ids = {*vertices, *(e[0] for e in edges), *(e[2] for e in edges)}
    return LabeledGraph(spark.createDataFrame(edges, "src long, label string, dst long"), spark.createDataFrame([(i,) for i in sorted(ids)], "id long"))


def pairs(df):
    return {(r["src"], r["dst"]) for r in df.collect()}


CLOSURES = ["linear", "incremental", "table"]


@pytest.mark.parametrize("kind", CLOSURES)
def test_worked_example(spark, kind):
    got = ix.build_full(example(spark), machine_of("anbn"), kind)
    assert pairs(got.reachable()) == {(0, 1), (1, 1)}
    assert got.index_edges.count() == 6 and got.closure.distinct().count() == 11
    if kind == "incremental":
        assert [(m["product_new"], m["closure_new"], m["facts_new"]) for m in got.metrics] == [(4, 5, 1), (1, 4, 1), (1, 2, 0)]


@pytest.mark.parametrize("kind", ["incremental", "table"])
def test_nullable_facts_are_in_the_first_delta(spark, kind):
    """Reflexive facts must take part in the first product, else (0, 1) is lost."""
    assert pairs(ix.build_full(example(spark), machine_of("nullable"), kind).reachable()) == {(0, 0), (0, 1), (1, 1)}


@pytest.mark.parametrize("strategy", ["loop", "task"])
def test_nullable_by_strategy(spark, strategy):
    assert pairs(ix.build(example(spark), machine_of("nullable"), strategy=strategy).reachable()) == {(0, 0), (0, 1), (1, 1)}


def test_facts_are_new_once(spark):
    """A box with two final states must not report a fact twice."""
    m = rsm.from_grammar("S -> a | a b | a S")
    got = ix.build_full(graph_of(spark, [(0, "a", 1), (1, "b", 1), (1, "a", 0)]), m)
    assert sum(x["facts_new"] for x in got.metrics) == got.facts.count() == got.facts.distinct().count()
    assert sum(x["closure_new"] for x in got.metrics) == got.closure.count()


def test_solver_against_saturation():
    rng = random.Random(5)
    for text in [*GRAMMARS.values(), "S -> S a | A\nA -> S b | c | ε"]:
        g = grammar.parse(text)
        labels = sorted(g.terminals)
        for _ in range(12):
            edges = {(rng.randrange(5), rng.choice(labels), rng.randrange(5)) for _ in range(rng.randrange(1, 14))}
            want = grammar_facts(edges, g.to_binary_normal_form(), range(5))
            for box in g.nonterminals:
                got = solve(edges, rsm.from_grammar(g), None, range(5), [box])[box]
                assert got == {(u, v) for u, a, v in want if a == box}


def test_rows_against_solver():
    rng = random.Random(8)
    for text in ("a b* c", "(a b)+ | (c a)+", "a*", "(a | b)+ c?"):
        m = fsm.from_regex(text)
        for _ in range(15):
            edges = {(rng.randrange(6), rng.choice("abc"), rng.randrange(6)) for _ in range(rng.randrange(1, 18))}
            got = set(regular_pairs(edges, {(q, s): p for q, s, p in m.edges}, 0, set(m.finals), m.n, range(6)))
            assert got == solve(edges, rsm.from_fsm(m), None, range(6))["S"]
    assert close_rows({0: [1], 1: [2], 2: [0]}) == {k: 0b111 for k in range(3)}


@pytest.mark.parametrize("text", ["S -> ε | a S b", "S -> d~ V d\nV -> ((S?) a~)* (S?) (a (S?))*"])
def test_all_methods_agree(spark, text):
    rng = random.Random(11)
    g = grammar.parse(text)
    edges = sorted({(rng.randrange(6), rng.choice(sorted(g.terminals)), rng.randrange(6)) for _ in range(14)})
    graph, m = graph_of(spark, edges, range(7)), rsm.from_grammar(g)
    want = {(u, v) for u, a, v in grammar_facts(set(edges), g.to_binary_normal_form(), range(7)) if a == "S"}
    assert pairs(ix.build(graph, m, strategy="task").reachable()) == want
    assert pairs(ix.build(graph, m, strategy="loop").reachable()) == want
    assert pairs(ix.build_full(graph, m, "packed").reachable()) == want
    assert pairs(baselines.matrix_reach(graph, g).where("label = 'S'")) == want
    assert pairs(baselines.matrix_single_path(graph, g).where("label = 'S'")) == want


def test_sources_pieces_and_unrolled(spark):
    rng = random.Random(3)
    edges = sorted({(p * 10 + rng.randrange(5), rng.choice("ab"), p * 10 + rng.randrange(5)) for p in range(4) for _ in range(7)})
    g = graph_of(spark, edges)
    parts = g.vertices.selectExpr("id", "id div 10 as piece")
    for text in ("a b*", "a b a", "(a | b)+"):
        m = fsm.from_regex(text)
        want = solve(edges, rsm.from_fsm(m), None)["S"]
        for graph in (g, LabeledGraph(g.edges, g.vertices, parts)):
            assert pairs(ix.build(graph, m).reachable()) == want
            some = g.vertices.where("id % 3 = 0")
            assert pairs(ix.build(graph, m, sources=some).reachable()) == {p for p in want if p[0] % 3 == 0}
        assert pairs(baselines.bfs(g, m)) == want
    m = machine_of("anbn")
    want = solve(edges, m, None)["S"]
    some = g.vertices.where("id % 2 = 0")
    for strategy in ("loop", "task"):
        assert pairs(ix.build(g, m, sources=some, strategy=strategy).reachable()) == {p for p in want if p[0] % 2 == 0}


def test_large_pieces_go_through_the_loop(spark, monkeypatch):
    monkeypatch.setattr(ix, "PIECE_ROWS", 5)
    edges = [(0, "a", 1), (1, "b", 2), *[(10 + k, "a", 11 + k) for k in range(8)], (18, "b", 19)]
    g = graph_of(spark, edges)
    got = ix.build(LabeledGraph(g.edges, g.vertices, g.vertices.selectExpr("id", "id div 10 as piece")), fsm.from_regex("a+ b"))
    assert pairs(got.reachable()) == solve(edges, rsm.from_regex("a+ b"), None)["S"]


def test_insertion_equals_batch(spark):
    edges = [(0, "a", 1), (1, "a", 2), (2, "b", 3), (3, "b", 4), (4, "a", 0)]
    m = machine_of("anbn")
    early = ix.build(graph_of(spark, edges[:2], range(5)), m, strategy="loop")
    got = early.insert(spark.createDataFrame(edges[2:4], "src long, label string, dst long")).insert(spark.createDataFrame(edges[4:], "src long, label string, dst long"))
    assert pairs(got.reachable()) == solve(edges, m, None, range(5))["S"]


@pytest.mark.parametrize("edges", [[], [(0, "z", 1)], [(0, "a", 0)]])
def test_small_graphs(spark, edges):
    g = graph_of(spark, edges, [0, 1, 2])
    for text in ("a", "a*", "∅", "ε"):
        want = solve(edges, rsm.from_regex(text), None, [0, 1, 2])["S"]
        for strategy in ("auto", "loop"):
            assert pairs(ix.build(g, rsm.from_regex(text), strategy=strategy).reachable()) == want


def test_closure_insertion(spark):
    e = lambda rows: spark.createDataFrame(rows, "x long, y long")
    stage = Stage(spark)
    full, _ = closure.scratch(e([(0, 1), (1, 2), (2, 0), (5, 0), (70, 5)]), stage, "linear")
    want = {tuple(r) for r in full.collect()}
    c, _, n1 = closure.insert(None, e([(0, 1), (5, 0)]), stage)
    c, added, n2 = closure.insert(c, e([(1, 2), (2, 0), (70, 5)]), stage)
    assert {tuple(r) for r in c.collect()} == want and n1 + n2 == len(want) and added.count() == n2
    for table in (None, closure.block_table(spark, 4), closure.block_table(spark, 2)):
        r, _, m1 = closure.insert_packed(None, e([(0, 1), (5, 0)]), stage)
        r, _, m2 = closure.insert_packed(r, e([(1, 2), (2, 0), (70, 5)]), stage)
        assert {tuple(x) for x in closure.to_pairs(r).collect()} == want and m1 + m2 == len(want)


def test_kronecker_forms_agree(spark):
    g = graph_of(spark, [(0, "a", 1), (1, "b", 1), (0, "b", 1), (1, "c", 0)])
    h = graph_of(spark, [(0, "a", 1), (0, "b", 1), (1, "b", 0)])
    flat = {tuple(r) for r in kron.graphs(g, h).select("src1", "src2", "dst1", "dst2", "label").collect()}
    sets = {(*r[:4], x) for r in kron.label_sets(g, h).select("src1", "src2", "dst1", "dst2", "labels").collect() for x in r[4]}
    fam = {(*r, k) for k, df in kron.families(g.decompose(), h.decompose()).items() for r in df.collect()}
    assert flat == sets == fam
    assert {x[:4] for x in flat} == {tuple(r) for r in kron.collapse(kron.graphs(g, h)).collect()}


def test_kronecker_is_distributive(spark):
    m = spark.createDataFrame([(0, 1, 2), (1, 1, 3)], "i long, j long, x long")
    a, b = (spark.createDataFrame([r], "i long, j long, x long") for r in ((0, 0, 1), (1, 0, 5)))
    left = kron.matrix(m, a.union(b), 2, 2).collect()
    right = kron.matrix(m, a, 2, 2).union(kron.matrix(m, b, 2, 2)).collect()
    assert sorted(map(tuple, left)) == sorted(map(tuple, right))


def test_pruned_index_and_storage(spark, tmp_path):
    got = ix.build(example(spark), machine_of("anbn"), strategy="loop")
    assert got.pruned().count() == 6
    got.save(str(tmp_path))
    again = ix.load(example(spark), machine_of("anbn"), str(tmp_path), with_reach=True)
    assert pairs(again.reachable()) == {(0, 1), (1, 1)}


def test_walks_in_the_language_are_the_answer():
    """Ground truth without any automaton: walks and word membership."""
    edges = [(0, "a", 1), (1, "a", 2), (2, "b", 3), (3, "b", 4)]
    g = grammar.parse(GRAMMARS["anbn"])
    want = {(u, v) for u, v, path in walks(edges, 4) if path and g.derives([e[1] for e in path])}
    assert solve(edges, rsm.from_grammar(g), None)["S"] == want
