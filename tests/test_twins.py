import random

import pytest

from langpath.language import grammar as gr
from langpath.language import rsm
from langpath.operators import baselines, measure, twins
from langpath.operators import index as ix

from .test_index import graph_of

GEO = "S -> bt S bt~\nS -> bt bt~"


def tree(spark, leaves=40):
    """Leaves below three nations of two regions, one leaf below two nations."""
    edges = [(100 + k, "bt", k % 3) for k in range(leaves)] + [(100, "bt", 1), (0, "bt", 10), (1, "bt", 10), (2, "bt", 11)]
    return graph_of(spark, edges + [(v, "bt~", u) for u, _, v in edges])


def rows(df):
    got = sorted(map(tuple, df.collect()))
    assert len(got) == len(set(got))
    return got


@pytest.mark.parametrize("strategy", ["auto", "loop"])
def test_geo_is_solved_on_classes_of_twins(spark, strategy):
    g, m = tree(spark), rsm.from_grammar(GEO)
    index = ix.build(g, m, strategy=strategy, twins=True)
    assert index.graph.vertices.count() == 3 + 1 + 5  # a leaf of each nation, the odd leaf, nations and regions
    assert rows(index.reachable()) == rows(ix.build(g, m, strategy="loop").reachable())


def test_full_tree_grows_with_the_answer_only(spark):
    """Facts of the reduced graph stay as many when leaves are doubled."""
    m = rsm.from_grammar(GEO)
    few, many = (ix.build(tree(spark, n), m, strategy="loop", twins=True) for n in (40, 80))
    assert few.facts.count() == many.facts.count() and few.reachable().count() < many.reachable().count()


def test_matrix_of_twins(spark):
    g, grammar = tree(spark), gr.parse(GEO)
    assert rows(baselines.matrix_reach(g, grammar, twins=True)) == rows(baselines.matrix_reach(g, grammar))
    null = gr.parse("S -> ε | bt S bt~")
    assert rows(baselines.matrix_reach(g, null, twins=True)) == rows(baselines.matrix_reach(g, null))


def test_differing_answers_are_written_out_by_classes(spark):
    g = tree(spark)
    part, members = twins.reduced(g)
    a, b = (ix.build(part, rsm.from_grammar(x)).reachable() for x in (GEO, "S -> bt bt~"))
    whole = (ix.build(g, rsm.from_grammar(x)).reachable() for x in (GEO, "S -> bt bt~"))
    got = rows(twins.expand(measure.diff(a, b), members))
    assert got and got == rows(measure.diff(*whole))


def test_random_graphs_and_equal_hashes(spark, monkeypatch):
    rng = random.Random(3)
    edges = {(rng.randrange(8), rng.choice("ab"), rng.randrange(8)) for _ in range(14)}
    g, m = graph_of(spark, sorted(edges)), rsm.from_grammar("S -> a S b | a b | a")
    want = rows(ix.build(g, m, strategy="loop").reachable())
    assert rows(ix.build(g, m, twins=True).reachable()) == want
    monkeypatch.setattr(twins.F, "xxhash64", lambda *c: twins.F.lit(7).cast("long"))  # all of one degree look like twins
    assert rows(ix.build(g, m, twins=True).reachable()) == want


def test_boxes_with_the_empty_word_are_refused(spark):
    with pytest.raises(ValueError):
        ix.build(tree(spark), rsm.from_grammar("S -> ε | bt S bt~"), twins=True)
