import random

import pytest

from langpath.language import rsm
from langpath.operators import index as ix
from langpath.operators import jumps
from langpath.operators.solver import solve

from .test_index import graph_of

GRAMMARS = ["S -> a b | a S b", "S -> ε | a S b", "S -> S S | a", "S -> a V b\nV -> ((S?) c)* (S?) (b (S?))*", "S -> a b* | c S"]


@pytest.mark.parametrize("limit", [0, 3, 50_000])
@pytest.mark.parametrize("text", GRAMMARS)
def test_jumps_as_the_solver(spark, monkeypatch, text, limit):
    rng = random.Random(len(text))
    edges = {(rng.randrange(12), rng.choice("abc"), rng.randrange(12)) for _ in range(22)}
    monkeypatch.setattr(jumps, "PART_EDGES", limit)
    g, m = graph_of(spark, sorted(edges), vertices=[100, -7]), rsm.from_grammar(text)
    box = sorted(m.boxes)[-1]
    want = sorted(solve(edges, m, vertices=[r[0] for r in g.vertices.collect()], boxes=[box])[box])
    assert sorted(map(tuple, ix.build(g, m, boxes=[box], strategy="jumps").reachable(box).collect())) == want


def test_components_by_joins(spark, monkeypatch):
    edges = [(k, "a", k + 1) for k in range(6)] + [(9, "a", 9), (10, "b", 11)]
    g, m = graph_of(spark, edges), rsm.from_grammar("S -> a* | b S")
    want = sorted(solve(edges, m, vertices=[r[0] for r in g.vertices.collect()])["S"])
    monkeypatch.setattr(jumps, "TASK_EDGES", 0)
    assert sorted(map(tuple, ix.build(g, m, strategy="jumps").reachable().collect())) == want


def test_long_chains_take_few_rounds(spark):
    """A round for each edge of a day's chain made the alias queries fail by time."""
    n = 40
    edges = [(k, "a", k + 1) for k in range(n)] + [(k, "d", 100 + k % 3) for k in range(n + 1)] + [(100 + k, "d", 200) for k in range(3)]
    edges += [(v, f"{s}~", u) for u, s, v in edges]
    g, m = graph_of(spark, edges), rsm.from_grammar("S -> d~ V d\nV -> ((S?) a~)* (S?) (a (S?))*")
    index = ix.build(g, m, strategy="jumps")
    assert len(index.metrics) <= 12
    assert sorted(map(tuple, index.reachable().collect())) == sorted(solve(edges, m)["S"])
