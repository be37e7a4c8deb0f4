import random

import pytest

from langpath.language import fsm as fa
from langpath.language import rsm
from langpath.operators import baselines, hubs
from langpath.operators import index as ix
from langpath.operators.solver import solve
from langpath.plans.optimizer import PathPlan, execute, optimize

from .test_index import graph_of

TEXTS = ["a*", "a b*", "a b* c", "(a b)+ | (c a)+", "(a | b)+ c?"]


def rows(df):
    got = sorted(map(tuple, df.collect()))
    assert len(got) == len(set(got))
    return got


def graph(spark, n=30, m=60, seed=1):
    """A dense part, a part behind it and a part that is not joined with them."""
    rng = random.Random(seed)
    edges = {(rng.randrange(n), rng.choice("abc"), rng.randrange(n)) for _ in range(m)}
    edges |= {(n + k, "a", n + k + 1) for k in range(4)} | {(0, "b", n), (50, "a", 51), (51, "b", 50)}
    return graph_of(spark, sorted(edges))


@pytest.mark.parametrize("text", TEXTS)
def test_hubs_as_the_solver(spark, text):
    g, m = graph(spark), rsm.from_regex(text)
    want = sorted(solve(map(tuple, g.edges.collect()), m, vertices=[r[0] for r in g.vertices.collect()])["S"])
    assert rows(ix.build(g, m, strategy="hubs").reachable()) == want
    assert rows(hubs.answers(g, m, task_edges=0)) == want  # by joins


def test_hubs_with_sources_and_targets(spark):
    g, m = graph(spark), rsm.from_regex("a b* c")
    some = g.vertices.where("id % 3 = 0")
    assert rows(ix.build(g, m, sources=some, strategy="hubs").reachable()) == rows(ix.build(g, m, sources=some, strategy="loop").reachable())
    ends = [execute(optimize(PathPlan(g, m, targets=some, strategy=s))) for s in ("hubs", "loop")]
    assert rows(ends[0].select("src", "dst")) == rows(ends[1].select("src", "dst"))
    assert rows(baselines.bfs(g, fa.from_regex("a b*"), by_hubs=True)) == rows(baselines.bfs(g, fa.from_regex("a b*")))


def test_a_quadratic_answer_is_kept_as_a_linear_one(spark, monkeypatch):
    """On a ring all pairs are answers; what is staged grows with the vertices only."""
    staged = []
    put = hubs.Stage.put
    monkeypatch.setattr(hubs.Stage, "put", lambda self, df: (staged.append(out[1]) or out) if (out := put(self, df)) else out)
    n = 60
    got = hubs.answers(graph_of(spark, [(k, "a", (k + 1) % n) for k in range(n)]), rsm.from_regex("a*"))
    assert got.count() == n * n and max(staged) == n
