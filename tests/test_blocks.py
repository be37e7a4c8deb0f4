import random

import numpy as np
import pytest

from langpath.language import grammar as gr
from langpath.language import rsm
from langpath.operators import baselines, blocks
from langpath.operators.solver import solve
from langpath.workloads.templates import GRAMMARS

from .test_index import graph_of


def pairs(df):
    return sorted(tuple(r) for r in df.where("label = 'S'").select("src", "dst").collect())


def both_ways(edges):
    return edges + [(v, f"{x}~", u) for u, x, v in edges]


def test_rounds_do_not_follow_a_chain(spark, monkeypatch):
    edges = both_ways([(k, "a", k + 1) for k in range(40)] + [(k, "d", 100 + k % 7) for k in range(41)] + [(100 + k, "d", 200 + k % 2) for k in range(7)])
    rounds = []
    times = blocks._times
    monkeypatch.setattr(blocks, "_times", lambda *x: rounds.append(1) or times(*x))
    got = pairs(baselines.matrix_reach(graph_of(spark, edges), gr.parse(GRAMMARS["ma"]), blocks={"S"}))
    assert got == sorted(solve(edges, rsm.from_grammar(gr.parse(GRAMMARS["ma"])))["S"])
    assert len(rounds) <= 2 * 10  # two products a round


@pytest.mark.parametrize("most", [2, 2048])
def test_blocks_and_joins_agree(spark, most):
    edges = [(1, "a", 2), (2, "a", 3), (3, "a", 1), (4, "a", 5), (6, "a", 6), (7, "b", 1)]
    g, grammar = graph_of(spark, edges), gr.parse("S -> S S | a")
    got = pairs(blocks.facts(g, grammar, {"S"}, vertices=most))
    assert got == pairs(baselines.matrix_facts(g, grammar)) and len(got) == 11


def test_dense_and_sparse_agree():
    rules = blocks.rules_of(gr.parse(GRAMMARS["ma"]).to_binary_normal_form())
    labels = sorted({x for r in rules for x in r})
    for seed in range(30):
        r = random.Random(seed)
        rows = list({(r.randrange(8), r.choice(labels), r.randrange(8)) for _ in range(12)})
        a, label, b = np.array([x for x, _, _ in rows]), [k for _, k, _ in rows], np.array([y for _, _, y in rows])
        inner = np.array([r.random() < 0.6 for _ in range(8)])
        made = [{(k, int(x), int(y)) for k, xs, ys in f(a, label, b, inner, rules) for x, y in zip(xs, ys, strict=True)} for f in (blocks._dense, blocks._sparse)]
        assert made[0] == made[1]
