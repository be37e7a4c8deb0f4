import random

import numpy as np
import pytest

from langpath.language import rsm
from langpath.operators import bitrows
from langpath.operators import index as ix
from langpath.operators.solver import solve

from .test_index import graph_of

GRAMMARS = ["S -> a b | a S b", "S -> ε | a S b", "S -> S S | a", "S -> a V b\nV -> ((S?) c)* (S?) (b (S?))*", "S -> a b* | c S"]


@pytest.mark.parametrize("text", GRAMMARS)
def test_bits_as_the_solver(spark, text):
    rng = random.Random(len(text))
    edges = {(rng.randrange(20), rng.choice("abc"), rng.randrange(20)) for _ in range(45)}
    g, m = graph_of(spark, sorted(edges), vertices=[100, -7]), rsm.from_grammar(text)
    for box in m.boxes:
        want = sorted(solve(edges, m, vertices=[r[0] for r in g.vertices.collect()], boxes=[box])[box])
        index = ix.build(g, m, boxes=[box], strategy="bits")
        assert index.reach is None and sorted(map(tuple, index.reachable(box).collect())) == want


def test_a_long_derivation_takes_no_jobs_of_its_own(spark):
    """The loop took a round of jobs for each of these 300 steps."""
    n = 150
    edges = [(k, "a", k + 1) for k in range(n)] + [(k, "b", k + 1) for k in range(n, 2 * n)]
    before = spark.sparkContext.statusTracker().getJobIdsForGroup(None)
    index = ix.build(graph_of(spark, edges), rsm.from_grammar("S -> a b | a S b"), strategy="bits")
    assert sorted(map(tuple, index.reachable().collect())) == [(n - k, n + k) for k in range(n, 0, -1)]
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup(None)) - len(before) < 20


def test_large_matrices_go_through_the_loop(spark, monkeypatch):
    edges = [(0, "a", 1), (1, "a", 0), (0, "b", 2), (2, "b", 3), (3, "b", 0)]
    g, m = graph_of(spark, edges), rsm.from_grammar("S -> a b | a S b")
    want = sorted(map(tuple, ix.build(g, m, strategy="bits").reachable().collect()))
    monkeypatch.setattr(bitrows, "BIT_BYTES", 0)
    index = ix.build(g, m, strategy="bits")
    assert index.reach is not None and sorted(map(tuple, index.reachable().collect())) == want and want


def test_transposed_bits():
    x = np.random.default_rng(1).integers(0, 2, (128, 128)).astype(np.uint8)
    m = np.packbits(x, axis=1, bitorder="little")
    assert (np.unpackbits(bitrows.transposed(m), axis=1, bitorder="little") == x.T).all()
