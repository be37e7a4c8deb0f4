"""Queries that used to fail on larger tables, or that read none."""

import pytest

from langpath import workloads
from langpath.operators import kron

from .test_index import graph_of

DIR = "/root/testdata/sf0.001"


def test_recursive_cte_has_no_row_limit(spark):
    old = spark.conf.get("spark.sql.cteRecursionRowLimit")
    want = workloads.queries()["recursive_cte"](spark, DIR).count()
    spark.conf.set("spark.sql.cteRecursionRowLimit", "5")
    try:
        assert workloads.queries()["recursive_cte"](spark, DIR).count() == want > 5
    finally:
        spark.conf.set("spark.sql.cteRecursionRowLimit", old)


def test_products_do_not_sort(spark, monkeypatch):
    g, h = graph_of(spark, [(1, "a", 2), (1, "b", 2), (2, "a", 3)]), graph_of(spark, [(7, "a", 8), (7, "b", 8), (8, "b", 9)])
    want = [(1, 7, "a", 2, 8), (1, 7, "b", 2, 8), (1, 8, "b", 2, 9), (2, 7, "a", 3, 8)]
    for held in (kron.HELD_ROWS, 0):
        monkeypatch.setattr(kron, "HELD_ROWS", held)
        got = kron.graphs(g, h)
        assert sorted(map(tuple, got.collect())) == want
        assert "SortMergeJoin" not in got._jdf.queryExecution().toString()


def test_label_sets_are_intersected_once_per_pair_of_sets(spark):
    g, h = graph_of(spark, [(1, "a", 2), (1, "b", 2), (2, "a", 3)]), graph_of(spark, [(7, "a", 8), (7, "b", 8), (8, "b", 9)])
    got = kron.label_sets(g, h, sep=" ")
    assert sorted(map(tuple, got.collect())) == [(1, 7, 2, 8, "a b"), (1, 8, 2, 9, "b"), (2, 7, 3, 8, "a")]
    assert "intersect" not in got._jdf.queryExecution().toString()


@pytest.mark.parametrize("name", ["fsm_intersection", "grammar_growth", "grammar_sizes", "udtf_transitions"])
def test_automata_and_grammars_come_from_a_table(spark, name):
    got = workloads.queries()[name](spark, DIR)
    assert any(f.endswith("events.parquet") for f in got.inputFiles()) and got.limit(1).count() == 1
