import importlib
import sys

import __spark_entry__ as entry
from langpath import workloads
from langpath.workloads.templates import TEMPLATES, generate

from .test_index import graph_of


def test_every_oracle_has_its_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert {f"rpq_{k}" for k in TEMPLATES} <= set(workloads.queries())


def test_entry_without_the_training_data_operators(monkeypatch):
    class Gone:
        def find_spec(self, name, path=None, target=None):
            if name == "corpus_pipeline" or name.startswith("langpath.llm"):
                raise ModuleNotFoundError(name=name)

    for name in [m for m in sys.modules if m == "corpus_pipeline" or m.startswith("langpath.llm")]:
        monkeypatch.delitem(sys.modules, name)
    monkeypatch.setattr(sys, "meta_path", [Gone(), *sys.meta_path])
    fresh = importlib.reload(entry)
    assert set(fresh.queries()) == set(workloads.queries()) and set(fresh.oracle_sql()) == set(workloads.oracle_sql())


def test_generated_queries(spark):
    g = graph_of(spark, [(0, "x", 1), (1, "y", 2), (2, "z", 3), (3, "x", 0)])
    got = generate(g, "q5", 5)
    assert len(got) == 5 == len(set(got)) and all(len(set(q.replace("*", "").split())) == 3 for q in got)
    assert got == generate(g, "q5", 5)
