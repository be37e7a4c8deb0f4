"""A small query language.

    MATCH <expression or grammar> ON <graph> [FROM <ids>] [TO <ids>] [RETURN reach|paths|single]
          [UP TO <length>] [LIMIT <walks> PER PAIR]

An expression is a regular expression over labels; a grammar is rules in braces, the first of which gives the start.  Ids are numbers in
parentheses, or the name of a view with a column ``id``."""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..graph import LabeledGraph
from ..language import grammar as gr
from ..language import rsm
from .optimizer import PathPlan, execute, optimize

_CLAUSE = re.compile(
    r"^\s*MATCH\s+(?P<what>\{.*?\}|.+?)\s+ON\s+(?P<graph>\w+)(?:\s+FROM\s+(?P<from>\([\d\s,-]+\)|\w+))?(?:\s+TO\s+(?P<to>\([\d\s,-]+\)|\w+))?"
    r"(?:\s+RETURN\s+(?P<mode>reach|paths|single))?(?:\s+UP\s+TO\s+(?P<len>\d+))?(?:\s+LIMIT\s+(?P<k>\d+)\s+PER\s+PAIR)?\s*;?\s*$",
    re.S | re.I,
)


class LangPathSession:
    """Named graphs of a Spark session, and queries over them."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.graphs: dict[str, Callable[[], LabeledGraph]] = {}

    def register(self, name: str, graph: LabeledGraph | Callable[[], LabeledGraph]) -> None:
        self.graphs[name.lower()] = graph if callable(graph) else lambda: graph

    def parse(self, text: str) -> PathPlan:
        m = _CLAUSE.match(text)
        if not m:
            raise ValueError(f"not a query: {text!r}")
        if m["graph"].lower() not in self.graphs:
            raise KeyError(f"no graph {m['graph']}")
        what = m["what"].strip()
        machine = rsm.from_grammar(gr.parse(what[1:-1])) if what.startswith("{") else rsm.from_regex(what)
        return PathPlan(
            self.graphs[m["graph"].lower()](), machine, self._ids(m["from"]), self._ids(m["to"]),
            (m["mode"] or "reach").lower(), int(m["len"]) if m["len"] else None, int(m["k"]) if m["k"] else None,
        )

    def _ids(self, text: str | None) -> DataFrame | None:
        if text is None:
            return None
        if text.startswith("("):
            return self.spark.createDataFrame([(int(x),) for x in text[1:-1].split(",")], "id long")
        return self.spark.table(text).selectExpr("cast(id as bigint) id")

    def sql(self, text: str) -> DataFrame:
        return execute(optimize(self.parse(text)))
