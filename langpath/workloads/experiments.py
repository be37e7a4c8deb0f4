"""The experiments as functions: each returns one row per measured cell.

    python -m langpath.workloads.experiments regular|structure|grammar|closures|paths DIR [DIR ...]"""

from __future__ import annotations

import sys

from pyspark.sql import DataFrame, SparkSession

from ..graph import LabeledGraph
from ..language import fsm as fa
from ..operators import baselines, measure
from ..operators import index as ix
from ..operators import paths as pt
from ..runtime import Stage
from ..sources import builders as B
from . import AB, grammar_of, machine_of
from .templates import TEMPLATES, TRAIL, bind, generate


def staged(graph: LabeledGraph) -> LabeledGraph:
    """The graph as stored tables, so that building it is not part of a measure."""
    stage = Stage(graph.edges.sparkSession)
    put = lambda df: None if df is None else stage.put(df)[0]
    return LabeledGraph(put(graph.edges), put(graph.vertices), put(graph.pieces))


def regular(spark: SparkSession, dirs: list[str], runs: int = 5, keys: list[str] | None = None) -> list[dict]:
    """One set of queries over growing graphs."""
    out = []
    for d in dirs:
        g = staged(B.trail(spark, d))
        for k in keys or TEMPLATES:
            m = fa.from_regex(bind(TEMPLATES[k], TRAIL))
            out.append({"dir": d, "query": k, **measure.time_runs(lambda g=g, m=m: ix.build(g, m).reachable(), runs)})
    return out


def structure(spark: SparkSession, d: str, runs: int = 5, keys: tuple[str, ...] = ("q2", "q5", "q11_2", "q12", "q16"), bindings: int = 10) -> list[dict]:
    """The same templates on unlike graphs, with bindings drawn from each graph's frequent labels."""
    out = []
    for name in ("trail", "handoff", "ontology", "commerce", "dialogue", "weblinks"):
        g = staged(B.BUILDERS[name](spark, d))
        for k in keys:
            for text in dict.fromkeys(generate(g, k, bindings)):
                out.append({"graph": name, "template": k, "query": text, **measure.time_runs(lambda g=g, t=text: ix.build(g, fa.from_regex(t)).reachable(), runs)})
    return out


GRAMMAR_GRAPHS = (("g1", "ontology"), ("g2", "ontology"), ("geo", "territory"), ("ma", "pointer"))


def grammar(spark: SparkSession, dirs: list[str], runs: int = 5) -> list[dict]:
    """Tensor method against matrix method, with their ratio."""
    out = []
    for d in dirs:
        for name, graph in GRAMMAR_GRAPHS:
            g = staged(B.BUILDERS[graph](spark, d))
            tensor = measure.time_runs(lambda g=g, n=name: ix.build(g, machine_of(n), strategy="loop").reachable(), runs)
            chosen = measure.time_runs(lambda g=g, n=name: ix.build(g, machine_of(n)).reachable(), runs)
            matrix = measure.time_runs(lambda g=g, n=name: baselines.matrix_single_path(g, grammar_of(n)).where("label = 'S'"), runs)
            out.append({"dir": d, "grammar": name, "graph": graph, "pairs": tensor["rows"], "tensor_s": tensor["mean_s"], "chosen_s": chosen["mean_s"], "matrix_s": matrix["mean_s"], "ratio": measure.ratio(tensor, matrix)})
    return out


def closures(spark: SparkSession, d: str, runs: int = 3) -> list[dict]:
    """Closure variants on one grammar, with the work each does."""
    g, out = staged(B.ontology(spark, d)), []
    for name, (kind, delta) in {"naive": ("linear", False), "scratch": ("squaring", True), "incremental": ("incremental", True), "packed": ("packed", True), "table": ("table", True)}.items():
        took = measure.time_runs(lambda k=kind, x=delta: ix.build_full(g, machine_of("g1"), k, x).reachable(), runs)
        work = ix.build_full(g, machine_of("g1"), kind, delta).metrics
        out.append({"variant": name, **took, "rounds": len(work), "product": sum(m["product_new"] for m in work), "closure": work[-1]["closure_total"]})
    return out


def paths(spark: SparkSession, d: str, length: int = 20, runs: int = 3) -> list[dict]:
    """All walks of all pairs up to a length: seconds per pair and walks per pair."""
    g = staged(B.trail(spark, d))
    work: DataFrame = pt.all_pairs(ix.PathIndex(g, machine_of("anbn", AB), None), length)
    took = measure.time_runs(lambda: work, runs)
    n = measure.paths_per_pair(work).first()
    return [{"dir": d, "pairs": n["pairs"], "walks": n["walks"], "mean_walks": n["mean_walks"], "most_walks": n["most_walks"], "s": took["mean_s"], "s_per_pair": took["mean_s"] / max(n["pairs"], 1)}]


def main(args: list[str]) -> None:
    spark = SparkSession.builder.config("spark.ui.showConsoleProgress", "false").getOrCreate()
    kind, dirs = args[0], args[1:]
    rows = {"regular": lambda: regular(spark, dirs), "structure": lambda: structure(spark, dirs[0]), "grammar": lambda: grammar(spark, dirs), "closures": lambda: closures(spark, dirs[0]), "paths": lambda: paths(spark, dirs[0])}[kind]()
    for r in rows:
        print(r)


if __name__ == "__main__":
    main(sys.argv[1:])
