"""Headline queries at ``$BENCH_SF_DIR`` on ``local[$BENCH_CPUS]``; prints one JSON line.

Graph tables are built, written and read back before the clock starts (the published times leave loading out), and each
query is the mean of ``$BENCH_RUNS`` runs after one warm-up."""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time

from pyspark.sql import SparkSession

from langpath.graph import LabeledGraph
from langpath.language import fsm as fa
from langpath.operators import baselines
from langpath.operators import index as ix
from langpath.operators import paths as pt
from langpath.sources import builders as B
from langpath.workloads import AB, grammar_of, machine_of
from langpath.workloads.templates import TEMPLATES, TRAIL, bind


def stored(spark: SparkSession, root: str, name: str, g: LabeledGraph) -> LabeledGraph:
    parts = {}
    for k, df in (("edges", g.edges), ("vertices", g.vertices), ("pieces", g.pieces)):
        if df is not None:
            df.write.parquet(f"{root}/{name}/{k}")
            parts[k] = spark.read.parquet(f"{root}/{name}/{k}").cache()
            parts[k].count()
    return LabeledGraph(parts["edges"], parts["vertices"], parts.get("pieces"))


def main() -> None:
    sf_dir, cpus, runs = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8"), int(os.environ.get("BENCH_RUNS", "2"))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    root = tempfile.mkdtemp(prefix="langpath-bench-")
    g = {k: stored(spark, root, k, B.BUILDERS[k](spark, sf_dir)) for k in ("trail", "ontology", "territory", "pointer", "commerce")}
    regular = lambda graph, text: ix.build(g[graph], fa.from_regex(text)).reachable()
    work = {f"rpq_{k}": lambda t=bind(TEMPLATES[k], TRAIL): regular("trail", t) for k in ("q2", "q5", "q11_2", "q11_3", "q12", "q14", "q16")}
    work["rpq_commerce"] = lambda: regular("commerce", "placed_by located within")
    for k, graph in (("g1", "ontology"), ("g2", "ontology"), ("geo", "territory"), ("ma", "pointer")):
        work[f"cf_{k}"] = lambda k=k, graph=graph: ix.build(g[graph], machine_of(k)).reachable()
    work["loop_g2"] = lambda: ix.build(g["ontology"], machine_of("g2"), strategy="loop").reachable()
    for k, graph in (("g1", "ontology"), ("g2", "ontology"), ("geo", "territory")):
        work[f"matrix_{k}"] = lambda k=k, graph=graph: baselines.matrix_reach(g[graph], grammar_of(k)).where("label = 'S'")
    work["paths_anbn_20"] = lambda: pt.all_pairs(ix.PathIndex(g["trail"], machine_of("anbn", AB), None), 20)
    took = {}
    for name, f in work.items():
        f().write.format("noop").mode("overwrite").save()
        began = time.perf_counter()
        for _ in range(runs):
            f().write.format("noop").mode("overwrite").save()
        took[name] = round((time.perf_counter() - began) / runs, 3)
        print(name, took[name], file=sys.stderr)
    print(json.dumps({"metric": "index and path queries, total of means", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(sf_dir.rstrip("/"))}))


if __name__ == "__main__":
    main()
