"""Cost measures and reports."""

from __future__ import annotations

import re
import time
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..language import grammar as gr
from ..language import rsm
from ..language.grammar import Grammar


def time_runs(work: Callable[[], DataFrame], runs: int = 5) -> dict:
    """Mean, least and largest seconds of ``runs`` runs, and the rows of the answer.  Inputs should be
    stored or cached before; loading is not part of the measure."""
    took, rows = [], 0
    for _ in range(runs):
        began = time.perf_counter()
        rows = work().count()
        took.append(time.perf_counter() - began)
    return {"runs": runs, "mean_s": sum(took) / runs, "min_s": min(took), "max_s": max(took), "rows": rows}


def ratio(a: dict, b: dict) -> float:
    return a["mean_s"] / b["mean_s"]


def grammar_growth(grammars: dict[str, Grammar], spark: SparkSession) -> DataFrame:
    """Sizes of a grammar, of its machine, and of its binary normal form."""
    rows = []
    for name, g in grammars.items():
        rows.append((name, *_sizes(g)))
    return spark.createDataFrame(rows, GROWTH)


GROWTH = "grammar string, grammar_size int, boxes int, states int, transitions int, normal_rules int, normal_size int"


def bound_growth(pairs: DataFrame, grammars: dict[str, str]) -> DataFrame:
    """The same sizes of grammars over x and y, bound to the label pairs (x, y) of a relation, with the number n of its rows that
    give these sizes.  Grammars are built in tasks, once for each pair in a batch."""
    def run(frames):
        for f in frames:
            for (x, y), n in f.groupby(["x", "y"]).size().items():
                put = lambda m, x=x, y=y: x if m.group(1) == "x" else y
                rows = [(name, *_sizes(gr.parse(re.sub(r"\b([xy])\b", put, text)))) for name, text in grammars.items()]
                yield pd.DataFrame([(*r, int(n)) for r in rows], columns=[*names, "n"])

    names = [c.split()[0] for c in GROWTH.split(", ")]
    return pairs.select("x", "y").mapInPandas(run, GROWTH + ", n long").groupBy(*names).agg(F.sum("n").alias("n"))


def _sizes(g: Grammar) -> tuple[int, ...]:
    m, nf = rsm.from_grammar(g), g.to_binary_normal_form()
    return g.size(), len(m.boxes), m.size(), len(m.edges), len(nf.pairs) + len(nf.units), nf.size()


def path_counts(paths: DataFrame) -> DataFrame:
    """Walks of each pair."""
    return paths.groupBy("src", "dst").agg(F.count("*").alias("n"))


def paths_per_pair(paths: DataFrame) -> DataFrame:
    """Pairs, walks, mean and most walks of a pair."""
    return path_counts(paths).agg(F.count("*").alias("pairs"), F.sum("n").alias("walks"), F.avg("n").alias("mean_walks"), F.max("n").alias("most_walks"))


def trace(metrics: list[dict], spark: SparkSession) -> DataFrame:
    """Work of each round."""
    names = sorted({k for m in metrics for k in m} - {"round"})
    return spark.createDataFrame([(m["round"], *(int(m.get(k, 0)) for k in names)) for m in metrics], "round int, " + ", ".join(f"{k} long" for k in names))


def diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of two answers (src, dst) that only one has."""
    left, right = a.select("src", "dst").distinct().withColumn("in_a", F.lit(1)), b.select("src", "dst").distinct().withColumn("in_b", F.lit(1))
    return left.join(right, ["src", "dst"], "full_outer").where("in_a is null or in_b is null").select("src", "dst", F.coalesce("in_a", F.lit(0)).alias("in_a"), F.coalesce("in_b", F.lit(0)).alias("in_b"))


def answer_rollup(answers: DataFrame) -> DataFrame:
    """Answers by kind of both ends, with subtotals."""
    kinds = answers.select((F.col("src") % 16).cast("int").alias("kind_src"), (F.col("dst") % 16).cast("int").alias("kind_dst"))
    return kinds.cube("kind_src", "kind_dst").agg(F.count("*").alias("n"))


def estimate_pairs(build: Callable[[DataFrame], DataFrame], vertices: DataFrame, share: int = 64) -> int:
    """Expected number of answer pairs: the answer for a hashed 1/share of the sources, scaled."""
    some = vertices.where(F.pmod(F.xxhash64("id"), F.lit(share)) == 0)
    return build(some).count() * share
