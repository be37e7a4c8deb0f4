"""Readers and writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import LabeledGraph
from ..language import grammar as gr


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", sep: str = ",") -> LabeledGraph:
    """Edge list: ``csv`` (src, label, dst with numbers), or ``ntriples`` (text; vertices are named by a 64-bit
    hash of their term, labels by the last part of the predicate)."""
    if fmt == "csv":
        e = spark.read.schema("src long, label string, dst long").csv(path, sep=sep)
    elif fmt == "ntriples":
        row = spark.read.text(path).where(~F.col("value").rlike(r"^\s*(#|$)"))
        part = lambda k: F.regexp_extract("value", r"^\s*(\S+)\s+(\S+)\s+(.*\S)\s*\.\s*$", k)
        e = row.select(F.xxhash64(part(1)).alias("src"), F.regexp_extract(part(2), r"([^/#>]+)>?$", 1).alias("label"), F.xxhash64(part(3)).alias("dst"))
    elif fmt == "parquet":
        e = spark.read.parquet(path)
    else:
        raise ValueError(f"unknown format {fmt}")
    return LabeledGraph.of(e.where("src is not null and label is not null and dst is not null"))


def write_edges(graph: LabeledGraph, path: str, mode: str = "overwrite") -> None:
    """Edges by label: choosing labels later reads only their folders."""
    graph.edges.repartition("label", "src").write.mode(mode).partitionBy("label").parquet(path)


def write_paths(paths: DataFrame, path: str, mode: str = "overwrite") -> None:
    paths.write.mode(mode).json(path)


def read_grammar(path: str, start: str | None = None) -> gr.Grammar:
    with open(path, encoding="utf-8") as f:
        return gr.parse(f.read(), start)
