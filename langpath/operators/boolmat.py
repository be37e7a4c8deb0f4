"""Boolean matrices as coordinate relations (src, dst)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def mxm(a: DataFrame, b: DataFrame) -> DataFrame:
    """Product: join on the middle, then distinct."""
    return a.select("src", F.col("dst").alias("mid")).join(b.select(F.col("src").alias("mid"), "dst"), "mid").select("src", "dst").distinct()


def add(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("src", "dst").union(b.select("src", "dst")).distinct()


def minus(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("src", "dst").join(b.select("src", "dst"), ["src", "dst"], "left_anti")


def vxm(v: DataFrame, a: DataFrame) -> DataFrame:
    """Row vector (id) times matrix: the successors, distinct."""
    return v.select(F.col("id").alias("src")).join(a.select("src", "dst"), "src").select(F.col("dst").alias("id")).distinct()
