"""Connected components by label propagation with pointer jumping, all on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def components(edges: DataFrame) -> DataFrame:
    """(v, root) for every vertex of ``edges`` (x long, y long); root is the component's
    smallest vertex.  Each round ends in a table in the shared folder, so a lost executor
    replays one round at most; rounds grow with the logarithm of a component's diameter."""
    both = common.cut(edges.where("x <> y").select("x", "y").union(edges.where("x <> y").select(F.col("y").alias("x"), F.col("x").alias("y"))).distinct(), "cc-edges")
    label = common.cut(both.groupBy(F.col("x").alias("v")).agg(F.min("y").alias("m")).select("v", F.least("v", "m").alias("root")), "cc-label")
    while True:
        near = both.join(label.select(F.col("v").alias("y"), "root"), "y").groupBy(F.col("x").alias("v")).agg(F.min("root").alias("near"))
        step = label.join(near, "v").select("v", F.least("root", "near").alias("hop"), "root")
        jump = label.select(F.col("v").alias("hop"), F.col("root").alias("far"))
        new = common.cut(step.join(jump, "hop").select("v", F.least("hop", "far").alias("root"), F.col("root").alias("was")), "cc-label")
        changed = new.where("root <> was").limit(1).count()
        common.drop_cut(label)
        label = new.select("v", "root")
        label.shared_path = new.shared_path
        if not changed:
            common.drop_cut(both)
            return label
