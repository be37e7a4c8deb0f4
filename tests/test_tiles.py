import glob
import os

from langpath.graph import LabeledGraph
from langpath.operators import kron


def _fan(spark, n, a, b, labels="x"):
    e = spark.range(n).selectExpr(f"id * {a} src", f"'{labels}' label", f"id * {b} + 1 dst")
    return LabeledGraph(e, e.selectExpr("src id"))


def test_product_is_written_in_few_bits(spark, tmp_path):
    g, h = _fan(spark, 1500, 7919, 104729), _fan(spark, 1300, 6101, 15485863)
    got = kron.graphs(g, h)
    got.write.parquet(out := str(tmp_path / "out"))
    size = sum(os.path.getsize(p) for p in glob.glob(f"{out}/*.parquet"))
    back = spark.read.parquet(out)
    assert back.count() == back.distinct().count() == 1500 * 1300
    # row by row a side costs its width in bits for each row
    assert size < 1500 * 1300


def test_product_keeps_labels_apart_and_repeated_edges(spark):
    g = LabeledGraph(spark.createDataFrame([(1, "x", 2), (1, "x", 2), (3, "y", 4), (5, None, 6)], "src long, label string, dst long"), spark.range(1))
    h = LabeledGraph(spark.createDataFrame([(7, "x", 8), (9, "z", 9), (5, None, 6)], "src long, label string, dst long"), spark.range(1))
    assert [tuple(r) for r in kron.graphs(g, h).collect()] == [(1, 7, "x", 2, 8)] * 2
    assert kron.graphs(g, LabeledGraph(h.edges.where("false"), h.vertices)).collect() == []
