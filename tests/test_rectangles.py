import glob
import os

from langpath.graph import LabeledGraph
from langpath.language import rsm
from langpath.operators import hubs, kron, twins

WIDE = 40_000


def _bytes_a_row(df, rows, out):
    df.write.parquet(str(out))
    back = df.sparkSession.read.parquet(str(out))
    assert back.count() == back.distinct().count() == rows
    return sum(os.path.getsize(p) for p in glob.glob(f"{out}/*.parquet")) / rows


def _ring(spark, n):
    e = spark.range(n).selectExpr("id * 7919 src", "'x' label", f"(id + 1) % {n} * 7919 dst")
    return LabeledGraph(e, e.selectExpr("src id"))


def test_pairs_joined_by_hubs_are_written_in_few_bits(spark, tmp_path):
    some = spark.range(64).selectExpr("id * 7919 id")
    got = hubs.answers(_ring(spark, WIDE), rsm.from_regex("x+"), some)
    assert _bytes_a_row(got, 64 * WIDE, tmp_path / "out") < 2


def test_pairs_of_twins_are_written_in_few_bits(spark, tmp_path):
    members = spark.range(64).selectExpr("id * 7919 id", "0L twin").union(spark.range(1000, 1000 + WIDE).selectExpr("id * 7919", "7919000L"))
    got = twins.expand(spark.createDataFrame([(0, 7919000)], "src long, dst long"), members)
    assert _bytes_a_row(got, 64 * WIDE, tmp_path / "out") < 2


def test_product_of_label_sets_is_written_in_few_bits(spark, tmp_path):
    g = LabeledGraph(spark.range(64).selectExpr("id * 7919 src", "'x' label", "id * 104729 dst"), spark.range(1))
    assert _bytes_a_row(kron.label_sets(g, _ring(spark, WIDE), sep=" "), 64 * WIDE, tmp_path / "out") < 4
