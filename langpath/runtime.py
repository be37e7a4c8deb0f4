"""Fixpoint runtime: staged relations and size checks.

Rounds of a fixpoint are ordinary DataFrame plans.  Between rounds a relation is written to the
shared folder and read again, so plans stay small, sizes are known to the optimizer, and a lost executor
costs one round at most."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

#: A relation below this many rows may be solved inside one task or broadcast.
LOCAL_ROWS = 200_000


def shared_root(spark: SparkSession) -> str:
    """Folder of ``spark.checkpoint.dir``; where that is unset (tests), an own temporary one."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = getattr(shared_root, "own", None) or f"file://{tempfile.mkdtemp(prefix='langpath-')}"
        shared_root.own = root
    return root.rstrip("/")


def local_table(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """A few driver rows as a local relation: scanning or broadcasting it starts no job."""
    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    kind = StructType.fromDDL(schema)
    fields = to_arrow_schema(kind)
    cols = list(zip(*rows, strict=True)) or [()] * len(fields)
    table = pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(cols, fields, strict=True)], schema=fields)
    return spark.createDataFrame(table, kind)


class Stage:
    """Staged relations of one run; :meth:`close` deletes those that nothing reads any more."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.root = f"{shared_root(spark)}/fixpoint-{uuid.uuid4().hex}"
        self.k = 0
        self.rows: dict[int, int] = {}

    def put(self, df: DataFrame) -> tuple[DataFrame, int]:
        """Write a relation and count it in the same job."""
        out, seen = self.observed(df)
        return out, seen["n"]

    def observed(self, df: DataFrame, **measures: Column) -> tuple[DataFrame, dict[str, int]]:
        """The same with further counts of the rows written."""
        self.k += 1
        path = f"{self.root}/{self.k}"
        seen = Observation()
        df.observe(seen, F.count(F.lit(1)).alias("n"), *[m.alias(k) for k, m in measures.items()]).write.parquet(path)
        return self.spark.read.schema(df.schema).parquet(path), {k: int(v or 0) for k, v in seen.get.items()}

    def drop(self) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.root)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


class Grown:
    """A relation that grows by staged segments; reading it reads all of them, and after
    ``most`` segments they are written together."""

    def __init__(self, stage: Stage, first: DataFrame, most: int = 8):
        self.stage, self.most, self.df, self.parts = stage, most, first, 1

    def add(self, segment: DataFrame) -> None:
        self.df, self.parts = self.df.union(segment), self.parts + 1
        if self.parts >= self.most:
            (self.df, _), self.parts = self.stage.put(self.df), 1


def small(df: DataFrame, limit: int = LOCAL_ROWS) -> bool:
    """Whether a relation has at most ``limit`` rows; reads no more than needed to tell."""
    return df.limit(limit + 1).count() <= limit


def union_all(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out
