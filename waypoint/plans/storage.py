"""Levels of a search as written tables, which cuts lineage and survives lost executors."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only where that is unset (tests on one machine)."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        folder = tempfile.mkdtemp(prefix="waypoint-")
        spark.conf.set("spark.checkpoint.dir", folder)
    return folder.rstrip("/")


def counted(df: DataFrame, name: str) -> tuple[DataFrame, int]:
    """``df`` written as Parquet and read back, and its number of rows, from the same job."""
    spark, seen = df.sparkSession, Observation()
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.observe(seen, F.count(F.lit(1)).alias("n")).write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), int(seen.get["n"])


def written(df: DataFrame, name: str) -> DataFrame:
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


class Buckets:
    """A table that grows by appended parts, bucketed by ``keys`` where ``n`` buckets are asked for, so joins on the keys do not shuffle it."""

    def __init__(self, spark: SparkSession, name: str, keys: list[str], n: int):
        self.spark, self.keys, self.n = spark, keys, n
        self.name, self.path = f"{name}_{uuid.uuid4().hex}", f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
        self.parts: list[DataFrame] = []

    def add(self, df: DataFrame) -> tuple[DataFrame, int]:
        """Append a part; the part as read back, and its rows."""
        if not self.n:
            part, rows = counted(df, self.name.rpartition("_")[0])
            if rows:
                self.parts.append(part)
            return part, rows
        seen, path = Observation(), f"{self.path}/{uuid.uuid4().hex}"
        name = f"{self.name}_{len(self.parts)}"
        df.observe(seen, F.count(F.lit(1)).alias("n")).write.bucketBy(self.n, *self.keys).sortBy(*self.keys).option("path", path).format("parquet").saveAsTable(name)
        part, rows = self.spark.table(name), int(seen.get["n"])
        if rows:
            self.parts.append(part)
        return part, rows

    def all(self, columns: list[str] | None = None) -> DataFrame:
        parts = [p.select(*columns) if columns else p for p in self.parts]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out
