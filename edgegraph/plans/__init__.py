"""Cutting lineage in loops: tables written to the folder that all executors share."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


class Scratch:
    """A folder below spark.checkpoint.dir for the tables of one loop."""

    def __init__(self, spark: SparkSession, name: str) -> None:
        base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
        if not base:
            if not spark.sparkContext.master.startswith("local["):
                raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
            base = "file:///tmp/checkpoints"
        self.spark, self.path, self.count = spark, f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}", 0
        self.held: dict[str, str] = {}

    def store(self, frame: DataFrame, name: str | None = None) -> DataFrame:
        """frame, written and read back. A named table replaces the one of that name before the last."""
        self.count += 1
        path = f"{self.path}/{self.count}"
        frame.write.parquet(path)
        if name is not None:
            self._replace(name, path)
        return self.spark.read.schema(frame.schema).parquet(path)

    def table(self, frame: DataFrame, key: str, buckets: int, name: str | None = None) -> DataFrame:
        """frame, written in buckets of key: reads of it need no exchange to be grouped by that key. A named
        one replaces the one of that name before the last. The catalog holds the table while it is opened only."""
        self.count += 1
        path, known = f"{self.path}/{self.count}", f"scratch_{uuid.uuid4().hex}"
        frame.write.bucketBy(buckets, key).option("path", path).format("parquet").saveAsTable(known)
        out = self.spark.table(known)
        self.spark.sql(f"drop table {known}")  # its files stay
        if name is not None:
            self._replace(name, path)
        return out

    def _replace(self, name: str, path: str) -> None:
        older = self.held.pop(f"{name}-older", None)
        if older:
            self._remove(older)
        if name in self.held:
            self.held[f"{name}-older"] = self.held[name]
        self.held[name] = path

    def _remove(self, path: str) -> None:
        jvm = self.spark.sparkContext._jvm
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
