"""Readers and writers of tables, edge lists, partitionings and run logs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

FORMATS = ("parquet", "orc", "json", "csv")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t") -> DataFrame:
    """(a, b) of a public edge-list text: one pair a line, lines after # are comments."""
    return spark.read.csv(path, sep=sep, comment="#", schema="a long, b long", mode="DROPMALFORMED")


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet") -> None:
    if fmt not in FORMATS:
        raise ValueError(f"format {fmt!r} is none of {FORMATS}")
    edges.write.mode("overwrite").format(fmt).save(path)


def read_edges(spark: SparkSession, path: str, schema: str, fmt: str = "parquet") -> DataFrame:
    return spark.read.format(fmt).schema(schema).load(path)


def save_partitioning(assigned: DataFrame, path: str) -> None:
    """One folder for each part, so that a worker reads its own part alone."""
    assigned.repartition("part").write.mode("overwrite").partitionBy("part").parquet(path)


def save_bucketed(assigned: DataFrame, table: str, k: int) -> None:
    """A table bucketed by part: joins and groups by part then need no exchange of the edges."""
    assigned.write.mode("overwrite").bucketBy(k, "part").sortBy("part").saveAsTable(table)


def load_partitioning(spark: SparkSession, path: str, parts: list[int] | None = None) -> DataFrame:
    """A saved partitioning, or some of its parts (the other folders are not read)."""
    edges = spark.read.parquet(path)
    return edges.where(F.col("part").isin(parts)) if parts is not None else edges


def append_runs(runs: DataFrame, path: str) -> None:
    runs.write.mode("append").parquet(path)
