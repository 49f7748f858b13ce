"""Connected components of a table of links, by label steps and shortcuts on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .exact import shared_folder


def store(frame: DataFrame, folder: str) -> DataFrame:
    """Written to a shared folder and read back: cuts the lineage for good."""
    frame.write.mode("overwrite").parquet(folder)
    return frame.sparkSession.read.schema(frame.schema).parquet(folder)


def components(links: DataFrame, most_rounds: int = 200) -> DataFrame:
    """(node, label) with the smallest node of its component, for each end of a link (a, b).

    A round takes the smallest label among a node and its neighbours, then the label of that label.
    """
    spark = links.sparkSession
    folder = shared_folder(spark, "components")
    ends = links.where("a != b").select(F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")), F.struct("a", F.col("a").alias("b")), F.struct(F.col("b").alias("a"), "b"))).alias("e"))
    both = store(ends.select("e.a", "e.b").distinct(), f"{folder}/links")  # each node beside itself, too
    labels = store(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("label")), f"{folder}/0")
    for i in range(1, most_rounds):
        step = both.join(labels.select(F.col("node").alias("b"), "label"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("label"), F.max("label").alias("most"))
        after = store(_jump(step.select("node", "label", "most"), labels), f"{folder}/{i}")
        # settled where all neighbours bear one label, and that is its own label
        open_ = after.where("label != most or label != near").limit(1).count()
        labels = after.select("node", "label")
        if not open_:
            return labels
    raise RuntimeError("components did not settle")


def _jump(step: DataFrame, labels: DataFrame) -> DataFrame:
    further = labels.select(F.col("node").alias("near"), F.col("label").alias("further"))
    return step.withColumnRenamed("label", "near").join(further, "near", "left").select("node", "near", "most", F.least("near", F.coalesce("further", "near")).alias("label"))


def roots(parents: DataFrame, most_rounds: int = 64) -> DataFrame:
    """(node, label) for each end of (a, b) where every b stands once and a < b: the last of its chain."""
    folder = shared_folder(parents.sparkSession, "roots")
    up = parents.select(F.col("b").alias("node"), F.col("a").alias("label"))
    tops = parents.select(F.col("a").alias("node")).distinct().join(up.select("node"), "node", "left_anti").withColumn("label", F.col("node"))
    labels = store(up.unionByName(tops), f"{folder}/0")
    for i in range(1, most_rounds):
        further = labels.select(F.col("node").alias("label"), F.col("label").alias("further"))
        after = store(labels.join(further, "label").select("node", "label", "further"), f"{folder}/{i}")
        moved = after.where("further != label").limit(1).count()
        labels = after.select("node", F.col("further").alias("label"))
        if not moved:
            return labels
    raise RuntimeError("chains did not end")
