"""Exact dedup by an extendible-hash index on shared files (DataFrame functions only).

1. *directory*: distinct hashes are counted by their leading bits, one cell for each value of these. A
   bucket starts as the whole table; an overfull one is split by one more bit, and where it already used
   all bits of the directory, the directory doubles. The directory is one byte a cell, the depth of the
   cell's bucket: at most 2**max_bits bytes, however large the table.
2. *entries*: copies of a text are merged where they lie and once more in salted groups, so that the
   copies of one text, however many, reach its owner as ``salts`` rows at most.
3. *index files*: owner tasks hold ranges of buckets. An owner lays the entries of a bucket in order of
   hash and text; entries of one hash form a chain, a new link wherever the bytes differ from those of
   the entry before. A link adds up its entries: the id that stays, and the size.
4. *probe*: each row goes to its bucket by the directory, to the chain of its hash there, and to the link
   with its SHA-256. Two links of one chain with the same SHA-256 would stop the run.
"""

from __future__ import annotations

import itertools
import math
import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder under spark.checkpoint.dir, which all executors see."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = "file:///tmp/checkpoints"
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def normalised(text: Column) -> Column:
    """Each run of space, tab, line feed, vertical tab, form feed or carriage return as one space; null as empty."""
    return F.regexp_replace(F.coalesce(text.cast("string"), F.lit("")), r"[\x20\x09-\x0D]+", " ")


def directory(cells: list[int], capacity: int) -> bytes:
    """The depth of the bucket of each of 2**k hash cells, from the number of entries in each.

    Starts from one bucket and doubles the directory as long as some bucket that can still be split
    holds more than capacity entries.
    """
    top = len(cells).bit_length() - 1
    before = [0, *itertools.accumulate(cells)]
    local, full = {0: 0}, [0]  # first cell of a bucket -> its depth
    while full:
        again = []
        for a in full:
            d = local[a]
            if d < top and before[a + (1 << (top - d))] - before[a] > capacity:
                half = 1 << (top - d - 1)
                local[a] = local[a + half] = d + 1
                again += [a, a + half]
        full = again
    return b"".join(bytes([d]) * (1 << (top - d)) for _, d in sorted(local.items()))


def bucket_of(hash_: Column, depths: bytes) -> Column:
    """The bucket of a hash: the first cell that its leading bits share with no other bucket."""
    top = len(depths).bit_length() - 1
    if not top:
        return F.lit(0)
    cell = F.shiftrightunsigned(hash_, 64 - top).cast("int")
    # the directory as one character a cell, from 'A' for depth 0: read in place, without a join
    table = F.lit(bytearray(65 + d for d in depths))
    rest = F.lit(top + 65) - F.ascii(F.substring(table, cell + 1, F.lit(1)).cast("string"))
    return F.call_function("shiftleft", F.call_function("shiftright", cell, rest), rest)


def _hashed(docs: DataFrame, carry: tuple[str, ...] = ()) -> DataFrame:
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), normalised(F.col("text")).alias("normalised_"), *(F.col(c).alias(f"__{c}") for c in carry))
    return rows.withColumn("hash", F.xxhash64("normalised_"))


def fit_directory(docs: DataFrame, capacity: int, max_bits: int) -> bytes:
    """directory() of the distinct hashes of docs."""
    spark = docs.sparkSession
    folder = shared_folder(spark, "exact-hashes")
    _hashed(docs).select("hash").distinct().write.parquet(folder)
    hashes = spark.read.schema("hash long").parquet(folder)
    n = hashes.count()
    top = min(max_bits, max(0, math.ceil(math.log2(max(1, n) / capacity)) + 2))
    cells = [0] * (1 << top)
    cell = F.shiftrightunsigned("hash", 64 - top).cast("int") if top else F.lit(0)
    for r in hashes.groupBy(cell.alias("cell")).count().collect():  # 2**max_bits rows at most
        cells[r["cell"]] = r["count"]
    return directory(cells, capacity)


def build_index(docs: DataFrame, folder: str, depths: bytes, salts: int = 16) -> DataFrame:
    """Writes the index of docs (doc_id, text) below folder and returns it: bucket, hash, chain,
    text_sha256, keep_id, group_size."""
    salt = F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(salts)).alias("salt")
    entries = _hashed(docs).groupBy("hash", F.col("normalised_").alias("text"), salt).agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("n"))
    owners = min(len(_buckets(depths)), 1 << 17)
    bucket = bucket_of(F.col("hash"), depths)
    owner = F.floor(bucket.cast("double") * owners / len(depths)).cast("int")
    dealt = entries.select(owner.alias("owner"), bucket.alias("bucket"), "hash", "text", "least", "n").repartition(owners, "owner")
    mine = Window.partitionBy("owner", "bucket", "hash")
    new = F.coalesce(F.lag("text").over(mine.orderBy("text")) != F.col("text"), F.lit(True))
    linked = dealt.withColumn("new", new.cast("int")).withColumn("chain", F.sum("new").over(mine.orderBy("text").rowsBetween(Window.unboundedPreceding, 0)).cast("int"))
    links = linked.groupBy("owner", "bucket", "hash", "chain").agg(F.max(F.when(F.col("new") == 1, F.sha2("text", 256))).alias("text_sha256"), F.min("least").alias("keep_id"), F.sum("n").alias("group_size"))
    again = F.lag("text_sha256").over(mine.orderBy("text_sha256")) == F.col("text_sha256")
    index = links.withColumn("chain", F.when(again, F.raise_error(F.lit("two texts of one SHA-256"))).otherwise(F.col("chain")).cast("int"))
    index.sortWithinPartitions("bucket", "hash", "chain").select("bucket", "hash", "chain", "text_sha256", "keep_id", "group_size").write.parquet(f"{folder}/index")
    return docs.sparkSession.read.parquet(f"{folder}/index")


def _buckets(depths: bytes) -> list[int]:
    """The depths of the buckets, one each, in order."""
    top, at, out = len(depths).bit_length() - 1, 0, []
    while at < len(depths):
        out.append(depths[at])
        at += 1 << (top - depths[at])
    return out


def exact_groups(docs: DataFrame, capacity: int = 8192, max_bits: int = 22, carry: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256) for every row of docs (doc_id, text).

    Texts are equal when identical after normalised(); a null text is empty, and all empty texts are
    equal. Of equal texts the row of the smallest doc_id stays; repeated rows of that id all count as
    kept, for nothing tells them apart. Rows without a doc_id never stay beside one that has an id; if
    a group has no id at all, all of it stays (keep_id null). carry: columns of docs to return as well.
    An empty table gives no rows.
    """
    depths = fit_directory(docs, capacity, max_bits)
    index = build_index(docs, shared_folder(docs.sparkSession, "exact-index"), depths)
    probe = _hashed(docs, carry).withColumn("text_sha256", F.sha2("normalised_", 256)).drop("normalised_").withColumn("bucket", bucket_of(F.col("hash"), depths))
    found = probe.join(index.drop("chain"), ["bucket", "hash", "text_sha256"])
    return found.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256", *(F.col(f"__{c}").alias(c) for c in carry))
