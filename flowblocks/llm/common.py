"""Helpers shared by the text operators."""
from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..durable import durable, shared_folder  # noqa: F401  durable is for the operators

#: log2 of the bits of a bitmap: 2 MB.
BITMAP = 24


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts(docs: DataFrame) -> DataFrame:
    """Only (doc_id, text): other columns, clashing names included, never reach an operator."""
    return docs.select("doc_id", "text")


class Scratch:
    """Named Parquet tables in the shared folder: they cut the lineage, the planner knows their sizes, and those that
    are superseded are deleted, so the disk holds only what later steps read."""

    def __init__(self, spark: SparkSession):
        self.spark, self.root = spark, f"{shared_folder(spark)}/scratch-{uuid.uuid4().hex}"

    def keep(self, name: str, df: DataFrame) -> DataFrame:
        df.write.parquet(f"{self.root}/{name}")
        return self.spark.read.schema(df.schema).parquet(f"{self.root}/{name}")

    def drop(self, *names: str) -> None:
        sc = self.spark.sparkContext
        for name in names:
            path = sc._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}")
            path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)
        sc._jvm.System.gc()  # shuffle files that no frame refers to any more go too


def _place(key: Column) -> Column:
    return F.call_function("shiftrightunsigned", key, F.lit(64 - BITMAP))


def bitmap(keys: DataFrame) -> DataFrame:
    """One row, bits: 2^BITMAP bits, one of them set for every hash in the only column of keys. Its size is fixed, so it may
    be broadcast; the more keys, the more others pass it too."""
    place = _place(F.col(keys.columns[0]))
    words = keys.groupBy(F.floor(place / 64).alias("id")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), (place % 64).cast("int"))).alias("b"))
    all_ = keys.sparkSession.range(1 << (BITMAP - 6)).join(words, "id", "left").select("id", F.coalesce("b", F.lit(0).cast("bigint")).alias("b"))
    return all_.agg(F.transform(F.array_sort(F.collect_list(F.struct("id", "b"))), lambda x: x["b"]).alias("bits"))


def marked(bits: Column, key: Column) -> Column:
    """Whether a hash may be among the keys."""
    place = _place(key)
    return F.call_function("shiftright", F.get(bits, F.floor(place / 64).cast("int")), (place % 64).cast("int")).bitwiseAND(F.lit(1).cast("bigint")) == 1


def components(edges: DataFrame) -> DataFrame:
    """(u, v) links -> (id, component): the smallest id reachable, for every id with a link.

    Each round takes the minimum label among neighbours (pre-aggregated before the shuffle), then jumps to the
    label's own label. Only a count of changed rows reaches the driver. Every round's labels are a table of their own,
    and the one before is deleted."""
    disk = Scratch(edges.sparkSession)
    both = disk.keep("both", edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))).where("u <> v").distinct())
    label = disk.keep("0", both.groupBy(F.col("u").alias("id")).agg(F.min("v").alias("v")).select("id", F.least("id", "v").alias("c")))
    turn = 0
    while True:
        near = both.join(label.select(F.col("id").alias("v"), F.col("c").alias("nc")), "v").groupBy(F.col("u").alias("id")).agg(F.min("nc").alias("nc"))
        step = label.join(near, "id", "left").select("id", F.col("c").alias("old"), F.least("c", "nc").alias("m"))
        jump = label.select(F.col("id").alias("m"), F.col("c").alias("jump"))
        turn += 1
        new = disk.keep(str(turn), step.join(jump, "m", "left").select("id", "old", F.least("m", "jump").alias("c")))
        disk.drop(str(turn - 1))
        if not new.where("c < old").limit(1).count():
            disk.drop("both")
            return new.select("id", F.col("c").alias("component"))
        label = new.select("id", "c")
