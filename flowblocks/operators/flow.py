"""Analyst queries over cells and blocks."""
from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def outflow(cells: DataFrame, regions: list[int], t_lo: int, t_hi: int) -> DataFrame:
    """Flow from a set of regions to each region outside it in a run of slots."""
    return cells.where(F.col("o").isin(regions) & ~F.col("d").isin(regions) & F.col("t").between(t_lo, t_hi)).groupBy("d").agg(F.sum("flow").alias("flow"))


def inflow(cells: DataFrame, regions: list[int], t_lo: int, t_hi: int) -> DataFrame:
    return cells.where(F.col("d").isin(regions) & ~F.col("o").isin(regions) & F.col("t").between(t_lo, t_hi)).groupBy("o").agg(F.sum("flow").alias("flow"))


def block_flow(blocks: DataFrame, cells: DataFrame) -> DataFrame:
    """Blocks with the total flow of their cells."""
    key = ["o", "d", "t_lo", "t_hi"]
    atoms = blocks.select(*key).withColumn("co", F.explode("o")).withColumn("cd", F.explode("d")).withColumn("ct", F.explode(F.sequence("t_lo", "t_hi")))
    flows = cells.select(F.col("o").alias("co"), F.col("d").alias("cd"), F.col("t").alias("ct"), "flow")
    total = atoms.join(flows, ["co", "cd", "ct"]).groupBy(*key).agg(F.sum("flow").alias("flow"))
    return blocks.join(total, key, "left").withColumn("flow", F.coalesce("flow", F.lit(0))).select(*blocks.columns, "flow")


def popular(blocks: DataFrame, top: int) -> DataFrame:
    """The blocks with most hot cells, then most flow."""
    return blocks.orderBy(F.desc("cnt"), F.desc("flow"), "o", "d", "t_lo", "t_hi").limit(top)


def cube(cells: DataFrame) -> DataFrame:
    return cells.cube("o", "d", "t").agg(F.sum("flow").alias("flow"), F.grouping_id().cast("int").alias("gid"))


def rollup(cells: DataFrame) -> DataFrame:
    return cells.rollup("o", "d", "t").agg(F.sum("flow").alias("flow"), F.grouping_id().cast("int").alias("gid"))
