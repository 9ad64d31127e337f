"""Edge lists, trips and blocks in files; schemas are fixed, nothing is inferred."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGES = "u int, v int"
TRIPS = "o int, d int, ts timestamp_ntz, pax bigint"
BLOCKS = "level int, o array<int>, d array<int>, t_lo int, t_hi int, cnt bigint, card bigint"


def read(spark: SparkSession, path: str, schema: str, fmt: str = "parquet") -> DataFrame:
    """Rows of a Parquet, CSV (with a header) or JSON file; a malformed line is an error."""
    reader = spark.read.schema(schema).option("mode", "FAILFAST")
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def stream(spark: SparkSession, path: str, schema, per_trigger: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(schema)
    return (reader if per_trigger is None else reader.option("maxFilesPerTrigger", per_trigger)).parquet(path)


def write_blocks(blocks: DataFrame, path: str, fmt: str = "parquet") -> None:
    """One folder for each level; CSV holds the sides as comma strings."""
    if fmt == "csv":
        text = lambda c: F.array_join(F.transform(c, lambda x: x.cast("string")), ",").alias(c)
        blocks = blocks.select(*[text(c) if c in ("o", "d") else c for c in blocks.columns])
    writer = blocks.write.partitionBy("level").format(fmt)
    (writer.option("header", True) if fmt == "csv" else writer).save(path)


def read_blocks(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(BLOCKS).parquet(path).select("level", "o", "d", "t_lo", "t_hi", "cnt", "card")
