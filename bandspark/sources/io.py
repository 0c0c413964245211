"""Reading and writing edges and orderings: Parquet, ORC, CSV, JSON lines, coordinate text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGES = T.StructType([T.StructField("a", T.LongType()), T.StructField("b", T.LongType())])


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """(a, b) pairs; the schema is given, not inferred. ``coordinate``: see read_coordinates."""
    if fmt == "coordinate":
        return read_coordinates(spark, path)
    reader = spark.read.schema(EDGES)
    return reader.option("header", "true").csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def write_edges(pairs: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists") -> None:
    writer = pairs.select("a", "b").write.mode(mode)
    writer.option("header", "true").csv(path) if fmt == "csv" else writer.format(fmt).save(path)


def read_coordinates(spark: SparkSession, path: str) -> DataFrame:
    """Coordinate text: comment lines of %, a line of sizes, then 1-based ``row col [value]`` of one triangle; gives 0-based pairs."""
    lines = spark.read.text(path).select(F.trim("value").alias("v")).where("v <> '' and not startswith(v, '%')")
    cells = lines.select(F.split("v", r"\s+").alias("c"))
    sizes = F.size("c") == 3
    entry = cells.select(F.get("c", F.lit(0)).cast("long").alias("r"), F.get("c", F.lit(1)).cast("long").alias("s"), F.get("c", F.lit(2)).alias("x"), sizes.alias("three"))
    head = spark.read.text(path).where("not startswith(value, '%')").limit(1).select(F.split(F.trim("value"), r"\s+").alias("c")).first()
    if head is None:
        return spark.createDataFrame([], EDGES)
    n, _, m = (int(x) for x in head["c"][:3])
    kept = entry.where(~((F.col("r") == n) & F.col("three") & (F.col("s") == n) & (F.col("x") == str(m))))
    return kept.select((F.col("r") - 1).alias("a"), (F.col("s") - 1).alias("b"))


def write_ordering(labels: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """(v, label), clustered by label."""
    labels.select("v", "label").repartitionByRange("label").sortWithinPartitions("label").write.mode(mode).parquet(path)
