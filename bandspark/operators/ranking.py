"""Ranks of rows in a total order: the sort primitive, by several strategies with one result.

bucket  rows go to buckets of a range of the leading key (parent labels), are ranked inside them, and the sizes of the buckets
        before are added. No sampling: the key's range is known. A bucket of more than ``most_rows`` rows (one hub's children) is split by
        sampled ranges of the whole key; whether there is one is only looked at if there are that many rows at all.
general ranges of the whole key are sampled (repartitionByRange).
single  one window; for small inputs.
Bucket and range sizes are one row each; they are joined, not collected.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from bandspark.session import materialize

STRATEGIES = ("bucket", "general", "single")
#: Rows that one part ranks in a window.
MOST_ROWS = 1_000_000


def _offsets(parts: DataFrame) -> DataFrame:
    """(_part, _before) from rows with _part: one row for each part."""
    sizes = parts.groupBy("_part").agg(F.count("*").alias("_n"))
    upto = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    return sizes.select("_part", F.coalesce(F.sum("_n").over(upto), F.lit(0)).alias("_before"))


def _ranked(rows: DataFrame, keys: list[str]) -> DataFrame:
    inside = F.row_number().over(Window.partitionBy("_part").orderBy(*keys)) - 1
    return rows.withColumn("_in", inside).join(_offsets(rows), "_part").withColumn("rank", (F.col("_before") + F.col("_in")).cast("long")).drop("_part", "_in", "_before")


def _split_crowded(rows: DataFrame, keys: list[str], most_rows: int) -> DataFrame:
    """Rows with ``_part``: buckets of more than ``most_rows`` rows become several parts, in the order of ``keys``."""
    sizes = rows.groupBy("_part").agg(F.count("*").alias("_n")).where(F.col("_n") > most_rows)
    crowded = materialize(sizes, "rank-crowded")
    n = crowded.agg(F.sum(F.ceil(F.col("_n") / most_rows))).first()[0]
    if not n:
        return rows.withColumn("_part", F.struct("_part", F.lit(0).alias("_sub")))
    marked = rows.join(F.broadcast(crowded.select("_part", F.lit(True).alias("_many"))), "_part", "left")  # at most rows / most_rows buckets
    split = materialize(marked.where("_many").drop("_many").repartitionByRange(2 * int(n), "_part", *keys).withColumn("_sub", F.spark_partition_id()), "rank-split")
    every = marked.where("_many is null").drop("_many").withColumn("_sub", F.lit(0)).unionByName(split)
    return every.withColumn("_part", F.struct("_part", "_sub")).drop("_sub")


def sort_rank(rows: DataFrame, keys: list[str], strategy: str = "bucket", base: int = 0, span: int | None = None, buckets: int | None = None, most_rows: int = MOST_ROWS, count: int | None = None) -> DataFrame:
    """Adds ``rank``, from 0, in the order of ``keys`` (which must tell all rows apart).

    bucket: the first key is a whole number from ``base`` to below ``base + span`` (looked up if no span is given); ``count``: how many rows there are, if that is known."""
    if strategy not in STRATEGIES:
        raise ValueError(f"strategy is one of {STRATEGIES}")
    if strategy == "single":
        return rows.withColumn("rank", (F.row_number().over(Window.orderBy(*keys)) - 1).cast("long"))
    n = buckets or int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if strategy == "general":
        parts = rows.repartitionByRange(n, *keys).withColumn("_part", F.spark_partition_id())
        return _ranked(materialize(parts, "rank-parts"), keys)
    if span is None:
        top = rows.agg(F.min(keys[0]).alias("lo"), F.max(keys[0]).alias("hi")).first()
        base, span = (top["lo"] or 0), (top["hi"] or 0) - (top["lo"] or 0) + 1
    part = F.floor((F.col(keys[0]) - base).cast("double") * n / max(1, span)).cast("long")
    dealt = rows.withColumn("_part", part)
    if (rows.count() if count is None else count) > most_rows:
        dealt = _split_crowded(dealt, keys, most_rows)
    return _ranked(dealt, keys)
