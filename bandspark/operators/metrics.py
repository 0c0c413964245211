"""Quality of an ordering: bandwidths of rows, bandwidth, profile, envelope, block density."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def permute(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """The matrix in the new order: (i, j) and val if there is one."""
    a = labels.select(F.col("v").alias("src"), F.col("label").alias("i"))
    b = labels.select(F.col("v").alias("dst"), F.col("label").alias("j"))
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    return edges.join(a, "src").join(b, "dst").select("i", "j", *rest)


def row_bandwidths(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(i, beta) for every row: i less the smaller of i and its least neighbour."""
    low = permute(edges, labels).groupBy("i").agg(F.min("j").alias("low"))
    return labels.select(F.col("label").alias("i")).join(low, "i", "left").select("i", (F.col("i") - F.least("i", F.coalesce("low", "i"))).alias("beta"))


def quality(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: n, bandwidth, profile."""
    b = row_bandwidths(edges, labels)
    return b.agg(F.count("*").alias("n"), F.coalesce(F.max("beta"), F.lit(0)).cast("long").alias("bandwidth"), F.coalesce(F.sum(F.col("beta").cast("decimal(38,0)")), F.lit(0)).cast("decimal(38,0)").alias("profile"))


def envelope_pairs(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(i, j) with 0 < i - j <= beta(i); for small matrices."""
    return row_bandwidths(edges, labels).where("beta > 0").select("i", F.explode(F.sequence(F.col("i") - F.col("beta"), F.col("i") - 1)).alias("j"))


def envelope_printed(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: the count under the other reading of the definition, pairs to the right of each row."""
    n = labels.count()
    return row_bandwidths(edges, labels).agg(F.coalesce(F.sum(F.least(F.col("beta"), F.lit(n - 1) - F.col("i"))), F.lit(0)).cast("long").alias("pairs"))


def in_envelope(edges: DataFrame, labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs (i, j) with ``inside``: whether 0 < i - j <= beta(i)."""
    beta = row_bandwidths(edges, labels)
    gap = F.col("i") - F.col("j")
    return pairs.join(beta, "i", "left").select("i", "j", ((gap > 0) & (gap <= F.coalesce("beta", F.lit(0)))).alias("inside"))


def spy(edges: DataFrame, labels: DataFrame, blocks: int, n: int) -> DataFrame:
    """(bi, bj, nnz): entries of each of blocks x blocks tiles."""
    p = permute(edges, labels)
    return p.groupBy(F.floor(F.col("i") * blocks / n).alias("bi"), F.floor(F.col("j") * blocks / n).alias("bj")).agg(F.count("*").alias("nnz"))


def compare(before: DataFrame, after: DataFrame) -> DataFrame:
    """One row of two qualities: the reduction factors; a factor near 1 is an ordering without effect."""
    b = before.select(F.col("bandwidth").alias("bw_before"), F.col("profile").alias("profile_before"))
    a = after.select("n", F.col("bandwidth").alias("bw_after"), F.col("profile").alias("profile_after"))
    both = a.crossJoin(b)  # one row each
    return both.withColumn("reduction", F.col("bw_before") / F.greatest(F.col("bw_after"), F.lit(1)))
