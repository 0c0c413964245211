"""Where matrix entries lie: random relabelling, one- and two-dimensional dealing, storage layouts, balance."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandspark.model import SymGraph
from bandspark.operators.metrics import permute
from bandspark.operators.ordering import random_order


def random_relabel(g: SymGraph, seed: int) -> tuple[SymGraph, DataFrame]:
    """The graph with seeded random ids 0 .. n - 1, and the map (v, label) from old ids."""
    labels = random_order(g, seed)
    a = labels.select(F.col("v").alias("src"), F.col("label").alias("a"))
    b = labels.select(F.col("v").alias("dst"), F.col("label").alias("b"))
    pairs = g.edges.join(a, "src").join(b, "dst").select("a", "b")
    return SymGraph.from_pairs(pairs, labels.select(F.col("label").alias("v"))), labels


def distribute_1d(edges: DataFrame, parts: int) -> DataFrame:
    """Entries dealt by source alone: a frontier goes nowhere, all partial results to their owners."""
    return edges.repartition(parts, "src")


def distribute_2d(edges: DataFrame, rows: int, cols: int) -> DataFrame:
    """Entries dealt to a grid of blocks (br, bc): a frontier goes down one block column, partial results across one block row."""
    return edges.withColumn("br", F.pmod(F.xxhash64("dst"), F.lit(rows))).withColumn("bc", F.pmod(F.xxhash64("src"), F.lit(cols))).repartition(rows * cols, "br", "bc")


def blocks_of_range(edges: DataFrame, labels: DataFrame, rows: int, cols: int, n: int) -> DataFrame:
    """Entries dealt to blocks of consecutive positions, as a matrix is cut; (i, j, br, bc)."""
    return permute(edges, labels).withColumn("br", F.floor(F.col("j") * rows / n)).withColumn("bc", F.floor(F.col("i") * cols / n))


def spmspv_2d(blocked: DataFrame, x: DataFrame, cols: int | None = None) -> DataFrame:
    """(select second, min) product block by block: partial minima inside each block, then over each block row.

    With ``cols`` (of the grid) the frontier is first dealt to its block column, so that it meets only that column's blocks."""
    x = x.select(F.col("v").alias("src"), "x")
    on = ["src"]
    if cols:
        x, on = x.withColumn("bc", F.pmod(F.xxhash64("src"), F.lit(cols))), ["bc", "src"]
    part = blocked.join(x, on).groupBy("br", "bc", F.col("dst").alias("v")).agg(F.min("x").alias("x"))
    return part.groupBy("v").agg(F.min("x").alias("x"))


def balance(blocked: DataFrame) -> DataFrame:
    """One row: blocks, the largest block, the mean, and their ratio."""
    sizes = blocked.groupBy("br", "bc").agg(F.count("*").alias("n"))
    return sizes.agg(F.count("*").alias("blocks"), F.max("n").alias("largest"), F.round(F.avg("n"), 6).alias("mean"), F.round(F.max("n") / F.avg("n"), 6).alias("ratio"))


def adjacency(edges: DataFrame) -> DataFrame:
    """Compressed columns: (src, nbrs), neighbours in order."""
    return edges.groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))


def spmspv_adjacency(columns: DataFrame, x: DataFrame) -> DataFrame:
    """The product over compressed columns."""
    return columns.join(x.withColumnRenamed("v", "src"), "src").select("x", F.explode("nbrs").alias("v")).groupBy("v").agg(F.min("x").alias("x"))
