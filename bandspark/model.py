"""The graph of a symmetric sparse matrix as DataFrames."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bandspark.session import materialize


@dataclass(frozen=True)
class SymGraph:
    """edges (src, dst): both directions, distinct, without loops, clustered by src; vertices (v, deg), isolated ones included."""

    edges: DataFrame
    vertices: DataFrame

    @staticmethod
    def from_pairs(pairs: DataFrame, vertices: DataFrame | None = None) -> "SymGraph":
        """From pairs (a, b) in any direction, with copies and loops; pairs with a null end are dropped. ``vertices`` (v) adds isolated ones."""
        p = pairs.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).where("a is not null and b is not null")
        if vertices is not None:
            alone = vertices.select(F.col("v").cast("long").alias("a")).where("a is not null")
            p = p.unionByName(alone.withColumn("b", F.col("a")))
        both = p.select(F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst")))).alias("e")).select("e.*")
        # pairs are worked out once: loops stay in the file, where they stand for vertices; one shuffle and one sort serve copies and order
        before = F.lag("dst").over(Window.partitionBy("src").orderBy("dst"))
        once = both.withColumn("_before", before).where("_before is null or _before <> dst").drop("_before")
        met = materialize(once, "graph-edges")
        deg = met.groupBy(F.col("src").alias("v")).agg(F.sum((F.col("src") != F.col("dst")).cast("long")).alias("deg"))
        return SymGraph(met.where("src <> dst"), materialize(deg, "graph-vertices"))

    def shape(self) -> DataFrame:
        """n, nnz_offdiag (2 m) and nnz with the diagonal."""
        n = self.vertices.agg(F.count("*").alias("n"), F.sum("deg").alias("nnz_offdiag"))
        return n.select("n", F.coalesce("nnz_offdiag", F.lit(0)).alias("nnz_offdiag"), (F.col("n") + F.coalesce("nnz_offdiag", F.lit(0))).alias("nnz_full"))


def is_symmetric(entries: DataFrame) -> bool:
    """Whether every (src, dst) has its (dst, src)."""
    turned = entries.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return entries.select("src", "dst").exceptAll(turned).isEmpty()
