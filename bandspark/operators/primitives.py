"""Sparse-vector primitives over DataFrames.

A sparse vector is (v, x), absent rows being zeros; a dense vector is (v, y), absent rows being unset.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bandspark.session import Steps

@dataclass(frozen=True)
class Semiring:
    """How an entry and a vector value are combined, and how several such values are added."""

    mul: Callable[[Column, Column], Column]
    add: Callable[[Column], Column]


SELECT2ND_MIN = Semiring(lambda a, x: x, F.min)
SELECT2ND_MAX = Semiring(lambda a, x: x, F.max)
SELECT2ND_ANY = Semiring(lambda a, x: x, F.any_value)
PLUS_TIMES = Semiring(lambda a, x: a * x, F.sum)


def indices(x: DataFrame) -> DataFrame:
    return x.select("v")


def select_where(x: DataFrame, y: DataFrame, keep: Column) -> DataFrame:
    """x at the indices whose dense value passes ``keep`` (over column y)."""
    return x.join(y.select("v", "y"), "v").where(keep).select("v", "x")


def select_unset(x: DataFrame, y: DataFrame) -> DataFrame:
    """x at the indices that y has no value for."""
    return x.join(y.select("v"), "v", "left_anti")


def scatter(y: DataFrame, x: DataFrame) -> DataFrame:
    """y with the values of x put in."""
    return y.join(x, "v", "full").select("v", F.coalesce("x", "y").alias("y"))


def scatter_new(y: Steps, x: DataFrame) -> DataFrame:
    """y, kept in steps, with the values of x put in at indices that y has no value for: they are appended, y is not rewritten. Returns x as written."""
    return y.put(x)


def gather(x: DataFrame, y: DataFrame) -> DataFrame:
    """x with the values that y has at its indices."""
    return x.select("v").join(y, "v").select("v", F.col("y").alias("x"))


def spmspv(edges: DataFrame, x: DataFrame, ring: Semiring = SELECT2ND_MIN, carry: tuple[str, ...] = ()) -> DataFrame:
    """The product of the matrix with a sparse vector; partial sums are made before the shuffle. ``carry``: columns of the edges that depend on dst alone."""
    value = F.col("val") if "val" in edges.columns else F.lit(1)
    met = edges.join(x.select(F.col("v").alias("src"), "x"), "src")
    return met.groupBy(F.col("dst").alias("v"), *carry).agg(ring.add(ring.mul(value, F.col("x"))).alias("x"))


def reduce_over(x: DataFrame, y: DataFrame, op: Callable[[Column], Column] = F.min) -> DataFrame:
    """One row: ``op`` over the dense values at the indices of x."""
    return x.select("v").join(y, "v").agg(op("y").alias("value"))


def argmin_over(x: DataFrame, y: DataFrame) -> DataFrame:
    """One row: the vertex among x's indices of the least dense value, then the least id."""
    return x.select("v").join(y, "v").agg(F.min(F.struct("y", "v")).alias("m")).select(F.col("m.v").alias("v"), F.col("m.y").alias("value"))
