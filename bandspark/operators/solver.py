"""Conjugate gradients with a block Jacobi preconditioner on a shifted graph Laplacian, to show what an ordering is for.

Rows are cut into blocks by position, so a better ordering puts more of the matrix inside the blocks: fewer iterations, and fewer entries
that cross blocks. A vector is (i, x), joined by position; only dot products reach the driver.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandspark.operators.metrics import permute
from bandspark.session import materialize


def shifted_laplacian(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(i, j, a): degree + 1 on the diagonal, -1 off it, in the order of the labels."""
    off = permute(edges.select("src", "dst"), labels).withColumn("a", F.lit(-1.0))
    deg = off.groupBy("i").agg((F.count("*") + 1).cast("double").alias("a"))
    diag = labels.select(F.col("label").alias("i")).join(deg, "i", "left").select("i", F.col("i").alias("j"), F.coalesce("a", F.lit(1.0)).alias("a"))
    return materialize(off.select("i", "j", "a").unionByName(diag), "solver-matrix")


def off_block(matrix: DataFrame, block: int) -> int:
    """Entries whose row and column lie in different blocks."""
    return matrix.where(F.floor(F.col("i") / block) != F.floor(F.col("j") / block)).count()


def cg_block_jacobi(matrix: DataFrame, rhs: DataFrame, block: int = 32, tol: float = 1e-8, most: int = 500) -> dict:
    """rhs (i, b). Returns x (a DataFrame), iterations, residual (relative) and off_block."""
    inside = matrix.withColumn("blk", F.floor(F.col("i") / block)).where(F.floor(F.col("j") / block) == F.col("blk"))

    def invert(m: pa.Table) -> pa.Table:
        i, j = m.column("i").to_numpy(), m.column("j").to_numpy()
        ids = np.unique(i)
        a = np.zeros((len(ids), len(ids)))
        a[np.searchsorted(ids, i), np.searchsorted(ids, j)] = m.column("a").to_numpy()
        return pa.table({"i": pa.array(np.repeat(ids, len(ids))), "j": pa.array(np.tile(ids, len(ids))), "w": pa.array(np.linalg.inv(a).ravel())})

    inverse = materialize(inside.groupBy("blk").applyInArrow(invert, "i long, j long, w double"), "solver-blocks")  # block x block numbers a block, made once

    def precondition(r: DataFrame) -> DataFrame:
        return inverse.join(r.select(F.col("i").alias("j"), "r"), "j").groupBy("i").agg(F.sum(F.col("w") * F.col("r")).alias("z"))

    def dot(df: DataFrame, x: str, y: str) -> float:
        return df.agg(F.sum(F.col(x) * F.col(y))).first()[0] or 0.0

    state = rhs.select("i", F.col("b").alias("r"))
    norm = dot(state, "r", "r") ** 0.5
    state = materialize(state.join(precondition(state), "i").select("i", F.lit(0.0).alias("x"), "r", "z", F.col("z").alias("p")), "solver")
    rz, done, k = dot(state, "r", "z"), norm == 0, 0
    residual = 0.0 if done else 1.0
    while not done and k < most:
        k += 1
        ap = matrix.join(state.select(F.col("i").alias("j"), "p"), "j").groupBy("i").agg(F.sum(F.col("a") * F.col("p")).alias("ap"))
        with_ap = materialize(state.join(ap, "i"), "solver")
        alpha = rz / dot(with_ap, "p", "ap")
        moved = with_ap.select("i", (F.col("x") + alpha * F.col("p")).alias("x"), (F.col("r") - alpha * F.col("ap")).alias("r"), "p")
        both = materialize(moved.join(precondition(moved), "i"), "solver")
        sums = both.agg(F.sum(F.col("r") * F.col("r")).alias("rr"), F.sum(F.col("r") * F.col("z")).alias("rz")).first()
        residual = (sums["rr"] or 0.0) ** 0.5 / norm
        state = both.select("i", "x", "r", (F.col("z") + ((sums["rz"] or 0.0) / rz) * F.col("p")).alias("p"))
        rz = sums["rz"]
        if residual <= tol:
            break
    return {"x": state.select("i", "x"), "iterations": k, "residual": residual, "off_block": off_block(matrix, block)}
