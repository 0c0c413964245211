"""Exact nearest neighbours: squared distances of all pairs of vectors, tile by tile, of which each vector keeps its nearest.

Vectors are dealt by id to blocks of about BLOCK, each packed as one row. Every pair of blocks meets in a task: a matrix product
gives the distances up to rounding, whatever may be among the nearest within that error is summed again in the order of the
dimensions, and only those sums are compared. So the result is that of the sum over all pairs, ties (by id) included.

Nulls and edges: rows with a null id are left out; vectors of another length than most, without elements, or with null, huge or
non-finite elements meet all others one by one (null elements are skipped; distances without elements are null and come last). A repeated id is one vertex.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bandspark.session import arrow_rows, materialize

#: Vectors of one block; rows of it that are multiplied at once; pairs of vectors summed at once; pairs of blocks sent to a task's Python at once.
BLOCK, ROWS, SUMMED, AT_ONCE = 2048, 256, 1 << 16, 8
#: Elements from here on could overflow when squared and summed.
HUGE = 1e100


def _sums(x: np.ndarray, rows: np.ndarray, y: np.ndarray, cols: np.ndarray) -> np.ndarray:
    """Squared distances of rows of x and rows of y, added up in the order of the dimensions."""
    out = np.zeros(len(rows))
    for a in range(0, len(rows), SUMMED):
        r, c, s = rows[a : a + SUMMED], cols[a : a + SUMMED], out[a : a + SUMMED]
        for u, v in zip(x.T, y.T, strict=True):
            d = u[r] - v[c]
            s += d * d
    return out


class Nearest:
    """The k nearest of each row of one block, among the blocks met so far."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, k: int):
        self.ids, self.x, self.k = ids, x, k
        self.square = np.einsum("ij,ij->i", x, x)
        self.row, self.d, self.j = np.zeros(0, np.int64), np.zeros(0), np.zeros(0, np.int64)
        self.worst = np.full(len(ids), np.inf)

    def meet(self, ids: np.ndarray, y: np.ndarray, same: bool) -> None:
        square = np.einsum("ij,ij->i", y, y)
        reach = 8 * (self.x.shape[1] + 8) * np.finfo(float).eps  # a generous bound of the relative error of either way to sum
        rows, cols = [], []
        for a in range(0, len(self.ids), ROWS):
            part = slice(a, a + ROWS)
            near = self.x[part] @ (-2 * y.T)
            near += self.square[part, None]
            near += square
            if same:
                near[self.ids[part, None] == ids] = np.inf
            slack = reach * (np.sqrt(self.square[part]) + np.sqrt(square.max())) ** 2
            limit = self.worst[part] * (1 + reach) + slack
            open_ = np.flatnonzero(np.isinf(limit))
            if len(open_) and len(ids) > self.k:
                limit[open_] = np.partition(near[open_], self.k - 1, axis=1)[:, self.k - 1] + 2 * slack[open_]
            r, c = np.nonzero(near <= limit[:, None])
            rows.append(r + a)
            cols.append(c)
        row, col = np.concatenate(rows), np.concatenate(cols)
        own = self.ids[row] != ids[col]
        row, col = row[own], col[own]
        if not len(row):
            return
        row, d, j = np.concatenate([self.row, row]), np.concatenate([self.d, _sums(self.x, row, y, col)]), np.concatenate([self.j, ids[col]])
        order = np.lexsort((j, d, row))
        row, d, j = row[order], d[order], j[order]
        head = np.flatnonzero(np.diff(row, prepend=-1))
        place = np.arange(len(row)) - np.repeat(head, np.diff(np.append(head, len(row))))
        kept = place < self.k
        self.row, self.d, self.j = row[kept], d[kept], j[kept]
        last = place == self.k - 1
        self.worst[row[last]] = d[last]

    def rows(self) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(self.ids[self.row]), pa.array(self.j), pa.array(self.d)], names=["i", "j", "d"])


def _pack(t: pa.Table) -> pa.Table:
    v = t.column("v").combine_chunks()
    x = v.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return pa.table({"block": t.column("block")[:1], "ids": pa.array([t.column("i").to_numpy().tobytes()], pa.binary()), "x": pa.array([x.tobytes()], pa.binary())})


def _among_plain(plain: DataFrame, n: int, dim: int, k: int, block: int) -> DataFrame:
    spark = plain.sparkSession
    dealt = plain.select(F.pmod(F.xxhash64("i"), F.lit(-(-n // block))).cast("int").alias("block"), "i", "v")
    blocks = materialize(dealt.groupBy("block").applyInArrow(_pack, "block int, ids binary, x binary"), "knn-blocks")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = lambda ids, x: (np.frombuffer(ids, np.int64), np.frombuffer(x).reshape(-1, dim))
        own, of = None, None
        for batch in batches:
            for r in range(batch.num_rows):
                a, ids, x, b, ids2, y = (batch.column(c)[r] for c in range(6))
                if a.as_py() != of:
                    if own is not None:
                        yield own.rows()
                    own, of = Nearest(*unpack(ids.as_buffer(), x.as_buffer()), k), a.as_py()
                own.meet(*unpack(ids2.as_buffer(), y.as_buffer()), a.as_py() == b.as_py())
        if own is not None:
            yield own.rows()

    met = blocks.hint("shuffle_replicate_nl").crossJoin(blocks.toDF("block2", "ids2", "x2"))  # a row a block on both sides
    with arrow_rows(spark, AT_ONCE):
        return materialize(met.mapInArrow(run, "i long, j long, d double"), "knn")


#: Of two vectors x and y; elements that are null on either side are skipped.
_DISTANCE = """CASE WHEN exists(zip_with(x, y, (u, v) -> u - v), u -> u IS NOT NULL) THEN
 aggregate(zip_with(x, y, (u, v) -> (u - v) * (u - v)), 0D, (s, u) -> s + coalesce(u, 0D)) END"""


def nearest(vectors: DataFrame, k: int, block: int = BLOCK) -> DataFrame:
    """(a, b): of each vector (i, v) the ids of its ``k`` nearest others, by squared distance, then id."""
    rows = vectors.where("i is not null").select(F.col("i").cast("long").alias("i"), F.col("v").cast("array<double>").alias("v"))
    rows = rows.withColumn("dim", F.when(F.size("v") > 0, F.when(~F.exists("v", lambda u: u.isNull() | F.isnan(u) | (F.abs(u) > HUGE)), F.size("v"))))
    rows = materialize(rows, "knn-vectors")
    sizes = rows.groupBy("dim").count()
    most = sizes.where("dim is not null").orderBy(F.desc("count"), "dim").first()
    total = rows.count()
    dim, n = (most["dim"], most["count"]) if most else (0, 0)
    found = _among_plain(rows.where(F.col("dim") == dim), n, dim, k, block) if n else None
    if n < total:  # the odd ones with all others, in both directions
        odd = rows.where(F.coalesce(F.col("dim") != dim, F.lit(True))).select(F.col("i").alias("i"), F.col("v").alias("x"))
        ways = [odd.crossJoin(rows.select(F.col("i").alias("j"), F.col("v").alias("y")))]
        if n:
            plain = rows.where(F.col("dim") == dim)
            ways.append(plain.select("i", F.col("v").alias("x")).crossJoin(odd.select(F.col("i").alias("j"), F.col("x").alias("y"))))
        for way in ways:
            one = way.where("i <> j").select("i", "j", F.expr(_DISTANCE).alias("d"))
            found = one if found is None else found.unionByName(one)
    if found is None:
        return vectors.sparkSession.createDataFrame([], "a long, b long")
    best = Window.partitionBy("i").orderBy(F.asc_nulls_last("d"), "j")
    return found.withColumn("r", F.row_number().over(best)).where(F.col("r") <= k).select(F.col("i").alias("a"), F.col("j").alias("b"))
