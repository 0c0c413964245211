"""Level structures by level-synchronous sweeps, all components in lockstep, and by asynchronous relaxation."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandspark.operators.primitives import select_unset, spmspv
from bandspark.operators.serial import Columns
from bandspark.session import Steps, materialize


def level_structure(edges: DataFrame, roots: DataFrame) -> DataFrame:
    """(comp, v, level) from roots (comp, v), one in each component, by one product and one filter a level.

    For graphs of few levels; :class:`sweep.Sweeper` fuses those of deep graphs."""
    steps = Steps(edges.sparkSession, "levels")
    last = steps.put(roots.select("comp", "v", F.lit(0).alias("level")))
    seen, k = last.select("v"), 0
    while True:
        k += 1
        near = select_unset(spmspv(edges, last.select("v", F.col("comp").alias("x"))), seen)
        near = steps.put(near.select(F.col("x").alias("comp"), "v", F.lit(k).alias("level")))
        if near.isEmpty():
            return steps.all()
        seen, last = last.select("v").unionByName(near.select("v")), near  # a new vertex can only have been met in the last two levels


def level_sizes(levels: DataFrame) -> DataFrame:
    return levels.groupBy("comp", "level").agg(F.count("*").alias("n"))


def eccentricity(levels: DataFrame) -> DataFrame:
    """comp, eccentricity, n_levels, width."""
    return level_sizes(levels).groupBy("comp").agg(F.max("level").alias("eccentricity"), (F.max("level") + 1).alias("n_levels"), F.max("n").alias("width"))


def last_level_vertex(levels: DataFrame, degrees: DataFrame, shrink: str = "min_degree") -> DataFrame:
    """(comp, v): of each component's last level the vertex of least degree, then least id (``first``: least id)."""
    deepest = levels.groupBy("comp").agg(F.max("level").alias("level"))
    last = levels.join(deepest, ["comp", "level"])
    if shrink == "first":
        return last.groupBy("comp").agg(F.min("v").alias("v"))
    return last.join(degrees, "v").groupBy("comp").agg(F.min(F.struct("deg", "v")).alias("m")).select("comp", F.col("m.v").alias("v"))


#: Directed edges of one part of the asynchronous search.
PART_EDGES = 1_000_000


def levels_async(edges: DataFrame, roots: DataFrame, parts: int | None = None, max_rounds: int = 10_000) -> tuple[DataFrame, int]:
    """((v, level), rounds): distances by relaxation inside ranges of vertices as far as they go, then across ranges.

    Rounds follow the number of times a shortest path leaves its range, not its length. Ranges are sampled; only those met by a better distance work in a round."""
    parts = parts or max(1, -(-edges.count() // PART_EDGES))
    degrees = edges.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg"))
    homes = materialize(degrees.repartitionByRange(parts, "v").select("v", F.spark_partition_id().alias("bin")), "async-homes")
    far = homes.withColumnsRenamed({"v": "dst", "bin": "other"})
    binned = materialize(edges.select("src", "dst").join(homes.withColumnRenamed("v", "src"), "src").join(far, "dst").select("src", "dst", "bin", (F.col("bin") == F.col("other")).cast("long").alias("inside")), "async-edges")
    state = materialize(roots.select("v", F.lit(0).cast("long").alias("level")), "async")
    seeds = materialize(state.join(homes, "v"), "async-seeds")
    for rounds in range(1, max_rounds + 1):
        state, seeds = relax_round(binned, homes, state, seeds)
        if seeds.isEmpty():
            return state, rounds
    raise RuntimeError("no fixed point")


def _relax(e: pa.Table, d: pa.Table) -> pa.Table:
    """Distances inside one bin from its seeds, and offers to vertices outside. d: v, level, seed; rows out: v, level, inside."""
    src, dst, own = (e.column(c).to_numpy() for c in ("src", "dst", "inside"))
    v, level, seed = (d.column(c).to_numpy(zero_copy_only=False) for c in ("v", "level", "seed"))
    g = Columns(src[own == 1], dst[own == 1], np.concatenate([v, src]))
    far = np.iinfo(np.int64).max // 2
    dist = np.full(len(g.ids), far)
    at = np.searchsorted(g.ids, v)
    np.minimum.at(dist, at, level)
    known = dist.copy()
    start = at[seed.astype(bool)]
    start = np.unique(start[np.argsort(dist[start], kind="stable")])
    start = start[np.argsort(dist[start], kind="stable")]
    moved = np.zeros(len(g.ids), bool)
    moved[start] = True
    marks, first = np.unique(dist[start], return_index=True)
    waiting = dict(zip(marks.tolist(), np.split(start, first[1:]), strict=True)) if len(start) else {}
    now, k = np.zeros(0, np.int64), 0
    while waiting or len(now):
        if not len(now):
            k = min(waiting)
        more = waiting.pop(k, None)
        if more is not None:
            now = np.unique(np.concatenate([now, more[dist[more] == k]]))
        near, _ = g.neighbours(now)
        now = np.unique(near[dist[near] > k + 1])
        dist[now] = k + 1
        moved[now] = True
        k += 1
    better = np.flatnonzero(dist < known)
    s = np.searchsorted(g.ids, src)
    out = (own == 0) & moved[s]
    there, offer = dst[out], dist[s[out]] + 1
    return pa.table({
        "v": pa.array(np.concatenate([g.ids[better], there])), "level": pa.array(np.concatenate([dist[better], offer])),
        "inside": pa.array(np.concatenate([np.ones(len(better), np.int64), np.zeros(len(there), np.int64)])),
    })


def relax_round(binned: DataFrame, homes: DataFrame, state: DataFrame, seeds: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(state, seeds) after one round: distances (v, level) relaxed inside every bin that has a seed (v, level, bin), and offers across bins taken where they are better.

    binned: src, dst, bin of src, inside (whether dst is in it too); homes: v, bin."""
    active = materialize(seeds.select("bin").distinct(), "relax-bins")
    known = state.join(homes, "v").join(active, "bin", "left_semi").join(seeds.select("v", F.lit(True).alias("seed")), "v", "left")
    known = known.select("bin", "v", "level", F.coalesce("seed", F.lit(False)).alias("seed"))
    e = binned.join(active, "bin", "left_semi").select("src", "dst", "inside", F.col("bin").alias("bin"))
    out = materialize(e.groupBy("bin").cogroup(known.groupBy("bin")).applyInArrow(_relax, "v long, level long, inside long"), "relax-out")
    least = out.groupBy("v").agg(F.min("level").alias("level"), F.min(F.when(F.col("inside") == 1, F.col("level"))).alias("own"))
    better = least.join(state.withColumnRenamed("level", "old"), "v", "left").where("old is null or level < old")
    better = materialize(better.join(homes, "v").select("v", "level", "bin", (F.col("own").isNull() | (F.col("own") > F.col("level"))).alias("seed")), "relax-better")
    state = materialize(state.join(better.select("v"), "v", "left_anti").unionByName(better.select("v", "level")), "relax-state")
    return state, better.where("seed").select("v", "level", "bin")


def diameter_exact(edges: DataFrame, limit: int = 2000) -> int:
    """The largest eccentricity of any vertex, by a search from each; for small connected graphs."""
    rows = edges.select("src", "dst").limit(limit * limit + 1).toArrow()
    g = Columns(rows.column("src").to_numpy(), rows.column("dst").to_numpy())
    if len(g.ids) > limit:
        raise ValueError(f"more than {limit} vertices")
    return max((len(g.levels(i, np.full(len(g.ids), -1, np.int32))[1]) - 2 for i in range(len(g.ids))), default=0)
