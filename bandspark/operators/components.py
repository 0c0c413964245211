"""Connected components by contraction.

Each round every vertex moves to the one of lowest priority among itself and its neighbours, where priorities are hashes
seeded by the round; edges are redrawn between those, and loops go, copies too after the first round. As priorities are random, the vertices that still have edges
shrink by a constant factor a round on any graph, long chains included. What is left at TAIL_EDGES edges or fewer is finished in one task. The maps of all
rounds are composed, and each component takes the smallest id of its vertices.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandspark.session import materialize


#: Contracted edges that one task may finish (16 bytes each).
TAIL_EDGES = 200_000
#: How often a round's map is applied to itself, from the second round on: chains of moves are gone along before edges are redrawn.
JUMPS = 2


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", tail_edges: int = TAIL_EDGES, symmetric: bool = False) -> DataFrame:
    """(v, comp) for every vertex that has an edge; comp is the smallest vertex id of its component.

    Edges may be given in one or both directions, with copies and loops; edges with a null end are ignored. ``symmetric``: every edge is given once in each direction, so none has to be looked for."""
    both = edges.select(F.col(src).cast("long").alias("a"), F.col(dst).cast("long").alias("b")).where("a is not null and b is not null and a <> b")
    e = both.where("a < b") if symmetric else materialize(both.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "cc-edges")
    maps: list[DataFrame] = []
    while n := e.count():
        if n <= tail_edges:
            rest = components_in_task(e.select(F.col("a").alias("src"), F.col("b").alias("dst")))
            maps.append(materialize(rest.withColumnRenamed("comp", "p"), "cc-map"))
            break
        seed = F.lit(len(maps))
        if maps or not symmetric:
            both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min(F.struct(F.xxhash64("b", seed).alias("h"), F.col("b").alias("v"))).alias("m"))
        own = F.struct(F.xxhash64("a", seed).alias("h"), F.col("a").alias("v"))
        parent = materialize(low.select(F.col("a").alias("v"), F.least("m", own).getField("v").alias("p")), "cc-map")
        for _ in range(JUMPS if maps else 0):  # the first map is as long as the graph has vertices
            parent = materialize(parent.join(parent.select(F.col("v").alias("p"), F.col("p").alias("_p")), "p").select("v", F.col("_p").alias("p")), "cc-map")
        left = e.join(parent.withColumnsRenamed({"v": "a", "p": "pa"}), "a")
        drawn = left.join(parent.withColumnsRenamed({"v": "b", "p": "pb"}), "b").where("pa <> pb")
        drawn = drawn.select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b"))
        e = materialize(drawn.distinct() if maps else drawn, "cc-edges")  # few copies come of the first round
        maps.append(parent)
    if not maps:
        return edges.sparkSession.createDataFrame([], "v long, comp long")
    out = maps[0].withColumnRenamed("p", "root")
    for m in maps[1:]:
        out = out.join(m.withColumnsRenamed({"v": "_v", "p": "_p"}), F.col("root") == F.col("_v"), "left").select("v", F.coalesce("_p", "root").alias("root"))
    out = materialize(out, "cc-roots")
    least = materialize(out.groupBy("root").agg(F.min("v").alias("comp")), "cc-least")
    return materialize(out.join(least, "root").select("v", "comp"), "cc-labels")


def components_in_task(edges: DataFrame) -> DataFrame:
    """The same for a graph that one task may hold."""

    def run(e: pa.Table) -> pa.Table:
        a, b = e.column("src").to_numpy(), e.column("dst").to_numpy()
        ids = np.unique(np.concatenate([a, b]))
        s, t = np.searchsorted(ids, a), np.searchsorted(ids, b)
        label = np.arange(len(ids))
        while True:
            new = label.copy()
            np.minimum.at(new, s, label[t])
            np.minimum.at(new, t, label[s])
            np.minimum.at(new, label, new.copy())  # a vertex's old label learns what it has met
            new = new[new]
            if (new == label).all():
                return pa.table({"v": pa.array(ids), "comp": pa.array(ids[label])})
            label = new

    return edges.select("src", "dst").withColumn("k", F.lit(0)).groupBy("k").applyInArrow(run, "v long, comp long")
