"""Search for roots of high eccentricity, all components in lockstep.

classic    ends at the root of the first search that is not deeper than the one before.
algebraic  takes one more hop: the least-degree vertex of that search's last level.
first      keeps the start (the component's smallest id, or what is given).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandspark.model import SymGraph
from bandspark.operators.traverse import eccentricity, last_level_vertex, level_structure
from bandspark.session import Steps, materialize

VARIANTS = ("classic", "algebraic", "first")
SHRINKS = ("min_degree", "first")


def search(levels_from: Callable[[DataFrame], DataFrame], vertices: DataFrame, starts: DataFrame, variant: str = "classic", shrink: str = "min_degree") -> tuple[DataFrame, DataFrame]:
    """((comp, root, depth, searches, hop), (comp, v, level) of each component's last search) from starts (comp, v).

    ``levels_from`` gives level structures from roots. The levels are those of the root itself, but for ``algebraic``; ``hop`` is that variant's root."""
    if variant not in VARIANTS or shrink not in SHRINKS:
        raise ValueError(f"variant is one of {VARIANTS}, shrink one of {SHRINKS}")
    spark = vertices.sparkSession
    open_ = materialize(starts.select("comp", "v", F.lit(-1).alias("depth"), F.lit(0).alias("searches")), "roots")
    done, last = Steps(spark, "roots"), Steps(spark, "root-levels")
    while True:
        levels = levels_from(open_.select("comp", "v"))
        found = open_.join(eccentricity(levels), "comp").join(last_level_vertex(levels, vertices, shrink).withColumnRenamed("v", "hop"), "comp")
        grew = F.lit(False) if variant == "first" else F.col("eccentricity") > F.col("depth")
        found = materialize(found.select("comp", "v", "hop", grew.alias("grew"), F.col("eccentricity").alias("depth"), (F.col("searches") + 1).alias("searches")), "roots")
        over = done.put(found.where("not grew").select("comp", F.col("hop" if variant == "algebraic" else "v").alias("root"), "depth", "searches", "hop"))
        last.put(levels.join(over.select("comp"), "comp", "left_semi").select("comp", "v", "level"))
        open_ = found.where("grew").select("comp", F.col("hop").alias("v"), "depth", "searches")
        if open_.isEmpty():
            return done.all(), last.all()


def pseudo_peripheral(g: SymGraph, starts: DataFrame, variant: str = "classic", shrink: str = "min_degree") -> DataFrame:
    """(comp, root, depth, searches) from starts (comp, v), level by level. depth is that of the last search."""
    return search(lambda roots: level_structure(g.edges, roots), g.vertices, starts, variant, shrink)[0].drop("hop")
