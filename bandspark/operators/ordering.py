"""Frontier orderings: reverse (the method) and forward, in one task a lot of components or as distributed sweeps.

Every plan gives the same labels: components by smallest member, vertices by level, then by (smallest parent label, degree, id).
The reversal is global.

sweep      levels first, then labels over edges laid out by level; small levels of deep graphs fused (:mod:`sweep`).
algebraic  levels and labels in one sweep: product, filter, sort and scatter a level.
task       whole components in tasks, packed into lots of bounded size.
auto       components of at most ``task_edges`` directed edges in tasks, larger ones swept.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandspark.model import SymGraph
from bandspark.operators.components import connected_components
from bandspark.operators.peripheral import SHRINKS, VARIANTS, search
from bandspark.operators.ranking import STRATEGIES, sort_rank
from bandspark.operators.serial import Columns, order_columns, order_components
from bandspark.operators.sweep import FUSE_EDGES, SYNC_LEVELS, Sweeper, prefix_sums
from bandspark.session import materialize

#: Directed edges up to which the gather baseline takes a graph in one task (24 bytes each, a few copies).
TASK_EDGES = 8_000_000
#: Directed edges of a component up to which one task orders it: packed in 8 bytes each while they are sorted, 4 after that.
PACKED_EDGES = 48_000_000
#: Contracted edges from which components are finished in one task (16 bytes each, a few copies).
TAIL_EDGES = 4_000_000
#: Packed edges of one block, and rows of one batch that a task gives back.
_BLOCK, _BATCH = 4_000_000, 100_000
PLANS, SORTS, TIES = ("auto", "task", "sweep", "algebraic"), ("degree", "parent", "level", "end"), ("original", "relabelled")
#: Components that may be ordered one after another.
MOST_SEQUENTIAL = 1000


@dataclass(frozen=True)
class Ordering:
    """labels (v, label), roots (comp, root, depth, searches, width), levels (comp, v, level)."""

    labels: DataFrame
    roots: DataFrame
    levels: DataFrame


def with_components(g: SymGraph) -> DataFrame:
    """(v, deg, comp); an isolated vertex is its own component."""
    comps = connected_components(g.edges, tail_edges=TAIL_EDGES, symmetric=True)
    return materialize(g.vertices.join(comps, "v", "left").select("v", "deg", F.coalesce("comp", "v").alias("comp")), "vertices")


def component_table(placed: DataFrame) -> DataFrame:
    """comp, n, edges (directed), base (vertices of components before). One row a component."""
    sizes = placed.groupBy("comp").agg(F.count("*").alias("n"), F.sum("deg").alias("edges"))
    return materialize(prefix_sums(sizes, "comp", "n", "base"), "components")


_HEAD = "kind int, comp long, v long, place long, level int, depth int, searches int, width long, hop long"


def _in_tasks(edges: DataFrame, vertices: DataFrame, table: DataFrame, lot_edges: int, variant: str, shrink: str, sort: str | None, given: dict | None, threads: int = 1) -> DataFrame:
    """Whole components in one task a lot: rows of kind 0 (vertices) and 1 (one a component, v being the root).

    A lot is a run of components with about ``lot_edges`` edges (a component is never cut), and of as many vertices at most. Its vertices are numbered by id,
    and its edges come to the task as pairs of numbers in 8 bytes, batch by batch."""
    lots = prefix_sums(table.select("comp", (F.col("edges") + F.col("n")).alias("w")), "comp", "w")
    lots = materialize(lots.select("comp", F.floor(F.col("before") / lot_edges).cast("int").alias("k")), "lots")
    count = lots.agg(F.max("k")).first()[0] + 1
    ranked = materialize(sort_rank(vertices.join(lots, "comp").select("k", "v", "comp"), ["k", "v"], "general"), "lot-ranks")
    first = ranked.groupBy("k").agg(F.min("rank").alias("first"))
    numbered = materialize(ranked.join(F.broadcast(first), "k").select("k", "v", "comp", (F.col("rank") - F.col("first")).alias("no")), "lot-vertices")  # a row a lot
    ends = edges.select("src", "dst").join(numbered.select(F.col("v").alias("src"), "k", F.shiftleft("no", 32).alias("high")), "src").join(numbered.select(F.col("v").alias("dst"), "no"), "dst")
    nothing = F.lit(None).cast("long")
    rows = numbered.select("k", F.col("no").alias("key"), "v", "comp").unionByName(ends.select("k", F.col("high").bitwiseOR(F.col("no")).alias("key"), nothing.alias("v"), nothing.alias("comp")))

    def run(batches):
        blocks, full, nodes = [], 0, []
        for batch in batches:
            key, v = batch.column("key").to_numpy(), batch.column("v")
            if v.null_count < len(v):
                here = v.is_valid().to_numpy(zero_copy_only=False)
                nodes.append(tuple(np.array(x) for x in (key[here], v.drop_null().to_numpy(), batch.column("comp").drop_null().to_numpy())))
                key = key[~here]
            while len(key):
                if not blocks or full == _BLOCK:
                    blocks.append(np.empty(_BLOCK, np.int64))
                    full = 0
                n = min(len(key), _BLOCK - full)
                blocks[-1][full : full + n] = key[:n]
                full, key = full + n, key[n:]
        if not nodes:
            return
        no, ids, comp = (np.concatenate(x) for x in zip(*nodes))
        nodes.clear()
        at = np.empty(len(no), np.int64)
        at[no] = np.arange(len(no))
        ids, comp = ids[at], comp[at]
        keys, k = np.empty(max(0, len(blocks) - 1) * _BLOCK + full, np.int64), 0
        while blocks:  # the last block first; each goes when it is copied
            block = blocks.pop()
            block = block[:full] if not k else block
            keys[k : k + len(block)] = block
            k += len(block)
        del no, at
        g = Columns.packed(ids, keys)
        del keys
        cols, heads = order_columns(g, comp, variant, shrink, sort, given, threads)
        del g, ids, comp
        h = np.array(heads, np.int64).reshape(-1, 6)
        for kind, (own, v, place, level, depth, searches, width, hop) in enumerate(((*cols, None, None, None, None), (h[:, 0], h[:, 1], None, None, h[:, 2], h[:, 3], h[:, 4], h[:, 5]))):
            for a in range(0, len(v), _BATCH):
                m = min(_BATCH, len(v) - a)
                one = lambda x, t: pa.array(np.full(m, -1) if x is None else x[a : a + m]).cast(t)  # noqa: B023, E731
                i, w = pa.int32(), pa.int64()
                arrays = [one(np.full(len(v), kind, np.int32), i), one(own, w), one(v, w), one(place, w), one(level, i), one(depth, i), one(searches, i), one(width, w), one(hop, w)]
                yield pa.RecordBatch.from_arrays(arrays, names=["kind", "comp", "v", "place", "level", "depth", "searches", "width", "hop"])

    dealt = rows.repartitionById(count, F.col("k")).select("key", "v", "comp")
    return materialize(dealt.mapInArrow(run, _HEAD), "task-orders")


def _lot_size(table: DataFrame, task_edges: int) -> int:
    """As many lots as keep all cores busy, none above the bound."""
    total = table.agg(F.sum("edges")).first()[0]
    return min(task_edges, max(1000, total // (2 * int(table.sparkSession.conf.get("spark.sql.shuffle.partitions")))))


def searched(g: SymGraph, placed: DataFrame, variant: str = "classic", shrink: str = "min_degree", task_edges: int = PACKED_EDGES) -> tuple[DataFrame, DataFrame]:
    """What :func:`peripheral.search` gives: components of at most ``task_edges`` directed edges in tasks, larger ones by sweeps."""
    table = component_table(placed)
    small, large = table.where(F.col("edges") <= task_edges), table.where(F.col("edges") > task_edges)
    roots, levels = [], []
    if not small.isEmpty():
        own = placed.join(small.select("comp"), "comp", "left_semi").select("comp", "v")
        done = _in_tasks(g.edges, own, small, _lot_size(table, task_edges), variant, shrink, None, None)
        roots.append(done.where("kind = 1").select("comp", F.col("v").alias("root"), "depth", "searches", "hop"))
        levels.append(done.where("kind = 0").select("comp", "v", "level"))
    if not large.isEmpty() or not roots:
        for all_of, one in zip((roots, levels), search(Sweeper(g, placed).levels, g.vertices, large.select("comp", F.col("comp").alias("v")), variant, shrink), strict=True):
            all_of.append(one)
    return tuple(x[0] if len(x) == 1 else x[0].unionByName(x[1]) for x in (roots, levels))


def _swept(g: SymGraph, placed: DataFrame, table: DataFrame, plan: str, variant: str, shrink: str, given: dict | None, strategy: str, sort: str, sync_levels: int, fuse_edges: int, task_edges: int):
    """(labels (comp, v, label) forward, heads, levels) of the components in ``table``."""
    sweeper = Sweeper(g, placed, sync_levels, fuse_edges, task_edges)
    spark = g.edges.sparkSession
    fixed = spark.createDataFrame(list((given or {}).items()), "comp long, v long").join(table.select("comp"), "comp", "left_semi") if given else None
    starts = table.select("comp", F.col("comp").alias("v"))
    if fixed is not None:
        starts = starts.join(fixed.select("comp"), "comp", "left_anti")
    roots, found = search(sweeper.levels, g.vertices, starts, variant, shrink)
    roots = roots.drop("hop")
    if variant == "algebraic" and plan == "sweep":  # the last search was not from the root
        found = sweeper.levels(roots.select("comp", F.col("root").alias("v")))
    if fixed is not None:
        own = sweeper.levels(fixed)
        roots = roots.unionByName(fixed.select("comp", F.col("v").alias("root"), F.lit(0).alias("depth"), F.lit(0).alias("searches")))
        found = materialize(found.unionByName(own), "levels")
    if plan == "algebraic":
        labels, found = sweeper.algebraic(roots.select("comp", F.col("root").alias("v")), table, strategy, sort)
    else:
        labels = sweeper.labels(found, table, strategy, sort)
    width = found.groupBy("comp", "level").count().groupBy("comp").agg(F.max("count").alias("width"), F.max("level").alias("d"))
    heads = roots.join(width, "comp").select("comp", "root", F.col("d").alias("depth"), "searches", "width")
    return labels, heads, found.select("comp", "v", "level")


def _one_of(name: str, value, allowed: tuple) -> None:
    if value not in allowed:
        raise ValueError(f"{name} is one of {allowed}, not {value!r}")


def frontier_order(
    g: SymGraph, root: str | int = "classic", plan: str = "auto", reverse: bool = True, strategy: str = "bucket", sort: str = "degree", shrink: str = "min_degree", task_edges: int = PACKED_EDGES,
    tie_break: str = "original", components: str = "lockstep", seed: int = 7, sync_levels: int = SYNC_LEVELS, fuse_edges: int = FUSE_EDGES,
) -> Ordering:
    """Labels of all vertices.

    root: classic, algebraic, first, or the id of a vertex, which is then its component's root (the others' are searched by the classic rule).
    strategy: of the ranks in a sweep. sort: by degree below the parent, by parent alone, by level alone, or once at the end by (level, degree).
    tie_break: ids as given, or as randomly relabelled by ``seed`` (labels are those of the ids given). components: in lockstep, or one after another."""
    _one_of("plan", plan, PLANS)
    _one_of("strategy", strategy, STRATEGIES)
    _one_of("sort", sort, SORTS)
    _one_of("shrink", shrink, SHRINKS)
    _one_of("tie_break", tie_break, TIES)
    _one_of("components", components, ("lockstep", "sequential"))
    if not isinstance(root, int):
        _one_of("root", root, VARIANTS)
    if plan == "algebraic" and sort not in ("degree", "parent"):
        raise ValueError("one sweep without known levels sorts by degree or parent")
    options = {"plan": plan, "reverse": reverse, "strategy": strategy, "sort": sort, "shrink": shrink, "task_edges": task_edges, "sync_levels": sync_levels, "fuse_edges": fuse_edges}
    if tie_break == "relabelled":
        return _relabelled(g, root, seed, components, options)
    placed = with_components(g)
    given = None
    if isinstance(root, int):
        at = placed.where(F.col("v") == root).first()
        if at is None:
            raise ValueError(f"root {root} is not a vertex")
        given, root = {at["comp"]: root}, "classic"
    if components == "sequential":
        return _sequential(g, placed, given, root, options)
    return _ordered(g, placed, component_table(placed), given, root, **options)


def _ordered(g, placed, table, given, root, plan, reverse, strategy, sort, shrink, task_edges, sync_levels, fuse_edges, threads=1) -> Ordering:
    spark = g.edges.sparkSession
    whole = {"task": F.lit(True), "auto": F.col("edges") <= task_edges}.get(plan, F.lit(False))
    small, large = table.where(whole), table.where(~whole)
    parts, heads, levels = [], [], []
    if not small.isEmpty():
        own = placed.join(small.select("comp"), "comp", "left_semi").select("comp", "v")
        done = _in_tasks(g.edges, own, small, _lot_size(table, task_edges), root, shrink, sort, given, threads)
        parts.append(done.where("kind = 0").join(small.select("comp", "base"), "comp").select("comp", "v", (F.col("place") + F.col("base")).alias("label")))
        heads.append(done.where("kind = 1").select("comp", F.col("v").alias("root"), "depth", "searches", "width"))
        levels.append(done.where("kind = 0").select("comp", "v", "level"))
    if not large.isEmpty():
        done = _swept(g, placed, large, "algebraic" if plan == "algebraic" else "sweep", root, shrink, given, strategy, sort, sync_levels, fuse_edges, task_edges)
        for all_of, one in zip((parts, heads, levels), done, strict=True):
            all_of.append(one)
    if not parts:
        return Ordering(spark.createDataFrame([], "v long, label long"), spark.createDataFrame([], "comp long, root long, depth int, searches int, width long"), spark.createDataFrame([], "comp long, v long, level int"))
    union = lambda frames: frames[0] if len(frames) == 1 else frames[0].unionByName(frames[1])
    labels = union(parts)
    if reverse:
        labels = labels.withColumn("label", F.lit(placed.count() - 1) - F.col("label"))
    return Ordering(labels.select("v", F.col("label").cast("long").alias("label")), union(heads), union(levels))


def _relabelled(g: SymGraph, root, seed: int, components: str, options: dict) -> Ordering:
    from bandspark.operators.distribution import random_relabel

    other, ids = random_relabel(g, seed)
    ids = materialize(ids, "relabelled")
    if isinstance(root, int):
        at = ids.where(F.col("v") == root).first()
        if at is None:
            raise ValueError(f"root {root} is not a vertex")
        root = at["label"]
    o = frontier_order(other, root, components=components, **options)
    back = ids.select(F.col("label").alias("_new"), F.col("v").alias("_old"))
    first = back.join(o.levels, back["_new"] == o.levels["v"]).groupBy("comp").agg(F.min("_old").alias("_comp"))  # components are named by their smallest id
    named = lambda df, c: df.join(back, df[c] == back["_new"]).drop(c, "_new").withColumnRenamed("_old", c)
    renamed = lambda df: df.join(first, "comp").drop("comp").withColumnRenamed("_comp", "comp")
    return Ordering(named(o.labels, "v").select("v", "label"), renamed(named(o.roots, "root")).select("comp", "root", "depth", "searches", "width"), renamed(named(o.levels, "v")).select("comp", "v", "level"))


def _sequential(g: SymGraph, placed: DataFrame, given, root, options: dict) -> Ordering:
    """Components one after another, each by a call of its own; at most MOST_SEQUENTIAL of them."""
    table = component_table(placed)
    comps = [r["comp"] for r in table.select("comp").orderBy("comp").limit(MOST_SEQUENTIAL + 1).collect()]
    if len(comps) > MOST_SEQUENTIAL:
        raise ValueError(f"more than {MOST_SEQUENTIAL} components: order them in lockstep")
    out = None
    for c in comps:
        own = materialize(placed.where(F.col("comp") == c), "vertices")
        edges = g.edges.join(own.select(F.col("v").alias("src")), "src", "left_semi")
        one = _ordered(SymGraph(materialize(edges, "edges"), own.select("v", "deg")), own, table.where(F.col("comp") == c), given, root, **{**options, "reverse": False})
        out = one if out is None else Ordering(*(a.unionByName(b) for a, b in zip((out.labels, out.roots, out.levels), (one.labels, one.roots, one.levels), strict=True)))
    if out is None:
        return _ordered(g, placed, table, given, root, **options)
    labels = out.labels.withColumn("label", F.lit(placed.count() - 1) - F.col("label")) if options["reverse"] else out.labels
    return Ordering(labels, out.roots, out.levels)


def natural_order(g: SymGraph, strategy: str = "general") -> DataFrame:
    """Labels by rank of id."""
    return sort_rank(g.vertices.select("v"), ["v"], strategy).withColumnRenamed("rank", "label")


def random_order(g: SymGraph, seed: int, strategy: str = "general") -> DataFrame:
    """Labels by rank of a seeded hash of the id."""
    keyed = g.vertices.select("v", F.xxhash64("v", F.lit(seed)).alias("h"))
    return sort_rank(keyed, ["h", "v"], strategy).select("v", F.col("rank").alias("label"))


def single_node_order(g: SymGraph, threads: int = 1, limit_edges: int = TASK_EDGES, root: str = "classic", above: str = "refuse") -> DataFrame:
    """The shared-memory baseline: all edges in one task, whose frontiers are expanded by ``threads`` threads; ``above`` the limit as in :func:`gather_order`."""
    return gather_order(g, limit_edges, root, threads, above)


def gather_order(g: SymGraph, limit_edges: int = TASK_EDGES, root: str = "classic", threads: int = 1, above: str = "refuse") -> DataFrame:
    """The gather-to-one-node baseline: all edges and vertices in one task.

    A graph of more than ``limit_edges`` directed edges is refused, or (``above``: ``lots``) its components are gathered in lots that a task may hold, and swept if one is larger than that."""
    _one_of("root", root, VARIANTS)
    _one_of("above", above, ("refuse", "lots"))
    m = g.edges.count()
    if m > limit_edges:
        if above == "lots":
            placed = with_components(g)
            return _ordered(g, placed, component_table(placed), None, root, "auto", True, "bucket", "degree", "min_degree", limit_edges, SYNC_LEVELS, FUSE_EDGES, threads).labels
        raise MemoryError(f"{m} directed edges are more than the {limit_edges} that one task may hold")
    placed = with_components(g)
    table = component_table(placed)
    edges = g.edges.join(placed.select(F.col("v").alias("src"), "comp"), "src").select("src", "dst", "comp", F.lit(0).alias("k"))
    own = placed.select(F.col("comp").alias("comp"), F.col("v").alias("v"), F.lit(0).alias("k"))

    def run(e: pa.Table, v: pa.Table) -> pa.Table:
        (comp, ids, place, _), _ = order_components(e.column("src").to_numpy(), e.column("dst").to_numpy(), e.column("comp").to_numpy(), root, vertices=v.column("v").to_numpy(), comp_of_vertices=v.column("comp").to_numpy(), threads=threads)
        return pa.table({"comp": pa.array(comp, pa.int64()), "v": pa.array(ids, pa.int64()), "place": pa.array(place, pa.int64())})

    done = edges.groupBy("k").cogroup(own.groupBy("k")).applyInArrow(run, "comp long, v long, place long")
    n = placed.count()
    return done.join(table, "comp").select("v", (F.lit(n - 1) - F.col("place") - F.col("base")).cast("long").alias("label"))


def gather_report(g: SymGraph, limit_edges: int = TASK_EDGES, threads: int = 1) -> dict:
    """Seconds to gather the matrix in one task, to order it, and to deal the labels out again, with the outcome: ok or refused."""
    m, seconds = g.edges.count(), {"gather": None, "order": None, "scatter": None}
    if m > limit_edges:
        return {"status": "refused", "edges": m, **seconds}
    began = time.perf_counter()
    one = materialize(g.edges.coalesce(1), "gathered")
    seconds["gather"] = time.perf_counter() - began
    labels = materialize(gather_order(SymGraph(one, g.vertices), limit_edges, threads=threads).coalesce(1), "ordered")
    seconds["order"] = time.perf_counter() - began - seconds["gather"]
    materialize(labels.repartition("v"), "dealt")
    seconds["scatter"] = time.perf_counter() - began - seconds["gather"] - seconds["order"]
    return {"status": "ok", "edges": m, **{k: round(v, 3) for k, v in seconds.items()}}
