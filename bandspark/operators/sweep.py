"""Distributed sweeps over the primitives: level structures and orderings of graphs of any depth.

A level is one sparse product and one filter (:func:`primitives.spmspv`, :func:`primitives.select_unset`), all components in lockstep; a
new vertex can only have been met in the last two levels. Edges are written once in buckets of their source, so that a level shuffles its frontier and not the edges.

Deep graphs: a level costs a job or two whatever its size, so small levels are fused.
* Levels: a sweep ends with the last vertex. After ``sync_levels`` levels, what lies beyond a small frontier is looked at: of each component, the vertices not met yet and their edges.
  Rests of at most ``fuse_edges`` edges (``task_edges`` if that is more) are searched in tasks, packed into lots. Larger ones are found by relaxation inside clusters (sets of vertices
  of at most about ``fuse_edges`` edges, grown along edges), as far as it goes in each, then across them. Rounds follow the clusters a shortest path crosses, not its length.
* Labels: edges that lead one level down are laid out by step. Consecutive levels of a component deeper than ``sync_levels`` are one step as long as
  their edges are at most about ``fuse_edges``, and one task orders them; a larger level is a step of its own, ranked by :func:`ranking.sort_rank`.
Both give what the level-by-level sweep gives.
"""

from __future__ import annotations

from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bandspark.model import SymGraph
from bandspark.operators.primitives import scatter_new, select_unset, spmspv
from bandspark.operators.ranking import sort_rank
from bandspark.operators.serial import Columns
from bandspark.operators.traverse import relax_round
from bandspark.session import Steps, arrow_rows, materialize, new_folder

#: Levels that are always swept one by one; directed edges of a run of levels, or of a cluster, that one task takes.
SYNC_LEVELS, FUSE_EDGES = 5, 1_000_000
#: A frontier is small, and what lies beyond it left to the clusters, at a vertex for so many edges of a run.
SMALL = 10
#: Directed edges of one bucket of the edge table.
BUCKET_EDGES = 4_000_000
#: Edges of a lot of rests below which it is not worth a task of its own; packed rows (some 100 kB each) that go to Python at once, and rows of one batch that comes back.
_LOT, _PACKS, _BATCH = 100_000, 200, 100_000


def bucket_count(spark, count: int) -> int:
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-count // BUCKET_EDGES))


def bucketed(edges: DataFrame, count: int) -> DataFrame:
    """(src, dst) as a table bucketed and sorted by src: joins on src need no shuffle of it."""
    spark = edges.sparkSession
    buckets = bucket_count(spark, count)
    path = new_folder(spark, "edges")
    name = "bandspark_" + path.rsplit("-", 1)[-1]
    edges.select("src", "dst").repartition(buckets, "src").write.bucketBy(buckets, "src").sortBy("src", "dst").option("path", path).format("parquet").saveAsTable(name)
    return spark.table(name)


def prefix_sums(rows: DataFrame, key: str, value: str, name: str = "before") -> DataFrame:
    """Adds the sum of ``value`` over all rows of smaller ``key`` (which tells rows apart): sums inside sampled ranges, plus those of the ranges before."""
    parts = materialize(rows.repartitionByRange(key).withColumn("_p", F.spark_partition_id()), "prefix")
    upto = Window.partitionBy("_p").orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
    totals = parts.groupBy("_p").agg(F.sum(value).alias("_t"))
    shift = totals.select("_p", F.coalesce(F.sum("_t").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_b"))
    out = parts.withColumn("_i", F.coalesce(F.sum(value).over(upto), F.lit(0))).join(shift, "_p")
    return out.withColumn(name, (F.col("_i") + F.col("_b")).cast("long")).drop("_p", "_i", "_b")


def clusters(edges: DataFrame, weights: DataFrame, most: int, rounds: int = 16) -> DataFrame:
    """(v, cluster) for (v, weight): vertices merged along edges while a cluster weighs at most ``most``.

    Each round every cluster moves to the one of lowest seeded priority among itself and its neighbours; a meeting that would weigh too much does not take place."""
    homes = weights.select("v", F.col("v").alias("cluster"), "weight")
    links = edges.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    for r in range(rounds):
        prior = lambda c: F.struct(F.xxhash64(c, F.lit(r)).alias("h"), F.col(c).alias("c"))  # noqa: E731, B023
        low = links.groupBy("a").agg(F.min(prior("b")).alias("m")).select(F.col("a").alias("cluster"), F.least("m", prior("a")).getField("c").alias("to"))
        sizes = homes.groupBy("cluster").agg(F.sum("weight").alias("w")).join(low, "cluster", "left").withColumn("to", F.coalesce("to", "cluster"))
        sizes = materialize(sizes, "cluster-moves")
        fit = sizes.groupBy("to").agg(F.sum("w").alias("sum"), F.count("*").alias("n")).where(f"sum <= {most} and n > 1").select("to")
        moves = materialize(sizes.join(fit, "to", "left_semi").where("to <> cluster").select("cluster", "to"), "cluster-moves")
        if moves.isEmpty():
            if r:
                break
            continue
        moved = homes.join(moves, "cluster", "left")
        homes = materialize(moved.select("v", F.coalesce("to", "cluster").alias("cluster"), "weight"), "clusters")
        ends = links.join(moves.withColumnsRenamed({"cluster": "a", "to": "ta"}), "a", "left").join(moves.withColumnsRenamed({"cluster": "b", "to": "tb"}), "b", "left")
        links = materialize(ends.select(F.coalesce("ta", "a").alias("a"), F.coalesce("tb", "b").alias("b")).where("a <> b").distinct(), "cluster-links")
        if links.isEmpty():
            break
    return homes.select("v", "cluster")


class Sweeper:
    """A graph prepared for sweeps. ``placed``: (v, deg, comp) of all vertices; ``task_edges``: packed edges that one task may hold."""

    def __init__(self, g: SymGraph, placed: DataFrame, sync_levels: int = SYNC_LEVELS, fuse_edges: int = FUSE_EDGES, task_edges: int = 0):
        self.spark, self.placed, self.sync, self.fuse, self.most = g.edges.sparkSession, placed, sync_levels, fuse_edges, max(fuse_edges, task_edges)
        self.n_edges = g.edges.count()
        self.buckets = bucket_count(self.spark, self.n_edges)
        self.edges = bucketed(g.edges, self.n_edges)

    # -- levels ---------------------------------------------------------------------------------------
    @cached_property
    def _sizes(self) -> DataFrame:
        """comp, n, w (directed edges). One row a component."""
        return materialize(self.placed.groupBy("comp").agg(F.count("*").alias("n"), F.sum("deg").alias("w")), "bin-sizes")

    @cached_property
    def _homes(self) -> DataFrame:
        """(v, bin): small components packed whole, clusters of large ones likewise, about ``fuse`` directed edges a bin."""
        large = materialize(self._sizes.where(F.col("w") > self.fuse).select("comp"), "bin-large")
        homes = self.placed.join(large, "comp", "left_anti").select("v", F.col("comp").alias("cluster"), "deg")
        if not large.isEmpty():
            own = self.placed.join(large, "comp", "left_semi").select("v", F.col("deg").alias("weight"))
            found = clusters(self.edges.join(own.select(F.col("v").alias("src")), "src", "left_semi"), own, self.fuse)
            homes = homes.unionByName(found.join(own, "v").select("v", "cluster", F.col("weight").alias("deg")))
        homes = materialize(homes, "bin-homes")
        packed = prefix_sums(homes.groupBy("cluster").agg(F.sum("deg").alias("w")), "cluster", "w")
        return materialize(homes.join(packed.select("cluster", F.floor(F.col("before") / self.fuse).alias("bin")), "cluster").select("v", "bin"), "bins")

    @cached_property
    def _binned(self) -> DataFrame:
        """Edges with the bin of src, and whether dst lies in it too."""
        out = self.edges.join(self._homes.withColumnsRenamed({"v": "src"}), "src").join(self._homes.withColumnsRenamed({"v": "dst", "bin": "other"}), "dst")
        return materialize(out.select("src", "dst", "bin", (F.col("bin") == F.col("other")).cast("long").alias("inside")), "binned")

    def levels(self, roots: DataFrame) -> DataFrame:
        """(comp, v, level) from roots (comp, v), one in each component that takes part."""
        steps = Steps(self.spark, "levels")
        last = steps.put(roots.select("comp", "v", F.lit(0).alias("level")))
        total = self._sizes.join(last.select("comp"), "comp", "left_semi").agg(F.sum("n")).first()[0] or 0
        seen, k, met = last.select("v"), 0, last.count()
        while met < total:
            k += 1
            near = select_unset(spmspv(self.edges, last.select("v", F.col("comp").alias("x"))), seen)
            near = steps.put(near.select(F.col("x").alias("comp"), "v", F.lit(k).alias("level")))
            count = near.count()
            met += count
            if k >= self.sync and SMALL * count <= self.fuse and met < total:
                self._beyond(steps, near, k)
                break
            seen, last = last.select("v").unionByName(near.select("v")), near
        return steps.all()

    def _beyond(self, steps: Steps, last: DataFrame, k: int) -> None:
        """Appends all levels past ``last``, which is level ``k``."""
        found = steps.all()
        rest = self.placed.join(last.select("comp").distinct(), "comp", "left_semi").join(found.select("v"), "v", "left_anti")
        rest = materialize(rest.select("comp", "v", "deg"), "rest")
        loads = materialize(rest.groupBy("comp").agg(F.sum("deg").alias("w")), "rest-loads")
        small, large = loads.where(F.col("w") <= self.most), loads.where(F.col("w") > self.most)
        if weight := small.agg(F.sum("w")).first()[0]:
            if 2 * weight >= self.n_edges and small.join(self._sizes.where(F.col("w") > self.most), "comp", "left_semi").isEmpty():  # nearly all is left: whole components, packed once for all searches
                packs, known = self._wholes, found
            else:
                into = last.join(small, "comp", "left_semi").select("comp", "v", F.lit(False).alias("open"))
                packs, known = self._packed(rest.join(small, "comp", "left_semi").select("comp", "v", F.lit(True).alias("open")).unionByName(into), small, weight), last
            steps.put(self._outwards(*packs, known, k))
        if not large.isEmpty():
            own = lambda df: df.join(large.select("comp"), "comp", "left_semi")
            steps.put(self._relaxed(own(found), own(last)).where(F.col("level") > k))

    @cached_property
    def _wholes(self) -> tuple[DataFrame, DataFrame, int]:
        """The packs of all components that a task may hold."""
        table = self._sizes.where(F.col("w") <= self.most)
        return self._packed(self.placed.join(table, "comp", "left_semi").select("comp", "v", F.lit(True).alias("open")), table, table.agg(F.sum("w")).first()[0])

    def _packed(self, vertices: DataFrame, loads: DataFrame, weight: int) -> tuple[DataFrame, DataFrame, int]:
        """(vertices (lot, v, no), packs (lot, kind, data), number of lots) of vertices (comp, v, open) and the edges from them to open ones.

        Components (comp, w) go to lots of at most about the edges of a task, and of as few as keep all cores busy.
        Packs hold whole numbers: kind 0 numbers, ids and components of vertices, kind 1 edges between numbers, ``src << 32 | dst`` each."""
        lot = min(self.most, max(_LOT, weight // (2 * int(self.spark.conf.get("spark.sql.shuffle.partitions")))))
        lots = materialize(prefix_sums(loads.select("comp", "w"), "comp", "w").select("comp", F.floor(F.col("before") / lot).cast("int").alias("lot")), "pack-lots")
        ranked = materialize(sort_rank(vertices.join(lots, "comp").select("lot", "comp", "v", "open"), ["lot", "v"], "general"), "pack-ranks")
        first = ranked.groupBy("lot").agg(F.min("rank").alias("first"))
        numbered = materialize(ranked.join(F.broadcast(first), "lot").select("lot", "comp", "v", "open", (F.col("rank") - F.col("first")).alias("no")), "pack-vertices")  # a row a lot
        near = self.edges.join(numbered.select(F.col("v").alias("src"), "lot", F.shiftleft("no", 32).alias("high")), "src").select("dst", "lot", "high")
        ends = self._dealt(near).join(numbered.where("open").select(F.col("v").alias("dst"), "no"), "dst")
        keys = ends.select("lot", F.col("high").bitwiseOR(F.col("no")).alias("key"))
        packs = materialize(_blocks(numbered, 0, "no", "v", "comp").unionByName(_blocks(keys, 1, "key")), "packs")
        return numbered.select("lot", "v", "no"), packs, lots.agg(F.max("lot")).first()[0] + 1

    def _dealt(self, rows: DataFrame) -> DataFrame:
        """Rows as many as edges by dst, in parts as small as the buckets of the edges."""
        return rows.repartition(self.buckets, "dst")

    def _outwards(self, numbered: DataFrame, packs: DataFrame, count: int, found: DataFrame, k: int) -> DataFrame:
        """(comp, v, level) past level ``k`` of the packs; ``found``: (comp, v, level) of all their vertices that have a level."""
        seeds = found.select("v", F.col("level").cast("long").alias("level")).join(numbered.select("v", "lot", "no"), "v")
        rows = packs.unionByName(_blocks(seeds, 2, "no", "level")).repartitionById(count, F.col("lot"))
        with arrow_rows(self.spark, _PACKS):
            return materialize(rows.select("kind", "data").mapInArrow(_levels_past(k), "comp long, v long, level int"), "rest-levels")

    def _relaxed(self, found: DataFrame, last: DataFrame) -> DataFrame:
        """All levels from those found so far, ``last`` being the deepest of them."""
        state = found.select("v", F.col("level").cast("long").alias("level"))
        seeds = materialize(last.select("v", F.col("level").cast("long").alias("level")).join(self._homes, "v"), "relax-seeds")
        while not seeds.isEmpty():
            state, seeds = relax_round(self._binned, self._homes, state, seeds)
        return materialize(state.join(self.placed.select("v", "comp"), "v").select("comp", "v", F.col("level").cast("int").alias("level")), "levels")

    # -- labels: levels known -------------------------------------------------------------------------
    def _plan(self, levels: DataFrame, bases: DataFrame) -> tuple[DataFrame, DataFrame]:
        """Of every level but the roots': step, fused, bin, start (its first label), and for levels of their own ``shift`` and ``low``: what turns a parent's label into its
        place in the frontier of the step, and a rank into a place in the component's level. With them the edges that lead one level down."""
        at = levels.join(self.placed.select("v", "deg"), "v")
        near = self.edges.join(at.select(F.col("v").alias("src"), F.col("level").alias("l0")), "src")
        down = self._dealt(near).join(at.select(F.col("v").alias("dst"), "comp", "deg", "level"), "dst").where("level = l0 + 1")
        down = materialize(down.select("comp", "level", "src", "dst", "deg"), "down")
        own = Window.partitionBy("comp").orderBy("level")
        before = own.rowsBetween(Window.unboundedPreceding, -1)
        sizes = levels.groupBy("comp", "level").agg(F.count("*").alias("n")).join(down.groupBy("comp", "level").agg(F.count("*").alias("e")), ["comp", "level"], "left")
        sizes = sizes.withColumns({"e": F.coalesce("e", F.lit(0)), "first": F.coalesce(F.sum("n").over(before), F.lit(0)), "upto": F.coalesce(F.sum("e").over(before), F.lit(0)), "depth": F.max("level").over(Window.partitionBy("comp")), "above": F.lag("n").over(own)})
        big = (F.col("e") > self.fuse) | (F.col("depth") <= self.sync)
        sizes = sizes.withColumns({"big": big, "lot": F.floor(F.col("upto") / self.fuse)})
        cut = (F.col("level") > 0) & (F.col("big") | (F.col("level") == 1) | F.lag("big").over(own) | (F.lag("lot").over(own) != F.col("lot")))
        sizes = sizes.withColumn("step", F.sum(cut.cast("int")).over(own.rowsBetween(Window.unboundedPreceding, 0))).join(bases.select("comp", "base"), "comp").where("level > 0")
        sizes = materialize(sizes.select("comp", "level", "step", (~F.col("big")).alias("fused"), "e", "n", "above", (F.col("first") + F.col("base")).alias("start")), "sweep-levels")
        runs = sizes.groupBy("step", "comp", "fused").agg(F.sum("e").alias("e"), F.sum("n").alias("n"), F.sum("above").alias("above"), F.max("level").alias("till"))
        mine = Window.partitionBy("step", "fused").orderBy("comp").rowsBetween(Window.unboundedPreceding, -1)  # a row a component
        runs = runs.select("step", "comp", "till", F.floor(F.coalesce(F.sum("e").over(mine), F.lit(0)) / self.fuse).alias("bin"), F.coalesce(F.sum("n").over(mine), F.lit(0)).alias("low"), F.coalesce(F.sum("above").over(mine), F.lit(0)).alias("place"))
        plan = sizes.join(runs, ["step", "comp"]).select("comp", "level", "step", "fused", "bin", "start", "low", (F.col("place") - F.col("start") + F.col("above")).alias("shift"), (F.col("level") == F.col("till")).alias("ends"), "n", "above")
        plan = materialize(plan, "sweep-plan")
        return plan, materialize(down.join(plan.drop("n", "above"), ["comp", "level"]), "sweep-edges", ["step"])

    def labels(self, levels: DataFrame, bases: DataFrame, strategy: str = "bucket", sort: str = "degree") -> DataFrame:
        """(comp, v, label), forward, from levels (comp, v, level) and bases (comp, base): vertices by level, then by smallest parent label, degree, id."""
        if sort in ("level", "end"):  # one sort of all vertices, with no parents: the level, then degree or not, then id
            rows = levels.join(bases.select("comp"), "comp", "left_semi").join(self.placed.select("v", "deg"), "v").join(bases.select("comp", "base"), "comp")
            ranked = sort_rank(rows, ["base", "level", *(["deg"] if sort == "end" else []), "v"], "single" if strategy == "single" else "general")
            lows = materialize(ranked, "sorted")
            own = lows.groupBy("comp").agg(F.min("rank").alias("low"))
            return lows.join(own, "comp").select("comp", "v", (F.col("rank") - F.col("low") + F.col("base")).cast("long").alias("label"))
        keys = {"degree": ["x", "deg", "v"], "parent": ["x", "v"]}[sort]
        plan, down = self._plan(levels, bases)
        totals = {r["step"]: r for r in plan.groupBy("step").agg(F.sum(F.when(~F.col("fused"), F.col("above"))).alias("span"), F.sum(F.when(~F.col("fused"), F.col("n"))).alias("n"), F.max(F.col("fused").cast("int")).alias("fused")).collect()}  # a row a step
        steps = Steps(self.spark, "sweep")
        roots = levels.where("level = 0").join(bases.select("comp", "base"), "comp")
        last = steps.put(roots.select("comp", "v", F.col("base").cast("long").alias("label"), F.lit(True).alias("ends")))
        for k in range(1, max(totals, default=0) + 1):
            here, parts, t = down.where(F.col("step") == k), [], totals[k]
            entering = last.where("ends")
            if t["span"]:
                x = entering.select("v", F.col("label").alias("x"))
                kids = spmspv(here.where("not fused"), x, carry=("comp", "deg", "start", "low", "shift")).withColumn("x", F.col("x") + F.col("shift"))
                kids = materialize(kids, "sweep-kids")
                ranked = sort_rank(kids, keys, strategy, 0, t["span"], count=t["n"])
                parts.append(ranked.select("comp", "v", (F.col("rank") - F.col("low") + F.col("start")).cast("long").alias("label"), F.lit(True).alias("ends")))
            if t["fused"]:
                bins = plan.where((F.col("step") == k) & F.col("fused")).select("comp", "bin").distinct()
                own = here.where("fused").select("bin", "comp", "level", "src", "dst", "deg", "start", "ends")
                into = entering.join(bins, "comp").select(F.col("bin").alias("bin"), "v", "label")
                parts.append(own.groupBy("bin").cogroup(into.groupBy("bin")).applyInArrow(_by_degree if sort == "degree" else _by_parent, "comp long, v long, label long, ends boolean"))
            done = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
            last = steps.put(done)
        return steps.all().select("comp", "v", "label")

    # -- labels: levels and labels in one sweep -------------------------------------------------------
    def algebraic(self, roots: DataFrame, bases: DataFrame, strategy: str = "bucket", sort: str = "degree") -> tuple[DataFrame, DataFrame]:
        """((comp, v, label) forward, (comp, v, level)) from roots (comp, v): the loop of product, filter, sort and scatter, without levels known before."""
        keys = {"degree": ["x", "deg", "v"], "parent": ["x", "v"]}[sort]
        labels = Steps(self.spark, "algebraic")
        last = labels.put(prefix_ranks(roots.join(bases.select("comp", "base"), "comp").select("comp", "v", F.col("base").cast("long").alias("label"), F.lit(0).alias("level"))))
        labelled = materialize(last.select("comp", (F.col("label") + 1).alias("nv")), "labelled")
        seen, size, k = last.select("v"), last.count(), 0
        while True:
            k += 1
            near = select_unset(spmspv(self.edges, last.select("v", F.col("rank").alias("x"))), seen)
            near = materialize(near.join(self.placed, "v"), "algebraic-next")
            count = near.count()
            if not count:
                return labels.all().select("comp", "v", "label"), labels.all().select("comp", "v", "level")
            ranked = sort_rank(near, keys, strategy, 0, size, count=count)
            own = near.groupBy("comp").agg(F.count("*").alias("n"))
            lows = prefix_sums(own, "comp", "n", "low").join(labelled, "comp")
            now = ranked.join(lows.select("comp", "low", "nv"), "comp").select("comp", "v", (F.col("rank") - F.col("low") + F.col("nv")).alias("label"), F.lit(k).alias("level"), "rank")
            before, last = last, scatter_new(labels, now)
            labelled = materialize(lows.select("comp", (F.col("nv") + F.col("n")).alias("nv")), "labelled")
            seen, size = before.select("v").unionByName(last.select("v")), count


def _blocks(rows: DataFrame, kind: int, *columns: str) -> DataFrame:
    """(lot, kind, data): whole numbers of rows that have a lot, column after column, a batch of one lot each."""

    def run(batches):
        for batch in batches:
            lot = batch.column("lot").to_numpy()
            order = np.argsort(lot, kind="stable")
            lot = lot[order]
            cut = np.flatnonzero(np.diff(lot, prepend=-1, append=-1)).tolist()
            cols = [batch.column(c).to_numpy()[order] for c in columns]
            data = [np.concatenate([c[a:b] for c in cols]).tobytes() for a, b in zip(cut, cut[1:])]
            if data:
                yield pa.RecordBatch.from_arrays([pa.array(lot[cut[:-1]]), pa.array(np.full(len(data), kind, np.int32)), pa.array(data, pa.binary())], names=["lot", "kind", "data"])

    return rows.select("lot", *columns).mapInArrow(run, "lot int, kind int, data binary")


def _levels_past(k: int):
    """Levels of the vertices of a lot that have none, outwards from those of level ``k``; see :meth:`Sweeper._packed`, kind 2 being numbers and levels known."""

    def run(batches):
        got: tuple[list, list, list] = ([], [], [])
        for batch in batches:
            for kind, data in zip(batch.column("kind").to_pylist(), batch.column("data")):
                got[kind].append(np.frombuffer(data.as_buffer(), np.int64).copy())
        n = sum(len(x) for x in got[0]) // 3
        ids, comp, level, keys, done = np.empty(n, np.int64), np.empty(n, np.int64), np.full(n, -1, np.int32), np.empty(sum(map(len, got[1])), np.int64), 0
        for no, v, c in (x.reshape(3, -1) for x in got[0]):
            ids[no], comp[no] = v, c
        for no, far in (x.reshape(2, -1) for x in got[2]):
            level[no] = far
        got[0].clear()
        while got[1]:  # each goes when it is copied
            block = got[1].pop()
            keys[done : done + len(block)] = block
            done += len(block)
        first = np.flatnonzero(level == k)
        if not len(first):
            return
        new = Columns.packed(ids, keys).levels(first, level, k)[0][len(first) :]
        for a in range(0, len(new), _BATCH):
            at = new[a : a + _BATCH]
            yield pa.RecordBatch.from_arrays([pa.array(comp[at]), pa.array(ids[at]), pa.array(level[at])], names=["comp", "v", "level"])

    return run


def prefix_ranks(rows: DataFrame) -> DataFrame:
    """Adds ``rank``: the place by label, of one row a component."""
    one = prefix_sums(rows.withColumn("_one", F.lit(1)), "label", "_one", "rank")
    return one.drop("_one")


def _fused(e: pa.Table, d: pa.Table, by_degree: bool) -> pa.Table:
    """Labels of a run of levels of several components, from the labels of the vertices that lead into it."""
    if not e.num_rows:
        return pa.table({"comp": pa.array([], pa.int64()), "v": pa.array([], pa.int64()), "label": pa.array([], pa.int64()), "ends": pa.array([], pa.bool_())})
    comp, level, src, dst, deg, start = (e.column(c).to_numpy() for c in ("comp", "level", "src", "dst", "deg", "start"))
    ends = e.column("ends").to_numpy(zero_copy_only=False)
    ids = np.unique(np.concatenate([src, dst, d.column("v").to_numpy()]))
    label = np.full(len(ids), -1)
    label[np.searchsorted(ids, d.column("v").to_numpy())] = d.column("label").to_numpy()
    s, t = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    order = np.argsort(level, kind="stable")
    cut = np.flatnonzero(np.diff(level[order], prepend=-1, append=-1))
    rows = []
    for a, b in zip(cut[:-1].tolist(), cut[1:].tolist()):
        at = order[a:b]
        p = label[s[at]]
        at, p = (x[np.lexsort((p, t[at]))] for x in (at, p))
        first = np.concatenate([[True], t[at][1:] != t[at][:-1]])
        at, p = at[first], p[first]
        at = at[np.lexsort((t[at], deg[at], p) if by_degree else (t[at], p))]  # parents' labels grow with components, which so stay together
        own = comp[at]
        head = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]]))
        place = np.arange(len(at)) - np.repeat(head, np.diff(np.append(head, len(at))))
        label[t[at]] = start[at] + place
        rows.append(at)
    at = np.concatenate(rows)
    return pa.table({"comp": pa.array(comp[at]), "v": pa.array(dst[at]), "label": pa.array(label[t[at]]), "ends": pa.array(ends[at].astype(bool))})


def _by_degree(e: pa.Table, d: pa.Table) -> pa.Table:
    return _fused(e, d, True)


def _by_parent(e: pa.Table, d: pa.Table) -> pa.Table:
    return _fused(e, d, False)
