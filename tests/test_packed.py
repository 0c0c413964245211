import numpy as np

from bandspark.model import SymGraph
from bandspark.operators import ordering, peripheral, serial
from bandspark.operators.serial import Columns
from bandspark.operators.sweep import Sweeper
from bandspark.sources import workloads

SF = "/root/testdata/sf0.001"


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_pairs_are_worked_out_once(spark):
    seen = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    pairs = spark.createDataFrame([(1, 2), (2, 1), (1, 2), (2, 3), (7, 7), (3, 3), (None, 4)], "a long, b long").mapInArrow(count, "a long, b long")
    g = SymGraph.from_pairs(pairs, spark.createDataFrame([(9,), (1,)], "v long"))
    assert rows(g.vertices) == [(1, 1), (2, 2), (3, 1), (7, 0), (9, 0)]
    assert rows(g.edges) == [(1, 2), (2, 1), (2, 3), (3, 2)]
    assert seen.value == 7


def test_rows_some_places_apart_are_ranked_by_ranges(spark):
    for w in workloads.STEPPED:
        workloads.register(spark, SF)
        want = rows(spark.sql(workloads.spark_sql(w)).select("a", "b"))
        assert rows(workloads.pairs(spark, SF, w)) == want
        table, key, time, steps = workloads.STEPPED[w]
        few = spark.read.parquet(f"{SF}/{table}.parquet").selectExpr(f"{key} AS k", f"{time} AS t")
        assert rows(workloads.stepped(few, steps, block=1)) == want  # blocks as short as the longest step


def test_narrow_and_wide_frontiers_agree(monkeypatch):
    p = np.random.default_rng(3).permutation(500)
    for steps in ((1, 50), (1, 2, 3), (1, 7, 90)):
        keys = np.concatenate([x for s in steps for x in (p[:-s] << 32 | p[s:], p[s:] << 32 | p[:-s])])
        found = []
        for narrow in (0, 16, 500):
            monkeypatch.setattr(serial, "NARROW", narrow)
            g, level = Columns.packed(np.arange(500), keys.copy()), np.full(500, -1, np.int32)
            root, *rest, cut = g.search(5, "classic", "min_degree", level)
            found.append((root, *rest, cut.tolist(), level.tolist(), *(g.order(root, s).tolist() for s in ("degree", "parent", "level", "end")), g.order(root, threads=3).tolist()))
        assert found[0] == found[1] == found[2] and found[0][-1] == found[0][-5]
        assert g.rows.dtype == np.int32


def test_searches_in_tasks_are_those_of_the_sweeps(spark):
    g = workloads.graph(spark, SF, "w7")
    placed = ordering.with_components(g)
    starts = placed.selectExpr("comp", "comp AS v").distinct()
    want = [rows(x) for x in peripheral.search(Sweeper(g, placed).levels, g.vertices, starts)]
    typical = placed.groupBy("comp").sum("deg").agg({"sum(deg)": "avg"}).first()[0]
    for bound in (10**6, int(typical)):  # all in tasks; some swept
        roots, levels = ordering.searched(g, placed, task_edges=bound)
        assert [rows(roots.select("comp", "root", "depth", "searches", "hop")), rows(levels)] == want
