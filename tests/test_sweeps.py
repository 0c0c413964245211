import pytest
from pyspark.sql import functions as F
from tests.test_core import MINI, SF, graph, labels_of

from bandspark import experiments
from bandspark.operators import distribution, metrics, ordering, ranking, sweep, traverse
from bandspark.session import Steps, forget, materialize, written


def test_levels_of_a_deep_graph_by_clusters(spark):
    """A scrambled chain with chords: clusters of a few edges, found levels beyond two by relaxation, against one-task levels."""
    place = [(i * 37) % 101 for i in range(101)]
    g = graph(spark, [(place[i], place[i + 1]) for i in range(100)] + [(place[i], place[i + 3]) for i in range(0, 97, 5)])
    placed = ordering.with_components(g)
    s = sweep.Sweeper(g, placed, sync_levels=2, fuse_edges=40)
    got = {r.v: r.level for r in s.levels(spark.createDataFrame([(0, 0)], "comp long, v long")).collect()}
    want = traverse.levels_async(g.edges, spark.createDataFrame([(0,)], "v long"), 1)[0]
    assert got == {r.v: r.level for r in want.collect()} and max(got.values()) > 40
    sizes = g.vertices.join(s._homes, "v").groupBy("bin").agg(F.sum("deg").alias("w")).collect()
    assert len(sizes) > 3 and max(r.w for r in sizes) <= 3 * 40


def test_what_a_sweep_leaves_is_searched_in_tasks(spark, monkeypatch):
    """Four stars of paths, heavier than a task's run of edges: a few vertices are left past a small frontier, and no clusters are made of all edges for them."""
    pairs = [p for c in range(4) for i in range(30) for p in ((1000 * c, 1000 * c + 10 + i), (1000 * c + 10 + i, 1000 * c + 50 + i))]
    pairs += [(1000 * c + 50 + i, 1000 * c + 100 + i) for c in range(4) for i in range(c)] + [(1000 * c + 100, 1000 * c + 200) for c in range(1, 4)]
    g = graph(spark, pairs)
    placed = ordering.with_components(g)
    want = {(0, 0)} | {(r.v, r.level) for r in traverse.level_structure(g.edges, placed.selectExpr("comp", "comp AS v").distinct()).collect()}
    monkeypatch.setattr(sweep, "clusters", None)
    monkeypatch.setattr(sweep, "SMALL", 0)
    for sync in (1, 2, 3):
        s = sweep.Sweeper(g, placed, sync_levels=sync, fuse_edges=40, task_edges=40 if sync > 1 else 200)
        got = s.levels(placed.selectExpr("comp", "comp AS v").distinct()).collect()
        assert {(r.v, r.level) for r in got} == want and len(got) == len(want) and all(r.comp == r.v // 1000 * 1000 for r in got)


def test_what_is_deep_is_packed_once(spark, monkeypatch):
    """A chain and a ring, heavier than a run of edges but not than what a task holds: all searches read the same packs, and no clusters are made."""
    g = graph(spark, [(i, i + 1) for i in range(60)] + [(i, i + 7) for i in range(0, 50, 3)] + [(100 + i, 100 + (i + 1) % 40) for i in range(40)])
    want = labels_of(ordering.frontier_order(g, plan="task").labels)
    monkeypatch.setattr(sweep, "clusters", None)
    packed, real = [], sweep.Sweeper._packed
    monkeypatch.setattr(sweep.Sweeper, "_packed", lambda self, *a: packed.append(1) or real(self, *a))
    monkeypatch.setattr(sweep, "SMALL", 0)
    o = ordering.frontier_order(g, plan="sweep", sync_levels=2, fuse_edges=30)
    assert labels_of(o.labels) == want and max(r.searches for r in o.roots.collect()) > 1
    assert len(packed) == 1


def test_a_sweep_ends_with_the_last_vertex(spark, monkeypatch):
    g = graph(spark, [(0, 1), (1, 2), (10, 11), (20, 21), (21, 22)])
    placed, products = ordering.with_components(g), []
    monkeypatch.setattr(sweep, "spmspv", lambda *a, **o: products.append(1) or traverse.spmspv(*a, **o))
    got = sweep.Sweeper(g, placed).levels(spark.createDataFrame([(0, 0), (10, 11)], "comp long, v long"))
    assert sorted(map(tuple, got.collect())) == [(0, 0, 0), (0, 1, 1), (0, 2, 2), (10, 10, 1), (10, 11, 0)]
    assert len(products) == 2  # none for what lies past the last level, nor for components that take no part


def test_a_hub_is_split(spark):
    """10,000 children of one parent and a few of others: no part above the bound, and the order of one window."""
    rows = spark.range(10_000).select(F.lit(5).cast("long").alias("p"), (F.col("id") % 3).alias("deg"), F.col("id").alias("v"))
    rows = materialize(rows.unionByName(spark.range(20_000, 20_050).select((F.col("id") % 9).alias("p"), F.lit(1).cast("long").alias("deg"), F.col("id").alias("v"))), "hub")
    dealt = ranking._split_crowded(rows.withColumn("_part", F.col("p")), ["p", "deg", "v"], 1000)
    assert dealt.groupBy("_part").count().agg(F.max("count")).first()[0] <= 1500
    got, want = (ranking.sort_rank(rows, ["p", "deg", "v"], s, 0, 9, most_rows=1000) for s in ("bucket", "single"))
    assert sorted(map(tuple, got.select("v", "rank").collect())) == sorted(map(tuple, want.select("v", "rank").collect()))


def test_options_are_checked(spark):
    g = graph(spark, MINI)
    for wrong in ({"root": "clasic"}, {"plan": "tasks"}, {"sort": "none"}, {"strategy": "bucket sort"}, {"shrink": "last"}, {"tie_break": "x"}, {"components": "each"}, {"root": 99}, {"plan": "algebraic", "sort": "end"}):
        with pytest.raises(ValueError, match=r"."):
            ordering.frontier_order(g, **wrong)


def test_given_root_relabelled_ties_and_one_component_after_another(spark):
    g = graph(spark, [*MINI, (20, 21), (21, 22)], [30])
    given = ordering.frontier_order(g, 3)
    assert {r.comp: r.root for r in given.roots.collect()}[0] == 3
    assert labels_of(ordering.frontier_order(g, 3, "sweep").labels) == labels_of(given.labels)
    want = labels_of(ordering.frontier_order(g).labels)
    assert labels_of(ordering.frontier_order(g, components="sequential").labels) == want
    other = ordering.frontier_order(g, tie_break="relabelled")
    assert sorted(labels_of(other.labels).values()) == list(range(12)) and {r.comp for r in other.roots.collect()} == {0, 20, 30}
    assert metrics.quality(g.edges, other.labels).first().bandwidth <= 4


def test_gathering_keeps_isolated_vertices_and_says_what_came_of_it(spark):
    g = graph(spark, [(2, 3), (5, 6), (6, 8)], [7, 9])
    want = labels_of(ordering.frontier_order(g).labels)
    assert set(want) == {2, 3, 5, 6, 7, 8, 9}
    assert labels_of(ordering.gather_order(g)) == want == labels_of(ordering.single_node_order(g, 3))
    assert ordering.gather_report(g)["status"] == "ok" and ordering.gather_report(g, 2)["status"] == "refused"


def test_grid_product_and_membership(spark):
    g = graph(spark, MINI)
    x = spark.createDataFrame([(1, 2), (4, 1)], "v long, x long")
    blocked = distribution.distribute_2d(g.edges, 2, 3)
    plain = sorted(map(tuple, distribution.spmspv_2d(blocked, x).collect()))
    assert plain == sorted(map(tuple, distribution.spmspv_2d(blocked, x, 3).collect()))
    labels = ordering.natural_order(g)
    inside = set(map(tuple, metrics.envelope_pairs(g.edges, labels).collect()))
    every = spark.range(8).select(F.col("id").alias("i")).crossJoin(spark.range(8).select(F.col("id").alias("j")))
    assert {(r.i, r.j) for r in metrics.in_envelope(g.edges, labels, every).collect() if r.inside} == inside


def test_stages_are_forgotten(spark):
    mark = written()
    s = Steps(spark, "forgotten")
    s.put(spark.range(3))
    s.put(spark.range(3, 5))
    assert sorted(r.id for r in s.all().collect()) == list(range(5))
    forget(spark, mark)
    assert written() == mark
    with pytest.raises(Exception, match=r"(?i)not.*exist|found"):
        s.all().count()


@pytest.mark.parametrize(("name", "options"), [("costs", {}), ("sorts", {"w": "w1"}), ("product_split", {"names": ("w1",), "parts": (4,)}), ("phases", {"w": "w12"}), ("gather", {"w": "w12"}), ("layouts", {"w": "w12"}), ("hybrid", {"w": "w12", "parts": (2, 4)})])
def test_experiments(spark, name, options):
    import pathlib

    if not pathlib.Path(SF).exists():
        pytest.skip("no test tables")
    rows = list(experiments.EXPERIMENTS[name](spark, SF, **options))
    assert rows and all(isinstance(r, dict) for r in rows)
    if name == "hybrid":
        assert all(r["same_labels"] for r in rows)
    if name == "layouts":
        assert len({r["checksum"] for r in rows}) == 1


def test_more_edges_than_a_task_holds_are_gathered_in_lots(spark):
    pairs = [(100 * c + i, 100 * c + i + 1) for c in range(6) for i in range(4)] + [(900, i) for i in range(901, 930)]
    g = graph(spark, pairs)
    want = labels_of(ordering.frontier_order(g, plan="task").labels)
    assert labels_of(ordering.gather_order(g, 8, above="lots")) == want  # components of 8 directed edges, and one of 58 that is swept
    assert labels_of(ordering.single_node_order(g, 3, 60, above="lots")) == want
