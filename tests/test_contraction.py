import random

from tests.test_core import graph

from bandspark import model
from bandspark.model import SymGraph
from bandspark.operators import components
from bandspark.session import materialize


def test_copies_go_in_the_sort_of_the_edges(spark, monkeypatch):
    """One shuffle and one sort: no table of all pairs is hashed, and copies, loops and turned pairs go."""
    plans = []

    def kept(df, name="stage", **rest):
        plans.append((name, df._jdf.queryExecution().executedPlan().toString()))
        return materialize(df, name, **rest)

    monkeypatch.setattr(model, "materialize", kept)
    rnd = random.Random(2)
    pairs = [(rnd.randrange(40), rnd.randrange(40)) for _ in range(600)]
    g = SymGraph.from_pairs(spark.createDataFrame([*pairs, (None, 3)], "a long, b long").repartition(7))
    want = {p for a, b in pairs for p in ((a, b), (b, a)) if a != b}
    got = [tuple(r) for r in g.edges.select("src", "dst").collect()]
    assert set(got) == want and len(got) == len(want)
    assert sum(r.deg for r in g.vertices.collect()) == len(want)
    plan = dict(plans)["graph-edges"]
    assert "Aggregate" not in plan and plan.count("hashpartitioning") == 1


def test_chains_of_moves_are_gone_along_at_once(spark, monkeypatch):
    """Four rings with chords, contracted to the end: few rounds, and the components of one task."""
    written = []
    monkeypatch.setattr(components, "materialize", lambda df, name="stage", **rest: written.append(name) or materialize(df, name, **rest))
    pairs = [(1000 * c + i, 1000 * c + (i + k) % 200) for c in range(4) for i in range(200) for k in (1, 17)]
    g = graph(spark, pairs)
    for symmetric in (True, False):
        written.clear()
        got = components.connected_components(g.edges, tail_edges=0, symmetric=symmetric)
        assert {(r.v, r.comp) for r in got.collect()} == {(1000 * c + i, 1000 * c) for c in range(4) for i in range(200)}
        assert written.count("cc-edges") <= 4 + (not symmetric), written.count("cc-edges")
