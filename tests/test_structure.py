import threading

from tests.test_large_results import SF

from bandspark import catalogue


def test_graphs_of_the_table_are_worked_on_at_once(spark, monkeypatch):
    """Two lines are begun before either is done, with the caller's settings and none of their own left in it."""
    real, both = catalogue.metrics_of, threading.Barrier(2)
    before = dict(spark.conf.getAll)

    def begun(session, sf_dir, w):
        both.wait(100)
        assert session is not spark and dict(session.conf.getAll) == before
        return real(session, sf_dir, w)

    monkeypatch.setattr(catalogue, "metrics_of", begun)
    got = catalogue.structure_table(spark, SF, ("w12", "w4"))
    assert dict(spark.conf.getAll) == before
    rows = got.collect()
    assert [r.graph for r in rows] == ["w12", "w4"] and got.dtypes == real(spark, SF, "w4").dtypes
    assert rows[1] == real(spark, SF, "w4").first()
