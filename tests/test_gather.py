from tests.test_core import graph, labels_of
from tests.test_large_results import SF

from bandspark import catalogue
from bandspark.operators import ordering
from bandspark.sources import workloads


def test_places_gathered_in_one_task_are_of_the_declared_type(spark):
    """Local places are 32 bits wide; the rows given back are declared with 64."""
    g = graph(spark, [(5, 6), (6, 8), (2, 3)], [7])
    want = labels_of(ordering.frontier_order(g).labels)
    got = ordering.gather_order(g)
    assert dict(got.dtypes) == {"v": "bigint", "label": "bigint"} and labels_of(got) == want


def test_gathered_orders_are_those_of_the_plans(spark):
    want = labels_of(ordering.frontier_order(workloads.graph(spark, SF, "w1"), plan="task").labels)
    for name in ("gather_w1", "order_threads_w1"):
        assert labels_of(catalogue.queries()[name](spark, SF)) == want
