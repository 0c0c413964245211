import random

import duckdb
import numpy as np
import pyarrow as pa
import pytest

from bandspark.operators import knn
from bandspark.sources import workloads


def nearest_by_sql(ids, vectors, k):
    embeddings = pa.table({"vec_id": pa.array(ids, pa.int64()), "embedding": pa.array(vectors, pa.list_(pa.float32()))})  # noqa: F841  DuckDB reads it
    return sorted(duckdb.sql(workloads.duck_sql("w10").replace("r <= 8", f"r <= {k}")).fetchall())


def nearest(spark, ids, vectors, k, block):
    df = spark.createDataFrame(list(zip(ids, vectors)), "i long, v array<float>")
    return sorted(tuple(r) for r in knn.nearest(df, k, block).collect())


@pytest.mark.parametrize("block", [7, 64])
def test_tiles_give_the_nearest_of_all_pairs(spark, block):
    r = np.random.default_rng(5)
    x = r.normal(size=(90, 6)).astype(np.float32)
    x[20:50] = x[20]  # more copies than neighbours: ties by id
    x[60:70] = x[60] + np.float32(1e-7) * r.normal(size=(10, 6)).astype(np.float32)  # nearer to each other than rounding tells apart
    ids = random.Random(1).sample(range(1000), 90)
    assert nearest(spark, ids, x.tolist(), 4, block) == nearest_by_sql(ids, x.tolist(), 4)


def test_vectors_unlike_the_others(spark):
    vectors = [[0.0, 1.0], [2.0, 1.0], [3.0, None], None, [5.0, 5.0], [float("inf"), 0.0], [1.0, 1.0], [0.0, 0.5]]
    ids = list(range(len(vectors)))
    assert nearest(spark, ids, vectors, 2, 2) == nearest_by_sql(ids, vectors, 2)
    assert nearest(spark, [*ids, None], [*vectors, [0.0, 0.0]], 7, 4) == nearest_by_sql(ids, vectors, 7)
    assert nearest(spark, [], [], 2, 2) == []
    assert nearest(spark, [3], [[1.0]], 2, 2) == []


def test_w10_meets_no_pair_in_sql(spark):
    got = workloads.pairs(spark, "/root/testdata/sf0.001", "w10")
    assert "zip_with" not in got._jdf.queryExecution().toString()
    workloads.register(spark, "/root/testdata/sf0.001", ["embeddings"])
    assert sorted(got.collect()) == sorted(spark.sql(workloads.spark_sql("w10")).collect())
