import duckdb

from bandspark import catalogue
from bandspark.streaming import edges as streams

SF = "/root/testdata/sf0.001"


def by_sql(name, sf=SF):
    con = duckdb.connect()
    con.sql("SET TimeZone = 'UTC'")
    for t in ("part", "events"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return sorted(map(str, con.sql(catalogue.oracle_sql()[name]).fetchall()))


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_offsets_are_joined_without_a_broadcast(spark):
    got = catalogue.queries()["op_join_offsets"](spark, SF)
    assert "Broadcast" not in plan_of(got)
    assert sorted(str(tuple(r)) for r in got.collect()) == by_sql("op_join_offsets")


def test_theta_join_meets_cells_not_all_rows(spark):
    got = catalogue.queries()["op_join_theta"](spark, SF)
    assert "NestedLoop" not in plan_of(got) and "Cartesian" not in plan_of(got) and "Broadcast" not in plan_of(got)
    assert sorted(str(tuple(r)) for r in got.collect()) == by_sql("op_join_theta")


def test_sessions_are_files_and_all_of_them(spark, tmp_path):
    got = catalogue.queries()["op_stream_session"](spark, SF)
    assert got.inputFiles()  # not rows held by the driver
    assert sorted(str(tuple(r)) for r in got.collect()) == by_sql("op_stream_session")
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.repartition(5).write.parquet(f"{tmp_path}/events.parquet")  # files in any order of time
    assert sorted(map(tuple, streams.sessions(spark, str(tmp_path)).collect())) == sorted(map(tuple, got.collect()))
