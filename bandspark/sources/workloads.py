"""The experiment graphs on the given tables, as SQL that Spark and DuckDB both read.

Each text makes pairs (a, b). A side with small dense keys keeps them; other sides are shifted by multiples of 10**9.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bandspark.model import SymGraph
from bandspark.operators.knn import nearest
from bandspark.operators.ranking import sort_rank

B = 1_000_000_000
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

_ORDER_PART = f"SELECT DISTINCT l_orderkey AS a, {B} + l_partkey AS b FROM lineitem"
_RANKED_ORDERS = "SELECT o_orderkey AS k, row_number() OVER (ORDER BY o_orderdate, o_orderkey) AS r FROM orders"
_RANKED_EVENTS = "SELECT event_id AS k, row_number() OVER (ORDER BY ts, event_id) AS r FROM events"


def _steps(ranked: str, steps: tuple[int, ...]) -> str:
    ways = " UNION ALL ".join(f"SELECT x.k AS a, y.k AS b FROM t x JOIN t y ON y.r = x.r + {s}" for s in steps)
    return f"WITH t AS ({ranked}) {ways}"


_MESH = """WITH t AS (SELECT p_partkey AS k, p_partkey % 10 AS x, CAST(floor(p_partkey / 10) AS BIGINT) % 10 AS y, CAST(floor(p_partkey / 100) AS BIGINT) AS z FROM part),
d AS (SELECT 0 AS o UNION ALL SELECT 1 UNION ALL SELECT -1),
o AS (SELECT i.o AS dx, j.o AS dy, k.o AS dz FROM d i CROSS JOIN d j CROSS JOIN d k),
s AS (SELECT t.k, t.x + o.dx AS x, t.y + o.dy AS y, t.z + o.dz AS z FROM t CROSS JOIN o)
SELECT s.k AS a, t.k AS b FROM s JOIN t ON s.x = t.x AND s.y = t.y AND s.z = t.z WHERE s.k < t.k"""

GRAPHS: dict[str, str] = {
    "w1": f"SELECT DISTINCT l_partkey AS a, {B} + l_suppkey AS b FROM lineitem",
    "w2": _ORDER_PART,
    "w3": f"SELECT a, b FROM ({_ORDER_PART}) UNION ALL SELECT lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS a, o_orderkey AS b FROM orders",
    "w4": _MESH,
    "w5": _steps(_RANKED_ORDERS, (1, 50)),
    "w6": _steps(_RANKED_EVENTS, (1, 2, 3)),
    "w7": "SELECT lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS a, event_id AS b FROM events",
    "w8": f"SELECT o_custkey AS a, {B} + o_orderkey AS b FROM orders",
    "w9": f"""SELECT {5 * B} AS a, {4 * B} + r_regionkey AS b FROM region UNION ALL SELECT {4 * B} + n_regionkey, {3 * B} + n_nationkey FROM nation
UNION ALL SELECT {3 * B} + c_nationkey, {B} + c_custkey FROM customer UNION ALL SELECT {3 * B} + s_nationkey, {2 * B} + s_suppkey FROM supplier UNION ALL SELECT {B} + o_custkey, o_orderkey FROM orders""",
    "w11": "SELECT 1000 * conv_id + lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS a, 1000 * conv_id + turn AS b FROM conversations",
    "w12": "WITH t AS (SELECT DISTINCT l_orderkey AS o, l_suppkey AS k FROM lineitem) SELECT DISTINCT x.k AS a, y.k AS b FROM t x JOIN t y ON x.o = y.o WHERE x.k < y.k",
    "w13": "WITH t AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS k FROM lineitem) SELECT DISTINCT x.k AS a, y.k AS b FROM t x JOIN t y ON x.o = y.o WHERE x.k < y.k",
}
#: Neighbours of each vector in W10.
NEIGHBOURS = 8
#: Spark and DuckDB spell these two differently: (Spark, DuckDB).
_KNN_TAIL = "SELECT i AS a, j AS b FROM (SELECT i, j, row_number() OVER (PARTITION BY i ORDER BY d, j) AS r FROM p) q WHERE r <= 8"
SPLIT: dict[str, tuple[str, str]] = {
    "w10": (
        "WITH p AS (SELECT x.vec_id AS i, y.vec_id AS j, aggregate(zip_with(x.embedding, y.embedding, (u, v) -> (CAST(u AS DOUBLE) - CAST(v AS DOUBLE)) * (CAST(u AS DOUBLE) - CAST(v AS DOUBLE))), 0D, (s, u) -> s + u) AS d FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) " + _KNN_TAIL,
        "WITH p AS (SELECT x.vec_id AS i, y.vec_id AS j, list_sum(list_transform(list_zip(x.embedding, y.embedding), lambda u: (u[1]::DOUBLE - u[2]::DOUBLE) * (u[1]::DOUBLE - u[2]::DOUBLE))) AS d FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) " + _KNN_TAIL,
    ),
    "w14": (
        f"WITH t AS (SELECT DISTINCT page_id AS p, explode(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS h FROM pages), k AS (SELECT h, row_number() OVER (ORDER BY h) AS r FROM (SELECT DISTINCT h FROM t) u) SELECT t.p AS a, {B} + k.r AS b FROM t JOIN k ON t.h = k.h",
        f"WITH t AS (SELECT DISTINCT page_id AS p, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS h FROM pages), k AS (SELECT h, row_number() OVER (ORDER BY h) AS r FROM (SELECT DISTINCT h FROM t) u) SELECT t.p AS a, {B} + k.r AS b FROM t JOIN k ON t.h = k.h",
    ),
}
#: Graphs of rows so many places apart: table, key, time, steps.
STEPPED = {"w5": ("orders", "o_orderkey", "o_orderdate", (1, 50)), "w6": ("events", "event_id", "ts", (1, 2, 3))}
NAMES = [f"w{i}" for i in range(1, 15)]


def register(spark: SparkSession, sf_dir: str, tables: list[str] | None = None) -> None:
    """Temporary views of the tables there are."""
    for t in tables or TABLES:
        spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)


def tables_of(sql: str) -> list[str]:
    return [t for t in TABLES if f" {t}" in sql]


def pairs(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(a, b) of a workload. The neighbours of W10 come from tiles of distances: its SQL sums up every pair one by one. W5 and W6 rank their rows by ranges: their SQL does in one task."""
    if name == "w10":
        return nearest(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("i"), F.col("embedding").alias("v")), NEIGHBOURS)
    if name in STEPPED:
        table, key, time, steps = STEPPED[name]
        return stepped(spark.read.parquet(f"{sf_dir}/{table}.parquet").select(F.col(key).alias("k"), F.col(time).alias("t")), steps)
    sql = spark_sql(name)
    register(spark, sf_dir, tables_of(sql))
    return spark.sql(sql)


def stepped(rows: DataFrame, steps: tuple[int, ...], block: int = 100_000) -> DataFrame:
    """Pairs (a, b) of the keys of rows (k, t) that are so many places apart in the order of t, k.

    Ranks come from sampled ranges. A block of ranks also holds the first rows of the next, so that every pair meets in the block of its first row."""
    most = max(steps)
    block = max(block, most)
    ranked = sort_rank(rows, ["t", "k"], "general").select("k", "rank", F.floor(F.col("rank") / block).alias("own"))
    also = F.when((F.col("rank") % block < most) & (F.col("own") > 0), F.array("own", F.col("own") - 1)).otherwise(F.array("own"))
    here = Window.partitionBy("block").orderBy("rank")
    met = ranked.withColumn("block", F.explode(also)).select("k", "own", "block", F.array(*[F.lead("k", s).over(here) for s in steps]).alias("next"))
    return met.where("own = block").select(F.col("k").alias("a"), F.explode("next").alias("b")).where("b is not null")


def spark_sql(name: str) -> str:
    return SPLIT[name][0] if name in SPLIT else GRAPHS[name]


def duck_sql(name: str) -> str:
    return SPLIT[name][1] if name in SPLIT else GRAPHS[name]


def graph(spark: SparkSession, sf_dir: str, name: str) -> SymGraph:
    return SymGraph.from_pairs(pairs(spark, sf_dir, name))
