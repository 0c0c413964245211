"""The relational operators a user of the graph methods needs around them, each as a query with its SQL.

``OPS``: name -> (function of a table reader, DuckDB SQL or None).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

Read = Callable[[str], DataFrame]
OPS: dict[str, tuple[Callable[[Read], DataFrame], str | None]] = {}


def op(sql: str | None):
    def add(f):
        OPS[f"op_{f.__name__}"] = (f, sql)
        return f

    return add


@op("SELECT l_orderkey, l_partkey, l_suppkey FROM lineitem")
def scan_parquet(t: Read) -> DataFrame:
    return t("lineitem").select("l_orderkey", "l_partkey", "l_suppkey")


@op("SELECT o_orderkey, CAST(round(o_totalprice * 100) AS BIGINT) AS cents, year(o_orderdate) AS y, month(o_orderdate) AS m FROM orders")
def project_cast(t: Read) -> DataFrame:
    return t("orders").select("o_orderkey", F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"), F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"))


@op("SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_returnflag IN ('A', 'R') AND l_discount BETWEEN 0.02 AND 0.06 AND l_quantity < 25")
def filter_compound(t: Read) -> DataFrame:
    return t("lineitem").where(F.col("l_returnflag").isin("A", "R") & F.col("l_discount").between(0.02, 0.06) & (F.col("l_quantity") < 25)).select("l_orderkey", "l_linenumber")


@op("SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages WHERE html LIKE '%href=%'")
def like_regex(t: Read) -> DataFrame:
    return t("pages").where(F.col("html").like("%href=%")).select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))


@op("SELECT l_partkey AS src, 1000000000 + l_suppkey AS dst FROM lineitem UNION SELECT 1000000000 + l_suppkey, l_partkey FROM lineitem")
def symmetrize(t: Read) -> DataFrame:
    p = t("lineitem").select(F.col("l_partkey").alias("a"), (F.col("l_suppkey") + 10**9).alias("b"))
    return p.select(F.col("a").alias("src"), F.col("b").alias("dst")).unionByName(p.select(F.col("b").alias("src"), F.col("a").alias("dst"))).distinct()


@op("SELECT l_partkey AS v, count(DISTINCT l_suppkey) AS deg FROM lineitem GROUP BY 1 UNION ALL SELECT 1000000000 + l_suppkey, count(DISTINCT l_partkey) FROM lineitem GROUP BY 1")
def degree(t: Read) -> DataFrame:
    return symmetrize(t).groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg"))


_JOIN = "SELECT o_orderpriority, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _joined(t: Read, hint: str) -> DataFrame:
    j = t("lineitem").join(t("orders").hint(hint), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("q"))


@op(_JOIN)
def join_hash(t: Read) -> DataFrame:
    return _joined(t, "shuffle_hash")


@op(_JOIN)
def join_merge(t: Read) -> DataFrame:
    return _joined(t, "merge")


@op("SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(t: Read) -> DataFrame:
    small = F.broadcast(t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")))  # 25 and 5 rows at every scale
    return t("customer").join(small, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name")


_BOX = """WITH t AS (SELECT p_partkey AS k, p_partkey % 10 AS x, CAST(floor(p_partkey / 10) AS BIGINT) % 10 AS y, CAST(floor(p_partkey / 100) AS BIGINT) AS z FROM part)
SELECT a.k AS a, b.k AS b FROM t a JOIN t b ON abs(a.x - b.x) <= 1 AND abs(a.y - b.y) <= 1 AND abs(a.z - b.z) <= 1 AND a.k < b.k"""


def _mesh(t: Read) -> DataFrame:
    k = F.col("p_partkey")
    return t("part").select(k.alias("k"), (k % 10).alias("x"), (F.floor(k / 10) % 10).alias("y"), F.floor(k / 100).alias("z"))


@op(_BOX)
def join_theta(t: Read) -> DataFrame:
    """Cells of two by two by two: a row's box of three touches two cells a side, so it meets what lies in eight, and the condition decides."""
    cell = lambda c: F.floor(F.col(c) / 2)
    touched = [F.explode(F.array(F.floor((F.col(c) - 1) / 2), F.floor((F.col(c) + 1) / 2))).alias(f"c{c}") for c in "xyz"]
    a = _mesh(t)
    for column in touched:  # one generator a step
        a = a.select("*", column)
    a, b = a.alias("a"), _mesh(t).select("*", *[cell(c).alias(f"c{c}") for c in "xyz"]).alias("b")
    near = (F.abs(F.col("a.x") - F.col("b.x")) <= 1) & (F.abs(F.col("a.y") - F.col("b.y")) <= 1) & (F.abs(F.col("a.z") - F.col("b.z")) <= 1)
    same = [F.col(f"a.c{c}") == F.col(f"b.c{c}") for c in "xyz"]
    return a.join(b.hint("merge"), same[0] & same[1] & same[2] & near & (F.col("a.k") < F.col("b.k"))).select(F.col("a.k").alias("a"), F.col("b.k").alias("b"))


@op(_BOX)
def join_offsets(t: Read) -> DataFrame:
    """Each row at the 27 places its neighbours may have, an equi-join. A hint keeps it off the driver: the file of a table that fits a broadcast can hold millions of rows."""
    moves = F.array(*[F.struct(*[F.lit(d).alias(n) for n, d in zip("ijk", (x, y, z))]) for x in (-1, 0, 1) for y in (-1, 0, 1) for z in (-1, 0, 1)])
    m = _mesh(t)
    a = m.withColumn("o", F.explode(moves)).select(F.col("k").alias("a"), (F.col("x") + F.col("o.i")).alias("x"), (F.col("y") + F.col("o.j")).alias("y"), (F.col("z") + F.col("o.k")).alias("z"))
    return a.join(m.withColumnRenamed("k", "b").hint("merge"), ["x", "y", "z"]).where("a < b").select("a", "b")


@op("SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND x.event_id < y.event_id AND y.ts BETWEEN x.ts AND x.ts + INTERVAL 10 MINUTE")
def join_range(t: Read) -> DataFrame:
    """Bins of the range's width: a row meets its own bin and the next, an equi-join with a filter."""
    e = t("events").select("event_id", "user_id", "ts", F.floor(F.unix_timestamp("ts") / 600).alias("bin"))
    x = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"), F.explode(F.array(F.col("bin"), F.col("bin") + 1)).alias("bin"))
    y = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"), "bin")
    return x.join(y, ["user_id", "bin"]).where("a < b and tb >= ta and tb <= ta + interval 10 minutes").select("a", "b")


@op("""SELECT event_id, (SELECT max(p.event_id) FROM events p WHERE p.user_id = e.user_id AND p.event_type <> 'purchase' AND (p.ts < e.ts OR p.ts = e.ts AND p.event_id < e.event_id)) AS before
FROM events e WHERE event_type = 'purchase'""")
def join_asof(t: Read) -> DataFrame:
    """The latest other event of the user before each purchase: one window over the union, no join. Events are numbered in time order."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = t("events").withColumn("before", F.last(F.when(F.col("event_type") != "purchase", F.col("event_id")), True).over(w))
    return e.where("event_type = 'purchase'").select("event_id", "before")


@op("SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)")
def join_semi(t: Read) -> DataFrame:
    return t("orders").join(t("lineitem").where("l_quantity > 45"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey")


@op("SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def join_anti(t: Read) -> DataFrame:
    return t("orders").join(t("lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@op("SELECT coalesce(c.k, s.k) AS k, c.n AS customers, s.n AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1) c FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) s ON c.k = s.k")
def join_outer(t: Read) -> DataFrame:
    c = t("customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("customers"))
    return c.join(t("supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("suppliers")), "k", "full").select("k", "customers", "suppliers")


@op("WITH t AS (SELECT DISTINCT l_orderkey AS o, l_suppkey AS k FROM lineitem) SELECT x.k AS a, y.k AS b, count(*) AS n FROM t x JOIN t y ON x.o = y.o AND x.k < y.k GROUP BY 1, 2")
def join_self(t: Read) -> DataFrame:
    d = t("lineitem").select(F.col("l_orderkey").alias("o"), F.col("l_suppkey").alias("k")).distinct()
    return d.withColumnRenamed("k", "a").join(d.withColumnRenamed("k", "b"), "o").where("a < b").groupBy("a", "b").agg(F.count("*").alias("n"))


@op("""SELECT l_returnflag, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS s, round(avg(l_quantity), 6) AS a, min(l_quantity) AS lo, max(l_quantity) AS hi, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem GROUP BY 1""")
def agg_basic(t: Read) -> DataFrame:
    q = F.col("l_quantity")
    return t("lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.sum(q).cast("long").alias("s"), F.round(F.avg(q), 6).alias("a"), F.min(q).alias("lo"), F.max(q).alias("hi"), F.round(F.stddev_samp(q), 6).alias("sd"))


@op("SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def agg_distinct(t: Read) -> DataFrame:
    return t("lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"))


@op("SELECT l_suppkey, true AS near FROM lineitem GROUP BY 1")
def agg_approx(t: Read) -> DataFrame:
    """Whether the estimate is within a tenth of the exact count."""
    both = t("lineitem").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey", 0.02).alias("about"), F.count_distinct("l_partkey").alias("parts"))
    return both.select("l_suppkey", (F.abs(F.col("about") - F.col("parts")) <= F.col("parts") * 0.1 + 1).alias("near"))


@op("SELECT c_nationkey, min(c_custkey) FILTER (WHERE c_acctbal = m) AS poorest FROM (SELECT *, min(c_acctbal) OVER (PARTITION BY c_nationkey) AS m FROM customer) q GROUP BY 1")
def agg_argmin(t: Read) -> DataFrame:
    return t("customer").groupBy("c_nationkey").agg(F.min(F.struct("c_acctbal", "c_custkey")).alias("m")).select("c_nationkey", F.col("m.c_custkey").alias("poorest"))


@op("SELECT l_suppkey AS src, array_to_string(list(DISTINCT l_partkey ORDER BY l_partkey), ',') AS nbrs FROM lineitem GROUP BY 1")
def agg_collect(t: Read) -> DataFrame:
    return t("lineitem").groupBy(F.col("l_suppkey").alias("src")).agg(F.array_join(F.sort_array(F.collect_set("l_partkey")).cast("array<string>"), ",").alias("nbrs"))


@op("SELECT user_id, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1")
def agg_percentile(t: Read) -> DataFrame:
    return t("events").groupBy("user_id").agg(F.round(F.percentile("value", 0.5), 6).alias("p50"), F.round(F.percentile("value", 0.9), 6).alias("p90"))


_G = "SELECT o_orderstatus AS s, o_orderpriority AS p, count(*) AS n FROM orders GROUP BY "


@op(_G + "GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderstatus), ())")
def grouping_sets(t: Read) -> DataFrame:
    t("orders").createOrReplaceTempView("orders_gs")
    return t("orders").sparkSession.sql((_G + "GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderstatus), ())").replace("FROM orders", "FROM orders_gs"))


@op(_G + "CUBE (o_orderstatus, o_orderpriority)")
def cube(t: Read) -> DataFrame:
    return t("orders").cube(F.col("o_orderstatus").alias("s"), F.col("o_orderpriority").alias("p")).agg(F.count("*").alias("n"))


@op(_G + "ROLLUP (o_orderstatus, o_orderpriority)")
def rollup(t: Read) -> DataFrame:
    return t("orders").rollup(F.col("o_orderstatus").alias("s"), F.col("o_orderpriority").alias("p")).agg(F.count("*").alias("n"))


@op("SELECT user_id, count(*) FILTER (WHERE event_type = 'purchase') AS purchase, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY 1")
def pivot(t: Read) -> DataFrame:
    return t("events").groupBy("user_id").pivot("event_type", ["purchase", "view"]).count().na.fill(0)


@op("""SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 9) AS pr FROM orders
WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)""")
def window_rank(t: Read) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return t("orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 9).alias("pr"))


@op("SELECT event_id, lag(event_id) OVER w AS prev, lead(event_id) OVER w AS next FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def window_lag_lead(t: Read) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t("events").select("event_id", F.lag("event_id").over(w).alias("prev"), F.lead("event_id").over(w).alias("next"))


@op("""SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS upto,
count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS hour FROM events""")
def window_frames(t: Read) -> DataFrame:
    rows = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    hour = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)
    return t("events").select("event_id", F.count("*").over(rows).alias("upto"), F.count("*").over(hour).alias("hour"))


@op("SELECT user_id, min(event_id) AS first, max(event_id) AS last, max(event_id) FILTER (WHERE r = 2) AS second FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY event_id) AS r FROM events) q GROUP BY 1")
def window_first_last(t: Read) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t("events").select("user_id", F.first("event_id").over(w).alias("first"), F.last("event_id").over(w).alias("last"), F.nth_value("event_id", 2).over(w).alias("second")).distinct()


@op("SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1 ORDER BY n DESC, l_suppkey LIMIT 10")
def topk(t: Read) -> DataFrame:
    return t("lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "l_suppkey").limit(10)


@op("SELECT l_orderkey, l_linenumber FROM lineitem")
def sort_multi(t: Read) -> DataFrame:
    return t("lineitem").select("l_orderkey", "l_linenumber").orderBy("l_orderkey", F.desc("l_linenumber"))


@op("SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier")
def union(t: Read) -> DataFrame:
    return t("customer").select(F.col("c_nationkey").alias("k")).union(t("supplier").select("s_nationkey"))


@op("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def intersect(t: Read) -> DataFrame:
    return t("customer").select(F.col("c_nationkey").alias("k")).intersect(t("supplier").select("s_nationkey"))


@op("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def except_all(t: Read) -> DataFrame:
    return t("customer").select(F.col("c_nationkey").alias("k")).exceptAll(t("supplier").select("s_nationkey"))


@op("SELECT doc_id, length(text) AS n, lower(source) AS s, concat_ws('-', lang, source) AS ls, split_part(text, ' ', 1) AS w FROM documents")
def string(t: Read) -> DataFrame:
    return t("documents").select("doc_id", F.length("text").cast("long").alias("n"), F.lower("source").alias("s"), F.concat_ws("-", "lang", "source").alias("ls"), F.split_part("text", F.lit(" "), F.lit(1)).alias("w"))


@op("SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS d FROM orders")
def date(t: Read) -> DataFrame:
    return t("orders").select("o_orderkey", F.to_date(F.date_trunc("month", "o_orderdate")).alias("m"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).cast("long").alias("d"))


@op("SELECT l_orderkey, l_linenumber, round(sqrt(l_quantity), 6) AS r, greatest(l_partkey, l_suppkey) AS g, abs(l_partkey - l_suppkey) AS d, CAST(floor(l_quantity / 7) AS BIGINT) AS f FROM lineitem")
def math(t: Read) -> DataFrame:
    return t("lineitem").select("l_orderkey", "l_linenumber", F.round(F.sqrt("l_quantity"), 6).alias("r"), F.greatest("l_partkey", "l_suppkey").alias("g"), F.abs(F.col("l_partkey") - F.col("l_suppkey")).alias("d"), F.floor(F.col("l_quantity") / 7).alias("f"))


@op("SELECT vec_id, len(embedding) AS n, len(list_filter(embedding, lambda x: x > 0)) AS pos FROM embeddings")
def array(t: Read) -> DataFrame:
    return t("embeddings").select("vec_id", F.size("embedding").cast("long").alias("n"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("pos"))


@op("SELECT o_custkey, count(*) FILTER (WHERE o_orderstatus = 'O') AS open FROM orders GROUP BY 1")
def map(t: Read) -> DataFrame:  # noqa: A001
    counts = t("orders").groupBy("o_custkey", "o_orderstatus").count().groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "count"))).alias("m"))
    return counts.select("o_custkey", F.coalesce(F.try_element_at("m", F.lit("O")), F.lit(0)).cast("long").alias("open"))


@op("SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
def json(t: Read) -> DataFrame:
    return t("events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@op("SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
def subquery(t: Read) -> DataFrame:
    t("orders").createOrReplaceTempView("orders_sq")
    return t("orders").sparkSession.sql("SELECT o_orderkey FROM orders_sq o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders_sq i WHERE i.o_custkey = o.o_custkey)")


@op("SELECT p_partkey, p_size * 2 + 1 AS x FROM part")
def udf(t: Read) -> DataFrame:
    @F.pandas_udf("long")
    def twice(s):
        return s.astype("int64") * 2 + 1

    return t("part").select("p_partkey", twice("p_size").alias("x"))


@op("SELECT l_suppkey, CAST(sum(l_linenumber) AS BIGINT) AS s FROM lineitem GROUP BY 1")
def udaf(t: Read) -> DataFrame:
    def total(s):
        return int(s.sum())

    return t("lineitem").groupBy("l_suppkey").agg(F.pandas_udf(total, "long", F.PandasUDFType.GROUPED_AGG)("l_linenumber").alias("s"))


@op("SELECT n_nationkey, unnest(range(n_nationkey)) AS i FROM nation WHERE n_nationkey < 4")
def udtf(t: Read) -> DataFrame:
    @F.udtf(returnType="i: long")
    class Count:
        def eval(self, n: int):
            for i in range(n):
                yield (i,)

    spark = t("nation").sparkSession
    spark.udtf.register("count_up", Count)
    t("nation").where("n_nationkey < 4").createOrReplaceTempView("nation_small")
    return spark.sql("SELECT n_nationkey, i FROM nation_small, LATERAL count_up(n_nationkey)")


def queries() -> dict:
    def made(f):
        return lambda spark, sf_dir: f(lambda name: spark.read.parquet(f"{sf_dir}/{name}.parquet"))

    return {name: made(f) for name, (f, _) in OPS.items()}


def oracle_sql() -> dict:
    return {name: sql for name, (_, sql) in OPS.items() if sql}
