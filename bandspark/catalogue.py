"""Registry of the engine's queries and their DuckDB oracles."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.util import inheritable_thread_target

from bandspark import model
from bandspark.functions import relational
from bandspark.operators import distribution, metrics, ordering, primitives, ranking, traverse
from bandspark.operators.solver import cg_block_jacobi, shifted_laplacian
from bandspark.plans import oracles
from bandspark.plans.costmodel import CostModel
from bandspark.session import apart, materialize, new_folder, shared_dir
from bandspark.sources import io, workloads
from bandspark.streaming import edges as streams

#: Graphs of few levels, for which the sweep that makes levels and labels at once is registered too.
LOOPED = ("w1", "w8", "w10", "w12", "w13")
#: Graphs of the structure table that are worked on at once.
AT_ONCE = 4


def components_of(spark, sf_dir, w) -> DataFrame:
    return ordering.with_components(workloads.graph(spark, sf_dir, w)).select("v", "comp")


def searched(spark, sf_dir, w, variant="classic"):
    """(roots, levels): components that a task may hold in tasks, larger ones by distributed sweeps."""
    g = workloads.graph(spark, sf_dir, w)
    return ordering.searched(g, ordering.with_components(g), variant)


def roots_of(spark, sf_dir, w) -> DataFrame:
    return searched(spark, sf_dir, w)[0].select("comp", F.col("root").alias("classic"), "depth", "searches", F.col("hop").alias("algebraic"))


def levels_of(spark, sf_dir, w) -> DataFrame:
    return searched(spark, sf_dir, w)[1]


def order_of(spark, sf_dir, w, **options) -> DataFrame:
    return ordering.frontier_order(workloads.graph(spark, sf_dir, w), **options).labels


def metrics_of(spark, sf_dir, w) -> DataFrame:
    """One row: the structure table's line for a graph."""
    g = workloads.graph(spark, sf_dir, w)
    o = ordering.frontier_order(g)
    both = metrics.compare(metrics.quality(g.edges, ordering.natural_order(g)), metrics.quality(g.edges, o.labels))
    heads = o.roots.agg(F.count("*").alias("comps"), F.max("depth").cast("long").alias("pseudo_diameter"), F.max("width").alias("width"))
    nnz = g.edges.agg(F.count("*").alias("nnz"))
    row = both.crossJoin(heads).crossJoin(nnz)  # one row each
    return row.select(F.lit(w).alias("graph"), "n", "nnz", "comps", "bw_before", "bw_after", F.col("profile_before").cast("long").alias("profile_before"), F.col("profile_after").cast("long").alias("profile_after"), "pseudo_diameter", "width")


def structure_table(spark, sf_dir, names=tuple(workloads.NAMES)) -> DataFrame:
    """The lines of all graphs. A few graphs are worked on at once, each in a session of its own: the jobs of one are mostly too small for all cores."""
    shared_dir(spark)  # a local session gets its folder before there are several

    def line(w):
        row, path = metrics_of(apart(spark), sf_dir, w), new_folder(spark, f"structure-{w}")
        materialize(row, path=path)
        return row.schema, path

    with ThreadPoolExecutor(AT_ONCE) as pool:
        rows = [spark.read.schema(schema).parquet(path) for schema, path in pool.map(inheritable_thread_target(line), names)]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def frontier(spark, sf_dir):
    """W1, the neighbours of its smallest vertex with the label 0 each, and degrees as a dense vector."""
    g = workloads.graph(spark, sf_dir, "w1")
    x = g.edges.where("src = 0").select(F.col("dst").alias("v"), F.lit(0).cast("long").alias("x"))
    return g, x, g.vertices.select("v", F.col("deg").alias("y"))


_E = "WITH e AS (SELECT l_partkey AS src, 1000000000 + l_suppkey AS dst FROM lineitem UNION SELECT 1000000000 + l_suppkey, l_partkey FROM lineitem), deg AS (SELECT src AS v, count(*) AS y FROM e GROUP BY 1), x AS (SELECT dst AS v, 0::BIGINT AS x FROM e WHERE src = 0) "


def p_indices(spark, d):
    return primitives.indices(frontier(spark, d)[1])


def p_select(spark, d):
    _, x, y = frontier(spark, d)
    return primitives.select_where(x, y, F.col("y") % 2 == 0)


def p_scatter(spark, d):
    _, x, y = frontier(spark, d)
    return primitives.scatter(y, x)


def p_gather(spark, d):
    _, x, y = frontier(spark, d)
    return primitives.gather(x, y)


def p_spmspv(spark, d):
    g, x, _ = frontier(spark, d)
    return primitives.spmspv(g.edges, x.withColumn("x", F.col("v")))


def p_spmspv_2d(spark, d):
    g, x, _ = frontier(spark, d)
    return distribution.spmspv_2d(distribution.distribute_2d(g.edges, 4, 4), x.withColumn("x", F.col("v")))


def p_spmspv_adjacency(spark, d):
    g, x, _ = frontier(spark, d)
    return distribution.spmspv_adjacency(distribution.adjacency(g.edges), x.withColumn("x", F.col("v")))


def p_reduce(spark, d):
    _, x, y = frontier(spark, d)
    return primitives.reduce_over(x, y)


def p_argmin(spark, d):
    _, x, y = frontier(spark, d)
    return primitives.argmin_over(x, y)


def p_select_unset(spark, d):
    _, x, y = frontier(spark, d)
    return primitives.select_unset(x, y.where("y % 2 = 0"))


def p_spmspv_1d(spark, d):
    g, x, _ = frontier(spark, d)
    return primitives.spmspv(distribution.distribute_1d(g.edges, 16), x.withColumn("x", F.col("v")))


def p_rank(strategy):
    """The children of one frontier, by smallest parent, degree and id; parents' labels are the parents' ranks."""

    def run(spark, d):
        g, x, y = frontier(spark, d)
        parents = ranking.sort_rank(x.select("v"), ["v"], "single")
        kids = primitives.spmspv(g.edges, parents.select("v", F.col("rank").alias("x"))).join(y, "v")
        return ranking.sort_rank(kids, ["x", "y", "v"], strategy, 0, parents.count()).select("v", "rank")

    return run


_PRODUCT = _E + "SELECT e.dst AS v, min(x.v) AS x FROM e JOIN x ON x.v = e.src GROUP BY 1"
_RANK = _E + "SELECT v, row_number() OVER (ORDER BY p, y, v) - 1 AS rank FROM (SELECT e.dst AS v, min(e.src) AS p FROM e JOIN x ON x.v = e.src GROUP BY 1) JOIN deg USING (v)"
PRIMITIVES = {
    "primitive_indices": (p_indices, _E + "SELECT v FROM x"),
    "primitive_select": (p_select, _E + "SELECT v, x FROM x JOIN deg USING (v) WHERE y % 2 = 0"),
    "primitive_select_unset": (p_select_unset, _E + "SELECT v, x FROM x JOIN deg USING (v) WHERE y % 2 <> 0"),
    "primitive_spmspv_1d": (p_spmspv_1d, _PRODUCT),
    "primitive_scatter": (p_scatter, _E + "SELECT v, coalesce(x, y) AS y FROM deg LEFT JOIN x USING (v)"),
    "primitive_gather": (p_gather, _E + "SELECT v, y AS x FROM x JOIN deg USING (v)"),
    "primitive_spmspv": (p_spmspv, _PRODUCT),
    "primitive_spmspv_2d": (p_spmspv_2d, _PRODUCT),
    "primitive_spmspv_adjacency": (p_spmspv_adjacency, _PRODUCT),
    "primitive_reduce": (p_reduce, _E + "SELECT min(y) AS value FROM x JOIN deg USING (v)"),
    "primitive_argmin": (p_argmin, _E + "SELECT v, y AS value FROM x JOIN deg USING (v) ORDER BY y, v LIMIT 1"),
    **{f"sort_{s}_w1": (p_rank(s), _RANK) for s in ranking.STRATEGIES},
}


def natural_w4(spark, d):
    return ordering.natural_order(workloads.graph(spark, d, "w4"))


def gather_w1(spark, d):
    return ordering.gather_order(workloads.graph(spark, d, "w1"), above="lots")


def spy_w4(spark, d):
    g = workloads.graph(spark, d, "w4")
    return metrics.spy(g.edges, ordering.frontier_order(g).labels, 16, g.vertices.count())


def row_bandwidths_w1(spark, d):
    g = workloads.graph(spark, d, "w1")
    return metrics.row_bandwidths(g.edges, ordering.frontier_order(g).labels)


def envelope_w12(spark, d):
    g = workloads.graph(spark, d, "w12")
    return metrics.envelope_pairs(g.edges, ordering.frontier_order(g).labels)


def permute_w1(spark, d):
    g = workloads.graph(spark, d, "w1")
    return metrics.permute(g.edges, ordering.frontier_order(g).labels)


def levels_async_w1(spark, d):
    g = workloads.graph(spark, d, "w1")
    return traverse.levels_async(g.edges, spark.createDataFrame([(0,)], "v long"))[0]


def relabel_scrambled_band(spark, d):
    """Planted band: event chains of three steps, scrambled, then ordered; the measure is what comes back."""
    g, _ = distribution.random_relabel(workloads.graph(spark, d, "w6"), 7)
    o = ordering.frontier_order(g)
    return metrics.quality(g.edges, o.labels).select("n", "bandwidth", F.col("profile").cast("long").alias("profile"))


def balance_2d_w1(spark, d):
    """Entries of a 4 x 4 grid over the natural order."""
    g = workloads.graph(spark, d, "w1")
    return distribution.balance(distribution.blocks_of_range(g.edges, ordering.natural_order(g), 4, 4, g.vertices.count()))


#: A bijection of 0 .. n - 1 for the mesh's n (no common factor with 1103).
_SCRAMBLE = "v * 1103 % n"


def solver_blocks_w4(spark, d):
    """Entries across blocks of 8 and 32: in natural, scrambled and reverse frontier order."""
    g = workloads.graph(spark, d, "w4")
    out = None
    for name, labels in _w4_orders(g).items():
        m = metrics.permute(g.edges, labels)
        for block in (8, 32):
            row = m.where(F.floor(F.col("i") / block) != F.floor(F.col("j") / block)).agg(F.count("*").alias("off_block")).select(F.lit(name).alias("ordering"), F.lit(block).alias("block"), "off_block")
            out = row if out is None else out.unionByName(row)
    return out


def _w4_orders(g):
    n = g.vertices.count()
    return {"natural": ordering.natural_order(g), "scrambled": g.vertices.select("v", F.expr(_SCRAMBLE.replace("% n", f"% {n}")).alias("label")), "frontier": ordering.frontier_order(g).labels}


def cg_w4(spark, d):
    """Iterations and entries across blocks, scrambled against reverse frontier order."""
    g = workloads.graph(spark, d, "w4")
    rows = []
    for name, labels in _w4_orders(g).items():
        if name != "natural":
            labels = materialize(labels, "cg-labels")
            r = cg_block_jacobi(shifted_laplacian(g.edges, labels), labels.select(F.col("label").alias("i"), (F.col("v") % 7).cast("double").alias("b")), 32, 1e-2)
            rows.append((name, r["iterations"], r["off_block"], r["residual"] <= 1e-2))
    return spark.createDataFrame(rows, "ordering string, iterations int, off_block long, converged boolean")


def cost_table(spark, d):
    """The cost model's estimates over processes for W1."""
    shape = workloads.graph(spark, d, "w1").shape().first()
    rows = [(p, *[round(CostModel().ordering(shape["n"], shape["nnz_offdiag"] // 2, p, 2)[k], 6) for k in ("operations", "messages", "words", "seconds")]) for p in (1, 4, 16, 64, 256, 1024)]
    return spark.createDataFrame(rows, "p int, operations double, messages double, words double, seconds double")


_COSTS = _E + """, s AS (SELECT (SELECT count(*) FROM deg)::DOUBLE AS n, (SELECT count(*) FROM e) / 2.0 AS m), c AS (SELECT p, m / p + n * log2(n) / p AS operations, 3 * sqrt(p) + p AS messages, m / p + n / sqrt(p) + n / p AS words
 FROM s, (SELECT unnest([1, 4, 16, 64, 256, 1024])::DOUBLE AS p)) SELECT p::INT AS p, round(operations, 6) AS operations, round(messages, 6) AS messages, round(words, 6) AS words, round(1e-9 * operations + 1e-6 * messages + 1e-9 * words, 6) AS seconds FROM c"""


def scan_formats(spark, d):
    """The edges of W12, written and read in each format."""
    edges, out = materialize(workloads.pairs(spark, d, "w12").select("a", "b"), "scan"), None
    for fmt in ("csv", "json", "orc", "parquet"):
        path = new_folder(spark, f"scan-{fmt}")
        io.write_edges(edges, path, fmt)
        back = io.read_edges(spark, path, fmt).withColumn("fmt", F.lit(fmt))
        out = back if out is None else out.unionByName(back)
    return out


def scan_coordinates(spark, d):
    """The lower triangle of W12 as coordinate text, read back and mirrored."""
    edges = workloads.pairs(spark, d, "w12").select(F.greatest("a", "b").alias("r"), F.least("a", "b").alias("c"))
    edges = materialize(edges, "scan")
    size = edges.agg(F.max("r").alias("n"), F.count("*").alias("m")).first()
    head = spark.createDataFrame([(0, "% symmetric"), (1, f"{size.n + 1} {size.n + 1} {size.m}")], "o int, value string")
    lines = head.unionByName(edges.select(F.lit(2).alias("o"), F.concat_ws(" ", F.col("r") + 1, F.col("c") + 1).alias("value")))
    path = new_folder(spark, "scan-text")
    lines.coalesce(1).sortWithinPartitions("o").select("value").write.text(path)
    return model.SymGraph.from_pairs(io.read_coordinates(spark, path)).edges.select("src", "dst")


def sink_ordering(spark, d):
    """The natural order of W4, written and read back."""
    path = new_folder(spark, "sink")
    io.write_ordering(natural_w4(spark, d), path)
    return spark.read.schema("v long, label long").parquet(path)


def gather_status_w1(spark, d):
    """The gather baseline with room, and with too little: the outcome column."""
    g = workloads.graph(spark, d, "w1")
    rows = [(limit, ordering.gather_report(g, limit)["status"]) for limit in (ordering.TASK_EDGES, 10)]
    return spark.createDataFrame(rows, "edge_limit long, status string")


_SPY = "SELECT floor(x.label * 16 / c.n)::BIGINT AS bi, floor(y.label * 16 / c.n)::BIGINT AS bj, count(*) AS nnz FROM e JOIN o x ON x.v = e.src JOIN o y ON y.v = e.dst, (SELECT count(*) AS n FROM o) c GROUP BY 1, 2"
OTHERS = {
    "natural_w4": (natural_w4, oracles._with(oracles._graph("w4"), "SELECT v, row_number() OVER (ORDER BY v) - 1 AS label FROM deg")),
    "gather_w1": (gather_w1, oracles.order("w1")),
    "spy_w4": (spy_w4, oracles.order("w4", tail=_SPY)),
    "row_bandwidths_w1": (row_bandwidths_w1, oracles.row_bandwidths("w1")),
    "envelope_w12": (envelope_w12, oracles.row_bandwidths("w12").replace("SELECT i, beta FROM b1", "SELECT i, unnest(range(i - beta, i)) AS j FROM b1 WHERE beta > 0")),
    "permute_w1": (permute_w1, oracles.order("w1", tail="SELECT x.label AS i, y.label AS j FROM e JOIN o x ON x.v = e.src JOIN o y ON y.v = e.dst")),
    "levels_async_w1": (levels_async_w1, oracles._with(oracles._graph("w1") + oracles._search("first"), "SELECT v, l AS level FROM lv")),
    "scrambled_band_w6": (relabel_scrambled_band, "SELECT count(*) AS n, 3 AS bandwidth, 3 * count(*) - 6 AS profile FROM events"),
    "balance_2d_w1": (balance_2d_w1, oracles._with(oracles._graph("w1") + ["nat AS (SELECT v, row_number() OVER (ORDER BY v) - 1 AS label FROM deg)", "b AS (SELECT count(*) AS n FROM e JOIN nat x ON x.v = e.src JOIN nat y ON y.v = e.dst, (SELECT count(*) AS n FROM deg) c GROUP BY floor(y.label * 4 / c.n), floor(x.label * 4 / c.n))"], "SELECT count(*) AS blocks, max(n) AS largest, round(avg(n), 6) AS mean, round(max(n) / avg(n), 6) AS ratio FROM b")),
    "solver_blocks_w4": (solver_blocks_w4, oracles.off_blocks("w4", _SCRAMBLE, (8, 32))),
    "cg_w4": (cg_w4, None),
    "cost_table_w1": (cost_table, _COSTS),
    "structure_table": (structure_table, oracles.structure(workloads.NAMES)),
    "op_scan_csv_json_orc": (scan_formats, " UNION ALL ".join(f"SELECT a, b, '{f}' AS fmt FROM ({workloads.duck_sql('w12')}) AS {f}" for f in ("csv", "json", "orc", "parquet"))),
    "op_scan_coordinate_text": (scan_coordinates, oracles._with(oracles._graph("w12"), "SELECT src, dst FROM e")),
    "op_sink_ordering": (sink_ordering, oracles._with(oracles._graph("w4"), "SELECT v, row_number() OVER (ORDER BY v) - 1 AS label FROM deg")),
    "gather_status_w1": (gather_status_w1, "SELECT * FROM (VALUES (8000000::BIGINT, 'ok'), (10, 'refused')) AS t(edge_limit, status)"),
    "order_threads_w1": (lambda s, d: ordering.single_node_order(workloads.graph(s, d, "w1"), 4, above="lots"), oracles.order("w1")),
    "order_given_w4": (lambda s, d: order_of(s, d, "w4", root=77, plan="sweep"), oracles.order("w4", 77)),
    "order_shrink_first_w4": (lambda s, d: order_of(s, d, "w4", shrink="first"), oracles.order("w4", shrink="")),
    "order_end_w1": (lambda s, d: order_of(s, d, "w1", plan="sweep", sort="end"), oracles.order("w1", sort="end")),
    "order_algebraic_w4": (lambda s, d: order_of(s, d, "w4", root="algebraic"), oracles.order("w4", "algebraic")),
    "order_first_w4": (lambda s, d: order_of(s, d, "w4", root="first"), oracles.order("w4", "first")),
    "order_forward_w1": (lambda s, d: order_of(s, d, "w1", reverse=False), oracles.order("w1", reverse=False)),
    "order_unsorted_parent_w1": (lambda s, d: order_of(s, d, "w1", sort="parent"), oracles.order("w1", sort="parent")),
    "order_unsorted_level_w1": (lambda s, d: order_of(s, d, "w1", sort="level"), oracles.order("w1", sort="level")),
    **{f"order_sweep_{s}_w1": (lambda spark, d, s=s: order_of(spark, d, "w1", plan="sweep", strategy=s), oracles.order("w1")) for s in ("general", "single")},
    **{f"order_sweep_{w}": (lambda spark, d, w=w: order_of(spark, d, w, plan="sweep"), oracles.order(w)) for w in workloads.NAMES},
    **{f"order_loop_{w}": (lambda spark, d, w=w: order_of(spark, d, w, plan="algebraic"), oracles.order(w)) for w in LOOPED},
}
PER_GRAPH = {
    "components": (components_of, oracles.components),
    "root": (roots_of, oracles.roots),
    "levels": (levels_of, oracles.levels),
    "order": (order_of, oracles.order),
    "metrics": (metrics_of, oracles.metrics),
}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The structure line of the part mesh: natural order against the reverse frontier ordering."""
    return metrics_of(spark, sf_dir, "w4")


def _each(f, w):
    return lambda spark, sf_dir: f(spark, sf_dir, w)


def queries() -> dict:
    out = {f"{kind}_{w}": _each(f, w) for kind, (f, _) in PER_GRAPH.items() for w in workloads.NAMES}
    out |= {k: f for part in (PRIMITIVES, OTHERS) for k, (f, _) in part.items()}
    return out | relational.queries() | streams.queries()


def oracle_sql() -> dict:
    out = {f"{kind}_{w}": sql(w) for kind, (_, sql) in PER_GRAPH.items() for w in workloads.NAMES}
    out |= {k: sql for part in (PRIMITIVES, OTHERS) for k, (_, sql) in part.items() if sql}
    return out | relational.oracle_sql() | streams.oracle_sql()
