"""The experiments, re-expressed on the given tables: ``python -m bandspark.experiments NAME [SF_DIR]`` prints one JSON line a row.

Times are of this machine in local mode; processes and threads of a cluster cannot be told apart there, so
``hybrid`` only sweeps the number of partitions, and says nothing about process boundaries. What an experiment wrote is deleted after it.
"""

from __future__ import annotations

import json
import pathlib
import subprocess
import sys
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bandspark.operators import distribution, metrics, ordering, primitives, ranking, sweep, traverse
from bandspark.operators.peripheral import search
from bandspark.operators.solver import cg_block_jacobi, shifted_laplacian
from bandspark.operators.sweep import Sweeper
from bandspark.plans.costmodel import PHASES, CostModel, Trace, speedups
from bandspark.plans.stagestats import measured
from bandspark.session import forget, local_session, materialize, written
from bandspark.sources.workloads import NAMES, graph


def _quality(g, labels: DataFrame) -> dict:
    r = metrics.quality(g.edges, labels).first()
    return {"bandwidth": r.bandwidth, "profile": int(r.profile)}


def _timed(f):
    began = time.perf_counter()
    out = f()
    return out, round(time.perf_counter() - began, 3)


def _labels(g, **options) -> DataFrame:
    return materialize(ordering.frontier_order(g, **options).labels, "experiment")


def structure(spark: SparkSession, sf: str, names=NAMES):
    """Size, bandwidth and profile before and after, depth and width, of every graph."""
    for w in names:
        g = graph(spark, sf, w)
        o, secs = _timed(lambda g=g: ordering.frontier_order(g))
        before, after = _quality(g, ordering.natural_order(g)), _quality(g, o.labels)
        head = o.roots.agg(F.max("depth").alias("depth"), F.max("width").alias("width"), F.count("*").alias("comps")).first()
        yield {"graph": w, **g.shape().first().asDict(), **head.asDict(), "bw_before": before["bandwidth"], "bw_after": after["bandwidth"], "profile_before": before["profile"], "profile_after": after["profile"], "seconds": secs}


def solver(spark, sf, names=("w4", "w5"), blocks=(8, 32), tol=1e-3):
    """Conjugate gradients: scrambled against ordered, by size of the preconditioner's blocks."""
    for w in names:
        g, _ = distribution.random_relabel(graph(spark, sf, w), 11)
        for name, labels in (("scrambled", ordering.natural_order(g)), ("ordered", _labels(g))):
            m = shifted_laplacian(g.edges, labels)
            for block in blocks:
                r, secs = _timed(lambda m=m, labels=labels, block=block: cg_block_jacobi(m, labels.select(F.col("label").alias("i"), (F.col("v") % 7).cast("double").alias("b")), block, tol))
                yield {"graph": w, "ordering": name, "block": block, "iterations": r["iterations"], "residual": r["residual"], "off_block": r["off_block"], "seconds": secs}


def plans(spark, sf, names=("w1", "w13")):
    """One task against the distributed sweep against gathering all edges: seconds, and whether labels agree."""
    for w in names:
        g = graph(spark, sf, w)
        base = None
        for plan, f in (("task", lambda: _labels(g, plan="task")), ("sweep", lambda: _labels(g, plan="sweep")), ("algebraic", lambda: _labels(g, plan="algebraic")), ("gather", lambda: materialize(ordering.gather_order(g), "experiment"))):
            labels, secs = _timed(f)
            base = base or labels
            yield {"graph": w, "plan": plan, "seconds": secs, "same_labels": labels.exceptAll(base).isEmpty()}


def concurrency(spark, sf, w="w4", parts=(1, 2, 4, 16)):
    """Labels must not depend on the number of partitions."""
    g, old, base = graph(spark, sf, w), spark.conf.get("spark.sql.shuffle.partitions"), None
    try:
        for p in parts:
            spark.conf.set("spark.sql.shuffle.partitions", p)
            labels, secs = _timed(lambda: _labels(g, plan="sweep"))
            base = base or labels
            yield {"graph": w, "partitions": p, "seconds": secs, "same_labels": labels.exceptAll(base).isEmpty(), **_quality(g, labels)}
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)


def hybrid(spark, sf, w="w5", parts=(4, 16, 64)):
    """Few large parts against many small ones, as a stand-in for processes of several threads against one: seconds only."""
    for row in concurrency(spark, sf, w, parts):
        yield {k: row[k] for k in ("graph", "partitions", "seconds", "same_labels")}


def shared(spark, sf, names=("w1", "w2", "w3", "w4", "w5", "w10", "w13"), threads=(1, 2, 4)):
    """The distributed sweep against one node at several numbers of threads: bandwidth and seconds."""
    for w in names:
        g = graph(spark, sf, w)
        labels, secs = _timed(lambda g=g: _labels(g, plan="sweep"))
        yield {"graph": w, "code": "sweep", **_quality(g, labels), "seconds": secs}
        for t in threads:
            labels, secs = _timed(lambda g=g, t=t: materialize(ordering.single_node_order(g, t), "experiment"))
            yield {"graph": w, "code": f"one node, {t} threads", **_quality(g, labels), "seconds": secs}


def gather(spark, sf, w="w2"):
    """Seconds to gather, order and deal out, and the outcome with too little room, beside the distributed sweep."""
    g = graph(spark, sf, w)
    _, secs = _timed(lambda: _labels(g, plan="sweep"))
    for limit in (ordering.TASK_EDGES, 1000):
        yield {"graph": w, "limit": limit, **ordering.gather_report(g, limit), "sweep_seconds": secs}


def scaling(spark, sf, names=("w1", "w2", "w4"), cores=(1, 2, 4)):
    """Strong scaling in local mode: five parts and the total for each number of cores, with speedup and efficiency. Each run is a process of its own."""
    for w in names:
        runs = {}
        for c in cores:
            code = f"import json; from bandspark.session import local_session; from bandspark.experiments import phases; s = local_session({c}); s.sparkContext.setLogLevel('ERROR'); print('ROW', json.dumps(next(iter(phases(s, {sf!r}, {w!r})))))"
            done = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, check=True)
            runs[c] = json.loads(next(x for x in done.stdout.splitlines() if x.startswith("ROW "))[4:])
        gain = speedups({c: r["total"] for c, r in runs.items()})
        for c, r in runs.items():
            yield {"cores": c, **r, "speedup": round(gain[c][0], 2), "efficiency": round(gain[c][1], 2)}


def product_split(spark, sf, names=("w1", "w2", "w4"), parts=(4, 16)):
    """One product of the whole graph's widest frontier: seconds computing against seconds in the shuffle, words and messages moved, beside the model's."""
    old = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for w in names:
            g = graph(spark, sf, w)
            x, shape = g.vertices.where("v % 3 = 0").select("v", F.col("v").alias("x")), g.shape().first()
            for p in parts:
                spark.conf.set("spark.sql.shuffle.partitions", p)
                with measured(spark) as m:
                    primitives.spmspv(g.edges, x).write.format("noop").mode("overwrite").save()
                bound = CostModel().spmspv(shape["n"], shape["nnz_offdiag"] // 2, p)
                yield {"graph": w, "partitions": p, **m, "model_words": round(bound["words"]), "model_messages": round(bound["messages"])}
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)


def sizes(spark, sf, w="w1"):
    """One graph over the scale factors there are: seconds a directed edge."""
    root = pathlib.Path(sf).parent
    for d in sorted(p for p in root.iterdir() if p.name.startswith("sf")):
        g = graph(spark, str(d), w)
        m = g.edges.count()
        labels, secs = _timed(lambda g=g: _labels(g, plan="sweep"))
        yield {"sf": d.name, "graph": w, "vertices": labels.count(), "edges": m, "seconds": secs, "microseconds_an_edge": round(1e6 * secs / m, 2)}


def sorts(spark, sf, w="w2"):
    """Bucket, general and single-window ranks of one large frontier, by real parents' labels."""
    g = graph(spark, sf, w)
    half = g.vertices.where("v >= 1000000000").select("v")
    parents = materialize(ranking.sort_rank(half, ["v"], "general"), "experiment")
    kids = primitives.spmspv(g.edges, parents.select("v", F.col("rank").alias("x"))).join(g.vertices, "v")
    kids, span = materialize(kids, "experiment"), parents.count()
    for s in ranking.STRATEGIES:
        n, secs = _timed(lambda s=s: ranking.sort_rank(kids, ["x", "deg", "v"], s, 0, span).agg(F.max("rank")).first()[0])
        yield {"graph": w, "strategy": s, "rows": n + 1, "seconds": secs}


def sort_free(spark, sf, names=("w1", "w4", "w14")):
    """What leaving out the degree, or the sort by parents, costs in quality."""
    for w in names:
        g = graph(spark, sf, w)
        for s in ("degree", "parent", "level", "end"):
            labels, secs = _timed(lambda g=g, s=s: _labels(g, plan="sweep", sort=s))
            yield {"graph": w, "sort": s, **_quality(g, labels), "seconds": secs}


def roots(spark, sf, names=("w1", "w4", "w5", "w14")):
    """Start as given, classic and algebraic search: depth and quality."""
    for w in names:
        g = graph(spark, sf, w)
        for v in ("first", "classic", "algebraic"):
            o = ordering.frontier_order(g, v)
            yield {"graph": w, "root": v, "depth": o.roots.agg(F.max("depth")).first()[0], "searches": o.roots.agg(F.max("searches")).first()[0], **_quality(g, o.labels)}


def layouts(spark, sf, w="w13"):
    """Pairs against compressed columns against two-dimensional blocks, one product."""
    g = graph(spark, sf, w)
    x = g.vertices.where("v % 7 = 0").select("v", F.col("v").alias("x"))
    columns, blocked = materialize(distribution.adjacency(g.edges), "columns"), materialize(distribution.distribute_2d(g.edges, 4, 4), "blocks")
    for name, f in (("pairs", lambda: primitives.spmspv(g.edges, x)), ("columns", lambda: distribution.spmspv_adjacency(columns, x)), ("blocks", lambda: distribution.spmspv_2d(blocked, x))):
        total, secs = _timed(lambda f=f: f().agg(F.sum("x")).first()[0])
        yield {"graph": w, "layout": name, "checksum": total, "seconds": secs}


def relabel(spark, sf, names=("w4", "w6")):
    """Balance of blocks and quality before and after a random relabelling."""
    for w in names:
        g = graph(spark, sf, w)
        other, _ = distribution.random_relabel(g, 7)
        for name, h in (("as given", g), ("relabelled", other)):
            by_range = h.edges.withColumn("br", F.floor(F.col("dst") * 4 / (h.vertices.agg(F.max("v")).first()[0] + 1))).withColumn("bc", F.floor(F.col("src") * 4 / (h.vertices.agg(F.max("v")).first()[0] + 1)))
            yield {"graph": w, "ids": name, "balance": distribution.balance(by_range).first().ratio, "natural": _quality(h, ordering.natural_order(h)), "ordered": _quality(h, _labels(h))}


def asynchronous(spark, sf, w="w7"):
    """Rounds of relaxation against levels."""
    g = graph(spark, sf, w)
    comps = ordering.with_components(g).select("comp").distinct().select(F.col("comp").alias("v"))
    (found, rounds), secs = _timed(lambda: traverse.levels_async(g.edges, comps))
    yield {"graph": w, "rounds": rounds, "levels": found.agg(F.max("level")).first()[0] + 1, "seconds": secs}


def diameters(spark, sf, names=("w12", "w1", "w14", "w4", "w5", "w6")):
    """Seconds, and seconds a level, from shallow to deep graphs, by distributed sweeps."""
    for w in names:
        g = graph(spark, sf, w)
        o, _ = _timed(lambda g=g: ordering.frontier_order(g, plan="sweep"))
        labels, secs = _timed(lambda g=g: _labels(g, plan="sweep"))
        depth = o.roots.agg(F.max("depth")).first()[0]
        yield {"graph": w, "vertices": labels.count(), "depth": depth, "seconds": secs, "seconds_a_level": round(secs / (depth + 1), 4)}


def phases(spark, sf, w="w1"):
    """Five-part breakdown of the distributed method; every phase ends in an action: the root search's products and the rest of it, the ordering's products, ranks and the rest."""
    g, t = graph(spark, sf, w), Trace()
    with t.phase("root_other"):
        placed = ordering.with_components(g)
        table = ordering.component_table(placed)
        sweeper = Sweeper(g, placed)

    def levels(roots):
        with t.phase("root_product"):
            return sweeper.levels(roots)

    began = time.perf_counter()
    found, _ = search(levels, g.vertices, table.select("comp", F.col("comp").alias("v")))
    t.phases["root_other"] += time.perf_counter() - began - t.phases["root_product"]
    own_product, own_rank = sweep.spmspv, sweep.sort_rank

    def timed(name, f):
        def run(*args, **options):
            with t.phase(name):
                return materialize(f(*args, **options), "phase")

        return run

    began, before = time.perf_counter(), t.total
    try:
        sweep.spmspv, sweep.sort_rank = timed("order_product", own_product), timed("order_sort", own_rank)
        sweeper.algebraic(found.select("comp", F.col("root").alias("v")), table)
    finally:
        sweep.spmspv, sweep.sort_rank = own_product, own_rank
    t.phases["order_other"] += time.perf_counter() - began - (t.total - before)
    yield {"graph": w, **{k: round(t.phases.get(k, 0.0), 3) for k in PHASES}, "total": round(t.total, 3)}


def costs(spark, sf, w="w1"):
    """The cost model over processes."""
    s = graph(spark, sf, w).shape().first()
    for p in (1, 4, 16, 64, 256, 1024, 4096):
        yield {"graph": w, "processes": p, **CostModel().ordering(s["n"], s["nnz_offdiag"] // 2, p, 2)}


EXPERIMENTS = {f.__name__: f for f in (structure, solver, plans, concurrency, hybrid, shared, gather, scaling, product_split, sizes, sorts, sort_free, roots, layouts, relabel, asynchronous, diameters, phases, costs)}


def main(args: list[str]) -> None:
    spark = local_session()
    spark.sparkContext.setLogLevel("ERROR")
    sf = args[1] if len(args) > 1 else "/root/testdata/sf0.01"
    for name in list(EXPERIMENTS) if args[:1] in ([], ["all"]) else args[:1]:
        mark = written()
        for row in EXPERIMENTS[name](spark, sf):
            print(json.dumps({"experiment": name, **row}, default=str), flush=True)
        forget(spark, mark)


if __name__ == "__main__":
    main(sys.argv[1:])
