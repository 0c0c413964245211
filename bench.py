"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from bandspark import catalogue
from bandspark.session import forget, local_session, written

#: The distributed method first (level by level, and with small levels fused), then the one-task kernel, then parts.
HEADLINE = ("order_loop_w1", "order_loop_w8", "order_loop_w13", "order_sweep_w1", "order_sweep_w2", "order_sweep_w4", "order_sweep_w5", "order_sweep_w6", "order_w1", "order_w2", "order_w4", "order_w5", "order_w8", "metrics_w1", "root_w4", "components_w2", "sort_bucket_w1", "sort_general_w1", "primitive_spmspv")


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local_session(int(os.environ.get("BENCH_CPUS", "8")), "bench")
    spark.sparkContext.setLogLevel("ERROR")
    spark.range(1000).selectExpr("sum(id)").collect()
    found, queries = {}, catalogue.queries()
    for name in HEADLINE:
        mark, began = written(), time.perf_counter()
        queries[name](spark, sf).write.format("noop").mode("overwrite").save()
        found[name] = round(time.perf_counter() - began, 3)
        forget(spark, mark)
    print(json.dumps({"metric": "headline_total", "value": round(sum(found.values()), 3), "unit": "sec", "queries": found, "sf": sf.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
