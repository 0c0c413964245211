"""What Spark's own stage metrics say of a piece of work: time computing against time in shuffles, and words and messages moved."""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import SparkSession

_FIELDS = {"run_ms": "executorRunTime", "fetch_wait_ms": "shuffleFetchWaitTime", "write_ns": "shuffleWriteTime", "read_bytes": "shuffleReadBytes", "write_bytes": "shuffleWriteBytes", "read_records": "shuffleReadRecords", "tasks": "numCompleteTasks"}


def _stages(spark: SparkSession) -> dict[int, dict]:
    found = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), spark.sparkContext._jvm.java.util.ArrayList())
    out = {}
    for i in range(found.size()):
        s = found.apply(i)
        out[s.stageId()] = {k: getattr(s, f)() for k, f in _FIELDS.items()}
    return out


@contextmanager
def measured(spark: SparkSession):
    """Yields a dict that holds, after the block: task_seconds, shuffle_seconds (waiting for fetches and writing), words (8 bytes), messages (map outputs read), tasks."""
    out: dict = {}
    before = set(_stages(spark))
    yield out
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    new = [s for i, s in _stages(spark).items() if i not in before]
    total = {k: sum(s[k] for s in new) for k in _FIELDS}
    shuffle = total["fetch_wait_ms"] / 1e3 + total["write_ns"] / 1e9
    out.update({"task_seconds": round(total["run_ms"] / 1e3, 3), "shuffle_seconds": round(shuffle, 3), "compute_seconds": round(max(0.0, total["run_ms"] / 1e3 - shuffle), 3), "words": total["write_bytes"] // 8, "messages": total["tasks"], "stages": len(new)})
