"""Streams of events as edges: windowed counts, late rows, stateful chains, and drift of an ordering."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bandspark.session import shared_dir


#: Later than any event.
END = "9000-01-01 00:00:00"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    base, name = path.rsplit("/", 1)
    reader = spark.readStream.schema(schema)
    rows = reader.option("pathGlobFilter", name).parquet(base) if not _is_folder(spark, path) else reader.parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def _is_folder(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def run_to_end(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs the stream over what there is, into a Parquet folder (append) or a table in memory, and returns the result."""
    spark, tag = df.sparkSession, uuid.uuid4().hex
    writer = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{shared_dir(spark)}/stream-{tag}")
    if mode == "append":
        out = f"{shared_dir(spark)}/stream-out-{tag}"
        query = writer.format("parquet").option("path", out).start()
        query.awaitTermination()
        return spark.read.schema(df.schema).parquet(out)
    query = writer.format("memory").queryName(f"t{tag}").start()
    query.awaitTermination()
    return spark.table(f"t{tag}")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events an hour, complete."""
    counts = event_stream(spark, sf_dir).groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return run_to_end(counts.select(F.col("w.start").alias("start"), "n"), "complete")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = event_stream(spark, sf_dir).groupBy(F.window("ts", "1 hour", "15 minutes").alias("w")).agg(F.count("*").alias("n"))
    return run_to_end(counts.select(F.col("w.start").alias("start"), "n"), "complete")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of a user: gaps of 30 minutes end them. They are as many as the events may be, so they are appended to files, not kept in the driver's memory:
    every event brings a mark of the end of time, which moves the watermark past all sessions once the one batch of what there is has been read, and goes before they are counted."""
    ends = F.lit(END).cast("timestamp")
    marked = event_stream(spark, sf_dir).select("user_id", "ts").withColumn("ts", F.explode(F.array("ts", ends))).withWatermark("ts", "0 seconds").where(F.col("ts") < ends)
    counts = marked.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return run_to_end(counts.select("user_id", F.col("w.start").alias("start"), "n"))


def watermark_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hours that the watermark has closed; rows later than an hour are dropped."""
    counts = event_stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return run_to_end(counts.select(F.col("w.start").alias("start"), "n"))


def dedupe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event twice in, once out."""
    twice = event_stream(spark, sf_dir).withColumn("i", F.explode(F.array(F.lit(0), F.lit(1)))).drop("i")
    return run_to_end(twice.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


def chains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges between consecutive events of a user: the last event of each user is the state."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        ids = ([] if last is None else [last]) + rows["event_id"].tolist()
        state.update((int(ids[-1]),))
        yield pd.DataFrame({"a": ids[:-1], "b": ids[1:]}).astype("int64")

    events = event_stream(spark, sf_dir).select("user_id", "event_id", "ts")
    return run_to_end(events.groupBy("user_id").applyInPandasWithState(step, "a long, b long", "last long", "append", "NoTimeout"))


def join_within_hour(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(view, purchase) of a user within an hour, as a join of two streams."""
    e = event_stream(spark, sf_dir)
    v = e.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("event_id").alias("a"), F.col("ts").alias("ta")).withWatermark("ta", "2 hours")
    p = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb")).withWatermark("tb", "2 hours")
    return run_to_end(v.join(p, F.expr("u = user_id and tb >= ta and tb <= ta + interval 1 hour")).select("a", "b"))


def drift(edges: DataFrame, labels: DataFrame, bandwidth: int, factor: float = 2.0) -> DataFrame:
    """One row for a batch of new pairs (a, b): the bandwidth with them, and whether it calls for a new ordering."""
    li, lj = labels.withColumnsRenamed({"v": "a", "label": "i"}), labels.withColumnsRenamed({"v": "b", "label": "j"})
    now = edges.join(li, "a").join(lj, "b").agg(F.coalesce(F.max(F.abs(F.col("i") - F.col("j"))), F.lit(0)).alias("widest"))
    return now.select(F.greatest("widest", F.lit(bandwidth)).alias("bandwidth"), (F.col("widest") > factor * bandwidth).alias("reorder"))


_STREAMS = {
    "op_stream_tumbling": (tumbling, "SELECT date_trunc('hour', ts) AS start, count(*) AS n FROM events GROUP BY 1"),
    "op_stream_sliding": (sliding, "SELECT start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 15 MINUTE, ts) - INTERVAL (15 * k) MINUTE AS start FROM events, range(4) r(k)) GROUP BY 1"),
    "op_stream_session": (sessions, """SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(g) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM
 (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS g FROM events)) GROUP BY user_id, s"""),
    "op_stream_watermark_late": (watermark_late, "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, count(*) AS n FROM events GROUP BY 1 HAVING time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 2 HOUR <= (SELECT max(ts) FROM events)"),
    "op_stream_dedupe": (dedupe, "SELECT event_id FROM events"),
    "op_stream_stateful": (chains, "SELECT a, b FROM (SELECT lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS a, event_id AS b FROM events) WHERE a IS NOT NULL"),
    "op_stream_join": (join_within_hour, "SELECT v.event_id AS a, p.event_id AS b FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts BETWEEN v.ts AND v.ts + INTERVAL 1 HOUR"),
}


def queries() -> dict:
    return {k: f for k, (f, _) in _STREAMS.items()}


def oracle_sql() -> dict:
    return {k: sql for k, (_, sql) in _STREAMS.items() if sql}
