"""Session helpers: where shared intermediate data goes, and how lineage is cut."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


#: Folders written by this process, in order.
_WRITTEN: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder every executor can read: ``spark.checkpoint.dir``. Only a local session without one gets a temporary folder."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir is unset: name a folder that all executors share")
        at = "file://" + tempfile.mkdtemp(prefix="bandspark-shared-")
        spark.sparkContext.setCheckpointDir(at)
    return at


def new_folder(spark: SparkSession, name: str) -> str:
    """A path of its own in the shared folder."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _WRITTEN.append(path)
    return path


def materialize(df: DataFrame, name: str = "stage", partition_by: list[str] | None = None, path: str | None = None) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder (or at ``path``) and read it back: lineage is cut and survives lost executors."""
    spark = df.sparkSession
    path = path or new_folder(spark, name)
    writer = df.write.mode("overwrite")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    before = spark.conf.get(_CLEANUP, None)
    try:
        spark.conf.set(_CLEANUP, "true")  # the table is what is read from now on: its shuffle files can go with the query
        writer.parquet(path)
    finally:
        spark.conf.unset(_CLEANUP) if before is None else spark.conf.set(_CLEANUP, before)
    return spark.read.schema(df.schema).parquet(path)


def apart(spark: SparkSession) -> SparkSession:
    """A session on the same context with the same settings, whose views and later settings are its own: for jobs of another thread."""
    return SparkSession(spark.sparkContext, spark._jsparkSession.cloneSession())


@contextmanager
def arrow_rows(spark: SparkSession, rows: int) -> Iterator[None]:
    """Jobs run inside send Python at most so many rows at once: a batch is held whole on both sides."""
    before = spark.conf.get(_BATCH, None)
    try:
        spark.conf.set(_BATCH, str(rows))
        yield
    finally:
        spark.conf.unset(_BATCH) if before is None else spark.conf.set(_BATCH, before)


class Steps:
    """One table appended to step by step: each step is written once, and all are read as one table, not as a union that grows."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.path, self.schema, self.n = spark, new_folder(spark, name), None, 0

    def put(self, df: DataFrame) -> DataFrame:
        self.schema = self.schema or df.schema
        out = materialize(df, path=f"{self.path}/step={self.n}")
        self.n += 1
        return out

    def all(self) -> DataFrame:
        return self.spark.read.schema(self.schema).option("recursiveFileLookup", "true").parquet(self.path)


def written() -> int:
    """A mark for :func:`forget`: what is written from here on."""
    return len(_WRITTEN)


def forget(spark: SparkSession, since: int = 0) -> None:
    """Delete the stages written since a mark, once nothing reads them any more."""
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for p in _WRITTEN[since:]:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(conf).delete(path, True)
    del _WRITTEN[since:]


def local_session(cores: int = 8, app: str = "bandspark") -> SparkSession:
    """A local session for tests and benches."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName(app)
        .config("spark.sql.shuffle.partitions", str(cores))
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )
