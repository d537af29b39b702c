"""Where iterative plans are cut: tables in the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator, Sequence
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

#: Folders made for applications that have none configured, by application id.
_own: dict[str, str] = {}
#: Setting by which Spark deletes the shuffle files of an execution at its end.
_SWEEP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: Tables of the scopes that are open, innermost last.
_scopes: list[list[tuple[SparkSession, str, str | None]]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir. One is made only under a local master; a cluster's executors could not share it."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        app = spark.sparkContext.applicationId
        found = _own.get(app) or _own.setdefault(app, "file://" + tempfile.mkdtemp(prefix="ripplerank-"))
    return found.rstrip("/")


def _hadoop(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def shared_path(spark: SparkSession, label: str) -> str:
    """A fresh path there, deleted when the driver's JVM ends."""
    path = f"{shared_dir(spark)}/ripplerank/{label}-{uuid.uuid4().hex}"
    fs, where = _hadoop(spark, path)
    fs.deleteOnExit(where)
    return path


def _made(df: DataFrame, path: str, table: str | None = None) -> DataFrame:
    df._cut = (df.sparkSession, path, table)
    if _scopes:
        _scopes[-1].append(df._cut)
    return df


@contextmanager
def swept(spark: SparkSession) -> Iterator[None]:
    """The shuffle files of what is written within are deleted as soon as it is written, not when the driver happens to collect its garbage."""
    before = spark.conf.get(_SWEEP, None)
    spark.conf.set(_SWEEP, "true")
    try:
        yield
    finally:
        spark.conf.unset(_SWEEP) if before is None else spark.conf.set(_SWEEP, before)


def cut(df: DataFrame, label: str, metrics: dict[str, Column] | None = None, codec: str = "snappy") -> DataFrame:
    """Write `df` and read it back: the next lap's plan starts here, and a lost executor costs a re-read.

    `metrics` (aggregates by name) are taken while the rows are written; they stand in `facts` of what is returned.
    """
    spark = df.sparkSession
    path = shared_path(spark, label)
    schema = df.schema
    if metrics:
        seen = Observation()
        df = df.observe(seen, *[c.alias(n) for n, c in metrics.items()])
    with swept(spark):
        df.write.parquet(path, compression=codec)
    out = _made(spark.read.schema(schema).parquet(path), path)
    if metrics:
        out.facts = seen.get
    return out


def bucketed(df: DataFrame, label: str, keys: Sequence[str], buckets: int, path: str | None = None) -> DataFrame:
    """Write `df` hashed once into `buckets` by `keys`, sorted within: joins on just these keys move the other side only.

    The files lie in the shared folder, or at `path` for good, under a table name of their own. The sort also lets literal filters on
    the keys skip row groups.
    """
    spark = df.sparkSession
    where, name = path or shared_path(spark, label), f"ripplerank_{uuid.uuid4().hex}"
    with swept(spark):
        df.repartition(buckets, *keys).write.bucketBy(buckets, *keys).sortBy(*keys).option("path", where).saveAsTable(name)
    out = spark.table(name)
    return out if path else _made(out, where, name)


def open_bucketed(spark: SparkSession, path: str, schema: str, key: str, buckets: int) -> DataFrame:
    """Files that were written in buckets, opened again in any session."""
    name = f"ripplerank_{uuid.uuid4().hex}"
    spark.sql(f"create table {name} ({schema}) using parquet options (path '{path}') clustered by ({key}) sorted by ({key}) into {buckets} buckets")
    return spark.table(name)


def children(spark: SparkSession, path: str) -> list[str]:
    """Names in a folder of any Hadoop file system."""
    fs, where = _hadoop(spark, path)
    return [s.getPath().getName() for s in fs.listStatus(where)]


def bucket_count(spark: SparkSession, rows: int, per_bucket: int = 4_000_000) -> int:
    """Buckets for so many rows: of bounded size, and enough to occupy the cluster where there is work for it."""
    busy = min(spark.sparkContext.defaultParallelism, -(-rows // 20_000))
    return max(1, busy, -(-rows // per_bucket))


def release(*frames: DataFrame | None) -> None:
    """Delete the tables that `cut` or `bucketed` wrote for these, once nothing reads them any more."""
    for df in frames:
        if df is not None and (made := getattr(df, "_cut", None)):
            _drop(*made)


def _drop(spark: SparkSession, path: str, table: str | None) -> None:
    if table:
        spark.sql(f"drop table if exists {table}")
    fs, where = _hadoop(spark, path)
    fs.delete(where, True)
    fs.cancelDeleteOnExit(where)


@contextmanager
def scope() -> Iterator[None]:
    """Tables that are cut within are deleted at the end: for answers that are written out before it."""
    _scopes.append([])
    try:
        yield
    finally:
        for made in _scopes.pop():
            _drop(*made)


def tree_bytes(spark: SparkSession, path: str) -> int:
    """Bytes of all files under a path of any Hadoop file system."""
    fs, where = _hadoop(spark, path)
    return int(fs.getContentSummary(where).getLength())
