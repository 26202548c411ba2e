"""Scratch tables in the folder that driver and executors share."""

from __future__ import annotations

import atexit
import hashlib
import threading
import uuid
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or a folder of our own where it is unset (single machine, tests)."""
    sc = spark.sparkContext
    at = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not at:
        at = f"/tmp/checkpoints/{sc.applicationId}"
        sc.setCheckpointDir(at)
    return at.rstrip("/")


def scratch_path(spark: SparkSession, label: str) -> str:
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    atexit.register(forget, spark, path)
    return path


def forget(spark: SparkSession, path: str) -> None:
    """Delete a scratch folder; the session may already be gone."""
    try:
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # noqa: BLE001  scratch only
        pass


def exists(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)


def saved(df: DataFrame, label: str = "table", partition_by: tuple[str, ...] = ()) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: lineage is cut and lost executors lose nothing."""
    path = scratch_path(df.sparkSession, label)
    w = df.write
    if partition_by:
        w = w.partitionBy(*partition_by)
    with dealt_by_one_key(df.sparkSession):
        w.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def table_name(path: str) -> str:
    """The session's name of the bucketed table at path."""
    return "shardgraph_" + hashlib.md5(path.encode()).hexdigest()[:20]


def bucketed(df: DataFrame, path: str, key: str, buckets: int, sort: tuple[str, ...] = ()) -> DataFrame:
    """Write df under path in buckets of key, one file each, and read it as a table that joins and groups on key don't shuffle."""
    w = df.repartition(buckets, key).write.bucketBy(buckets, key)
    if sort:
        w = w.sortBy(*sort)
    with dealt_by_one_key(df.sparkSession):
        w.option("path", path).saveAsTable(table_name(path))
    return df.sparkSession.table(table_name(path))


def open_bucketed(spark: SparkSession, path: str, schema: str, key: str, buckets: int) -> DataFrame:
    """The same for files that another session wrote."""
    spark.sql(f"create table if not exists {table_name(path)} ({schema}) using parquet clustered by ({key}) into {buckets} buckets location '{path}'")
    return spark.table(table_name(path))


#: How many threads are inside dealt_by_one_key, by session, and the setting that the last of them puts back.
_INSIDE: dict[int, tuple[int, str | None]] = {}
_TURN = threading.Lock()


@contextmanager
def dealt_by_one_key(spark: SparkSession) -> Iterator[None]:
    """Plans made in here may join on several keys tables that are both dealt by one of them, without dealing them again."""
    key, session = "spark.sql.requireAllClusterKeysForCoPartition", id(spark)
    with _TURN:
        inside, old = _INSIDE.get(session) or (0, spark.conf.get(key, None))
        spark.conf.set(key, "false")
        _INSIDE[session] = inside + 1, old
    try:
        yield
    finally:
        with _TURN:
            inside, old = _INSIDE.pop(session)
            if inside > 1:
                _INSIDE[session] = inside - 1, old
            else:
                spark.conf.unset(key) if old is None else spark.conf.set(key, old)


def together(spark: SparkSession, *steps: Callable) -> list:
    """What the steps return; they run at the same time, as their jobs leave cores free. The first error is raised once all have ended."""
    if len(steps) < 2:
        return [f() for f in steps]
    with ThreadPoolExecutor(len(steps)) as pool:
        return [x.result() for x in [pool.submit(inheritable_thread_target(spark)(f)) for f in steps]]


def drop_bucketed(spark: SparkSession, path: str) -> None:
    """Forget such a table and delete its files."""
    spark.sql(f"drop table if exists {table_name(path)}")
    forget(spark, path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """Rows of few files dealt to all cores, for work that is long for each row: a file's row group is one task, however many
    splits the file has. Tables of more files or splits than cores are left as they lie."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    few = len(df.inputFiles()) < cores and df.rdd.getNumPartitions() <= cores
    return df.repartition(cores) if few else df
