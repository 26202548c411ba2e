"""Helpers that the corpus operators share: reading, scratch tables, ranks and components."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: The white space that words and lines are cut at, [\x20\x09-\x0D].
SPACE = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def ascii_lower(c: Column) -> Column:
    """A-Z only; other letters stay."""
    return F.translate(c, UPPER, LOWER)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one of our own where it is unset (tests)."""
    sc = spark.sparkContext
    at = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not at:
        at = f"/tmp/checkpoints/{sc.applicationId}"
        sc.setCheckpointDir(at)
    return at.rstrip("/")


def _forget(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # noqa: BLE001  the session may be gone; the folder is scratch
        pass


def saved(df: DataFrame, label: str = "t", few: bool = False) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: cuts lineage, survives lost executors.

    few: write two files a core at most, for tables that are much smaller than the input.
    """
    spark = df.sparkSession
    if few:
        df = df.coalesce(2 * spark.sparkContext.defaultParallelism)
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    atexit.register(_forget, spark, path)
    return spark.read.schema(df.schema).parquet(path)


def drop_saved(df: DataFrame) -> None:
    """Delete the files of a table made by saved() that nothing reads any more."""
    for f in {x.rsplit("/", 1)[0] for x in df.inputFiles()}:
        _forget(df.sparkSession, f)


def with_index(df: DataFrame, order: list[Column], name: str) -> DataFrame:
    """Add a global 0-based row index by `order` without a single-task sort.

    Rows are range-partitioned and written, so the sampled bounds are fixed; only one count
    for each partition is summed in one task (as many rows as there are partitions).
    """
    parts = saved(df.repartitionByRange(*order).withColumn("_wi_pid", F.spark_partition_id()), "ranged")
    sums = Window.orderBy("_wi_pid").rowsBetween(Window.unboundedPreceding, -1)
    offsets = parts.groupBy("_wi_pid").agg(F.count("*").alias("_wi_n")).select("_wi_pid", F.coalesce(F.sum("_wi_n").over(sums), F.lit(0)).alias("_wi_off"))
    local = F.row_number().over(Window.partitionBy("_wi_pid").orderBy(*order))
    return parts.join(F.broadcast(offsets), "_wi_pid").withColumn(name, F.col("_wi_off") + local - 1).drop("_wi_pid", "_wi_off")


def components(edges: DataFrame, max_rounds: int = 200) -> DataFrame:
    """(id, root): the smallest id reachable over edges(a, b), for every id that has an edge.

    Contraction: each id hooks on its smallest lower neighbour, pointer jumping turns the hooks
    into stars, and edges are renamed by their roots until none joins two roots. Every state is
    a written table, joins meet tables on plain keys, so AQE can split hot keys, and nothing is collected but counts.
    """
    e = saved(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct(), "cc-edges", few=True)
    whole = None
    for _ in range(max_rounds):
        if e.isEmpty():
            break
        p = saved(e.groupBy(F.col("b").alias("id")).agg(F.min("a").alias("root")), "cc-hook", few=True)
        for _ in range(64):  # each jump halves the depth
            up = p.select(F.col("id").alias("root"), F.col("root").alias("up"))
            q = saved(p.join(up, "root", "left").select("id", F.coalesce("up", "root").alias("root"), F.col("up").isNotNull().alias("moved")), "cc-jump", few=True)
            moved = not q.where("moved").isEmpty()
            p = q.select("id", "root")
            if not moved:
                break
        if whole is None:
            whole = p
        else:
            up = p.select(F.col("id").alias("root"), F.col("root").alias("up"))
            old = whole.join(up, "root", "left").select("id", F.coalesce("up", "root").alias("root"))
            whole = saved(old.unionByName(p.join(whole.select("id"), "id", "left_anti")), "cc-whole", few=True)
        pa, pb = p.select(F.col("id").alias("a"), F.col("root").alias("ra")), p.select(F.col("id").alias("b"), F.col("root").alias("rb"))
        r = e.join(pa, "a", "left").join(pb, "b", "left").select(F.coalesce("ra", "a").alias("x"), F.coalesce("rb", "b").alias("y"))
        e = saved(r.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "cc-edges", few=True)
    else:
        raise RuntimeError("components did not settle")
    if whole is None:
        return e.select(F.col("a").alias("id"), F.col("b").alias("root"))
    roots = whole.select("root").distinct().select(F.col("root").alias("id"), "root")
    return whole.unionByName(roots)


def packed(df: DataFrame) -> DataFrame:
    """df as one column _d, so that no name of its columns can meet a name of ours."""
    return df.select(F.struct(*(F.col(f"`{c}`") for c in df.columns)).alias("_d"))


def own(df: DataFrame, but: tuple[str, ...] = ()) -> list[Column]:
    """df's columns out of packed(df), without those named."""
    return [F.col(f"_d.`{c}`").alias(c) for c in df.columns if c not in but]


def in_blocks(df: DataFrame, key: str, row_hash: Column, block: int) -> DataFrame:
    """df dealt and sorted by (key, _lo, _hi), with _own: rows of a key up to `block` stay together, as block 0 with 0.

    A larger key's rows are dealt in blocks by row_hash, and every two blocks meet under a key of
    their own (a block with itself too), so no task holds more than about `block` rows of one key.
    """
    large = df.groupBy(key).agg(F.count("*").alias("_n")).where(F.col("_n") > block)
    large = saved(large.select(key, F.ceil(2 * F.col("_n") / block).cast("int").alias("_k")), "large-keys", few=True)  # few: each has over `block` rows
    if large.isEmpty():
        zero = F.lit(0)
        out = df.withColumns({"_own": zero, "_lo": zero, "_hi": zero})
    else:
        met = df.join(large, key, "left").withColumn("_own", F.when(F.col("_k").isNull(), 0).otherwise(F.pmod(row_hash, F.col("_k"))).cast("int"))
        all_ = F.sequence(F.lit(0), F.coalesce(F.col("_k") - 1, F.lit(0)))
        out = met.withColumn("_p", F.explode(all_)).withColumns({"_lo": F.least("_own", "_p"), "_hi": F.greatest("_own", "_p")}).drop("_p", "_k")
    return out.repartition(key, "_lo", "_hi").sortWithinPartitions(key, "_lo", "_hi")


def whole_runs(batches: Iterator[pa.RecordBatch], keys: int = 3) -> Iterator[tuple[np.ndarray, pa.Table]]:
    """(run lengths, rows) of sorted rows, cut so that no run of equal first `keys` columns spans two tables."""
    held: list[pa.Table] = []

    def starts(t: pa.Table) -> np.ndarray:
        new = np.zeros(t.num_rows, bool)
        new[:1] = True
        for k in range(keys):
            c = t.column(k).to_numpy()
            new[1:] |= c[1:] != c[:-1]
        return np.flatnonzero(new)

    def out(t: pa.Table) -> tuple[np.ndarray, pa.Table]:
        return np.diff(np.append(starts(t), t.num_rows)), t.combine_chunks()

    for b in batches:
        if not b.num_rows:
            continue
        t = pa.Table.from_batches([b])
        last = int(starts(t)[-1])
        if held and not last and [c[0] for c in held[0].columns[:keys]] == [c[0] for c in t.columns[:keys]]:
            held.append(t)  # one run goes on
            continue
        head = t.slice(0, last)
        if held or last:
            yield out(pa.concat_tables([*held, head]))
        held = [t.slice(last)]
    if held:
        yield out(pa.concat_tables(held))


def shared_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows (s, node) sorted by both, the distinct ones whose s has another node."""
    held, goes_on = None, False  # the last row met, and whether its run began before it
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = np.stack([batch.column(k).to_numpy() for k in range(2)], 1)
        if held is not None:
            rows = np.concatenate([held, rows])
        rows = rows[np.append(True, (rows[1:] != rows[:-1]).any(1))]
        same = rows[1:, 0] == rows[:-1, 0]
        before = np.append(goes_on, same)
        held, goes_on = rows[-1:], bool(before[-1])
        out = rows[:-1][before[:-1] | same]
        yield pa.RecordBatch.from_arrays([pa.array(out[:, 0]), pa.array(out[:, 1])], names=["s", "node"])
    if held is not None and goes_on:
        yield pa.RecordBatch.from_arrays([pa.array(held[:, 0]), pa.array(held[:, 1])], names=["s", "node"])


class Links:
    """Sets of linked positions (union by least position), and the links that joined two of them."""

    def __init__(self, n: int):
        self.up, self.made = np.arange(n), []

    def find(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def join(self, a: np.ndarray, b: np.ndarray) -> None:
        for i, j in zip(a.tolist(), b.tolist(), strict=True):
            x, y = self.find(i), self.find(j)
            if x != y:
                self.up[max(x, y)] = min(x, y)
                self.made.append((i, j))

    def roots(self) -> np.ndarray:
        up = self.up
        while not np.array_equal(up, nxt := up[up]):
            up = nxt
        self.up = up
        return up
