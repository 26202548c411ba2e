"""Edge lists in files of any format, bucketed tables, and a data source over CSR payload files."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, InputPartition

from shardgraph.model.schema import EDGES
from shardgraph.session import scratch_path


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = EDGES, sep: str = ",") -> DataFrame:
    """An edge list with a declared schema; nothing is inferred."""
    r = spark.read.schema(schema)
    if fmt == "csv":
        return r.option("sep", sep).csv(path)
    if fmt == "text":
        lines = spark.read.text(path)
        from pyspark.sql import functions as F

        parts = F.split(F.trim("value"), r"\s+")
        names = [x.split()[0] for x in schema.split(", ")]
        return lines.where("trim(value) <> '' and not value like '#%'").select(*(F.try_element_at(parts, F.lit(k + 1)).cast("long").alias(n) for k, n in enumerate(names)))
    return getattr(r, fmt)(path)


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite") -> None:
    getattr(edges.write.mode(mode), fmt)(path)


def save_bucketed(edges: DataFrame, name: str, buckets: int = 16) -> None:
    """A table whose rows of one destination share a bucket: grouping and joining on dst needs no shuffle."""
    spark = edges.sparkSession
    spark.sql(f"drop table if exists {name}")
    edges.write.option("path", scratch_path(spark, name)).bucketBy(buckets, "dst").sortBy("dst").saveAsTable(name)


class CsrShards(DataSource):
    """Format csr_shards: a folder of compressed shard files, one input partition each; equality on shard_id skips files.

    Files are <shard>.z, written by write_csr_files to a folder that the driver and executors share as a path.
    """

    @classmethod
    def name(cls) -> str:
        return "csr_shards"

    def schema(self) -> str:
        return "shard_id int, src long, dst long"

    def reader(self, schema) -> DataSourceReader:
        return _CsrReader(self.options["path"])


class _CsrReader(DataSourceReader):
    def __init__(self, path: str):
        self.path, self.only = path, None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("shard_id",):
                self.only = f.value
            else:
                yield f

    def partitions(self) -> list[InputPartition]:
        fs, at = _files(self.path)
        found = [f.base_name for f in fs.get_file_info(pafs.FileSelector(at))]
        ids = sorted(int(f[:-2]) for f in found if f.endswith(".z"))
        return [InputPartition(k) for k in ids if self.only in (None, k)] or [InputPartition(-1)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        k = partition.value
        if k < 0:
            return
        fs, at = _files(self.path)
        with fs.open_input_stream(f"{at}/{k}.z") as f:
            x = np.frombuffer(zlib.decompress(f.read()), "<i8")
        lo, n = int(x[0]), int(x[1])
        row, col = x[2 : 2 + n], x[2 + n :]
        dst = np.repeat(np.arange(lo, lo + n - 1), np.diff(row))
        for i in range(0, len(col), 1 << 16):
            part = col[i : i + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), k, np.int32)), pa.array(part), pa.array(dst[i : i + (1 << 16)])], names=["shard_id", "src", "dst"])


def _files(path: str) -> tuple[pafs.FileSystem, str]:
    """The file system of a path and the path in it; one without a scheme is of the local, or mounted, file system."""
    if "://" in path:
        return pafs.FileSystem.from_uri(path)
    return pafs.LocalFileSystem(), path.removeprefix("file:")


def write_csr_files(csr: DataFrame, path: str) -> None:
    """CSR rows as files of the csr_shards format, by the tasks that hold them; a file that a task writes again is the same."""
    fs, at = _files(path)
    fs.create_dir(at)

    def put(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, at = _files(path)
        for b in batches:
            for i in range(b.num_rows):
                row, col = (b.column(c)[i].values.to_numpy() for c in ("row", "col"))
                block = np.concatenate([[b.column("lo")[i].as_py(), len(row)], row, col]).astype("<i8").tobytes()
                with fs.open_output_stream(f"{at}/{b.column('shard_id')[i].as_py()}.z") as f:
                    f.write(zlib.compress(block, 3))
            yield pa.RecordBatch.from_arrays([b.column("shard_id")], names=["shard_id"])

    csr.select("shard_id", "lo", "row", "col").mapInArrow(put, "shard_id int").count()


def register(spark: SparkSession) -> None:
    spark.dataSource.register(CsrShards)
