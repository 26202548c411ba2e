"""Column functions and Python function surfaces that graph users need beside the built-in ones."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def json_number(c: Column, key: str) -> Column:
    return F.get_json_object(c, f"$.{key}").cast("long")


def url_part(c: Column, part: str) -> Column:
    """scheme, host or path of a url by patterns, null-safe for malformed ones."""
    pattern = {"scheme": r"^([a-z]+)://", "host": r"^[a-z]+://([^/]+)", "path": r"^[a-z]+://[^/]+([^?#]*)"}[part]
    return F.regexp_extract(c, pattern, 1)


def adjacency(src: Column, weight: Column) -> Column:
    """Map from neighbour to weight."""
    return F.map_from_entries(F.sort_array(F.collect_list(F.struct(src, weight))))


def as_text(array: Column) -> Column:
    return F.concat_ws(",", F.transform(array, lambda x: x.cast("string")))


@F.pandas_udf(LongType())
def words_in(text: pd.Series) -> pd.Series:
    """Words by white space: an Arrow-batched scalar function."""
    return text.fillna("").str.split().str.len()


@F.pandas_udf(LongType())
def mode_least(values: pd.Series) -> int:
    """The commonest value, the least of equals: a grouped aggregate."""
    return int(values.mode().min())


@F.udtf(returnType=StructType([StructField("dst", LongType()), StructField("src", LongType())]), useArrow=True)
class CsrRows:
    """Table function: the edges of one CSR shard; its rows travel in Arrow batches."""

    def eval(self, lo: int, row: list[int], col: list[int]) -> Iterator[tuple[int, int]]:
        for r in range(len(row) - 1):
            yield from ((lo + r, s) for s in col[row[r] : row[r + 1]])


def codec_sizes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow kernel: bytes of each batch's binary column under a codec."""
    for b in batches:
        raw = [x.as_py() for x in b.column(0)]
        yield pa.RecordBatch.from_arrays([pa.array([len(x) for x in raw]), pa.array([len(pa.Codec("snappy").compress(x, asbytes=True)) for x in raw])], names=["raw", "packed"])


def register_sql(spark: SparkSession) -> None:
    """SQL functions: a damping step as an inlined expression, and the CSR table function."""
    spark.sql("create or replace temporary function damped(x double, n long) returns double return 0.15D / n + 0.85D * x")
    spark.udtf.register("csr_rows", CsrRows)
