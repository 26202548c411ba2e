"""The compressed edge cache: codecs, their choice, admission without eviction, and measures."""

from __future__ import annotations

import time
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from shardgraph.session import saved

#: Codecs of the cache modes and the ratios expected of modes 1 to 4.
CODECS = {0: "none", 1: "raw", 2: "snappy", 3: "zlib-1", 4: "zlib-3"}
GAMMAS = (1.0, 2.0, 4.0, 5.0)
EXTRA = ("zstd", "lz4")


def choose_mode(size: float, capacity: float, gammas: tuple[float, ...] = GAMMAS) -> int:
    """The least mode whose expected compressed size fits, else the last; measured ratios may replace the expected ones."""
    return next((i for i, g in enumerate(gammas, 1) if size / g <= capacity), len(gammas))


def mode_of(size: Column, capacity: Column, gammas: tuple[float, ...] = GAMMAS) -> Column:
    """choose_mode of columns."""
    fits = [F.when(size / F.lit(g) <= capacity, F.lit(i)) for i, g in enumerate(gammas, 1)]
    return F.coalesce(*fits, F.lit(len(gammas)))


def compress(raw: bytes, codec: str) -> bytes:
    if codec in ("raw", "none"):
        return raw
    if codec.startswith("zlib-"):
        return zlib.compress(raw, int(codec[5:]))
    return pa.Codec(codec).compress(raw, asbytes=True)


def decompress(packed: bytes, codec: str, size: int) -> bytes:
    if codec in ("raw", "none"):
        return packed
    if codec.startswith("zlib-"):
        return zlib.decompress(packed)
    return pa.Codec(codec).decompress(packed, size, asbytes=True)


def encode(row: np.ndarray, col: np.ndarray, val: np.ndarray | None, delta: bool) -> bytes:
    """The three arrays as 64-bit numbers in one block; with delta, sources as differences to the one before."""
    col = np.diff(col, prepend=0) if delta else col
    parts = [np.array([len(row), len(col), val is not None]), row, col, *([val] if val is not None else [])]
    return np.concatenate(parts).astype("<i8").tobytes()


def decode(block: bytes, delta: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    x = np.frombuffer(block, "<i8")
    n, m, has = int(x[0]), int(x[1]), bool(x[2])
    row, col = x[3 : 3 + n], x[3 + n : 3 + n + m]
    return row, np.cumsum(col) if delta else col, x[3 + n + m :] if has else None


_PAYLOAD = "shard_id int, lo long, hi long, codec string, raw_bytes long, bytes long, pack_s double, unpack_s double, payload binary"


def payloads(csr: DataFrame, codec: str, delta: bool = False, timed: bool = False) -> DataFrame:
    """CSR rows as compressed blocks, with sizes and seconds; only with timed are they unpacked again to measure that."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for k in range(b.num_rows):
                flat = lambda c: b.column(c)[k].values.to_numpy(zero_copy_only=False) if c in b.schema.names else None  # noqa: B023, E731
                raw = encode(flat("row"), flat("col"), flat("val"), delta)
                t0 = time.perf_counter()
                packed = compress(raw, codec)
                t1 = time.perf_counter()
                if timed:
                    decompress(packed, codec, len(raw))
                out.append((*(b.column(c)[k].as_py() for c in ("shard_id", "lo", "hi")), codec, len(raw), len(packed), t1 - t0, time.perf_counter() - t1, packed))
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True) if out else [[]] * 9, (pa.int32(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.binary()), strict=True)], names=[x.split()[0] for x in _PAYLOAD.split(", ")])

    return csr.mapInArrow(run, _PAYLOAD)


_MEASURED = "delta boolean, codec string, raw_bytes long, bytes long, unpack_s double"


def measured(csr: DataFrame, codecs: tuple[str, ...], deltas: tuple[bool, ...]) -> DataFrame:
    """Sizes and seconds of unpacking of each shard under each codec, in one pass: blocks stay where they are packed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(b.num_rows):
                flat = lambda c: b.column(c)[k].values.to_numpy(zero_copy_only=False) if c in b.schema.names else None  # noqa: B023, E731
                out = []
                for delta in deltas:
                    raw = encode(flat("row"), flat("col"), flat("val"), delta)
                    for codec in codecs:
                        packed = compress(raw, codec)
                        t = time.perf_counter()
                        decompress(packed, codec, len(raw))
                        out.append((delta, codec, len(raw), len(packed), time.perf_counter() - t))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), (pa.bool_(), pa.string(), pa.int64(), pa.int64(), pa.float64()), strict=True)], names=[x.split()[0] for x in _MEASURED.split(", ")])

    return csr.select(*(c for c in ("row", "col", "val") if c in csr.columns)).mapInArrow(run, _MEASURED)


def compression_reports(csr: DataFrame, codecs: tuple[str, ...] = ("raw", "snappy", "zlib-1", "zlib-3", *EXTRA), deltas: tuple[bool, ...] = (False, True)) -> DataFrame:
    """(delta, codec, raw_bytes, bytes, ratio, mb_s) of each codec over all shards; mb_s is of decompressed bytes a second and core."""
    each = measured(csr, codecs, deltas).groupBy("delta", "codec").agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("bytes").alias("bytes"), F.sum("unpack_s").alias("s"))
    return each.select("delta", "codec", "raw_bytes", "bytes", F.round(F.col("raw_bytes") / F.col("bytes"), 4).alias("ratio"), F.round(F.col("raw_bytes") / 1e6 / F.greatest("s", F.lit(1e-9)), 1).alias("mb_s"))


def compression_report(csr: DataFrame, codecs: tuple[str, ...] = ("raw", "snappy", "zlib-1", "zlib-3", *EXTRA), delta: bool = False) -> DataFrame:
    """The same with one way to write sources, which is no column."""
    return compression_reports(csr, codecs, (delta,)).drop("delta")


def admission(sizes: DataFrame, capacity: int) -> DataFrame:
    """(shard_id, bytes, cached): shards are visited by id and stay while room remains; nothing is evicted.

    A shard that doesn't fit is left out and later, smaller ones may still enter, as the running sum
    counts admitted shards only. sizes has one row a shard.
    """
    return sizes.sparkSession.createDataFrame(admitted(sizes, capacity), "shard_id int, bytes long, cached boolean")


def admitted(sizes: DataFrame, capacity: int) -> list[tuple[int, int, bool]]:
    """The rows of admission, on the driver."""
    used, out = 0, []
    for r in sorted(sizes.select("shard_id", "bytes").collect()):  # one a shard
        fits = used + r["bytes"] <= capacity
        used += r["bytes"] * fits
        out.append((r["shard_id"], r["bytes"], bool(fits)))
    return out


def admission_by_prefix(sizes: DataFrame, capacity: int) -> DataFrame:
    """The same with a plain running sum: the first shard that overflows closes the cache."""
    w = Window.orderBy("shard_id").rowsBetween(Window.unboundedPreceding, 0)
    return sizes.select("shard_id", "bytes", (F.sum("bytes").over(w) <= capacity).alias("cached"))


class EdgeCache:
    """Cached shards of a prepared graph: compressed payloads in executors' memory, the rest read from files.

    mode 0 keeps nothing (files and the operating system's cache only), 1 to 4 use CODECS; 'auto' takes
    choose_mode with ratios measured on the shards.
    """

    def __init__(self, csr: DataFrame, capacity: int, mode: int | str = "auto"):
        if mode == "auto":
            r = {x["codec"]: x for x in compression_report(csr, ("raw", "snappy", "zlib-1", "zlib-3")).collect()}
            raw = r["raw"]["raw_bytes"]
            mode = choose_mode(raw, capacity, tuple(r[CODECS[i]]["ratio"] for i in (1, 2, 3, 4)))
        self.mode, self.capacity = mode, capacity
        if mode == 0:
            self.cached: set[int] = set()
            self.payload, self.total = None, csr.count()
            return
        packed = saved(payloads(csr, CODECS[mode]), "cache-payloads")  # packed once; a lost executor's shards are read from here again
        kept = {k: fits for k, _, fits in admitted(packed, capacity)}
        self.cached, self.total = {k for k, x in kept.items() if x}, len(kept)
        self.payload = packed.where(F.col("shard_id").isin(sorted(self.cached))).select("shard_id", "lo", "hi", "codec", "raw_bytes", "payload").persist(StorageLevel.MEMORY_ONLY)

    @property
    def ratio(self) -> float:
        return len(self.cached) / max(1, self.total)

    def edges(self, shards: list[int]) -> DataFrame:
        """(shard_id, src, dst, weight) of cached shards, unpacked where they lie."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for r in b.to_pylist():  # a shard's payload is one block of bytes
                    row, col, val = decode(decompress(r["payload"], r["codec"], r["raw_bytes"]), False)
                    dst = np.repeat(np.arange(r["lo"], r["hi"] + 1), np.diff(row))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(dst), r["shard_id"], np.int32)), pa.array(col), pa.array(dst), pa.array(val if val is not None else np.ones(len(dst), np.int64))], names=["shard_id", "src", "dst", "weight"])

        return self.payload.where(F.col("shard_id").isin(shards)).mapInArrow(run, "shard_id int, src long, dst long, weight long")

    def scan(self, files: DataFrame, shards: list[int] | None, all_shards: list[int]) -> tuple[DataFrame | None, int, DataFrame | None]:
        """(edges of these shards from pruned files, hits, edges from memory); None where there are none."""
        want = all_shards if shards is None else shards
        hits = sorted(self.cached & set(want))
        misses = sorted(set(want) - self.cached)
        missed = files.where(F.col("shard_id").isin(misses)) if len(misses) < len(all_shards) else files
        return missed.select("shard_id", "src", "dst", "weight") if misses or not hits else None, len(hits), self.edges(hits) if hits else None

    def close(self) -> None:
        if self.payload is not None:
            self.payload.unpersist()
