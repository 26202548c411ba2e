"""Which shards can change anything: Bloom filters over source ids, an exact index, and vertex-level scheduling."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


#: Active ids that are probed together: each filter meets a table of them, not each id.
CHUNK = 1 << 16


def positions(h: Column, m: Column, k: int) -> Column:
    """k bit positions, in a filter of m bits, of an id with this hash: steps of its upper half from its lower half."""
    low, high = h.bitwiseAND(0xFFFFFFFF), F.shiftrightunsigned(h, 32).bitwiseOR(1)
    return F.array(*((low + i * high) % m for i in range(k)))


def build_filters(mirror: DataFrame, fpp: float = 0.01) -> DataFrame:
    """(shard_id, m, k, places, words) over each shard's distinct sources: the 64-bit words of its filter that aren't zero.

    m is sized by the shard's own count for this false positive rate. Bits meet in words by
    (shard, word), so no task holds more than a word's ids; the arrays are bounded by m / 64.
    """
    k = max(1, round(-math.log2(fpp)))
    n = mirror.groupBy("shard_id").agg(F.count("*").alias("n"))
    sized = n.select("shard_id", F.greatest(F.lit(64), F.ceil(-F.col("n") * F.lit(math.log(fpp) / math.log(2) ** 2))).cast("long").alias("m"))
    at = mirror.join(sized, "shard_id").select("shard_id", "m", F.explode(positions(F.xxhash64("src"), F.col("m"), k)).alias("p"))
    words = at.groupBy("shard_id", "m", F.floor(F.col("p") / 64).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p % 64 as int))")).alias("b"))
    held = words.groupBy("shard_id", "m").agg(F.collect_list(F.struct("w", "b")).alias("x"))
    return held.select("shard_id", "m", F.lit(k).alias("k"), F.col("x.w").alias("places"), F.col("x.b").alias("words"))


def hashes(ids: np.ndarray) -> np.ndarray:
    """xxhash64 of 64-bit ids, with the seed that Spark's function has (fixed values: its five primes)."""
    p1, p2, p3, p4, p5 = (np.uint64(p) for p in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
    turn = lambda x, r: x << np.uint64(r) | x >> np.uint64(64 - r)
    x = ids.astype(np.int64).view(np.uint64)
    h = np.full(len(x), np.uint64(42 + 8) + p5) ^ turn(x * p2, 31) * p1
    h = turn(h, 27) * p1 + p4
    h = (h ^ h >> np.uint64(33)) * p2
    h = (h ^ h >> np.uint64(29)) * p3
    return (h ^ h >> np.uint64(32)).view(np.int64)


def probe(h: np.ndarray, m: int, k: int, places: np.ndarray, words: np.ndarray) -> np.ndarray:
    """Whether the filter may hold each hash."""
    bits = np.zeros(m // 64 + 1, np.uint64)
    bits[places] = words.view(np.uint64)
    low, high = h.view(np.uint64) & np.uint64(0xFFFFFFFF), h.view(np.uint64) >> np.uint64(32) | np.uint64(1)
    maybe = np.arange(len(h))
    for i in range(k):  # most ids leave at their first zero bit
        p = (low[maybe] + np.uint64(i) * high[maybe]) % np.uint64(m)
        maybe = maybe[bits[p >> np.uint64(6)] >> (p & np.uint64(63)) & np.uint64(1) == 1]
    out = np.zeros(len(h), bool)
    out[maybe] = True
    return out


def may_hold(h: np.ndarray, m: int, k: int, places: np.ndarray, words: np.ndarray) -> bool:
    """Whether the filter may hold any of the hashes: asked in growing portions, until one is found."""
    at, size = 0, 256
    while at < len(h):
        if probe(h[at : at + size], m, k, places, words).any():
            return True
        at, size = at + size, 8 * size
    return False


def active_shards_bloom(filters: DataFrame, active: DataFrame, count: int | None = None) -> DataFrame:
    """Shards whose filter may hold an active id: every shard with an active source, and few others.

    Each filter is asked about each active id, where the filter lies, by tables of CHUNK ids; count is how many are active.
    """
    chunks = max(1, -(-(active.count() if count is None else count) // CHUNK))
    h = F.xxhash64("id")
    asked = active.select(F.pmod(h, F.lit(chunks)).alias("chunk"), h.alias("h")).groupBy("chunk").agg(F.collect_list("h").alias("h"))
    met = filters.withColumn("chunk", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(chunks - 1).cast("long")))).join(asked, "chunk").select("shard_id", "m", "k", "places", "words", "h")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat = lambda c, i: b.column(c)[i].values.to_numpy(zero_copy_only=False)
            hit = [may_hold(flat(5, i), b.column(1)[i].as_py(), b.column(2)[i].as_py(), flat(3, i), flat(4, i)) for i in range(b.num_rows)]
            yield pa.RecordBatch.from_arrays([b.column(0).filter(pa.array(hit, pa.bool_()))], names=["shard_id"])

    return met.mapInArrow(run, "shard_id int").distinct()


def active_shards_exact(mirror: DataFrame, active: DataFrame) -> DataFrame:
    """Shards with an active source, from the index of (shard, source)."""
    return mirror.join(active.select(F.col("id").alias("src")), "src", "left_semi").select("shard_id").distinct()


def edges_of_active(edges: DataFrame, active: DataFrame) -> DataFrame:
    """Edges into destinations that have an active source: vertex-level scheduling."""
    hit = edges.join(active.select(F.col("id").alias("src")), "src", "left_semi").select("dst").distinct()
    return edges.join(hit, "dst", "left_semi")


def pick(sg, schedule: str, threshold: float, active: DataFrame, ratio: float) -> list[int] | None:
    """Shard ids to visit (P at most), or None for all: filters, or the exact index, are asked only at or below the threshold."""
    if schedule in ("all", "vertex") or ratio > threshold and schedule == "selective":
        return None
    found = active_shards_bloom(sg.filters, active, round(ratio * sg.n)) if schedule == "selective" else active_shards_exact(sg.mirror, active)
    return sorted(r["shard_id"] for r in found.collect())
