"""Packing by minimum bin slack: subset sums over a histogram of lengths, applied to ranked pieces."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shardgraph.llm.common import saved
from shardgraph.llm.tokens import default_vocabulary, word_ids

WINDOW, END_ID = 4096, 2
#: Parts that each length's ranks are counted in at least, so no task ranks a whole hot length, and pieces of which there is a part for each so many.
SALTS, SALTED = 256, 100_000
#: Cut documents up to which their ids are broadcast (16 bytes each); more are joined by a shuffle.
BROADCAST_ROWS = 50_000


def fill(counts: dict[int, int], room: int) -> dict[int, int]:
    """The multiset of counts' lengths whose sum is as close to room as can be without passing it.

    Bit s of a bitset says that a sum s is reachable. Lengths join in falling order, each by shifts
    for 1, 2, 4, ... copies and the rest; the bitsets before each length lead the way back.
    """
    reach, steps, mask = 1, [], (1 << (room + 1)) - 1
    for length in sorted((x for x in counts if x <= room and counts[x] > 0), reverse=True):
        steps.append((length, reach))
        copies, size = min(counts[length], room // length), 1
        while copies > 0:
            step = min(size, copies)
            reach |= (reach << (length * step)) & mask
            copies, size = copies - step, size * 2
        if reach >> room & 1:
            break
    at, used = reach.bit_length() - 1, {}
    for length, before in reversed(steps):
        n = 0
        while not before >> (at - n * length) & 1:
            n += 1
        if n:
            used[length], at = n, at - n * length
    return used


def plan(counts: dict[int, int], window: int = WINDOW) -> tuple[list[tuple[dict[int, int], int]], dict[int, int]]:
    """(patterns, rest): multisets that fill a window exactly, with their repetitions; what no exact fill takes.

    The longest length left opens a window and fill() finds its company. A pattern repeats until
    one of its lengths runs out, so the number of patterns follows the number of lengths, not of rows.
    """
    left, patterns, rest = {k: n for k, n in counts.items() if n > 0}, [], {}
    while left:
        big = max(left)
        left[big] -= 1
        used = fill(left, window - big)
        left[big] += 1
        used[big] = used.get(big, 0) + 1
        if sum(k * n for k, n in used.items()) < window:
            rest[big] = left.pop(big)
            continue
        times = min(left[k] // n for k, n in used.items())
        patterns.append((used, times))
        for k, n in used.items():
            left[k] -= n * times
            if not left[k]:
                del left[k]
    return patterns, rest


def placement(counts: dict[int, int], window: int = WINDOW) -> tuple[np.ndarray, int, int, int]:
    """(table, first_rest_sequence, rest_tokens, window) from the plan.

    Rows of table: length, first rank, end rank, copies in a window, first sequence, offset; copies
    0 marks a rest, whose offset is where its first rank stands in the stream of the rest.
    """
    patterns, rest = plan(counts, window)
    taken: dict[int, int] = {}
    rows, sequence = [], 0
    for used, times in patterns:
        offset = 0
        for length, n in sorted(used.items(), reverse=True):
            lo = taken.get(length, 0)
            taken[length] = lo + n * times
            rows.append((length, lo, taken[length], n, sequence, offset))
            offset += n * length
        sequence += times
    stream = 0
    for length, n in sorted(rest.items(), reverse=True):
        lo = taken.get(length, 0)
        rows.append((length, lo, lo + n, 0, 0, stream))
        stream += n * length
    return np.array(sorted(rows), np.int64).reshape(-1, 6), sequence, stream, window


def stream_bounds(start: int, length: int, total: int, window: int) -> Iterator[tuple[int, int, int]]:
    """(sequence in the rest, offset there, length) of each part of a piece that stands at start in the rest.

    The rest is cut at every window; its last, partial window into sequences of powers of two.
    """
    whole = total // window * window
    end = start + length
    while start < end:
        if start < whole:
            sequence, offset = divmod(start, window)
            stop = (sequence + 1) * window
        else:
            sequence, at, size = whole // window, whole, 1 << (total - whole).bit_length() - 1
            while at + size <= start:
                at, sequence = at + size, sequence + 1
                size = 1 << (total - at).bit_length() - 1
            offset, stop = start - at, at + size
        stop = min(stop, end)
        yield sequence, offset, stop - start
        start = stop


_PIECE = "doc_id long, _row long, start long, length int, crc long, doc_tokens long"


def _tokenised(docs: DataFrame, path: str, window: int) -> DataFrame:
    """Each document's pieces of a full window and its rest, with their checksums."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, end = word_ids(path), np.array([END_ID], "<u4").tobytes()
        for b in batches:
            out: list[tuple] = []
            for doc, row, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
                ids = words.packed(text.as_py()) + end
                n = len(ids) // 4
                out += [(doc, row, s, min(window, n - s), zlib.crc32(ids[4 * s : 4 * (s + window)]), n) for s in range(0, n, window)]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True) if out else [[]] * 6, (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64()), strict=True)], names=["doc_id", "_row", "start", "length", "crc", "doc_tokens"])

    text = F.coalesce("text", F.lit(""))
    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.xxhash64(text).alias("_row"), text.alias("text")).mapInArrow(run, _PIECE)


def _cut_checksums(docs: DataFrame, cut: DataFrame, path: str) -> DataFrame:
    """(_doc, _row, start, length, crc) of parts cut inside a piece: only their documents are tokenised again."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, end = word_ids(path), np.array([END_ID], "<u4").tobytes()
        for b in batches:
            out: list[tuple] = []
            for doc, row, text, parts in zip(*(c.to_pylist() for c in b.columns), strict=True):
                ids = words.packed(text) + end
                out += [(doc, row, p["start"], p["length"], zlib.crc32(ids[4 * p["start"] : 4 * (p["start"] + p["length"])])) for p in parts]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (zip(*out, strict=True) if out else [[]] * 5)], names=["_doc", "_row", "start", "length", "crc"])

    asked = cut.groupBy(F.col("doc_id").alias("_doc"), F.col("_row").alias("_r")).agg(F.collect_set(F.struct("start", "length")).alias("_parts"))
    if cut.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS:
        asked = F.broadcast(asked)
    text = F.coalesce("text", F.lit(""))
    own = docs.select(F.col("doc_id").cast("bigint").alias("_id"), F.xxhash64(text).alias("_row"), text.alias("_text"))
    met = own.join(asked, F.col("_id").eqNullSafe(F.col("_doc")) & (F.col("_row") == F.col("_r")))
    return met.select("_doc", "_row", "_text", "_parts").mapInArrow(run, "_doc long, _row long, start long, length long, crc long").distinct()


def pack(docs: DataFrame, path: str | None = None, window: int = WINDOW) -> DataFrame:
    """One row a piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    A null or empty text is the end id alone. Long documents give full windows, which are sequences
    by themselves, and one rest; rests of all documents meet by length only, in a histogram of at
    most `window` counts on the driver, whose plan is applied to ranked pieces. What no exact fill
    takes is laid end to end and cut at the window; the last partial window is cut at powers of two,
    so nothing is padded. Repeated rows are packed each; null ids stay null; an empty table gives no
    rows; columns but doc_id and text are not read.
    """
    path = path or default_vocabulary()
    pieces = saved(_tokenised(docs, path, window), "pack-pieces")
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `window` rows
    table, first, total, _ = placement(counts, window)

    salts = max(SALTS, sum(counts.values()) // SALTED)
    salt = F.pmod(F.xxhash64("doc_id", "start", "crc"), F.lit(salts)).cast("int")
    salted = pieces.withColumn("_salt", salt)
    before = Window.partitionBy("length").orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)
    offsets = salted.groupBy("length", "_salt").agg(F.count("*").alias("_n")).select("length", "_salt", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_off"))
    within = Window.partitionBy("length", "_salt").orderBy("doc_id", "_row", "start")
    ranked = salted.join(offsets, ["length", "_salt"]).withColumn("_rank", F.col("_off") + F.row_number().over(within) - 1)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = table[:, 0] * (1 << 48) + table[:, 1]
        for b in batches:
            doc, row, start, length, crc, n, rank = (c.to_numpy(zero_copy_only=False) if i else c for i, c in enumerate(b.columns))
            length = length.astype(np.int64)
            t = table[np.searchsorted(keys, length * (1 << 48) + rank, "right") - 1]
            own, each = rank - t[:, 1], np.maximum(t[:, 3], 1)
            sequence, offset = t[:, 4] + own // each, t[:, 5] + own % each * length
            stay, src, extra = t[:, 3] > 0, [], []
            for i in np.flatnonzero(~stay).tolist():
                s = 0
                for q, o, size in stream_bounds(int(t[i, 5] + own[i] * length[i]), int(length[i]), total, window):
                    src.append(i)
                    extra.append((s, size, first + q, o))
                    s += size
            at = np.concatenate([np.flatnonzero(stay), np.array(src, np.int64)])
            x = np.array(extra, np.int64).reshape(-1, 4)
            size = np.concatenate([length[stay], x[:, 1]])
            cut = size != length[at]
            cols = [start[at] + np.concatenate([np.zeros(int(stay.sum()), np.int64), x[:, 0]]), size, pa.array(crc[at], mask=cut), n[at], np.concatenate([sequence[stay], x[:, 2]]), np.concatenate([offset[stay], x[:, 3]])]
            yield pa.RecordBatch.from_arrays([doc.take(pa.array(at)), pa.array(row[at]), *map(pa.array, cols)], names=["doc_id", "_row", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    placed = ranked.select("doc_id", "_row", "start", "length", "crc", "doc_tokens", "_rank").mapInArrow(place, "doc_id long, _row long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
    if total == 0:
        return placed.drop("_row")
    placed = saved(placed, "pack-placed", few=True)
    cut = placed.where("ids_crc32 is null")
    sums = _cut_checksums(docs, cut, path)
    c, s = cut.alias("c"), sums.alias("s")
    found = c.join(s, F.col("c.doc_id").eqNullSafe(F.col("s._doc")) & (F.col("c._row") == F.col("s._row")) & (F.col("c.start") == F.col("s.start")) & (F.col("c.length") == F.col("s.length"))).select("c.doc_id", "c.start", "c.length", F.col("s.crc").alias("ids_crc32"), "c.doc_tokens", "c.sequence_id", "c.offset")
    return placed.where("ids_crc32 is not null").drop("_row").unionByName(found)


def query(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
