"""Document fingerprints from modular prefix polynomial hashes."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import saved

#: The Mersenne prime 2^31 - 1 and two bases, which together give 62 bits.
PRIME = (1 << 31) - 1
BASES = (911382323, 972663749)
#: Code points in a window, slots of a fingerprint, and code points hashed at a time.
SPAN, SLOTS, CHUNK = 12, 64, 1 << 18


def _mod(x: np.ndarray) -> np.ndarray:
    """x modulo PRIME for x below 2^62, by folding."""
    for _ in range(2):
        high = x >> np.uint64(31)
        x = x & np.uint64(PRIME)
        x += high
    return np.subtract(x, np.uint64(PRIME), out=x, where=x >= PRIME)


def _powers(base: int, n: int) -> np.ndarray:
    """base^0 .. base^(n-1) modulo PRIME, by doubling."""
    out = np.ones(1, np.uint64)
    while len(out) < n:
        out = np.concatenate([out, _mod(out * np.uint64(pow(base, len(out), PRIME)))])
    return out[:n]


class Powers:
    """Powers of a base and of its inverse, grown as texts need them."""

    def __init__(self, base: int):
        self.base, self.up, self.down = base, np.ones(1, np.uint64), np.ones(1, np.uint64)

    def need(self, n: int) -> None:
        if len(self.up) < n:
            n = 1 << (n - 1).bit_length()
            self.up, self.down = _powers(self.base, n), _powers(pow(self.base, PRIME - 2, PRIME), n)


_POWERS = [Powers(b) for b in BASES]


def points(text: str) -> np.ndarray:
    """The code points of text."""
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)


class Prefixes:
    """Prefix hashes of a text: any span's hash, span equality, and common extensions by binary search."""

    def __init__(self, codes: np.ndarray, bases: int = len(BASES)):
        self.n, self.sums = len(codes), []
        for p in _POWERS[:bases]:
            p.need(self.n + 1)
            part = np.cumsum(_mod((codes + np.uint64(1)) * p.up[: self.n]), dtype=np.uint64)  # each below 2^31: no overflow below 2^33 code points
            self.sums.append(np.concatenate([np.zeros(1, np.uint64), _mod(part)]))

    def spans(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hashes of the spans [start, end), 31 bits for each base, which don't depend on where they stand."""
        out = None
        for p, s in zip(_POWERS, self.sums, strict=False):
            h = _mod(_mod(s[end] + np.uint64(PRIME) - s[start]) * p.down[start])
            out = h if out is None else (out << np.uint64(31)) | h
        return out

    def span(self, start: int, end: int) -> int:
        return int(self.spans(np.array([start]), np.array([end]))[0])


def same_span(a: Prefixes, i: int, b: Prefixes, j: int, n: int) -> bool:
    """Whether a[i:i+n] and b[j:j+n] are equal, in constant time."""
    return i + n <= a.n and j + n <= b.n and a.span(i, i + n) == b.span(j, j + n)


def common_extension(a: Prefixes, i: int, b: Prefixes, j: int) -> int:
    """The length of the longest equal spans that start at a[i] and b[j]."""
    low, high = 0, min(a.n - i, b.n - j)
    while low < high:
        mid = (low + high + 1) // 2
        low, high = (mid, high) if a.span(i, i + mid) == b.span(j, j + mid) else (low, mid - 1)
    return low


_MIX = np.uint64(0x9E3779B97F4A7C15)


def _slots(hashes: np.ndarray, least: np.ndarray) -> None:
    """Keep each slot's least mixed hash."""
    h = hashes * _MIX
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    np.minimum.at(least, (h >> np.uint64(58)).astype(np.int64), h)


class Sketch:
    """Window minima and the hash of the whole, over code points that come in one or more runs."""

    def __init__(self, span: int = SPAN):
        self.span, self.least, self.n, self.whole, self.tail = span, np.full(SLOTS, np.iinfo(np.uint64).max, np.uint64), 0, [0] * len(BASES), np.zeros(0, np.uint64)

    def add(self, codes: np.ndarray) -> None:
        for k in range(0, len(codes), CHUNK):
            self._add(codes[k : k + CHUNK])

    def _add(self, codes: np.ndarray) -> None:
        both = np.concatenate([self.tail, codes])
        p, kept, n = Prefixes(both, 1), len(self.tail), len(both)  # minima do with one base, the whole takes both
        if n >= self.span:
            at = np.arange(n - self.span + 1)
            _slots(p.spans(at, at + self.span), self.least)
        other = _POWERS[1]
        other.need(len(codes) + 1)
        own = (p.span(kept, n), int(_mod((codes + np.uint64(1)) * other.up[: len(codes)]).sum(dtype=np.uint64)))
        for k, base in enumerate(BASES):
            self.whole[k] = (self.whole[k] + own[k] * pow(base, self.n, PRIME)) % PRIME
        self.n += len(codes)
        self.tail = both[max(0, len(both) - self.span + 1) :]

    def copy(self) -> Sketch:
        new = Sketch(self.span)
        new.least, new.n, new.whole, new.tail = self.least.copy(), self.n, self.whole[:], self.tail
        return new

    def text(self) -> str:
        """Hex digits: 8 for the length, 16 for the whole, 4 for each slot (0000: no window)."""
        least = self.least
        if self.n and self.n < self.span:
            least = least.copy()
            _slots(np.array([self.whole[0] << 31 | self.whole[1]], np.uint64), least)
        some = least != np.iinfo(np.uint64).max
        digits = np.where(some, np.maximum(least >> np.uint64(8) & np.uint64(0xFFFF), np.uint64(1)), np.uint64(0)).astype(">u2")
        return f"{self.n & 0xFFFFFFFF:08x}{self.whole[0] << 31 | self.whole[1]:016x}{digits.tobytes().hex()}"


def likeness(a: str, b: str) -> float:
    """An estimate of the share of windows that two texts have in common; 1 for equal fingerprints.

    The share j of filled slots that agree estimates shared windows over all; 2j / (1 + j) is their part of either text.
    """
    if a == b:
        return 1.0
    x, y = (np.frombuffer(bytes.fromhex(f[24:]), ">u2") for f in (a, b))
    some = (x > 0) | (y > 0)
    j = float(((x == y) & some).sum() / some.sum()) if some.any() else 0.0
    return 2 * j / (1 + j)


def fingerprint(text: str) -> str:
    s = Sketch()
    s.add(points(text))
    return s.text()


#: Text that one range of documents holds at least, about, in code points, and ranges at most: beyond, they grow.
RANGE_CHARS, RANGES = 1 << 24, 50_000
_FIELDS = [("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64()), ("common_prefix", pa.int64())]


class _Held:
    """A document that waits for its successor: the sketches of its first three quarters and of the whole."""

    def __init__(self, place: int, doc: int | None, text: str):
        self.place, self.doc, self.text = place, doc, text
        self.cut = len(text) // 4
        self.keep, self.last = text[: len(text) - self.cut], text[len(text) - self.cut :]
        self.start = Sketch()
        self.start.add(points(self.keep))
        whole = self.start.copy()
        whole.add(points(self.last))
        self.print = whole.text()

    def row(self, nxt: str, next_print: str) -> tuple:
        head = nxt[: self.cut]
        self.start.add(points(head))
        other = self.start.text()
        shared = len(self.keep)
        if self.last[:1] == head[:1]:
            shared += common_extension(Prefixes(points(self.last)), 0, Prefixes(points(head)), 0)
        sha = hashlib.sha256((self.keep + head).encode("utf-8", "surrogatepass")).hexdigest()
        return self.doc, len(self.text), sha, self.print, other, likeness(self.print, other), likeness(self.print, next_print), shared


def _ranges(own: DataFrame) -> list[int]:
    """The least id of each range of ids; their number follows the amount of text."""
    chars = own.agg(F.sum(F.length("text"))).first()[0] or 0
    n = max(int(own.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(RANGES, chars // RANGE_CHARS + 1))
    ids = saved(own.select("doc_id").where("doc_id is not null").repartitionByRange(n, "doc_id").withColumn("_pid", F.spark_partition_id()), "fp-ids")
    return sorted(r["b"] for r in ids.groupBy("_pid").agg(F.min("doc_id").alias("b")).collect())


def fingerprints(docs: DataFrame) -> DataFrame:
    """One row a document: its fingerprint, that of its edited text, their likeness and the next document's.

    A null text is empty. Documents are ordered by doc_id, null first, and equal ids by text; after
    the last comes the first. Equal texts have equal fingerprints; texts shorter than a window fill
    one slot, empty ones none. Repeated rows follow each other; an empty table gives no rows; columns
    but doc_id and text are not read.

    Range k holds ids from the k-th bound on, range 0 null ids. A range's first document also goes,
    as its end, to the range before, so successors meet in one shuffle of the texts.
    """
    own = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    bounds = np.array(_ranges(own), np.int64)
    m, nulls = len(bounds), not own.where("doc_id is null").isEmpty()

    @F.pandas_udf("at int, opens boolean")
    def place(ids: pd.Series) -> pd.DataFrame:
        x = ids.fillna(np.iinfo(np.int64).min).to_numpy(np.int64)
        at = np.searchsorted(bounds, x, "right")
        return pd.DataFrame({"at": at.astype(np.int32), "opens": (at == 0) | (bounds[np.maximum(at, 1) - 1] == x) if m else np.ones(len(x), bool)})

    # A nullable integer column would reach pandas as floats; nulls are told apart by themselves.
    put = place(F.coalesce("doc_id", F.lit(0)))
    at = F.when(F.col("doc_id").isNull(), 0).otherwise(F.col("_x.at"))
    before = F.when(at == 0, m).when((at == 1) & F.lit(not nulls), m).otherwise(at - 1)
    opens = F.col("doc_id").isNull() | F.col("_x.opens")
    here = F.struct(at.cast("int").alias("p"), F.lit(False).alias("e"))
    sent = own.withColumn("_x", put).select("doc_id", "text", F.explode(F.when(opens, F.array(here, F.struct(before.cast("int").alias("p"), F.lit(True).alias("e")))).otherwise(F.array(here))).alias("_y"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: _Held | None = None
        for b in batches:
            out = []
            for p, end, doc, text in zip(*(c.to_pylist() for c in b.columns), strict=True):
                waits = held is not None and held.place == p
                if end and not waits:  # a further document with the id that ended the range
                    continue
                new = _Held(p, doc, text)
                if waits:
                    out.append(held.row(text, new.print))
                held = None if end else new
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, (_, k) in zip(zip(*out, strict=True) if out else [[]] * len(_FIELDS), _FIELDS, strict=True)], names=[n for n, _ in _FIELDS])

    dealt = sent.select(F.col("_y.p").alias("_p"), F.col("_y.e").alias("_e"), "doc_id", "text").repartitionById(m + 1, "_p")
    sorted_ = dealt.sortWithinPartitions("_p", "_e", F.col("doc_id").asc_nulls_first(), "text")
    return sorted_.mapInArrow(run, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, common_prefix long")


def query(spark, sf_dir: str) -> DataFrame:
    return fingerprints(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
