"""LM scoring: an Elias-Fano trie of all pairs and triples of words, in shards by context, and texts scored where the shards are."""

from __future__ import annotations

import ctypes
import math
from collections import Counter
from collections.abc import Iterator
from itertools import repeat
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import saved
from shardgraph.llm.succinct import EliasFano, Level, Mapped, pack
from shardgraph.llm.words import part_of


class Sizes(NamedTuple):
    """How work is cut; nothing is left out by any of them.

    held: the most frequent words, which workers know by rank, with their counts; all other words go
    by hash; their counts stay in a table, which score() joins or lets them share the mass of equally. shard: tokens
    that a shard of the trie is meant to see. split: training occurrences of a word from which on its followers are kept by
    classes of the word before it, so that no shard must hold all that follows a very frequent word.
    flush: tokens that a task gathers before it passes them on.
    """

    held: int = 1 << 18
    shard: int = 3 << 19
    split: int = 1 << 20
    flush: int = 1 << 21


#: The code of the end of a text, which also stands before its first word.
END = 0
#: Questions to a shard at once.
ASKED = 1 << 17
#: Distinct words that a task gathers before it passes their counts on.
GATHER = 250_000
#: One document in so many tells which shards will be hot; only the dealing of work depends on it.
SAMPLED = 64
#: Documents between two flushes, and salts of a shard, are fewer.
_DOCS, _SALTS = 1 << 15, 1 << 20
#: Stands for the end of a text among hashes of words; no word holds a line feed.
_END = b"\n"
#: Codes: END, held words by rank, then hashed words, then classes of split words.
_HASH, _CLASS = 1 << 48, 1 << 50


def _hash(word: bytes) -> int:
    from xxhash import xxh64_intdigest

    h = xxh64_intdigest(word)
    return h - (1 << 64) if h >> 63 else h


def split(text: bytes) -> list[bytes]:
    """Words of a text as the model sees them: of bytes, lower() and split() touch A-Z and [\\x20\\x09-\\x0D] only."""
    return text.lower().split()


def count_words(training: DataFrame) -> DataFrame:
    """(h, c): each distinct token's hash and count, the end of texts among them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()

        def out() -> pa.RecordBatch:
            b = pa.RecordBatch.from_arrays([pa.array([_hash(w) for w in seen], pa.int64()), pa.array(list(seen.values()), pa.int64())], names=["h", "c"])
            seen.clear()
            return b

        for b in batches:
            for t in b.column(0):
                seen.update(split(t.as_py()))
                seen[_END] += 1
                if len(seen) > GATHER:
                    yield out()
        if seen:
            yield out()

    text = F.coalesce("text", F.lit("")).cast("binary").alias("text")
    return training.select(text).mapInArrow(run, "h long, c long").groupBy("h").agg(F.sum("c").alias("c"))


def mix(x: np.ndarray) -> np.ndarray:
    """Well spread 40-bit numbers of codes."""
    return ((x.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(24)).astype(np.int64)


class Vocabulary:
    """Counts of the training text: what each worker is sent. Its size is bounded by Sizes.held."""

    def __init__(self, words: DataFrame, sizes: Sizes):
        row = words.agg(F.sum("c").alias("n"), F.count("*").alias("v")).first()
        self.n, self.v, self.sizes = row["n"] or 0, row["v"], sizes
        end = words.where(F.col("h") == _hash(_END)).first()
        top = words.where(F.col("h") != _hash(_END)).orderBy(F.desc("c"), "h").limit(sizes.held).toArrow()
        self.held = top["h"].to_numpy()
        #: Counts by code: the end, then held words.
        self.counts = np.concatenate([[end["c"] if end else 0], top["c"].to_numpy()]).astype(np.int64)
        self.total = self.n + 0.5 * (self.v + 1)
        others = max(0, self.v - len(self.held) - (end is not None)) + 1  # types that aren't held; the last stands for all unseen
        self.other = max(0.5, (self.n - self.counts.sum() + 0.5 * others) / others) / self.total
        self.classes = 1 + self.counts // sizes.split

    def unigram(self, codes: np.ndarray) -> np.ndarray:
        """P(word) of codes."""
        own = codes < len(self.counts)
        return np.where(own, (self.counts[np.where(own, codes, 0)] + 0.5) / self.total, self.other)

    def unit(self, v: np.ndarray, u: np.ndarray) -> np.ndarray:
        """The code that the followers of v, after u, are kept under: v's own, or that of v and a class of u."""
        k = np.where(v < len(self.classes), self.classes[np.minimum(v, len(self.classes) - 1)], 1)
        return np.where(k > 1, _CLASS + mix(v * 1009 + mix(u) % k) % _HASH, v)


class Codes:
    """Words to codes; what a worker has met is remembered."""

    def __init__(self, held: np.ndarray, most: int = 150_000):
        self.rank = {h: k + 1 for k, h in enumerate(held.tolist())}
        self.first, self.most, self.met = len(held) + 1, most, {}

    def of(self, words: list[bytes]) -> np.ndarray:
        if len(self.met) > self.most:  # words met first are the frequent ones
            self.met = dict(list(self.met.items())[: self.most // 3])
        got = np.fromiter(map(self.met.get, words, repeat(-1)), np.int64, len(words))
        for k in np.flatnonzero(got < 0).tolist():
            w = words[k]
            code = self.met.get(w)
            if code is None:
                h = _hash(w)
                code = self.met[w] = self.rank.get(h) or self.first + h % _HASH
            got[k] = code
        return got


class Portion(NamedTuple):
    """Some documents: their rising codes; of each token its place among them and those of the two before it, and 2 * document + trains."""

    codes: np.ndarray
    u: np.ndarray
    v: np.ndarray
    w: np.ndarray
    doc: np.ndarray


def _gather(batches: Iterator[pa.RecordBatch], codes: Codes, flush: int) -> Iterator[tuple[Portion, list, list[np.ndarray]]]:
    """(tokens, (doc_id, held out, trains) of documents, the codes of each one's words) in portions."""
    docs, runs, n = [], [], 0

    def out():
        run = np.concatenate([x for r in runs for x in ((END, END), r, (END,))]).astype(np.int64)
        lengths = np.array([len(r) + 3 for r in runs])
        start = np.cumsum(lengths) - lengths
        known, at = np.unique(run, return_inverse=True)
        run, at = None, at.astype(np.int32)
        k = np.delete(np.arange(len(at), dtype=np.int32), np.concatenate([start, start + 1]))
        of = np.repeat((np.arange(len(runs)) * 2 + [d[2] for d in docs]).astype(np.int32), lengths - 2)
        return Portion(known, at[k - 2], at[k - 1], at[k], of), docs, runs

    for b in batches:
        ids, held, trains = (b.column(k).to_pylist() for k in range(3))
        for k, t in enumerate(b.column(3)):
            runs.append(codes.of(split(t.as_py())))
            docs.append((ids[k], held[k], trains[k]))
            n += len(runs[-1]) + 1
            if n >= flush or len(runs) == _DOCS:
                yield out()
                docs, runs, n = [], [], 0
    if runs:
        yield out()


def _planes(a: np.ndarray, kind: str) -> bytes:
    """The first bytes of all numbers, then the second ones, and so on: high bytes are alike and compress."""
    return np.ascontiguousarray(a.astype(kind).view(np.uint8).reshape(len(a), int(kind[2])).T).tobytes()


class Blob:
    """Arrays in one compressed block."""

    @staticmethod
    def of(*arrays: np.ndarray) -> bytes:
        kinds = ["<f8" if a.dtype.kind == "f" else "<i4" if not len(a) or a.itemsize == 4 or 0 <= a.min() and a.max() < 1 << 31 else "<i8" for a in arrays]
        head = np.array([len(arrays), *(x for a, k in zip(arrays, kinds, strict=True) for x in (len(a), ("<i4", "<i8", "<f8").index(k)))], "<i8")
        raw = head.tobytes() + b"".join(_planes(a, k) for a, k in zip(arrays, kinds, strict=True))
        return len(raw).to_bytes(8, "little") + pa.Codec("zstd", compression_level=3).compress(raw, asbytes=True)

    @staticmethod
    def arrays(blob: bytes) -> list[np.ndarray]:
        raw = pa.Codec("zstd").decompress(blob[8:], int.from_bytes(blob[:8], "little"), asbytes=True)
        count = int(np.frombuffer(raw, "<i8", 1)[0])
        head = np.frombuffer(raw, "<i8", 2 * count, 8).reshape(-1, 2).tolist()
        at, out = 8 + 16 * count, []
        for n, k in head:
            kind = ("<i4", "<i8", "<f8")[k]
            size = n * int(kind[2])
            by = np.frombuffer(raw, np.uint8, size, at).reshape(-1, n) if n else np.zeros((int(kind[2]), 0), np.uint8)
            out.append(np.ascontiguousarray(by.T).view(kind).ravel())
            at += size
        return out


def _sorted(a: np.ndarray, b: np.ndarray, c: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(order, starts of runs) of triples of numbers below n."""
    if n <= 1 << 21:
        key = a.astype(np.int64) * n
        key += b
        key *= n
        key += c
        order = np.argsort(key)
        key = key[order]
        new = key[1:] != key[:-1]
        key = None
    else:
        order = np.lexsort((c, b, a))
        a, b, c = a[order], b[order], c[order]
        new = (a[1:] != a[:-1]) | (b[1:] != b[:-1]) | (c[1:] != c[:-1])
    return order, np.flatnonzero(np.concatenate([np.ones(min(1, len(a)), bool), new]))


def _units(p: Portion, vocabulary: Vocabulary) -> tuple[np.ndarray, np.ndarray]:
    """(unit codes, the place among them of each token's unit): a code that isn't split is its own unit."""
    split_ = np.append(vocabulary.classes, 1)[np.minimum(p.codes, len(vocabulary.classes))] > 1
    some = np.flatnonzero(split_[p.v])
    more, at = np.unique(vocabulary.unit(p.codes[p.v[some]], p.codes[p.u[some]]), return_inverse=True)
    unit = p.v.copy()
    unit[some] = (len(p.codes) + at).astype(np.int32)
    return np.concatenate([p.codes, more]), unit


def _cut(p: Portion, vocabulary: Vocabulary, shards: int) -> Iterator[tuple[int, tuple]]:
    """(shard, its tokens): codes, distinct triples by place among them, how often each comes, and the documents of each time."""
    codes, unit = _units(p, vocabulary)
    shard = mix(codes) % shards
    by_shard = np.lexsort((codes, shard))
    rank = np.empty(len(codes), np.int64)
    rank[by_shard] = np.arange(len(codes))
    order, start = _sorted(rank[unit], p.u, p.w, len(codes))
    first, end = order[start], len(order)
    times = np.diff(np.append(start, end)).astype(np.int32)
    unit, u, w, doc = unit[first], p.u[first], p.w[first], p.doc[order]
    order = first = None
    cuts = np.flatnonzero(np.diff(shard[unit])) + 1
    seat = np.empty(len(codes), np.int32)
    for at, to in zip([0, *cuts.tolist()], [*cuts.tolist(), len(unit)], strict=True):
        own = [x[at:to] for x in (unit, u, w)]
        some = np.unique(np.concatenate(own))
        some = some[np.argsort(codes[some], kind="stable")]
        seat[some] = np.arange(len(some))
        stop = start[to] if to < len(unit) else end
        yield int(shard[unit[at]]), (np.diff(codes[some], prepend=0), *(seat[x] for x in own), times[at:to], doc[start[at] : stop])


def _learnt(delta: np.ndarray, unit: np.ndarray, u: np.ndarray, w: np.ndarray, times: np.ndarray, doc: np.ndarray) -> tuple:
    """What training documents teach of these tokens, without the documents."""
    count = np.add.reduceat(doc & 1, np.cumsum(times, dtype=np.int64) - times)
    keep = count > 0
    return delta, unit[keep], u[keep], w[keep], count[keep], doc[:0]


def _sources(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "_out", "_trains", F.coalesce("text", F.lit("")).cast("binary").alias("text"))


def _loads(docs: DataFrame, sent, shards: int) -> DataFrame:
    """(shard, n): about how many tokens each shard will see, from one document in SAMPLED."""
    some = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(SAMPLED)) == 0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = sent.value
        codes = Codes(vocabulary.held)
        for p, _, _ in _gather(batches, codes, vocabulary.sizes.flush):
            units, unit = _units(p, vocabulary)
            shard, n = np.unique((mix(units) % shards)[unit], return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(shard), pa.array(n.astype(np.int64) * SAMPLED)], names=["shard", "n"])

    return _sources(some).mapInArrow(run, "shard long, n long").groupBy("shard").agg(F.sum("n").alias("n"))


def _routed(docs: DataFrame, sent, shards: int, hot: dict[int, int]) -> DataFrame:
    """(dest, flush, asked, payload): the tokens of each portion of documents by shard, and a row about its documents.

    A hot shard's portions are dealt to salts, and what it must learn from them, counted once a portion, goes to each salt.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _give_back()
        vocabulary = sent.value
        codes = Codes(vocabulary.held)
        logs = np.log10(vocabulary.counts + 0.5)
        flush = TaskContext.get().partitionId() << 24
        for p, about, runs in _gather(batches, codes, vocabulary.sizes.flush):
            ids = np.array([d[0] or 0 for d in about], np.int64)
            flags = np.array([(d[0] is None) + 2 * d[1] for d in about], np.int64)
            known = [r[r < len(logs)] for r in runs]
            base = np.array([float(logs[r].sum()) + logs[END] for r in known])
            seen = np.array([int((vocabulary.counts[r] > 0).sum()) + int(vocabulary.counts[END] > 0) for r in known])
            rows = [(-1 - flush, flush, True, Blob.of(ids, flags, np.array([len(r) + 1 for r in runs]), seen, base))]
            del known, runs
            for s, own in _cut(p, vocabulary, shards):
                salts = hot.get(s, 1)
                rows.append((s * _SALTS + flush % 0xFFFFFB % salts, flush, True, Blob.of(*own)))
                if salts > 1:
                    learnt = Blob.of(*_learnt(*own))
                    rows += [(s * _SALTS + k, flush, False, learnt) for k in range(salts)]
                if len(rows) >= 64:
                    yield _batch(rows)
                    rows = []
            yield _batch(rows)
            flush += 1

    return _sources(docs).mapInArrow(run, "dest long, flush long, asked boolean, payload binary")


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.int64(), pa.bool_(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True) if rows else [[]] * 4, kinds, strict=True)], names=["dest", "flush", "asked", "payload"])


class Shard:
    """One shard of the trie, mapped to memory: its codes, the followers of each unit, and of each unit after each word.

    With Witten-Bell shares at both levels, P(w | u, v) = own(u, v, w) + left(u, v) * (own(v, w) + left(v) * P(w)).
    """

    def __init__(self, codes: EliasFano, two: Level, three: Level, seen: np.ndarray):
        self.codes, self.two, self.three, self.seen = codes, two, three, seen

    @staticmethod
    def build(codes: np.ndarray, unit: np.ndarray, u: np.ndarray, w: np.ndarray, count: np.ndarray) -> Shard:
        """From distinct triples of places among the rising codes, sorted, with their counts."""
        n = len(codes) + 1
        order, start = _sorted(unit, w, np.zeros(1, np.int64), n)
        pairs, times = order[start], np.add.reduceat(count[order], start) if len(start) else count
        order = start = None
        two = Level.of(unit[pairs], w[pairs], times, n, n)
        pairs = times = None
        context = unit.astype(np.int64)
        context *= n
        context += u
        three = Level.of(context, w, count, n * n, n)
        context = None
        seen = np.bincount(unit, count, len(codes)).astype("<u8")
        whole = EliasFano.of(codes, 1 << 52)
        parts = [EliasFano.arrays(whole), two.arrays(), three.arrays()]
        mapped = Mapped(*pack([a for arrays, _ in parts for a in arrays] + [seen])).arrays
        return Shard(EliasFano.from_arrays(mapped[:3], parts[0][1]), Level.from_arrays(mapped[3:14], parts[1][1]), Level.from_arrays(mapped[14:25], parts[2][1]), mapped[25])

    def places(self, codes: np.ndarray) -> np.ndarray:
        """Places of codes; those never learnt share one beyond all others."""
        at, known = self.codes.find(codes)
        return np.where(known, at, self.codes.n)

    def parts(self, unit: np.ndarray, u: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(own, left) of triples of places, sorted: P(w | u, v) = own + left * P(w). They are asked in turns: what a
        question takes on its way is several times what its answer takes."""
        n = len(self.seen) + 1
        own, left = np.zeros(len(unit)), np.ones(len(unit))
        for level in (self.two, self.three):
            whole = level.whole() if 4 * len(unit) > level.children.n else None
            for at in range(0, len(unit), ASKED):
                k = slice(at, at + ASKED)
                context = unit[k] if level is self.two else unit[k] * n + u[k]
                mine, rest = level.shares(context, w[k], whole)
                own[k] = mine + rest * own[k]
                left[k] *= rest
        return own, left

    def probability(self, unit: np.ndarray, u: np.ndarray, w: np.ndarray, one: np.ndarray) -> np.ndarray:
        """P of triples of places, sorted; one is P(w) of each."""
        own, left = self.parts(unit, u, w)
        return own + left * one


def _learn(blobs: list[list[np.ndarray]], asked: list[bool]) -> tuple[np.ndarray, tuple[np.ndarray, np.ndarray, np.ndarray], np.ndarray, np.ndarray]:
    """(codes, distinct triples of places among them, training count of each, the triple of each blob's triples)."""
    codes = [np.cumsum(b[0], dtype=np.int64) for b in blobs]
    whole = np.sort(np.concatenate(codes))
    whole = whole[np.append(True, whole[1:] != whole[:-1])[: len(whole)]]
    places = [np.searchsorted(whole, c).astype(np.int32) for c in codes]
    triples = [np.concatenate([p[b[k]] for p, b in zip(places, blobs, strict=True)]) for k in (1, 2, 3)]
    for b in blobs:
        b[:4] = [None] * 4
    codes = places = None
    counted = not all(asked)  # a hot shard: what portions teach comes apart from what they ask
    count = []
    for b, a in zip(blobs, asked, strict=True):
        if not a:
            count.append(b[4])
        elif counted:
            count.append(np.zeros(len(b[4]), np.int32))
        else:
            begin = np.cumsum(b[4], dtype=np.int64) - b[4]
            count.append(np.add.reduceat(b[5] & 1, begin) if len(begin) else b[4])
    order, start = _sorted(*triples, max(1, len(whole)))
    first = order[start]
    total = np.add.reduceat(np.concatenate(count)[order].astype(np.int64), start) if len(start) else np.zeros(0, np.int64)
    inverse = np.empty(len(order), np.int32)
    inverse[order] = np.repeat(np.arange(len(start), dtype=np.int32), np.diff(np.append(start, len(order))))
    return whole, tuple(x[first] for x in triples), total, inverse


#: What a shard says: for each portion the sums of its documents or, without payload, a token whose P(w) is looked up by code.
_ANSWERS = "flush long, about boolean, payload binary, code long, at long, own float, rest float"
_RARE = (pa.int64(), pa.int64(), pa.float32(), pa.float32())


def _said(flush: list | pa.Array, about: list, payload: list, rare: list[np.ndarray] | None = None) -> pa.Table:
    n = len(flush)
    more = [pa.array(x, k) for x, k in zip(rare, _RARE, strict=True)] if rare else [pa.nulls(n, k) for k in _RARE]
    return pa.table([pa.array(flush, pa.int64()), pa.array(about, pa.bool_()), pa.array(payload, pa.binary()), *more], names=["flush", "about", "payload", "code", "at", "own", "rest"])


def _give_back() -> None:
    """Arrays of a worker that are freed leave its memory at once, instead of lying between smaller things that stay."""
    try:
        ctypes.CDLL(None).mallopt(-3, 1 << 18)  # M_MMAP_THRESHOLD
    except (AttributeError, OSError):  # another C library
        pass


def _answer(rows: pa.Table, vocabulary: Vocabulary, counted: bool) -> pa.Table:
    """For each portion the documents' sums of logarithms over this shard's tokens; where rare words are counted, each of
    them with what it takes to know its probability by its count."""
    if rows["dest"][0].as_py() < 0:  # about documents: nothing is asked
        return _said(rows["flush"].to_pylist(), rows["about"].to_pylist(), rows["payload"].to_pylist())
    _give_back()
    asked = rows["asked"].to_pylist()
    blobs = [Blob.arrays(x.as_py()) for x in rows["payload"]]
    codes, (unit, u, w), count, inverse = _learn(blobs, asked)
    some = count > 0
    used = np.zeros(len(codes), bool)
    for x in (unit, u, w):
        used[x[some]] = True
    seat = (np.cumsum(used) - 1).astype(np.int32)
    trie = Shard.build(codes[used], *(seat[x[some]] for x in (unit, u, w)), count[some].astype(np.float64))
    used = some = count = seat = None
    place = trie.places(codes)
    hashed = (codes >= len(vocabulary.counts)) & (codes < _CLASS)
    own_part, rest = trie.parts(place[unit], place[u], place[w])
    if counted:
        rare = hashed[w]
        logs = np.log10(np.where(rare, 1.0, own_part + rest * vocabulary.unigram(codes[w])))
    else:
        logs = np.log10(own_part + rest * vocabulary.unigram(codes[w]))
        rare = own_part = rest = None
    seen = np.append(trie.seen.astype(np.int64), 0)[place]
    flushes, out, begin, tokens = rows["flush"].to_pylist(), [], 0, []
    for k, b in enumerate(blobs):
        own = inverse[begin : begin + len(b[4])]
        begin += len(b[4])
        if not asked[k]:
            continue
        doc, own = b[5] >> 1, np.repeat(own, b[4])
        n = int(doc.max()) + 1
        met = np.flatnonzero(np.bincount(doc, minlength=n)).astype(np.int32)
        far = np.flatnonzero(hashed[unit[own]])  # the word before, counted here by what follows it
        c = seen[unit[own[far]]]
        who = np.flatnonzero(np.bincount(doc[far], minlength=n)).astype(np.int32)
        fit = np.bincount(doc, logs[own], n)[met].astype("<f4").view("<i4")
        out.append((flushes[k], Blob.of(met, fit, who, np.bincount(doc[far], np.log10(c + 0.5), n)[who], np.bincount(doc[far], c > 0, n)[who].astype(np.int32))))
        if counted:
            at = np.flatnonzero(rare[own])
            token = own[at]
            tokens.append((codes[w[token]], flushes[k] * _DOCS + doc[at].astype(np.int64), own_part[token].astype(np.float32), rest[token].astype(np.float32)))
    sums = _said([x[0] for x in out], [False] * len(out), [x[1] for x in out])
    if not tokens:
        return sums
    more = [np.concatenate(x) for x in zip(*tokens, strict=True)]
    none = [pa.nulls(len(more[0]), k) for k in (pa.int64(), pa.bool_(), pa.binary())]
    return pa.concat_tables([sums, _said(*none, more)])


def _rare_sums(answers: DataFrame, words: DataFrame, first: int, total: float) -> DataFrame:
    """(flush, doc, fit): logarithms of tokens that aren't held, by their own counts, summed by document."""
    counts = words.select((F.pmod("h", F.lit(_HASH)) + F.lit(first)).alias("code"), "c").groupBy("code").agg(F.sum("c").alias("c"))
    p = F.col("own").cast("double") + F.col("rest") * (F.coalesce("c", F.lit(0)) + F.lit(0.5)) / F.lit(total)
    return answers.where("code is not null").select("code", "at", "own", "rest").join(counts, "code", "left").groupBy("at").agg(F.sum(F.log10(p)).alias("fit")).select(F.shiftright("at", _DOCS.bit_length() - 1).alias("flush"), F.pmod("at", F.lit(_DOCS)).cast("int").alias("doc"), "fit")


def _sum(rows: pa.Table, n: int, total: float) -> pa.Table:
    """The rows of one portion's documents."""
    about = rows["about"].to_pylist()
    payload = [x.as_py() and Blob.arrays(x.as_py()) for x in rows["payload"]]
    *whole, base = payload[about.index(True)]
    ids, flags, tokens, known = (x.astype(np.int64) for x in whole)
    fit, base = np.zeros(len(ids)), base.copy()
    for a, p in zip(about, payload, strict=True):
        if p and not a:
            fit[p[0]] += p[1].view("<f4")
            base[p[2]] += p[3]
            known[p[2]] += p[4]
    rare = rows.filter(pc.is_valid(rows["doc"]))  # one row a document
    fit[rare["doc"].to_numpy()] += rare["fit"].to_numpy()
    return pa.table({"doc_id": pa.array(ids, mask=flags & 1 == 1), "held_out": flags & 2 == 2, "n_tokens": tokens, "n_known": known, "train_tokens": np.full(len(ids), n, np.int64), "base_score": base - tokens * math.log10(total), "score": fit})


SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def score(docs: DataFrame, parts: int = 5, sizes: Sizes = Sizes(), rare: str = "shared") -> DataFrame:
    """One row a document: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score.

    Documents whose crc32(doc_id as text) mod parts isn't 1 train. Every token goes, with the two before it, to the shard
    of the trie that its context belongs to, once: there all distinct pairs and triples are counted, the
    shard is built, and every token asked; sums go back to the documents. Shards that would see more than
    twice sizes.shard tokens, whether by a frequent pair of words or by many copies, are asked in salts.
    rare says what P(w) is of words that aren't held: "shared", an equal part of their common mass, or "counted", by
    the count of each, which a join with the table of all words gives.

    Null or empty texts are one end; null ids train and aren't held out; repeated rows are scored each;
    without training text the base has no counts. An empty table gives no rows; columns but doc_id and
    text are not read. docs is read three times and must give its rows in the same order when a lost
    task is run again, as a scan of files does.
    """
    spark = docs.sparkSession
    out = part_of(F.col("doc_id"), parts) == 1
    own = docs.select("doc_id", "text", out.alias("_out"), (~out).alias("_trains"))
    words = saved(count_words(own.where("_trains")), "lm-words")
    vocabulary = Vocabulary(words, sizes)
    sent = spark.sparkContext.broadcast(vocabulary)
    shards = max(1, vocabulary.n // sizes.shard)
    heavy = _loads(own, sent, shards).where(F.col("n") > 2 * sizes.shard).collect()  # fewer than shards, as a rule none
    hot = {r["shard"]: min(_SALTS - 1, -(-r["n"] // sizes.shard)) for r in heavy}
    routed = _routed(own, sent, shards, hot).withColumn("about", F.col("dest") < 0)
    counted = rare == "counted"
    answers = routed.groupBy("dest").applyInArrow(lambda t: _answer(t, sent.value, counted), _ANSWERS)
    n, total = vocabulary.n, vocabulary.total
    sums = "flush long, about boolean, payload binary, doc int, fit double"
    if counted:
        answers = saved(answers, "lm-answers")
        more = _rare_sums(answers, words, len(vocabulary.held) + 1, total)
        none = lambda *kinds: [F.lit(None).cast(k) for k in kinds]
        told = answers.where("code is null").select("flush", "about", "payload", *none("int", "double"))
        answers = told.union(more.select("flush", F.lit(False), *none("binary"), "doc", "fit")).toDF(*(x.split()[0] for x in sums.split(", ")))
    else:
        answers = answers.select("flush", "about", "payload", F.lit(None).cast("int").alias("doc"), F.lit(None).cast("double").alias("fit"))
    return answers.groupBy("flush").applyInArrow(lambda t: _sum(t, n, total), SCORES)


def query(spark, sf_dir: str) -> DataFrame:
    return score(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), rare="counted")
