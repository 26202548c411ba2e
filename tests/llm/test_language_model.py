import math
import tracemalloc
import zlib
from collections import Counter

import numpy as np
import pytest

from shardgraph.llm import language_model as lm
from shardgraph.llm import succinct


END = b"\n"


@pytest.mark.parametrize("n,top", [(1, 1), (1, 10**9), (500, 600), (3000, 10**7), (64, 64), (0, 50), (9, 1 << 52)])
def test_elias_fano(n, top):
    rng = np.random.default_rng(n)
    v = np.sort(rng.integers(0, top, n))
    e = succinct.EliasFano.of(v, top)
    assert e.get(np.arange(n)).tolist() == v.tolist()
    x = rng.integers(0, top, 400)
    assert e.successor(x).tolist() == np.searchsorted(v, x, "left").tolist()
    assert e.whole().tolist() == v.tolist()
    for some in (x, x[: max(1, n // 8)], v):  # by one pass, by successor search
        at, equal = e.find(some)
        assert at.tolist() == np.searchsorted(v, some, "left").tolist() and equal.tolist() == np.isin(some, v).tolist()
    if n == 3000:
        assert e.lows.nbytes + e.high.words.nbytes < n * (math.log2(top / n) + 3) / 8 + 64


def test_mapped_block_returns_arrays():
    arrays = [np.arange(5, dtype="<u8"), np.zeros(0, "<u2"), np.arange(3, dtype="<f4")]
    m = succinct.Mapped(*succinct.pack(arrays))
    assert all((a == b).all() and a.dtype == b.dtype for a, b in zip(arrays, m.arrays, strict=True))


def brute(docs, sizes=lm.Sizes(), kind=None):
    """All pairs and triples in dictionaries, shares unrounded; kind(v, u) names the class of a split word."""
    train = [t for i, t in docs if i is None or zlib.crc32(str(i).encode()) % 5 != 1]
    words = [(t or "").encode().lower().split() for t in train]
    c = Counter(w for ws in words for w in ws)
    c[END] += len(words)
    c = +c
    n, v = sum(c.values()), len(c)
    unit = kind(c) if kind else lambda v, u: v
    held = {END, *sorted((w for w in c if w != END), key=lambda w: (-c[w], lm._hash(w)))[: sizes.held]}
    total, others = n + 0.5 * (v + 1), len(set(c) - held) + 1
    other = max(0.5, (n - sum(c[w] for w in held) + 0.5 * others) / others) / total
    two, three = Counter(), Counter()
    for ws in words:
        run = [END, END, *ws, END]
        three.update((unit(b, a), a, w) for a, b, w in zip(run, run[1:], run[2:]))
        two.update((unit(b, a), w) for a, b, w in zip(run, run[1:], run[2:]))

    def level(table):
        n, t = Counter(), Counter()
        for key, x in table.items():
            n[key[:-1]] += x
            t[key[:-1]] += 1
        return n, t

    (n2, t2), (n3, t3) = level(two), level(three)

    def p(u, v, w):
        x = (c[w] + 0.5) / total if w in held else other
        v = unit(v, u)
        for table, n, t, key in ((two, n2, t2, (v,)), (three, n3, t3, (v, u))):
            if n[key]:
                x = (table[(*key, w)] + t[key] * x) / (n[key] + t[key])
        return x

    out = []
    for i, t in docs:
        ws = (t or "").encode().lower().split()
        run = [END, END, *ws, END]
        base = sum(math.log10((c[w] + 0.5) / total) for w in [*ws, END])
        model = sum(math.log10(p(*x)) for x in zip(run, run[1:], run[2:]))
        out.append((i, i is not None and zlib.crc32(str(i).encode()) % 5 == 1, len(ws) + 1, sum(c[w] > 0 for w in [*ws, END]), n, base, model))
    return out


def compare(got, want):
    key = lambda r: (r[0] is not None, r[0] or 0, r[2], round(r[5], 3))
    got, want = sorted((tuple(r) for r in got), key=key), sorted(want, key=key)
    assert [r[:5] for r in got] == [r[:5] for r in want]
    for a, b in zip(got, want, strict=True):
        assert a[5] == pytest.approx(b[5], rel=1e-9) and a[6] == pytest.approx(b[6], abs=3e-4 * b[2] + 1e-9)


def test_whole_table(spark, data):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{data}/documents.parquet").collect()]
    rows = lm.query(spark, data).collect()
    compare(rows, brute(docs))
    held = [r for r in rows if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_small_sizes(spark, data):
    """Split words, words that aren't held, many shards, salted ones and many flushes change no count."""
    sizes = lm.Sizes(held=40, shard=3000, split=60, flush=900)
    docs = spark.read.parquet(f"{data}/documents.parquet").where("doc_id < 80")
    rows = [(r.doc_id, r.text) for r in docs.collect()]

    def kind(c):
        order = sorted((w for w in c if w != END), key=lambda w: (-c[w], lm._hash(w)))
        rank = {END: 0} | {w: k + 1 for k, w in enumerate(order[:40])}
        first = len(rank)

        def unit(v, u):
            k = 1 + c[v] // 60 if v in rank else 1
            code = rank[u] if u in rank else first + lm._hash(u) % (1 << 48)
            return (v, int(lm.mix(np.array([code]))[0]) % k)

        return unit

    compare(lm.score(docs, sizes=sizes).collect(), brute(rows, sizes, kind))


def test_probabilities_sum_to_one():
    rng = np.random.default_rng(5)
    codes = np.arange(10, 60) ** 5
    t = np.unique(rng.integers(0, 50, (400, 3)), axis=0)
    t = t[np.lexsort((t[:, 2], t[:, 1], t[:, 0]))]
    trie = lm.Shard.build(codes, *t.T, rng.integers(1, 9, len(t)).astype(float))
    w, one = np.arange(51), np.full(51, 1 / 51)  # the last stands for all words never met
    assert trie.places(codes).tolist() == list(range(50)) and trie.places(np.array([1, 10**5 + 1, 1 << 51])).tolist() == [50] * 3
    for unit, u in [tuple(t[0, :2]), tuple(t[-1, :2]), (t[0, 0], 50), (50, 50)]:
        assert trie.probability(np.full(51, unit), np.full(51, u), w, one).sum() == pytest.approx(1, abs=1e-3)


def test_a_hot_group_of_copies_is_salted(spark):
    rows = [(k, "one two three four") for k in range(300)] + [(k, f"one two {k} four") for k in range(300, 330)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    df.write.mode("overwrite").parquet("/tmp/checkpoints/lm-hot")
    got = lm.score(spark.read.parquet("/tmp/checkpoints/lm-hot"), sizes=lm.Sizes(shard=100, flush=50)).collect()
    compare(got, brute(rows))


@pytest.mark.parametrize("rows", [[], [(None, None)], [(1, "a b a b"), (1, "a b a b"), (2, ""), (None, "A c"), (7, "zz " * 3000), (12, "b")]])
def test_edges(spark, rows):
    df = spark.createDataFrame([(*r, 1.0) for r in rows], "doc_id long, text string, score double")
    compare(lm.score(df).collect(), brute(rows))


@pytest.mark.parametrize("held", [3, 40])
def test_counted_words_that_are_not_held_keep_their_own_counts(spark, data, held):
    whole = spark.read.parquet(f"{data}/documents.parquet")
    docs = whole.where("doc_id < 40").union(whole.where("doc_id >= 40 and doc_id < 80"))  # flushes of a second task have large numbers
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    got = lm.score(docs, sizes=lm.Sizes(held=held, shard=3000, flush=900), rare="counted").collect()
    compare(got, brute(rows))  # as where every word is held


def test_a_shard_is_built_and_asked_in_little_memory():
    """What a worker takes at once beside its input, for each triple; executors run several workers."""
    rng = np.random.default_rng(3)
    n, words = 1_000_000, 200_000
    t = np.unique(np.stack([rng.integers(0, words, n), rng.integers(0, words, n), rng.integers(0, words, n)], 1), axis=0)
    codes, count = np.arange(words) * 7919, np.ones(len(t))
    unit, u, w = (np.ascontiguousarray(x) for x in t.T)
    asked = (unit, u, w)
    peaks = []
    trie = None
    for step in (lambda: lm.Shard.build(codes, unit, u, w, count), lambda: trie.parts(*asked)):
        tracemalloc.start()
        got = step()
        peaks.append(tracemalloc.get_traced_memory()[1] / len(t))
        tracemalloc.stop()
        trie = trie or got
    assert peaks[0] < 100 and peaks[1] < 100, peaks  # 130 and 178 before
    for a, b in zip(trie.parts(*(x[:1000] for x in asked)), got, strict=True):  # few questions, by successor search
        assert (a == b[:1000]).all()
