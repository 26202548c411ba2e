import random

import numpy as np
import pytest
import xxhash

from shardgraph.llm import simhash


def brute_print(text, shingle=3):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    grams = [b" ".join(words[i : i + shingle]) for i in range(max(1, len(words) - shingle + 1))]
    hs = [xxhash.xxh64(g, seed=42).intdigest() for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def brute_groups(fps):
    up = list(range(len(fps)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    a = np.array(fps, np.uint64)
    for i in range(len(a)):
        for j in np.flatnonzero(np.bitwise_count(a[:i] ^ a[i]) <= 3).tolist():
            x, y = find(i), find(j)
            up[max(x, y)] = min(x, y)
    return [find(i) for i in range(len(a))]


@pytest.mark.parametrize("kind", ["random", "ball", "chain", "copies"])
def test_tree_join(kind):
    rng = np.random.default_rng(4)
    if kind == "random":
        fp = rng.integers(0, 1 << 63, 3000, dtype=np.uint64)
        fp[:1500] = fp[1500:] ^ (np.uint64(1) << rng.integers(0, 64, 1500).astype(np.uint64))
    elif kind == "ball":
        fp = np.uint64(12345)
        for _ in range(4):
            fp = fp ^ (np.uint64(1) << rng.integers(0, 64, 2000).astype(np.uint64))
    elif kind == "chain":
        fp = np.cumsum(np.uint64(1) << (np.arange(60) % 64).astype(np.uint64), dtype=np.uint64)
    else:
        fp = np.full(500, 7, np.uint64)
    links = simhash.Links(len(fp))
    simhash.tree_join(fp, np.arange(len(fp)), None, links)
    assert links.roots().tolist() == brute_groups(fp.tolist())


@pytest.mark.parametrize("block", [20000, 64])
def test_links_find_all(spark, block):
    rng = np.random.default_rng(6)
    fp = rng.integers(0, 1 << 63, 800, dtype=np.uint64)
    near = fp[:300] ^ (np.uint64(1) << rng.integers(0, 64, 300).astype(np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 300).astype(np.uint64))
    ball = np.uint64(99) ^ (np.uint64(1) << rng.integers(0, 64, 400).astype(np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 400).astype(np.uint64)) ^ (np.uint64(1) << rng.integers(0, 16, 400).astype(np.uint64))
    both = np.unique(np.concatenate([fp, near, ball]))
    df = spark.createDataFrame([(int(x),) for x in both.view(np.int64)], "fp long")
    from shardgraph.llm.common import components

    got = {r.id: r.root for r in components(simhash.links(df, block=block)).collect()}
    want = brute_groups(both.tolist())
    names = both.view(np.int64).tolist()
    parts, mine = {}, {}
    for x, w in zip(names, want, strict=True):
        parts.setdefault(w, set()).add(x)
        mine.setdefault(got.get(x, x), set()).add(x)
    assert sorted(map(sorted, parts.values())) == sorted(map(sorted, mine.values()))


def expected(docs):
    fps = [brute_print(t) for _, t in docs]
    groups = brute_groups(fps)
    least = {}
    for (i, _), g in zip(docs, groups, strict=True):
        least[g] = min((x for x in (i, least.get(g)) if x is not None), default=None)
    return sorted(((i, f"{f:016x}", least[g]) for (i, _), f, g in zip(docs, fps, groups, strict=True)), key=str)


def test_whole_table(spark, data):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{data}/documents.parquet").collect()]
    assert sorted((tuple(r) for r in simhash.query(spark, data).collect()), key=str) == expected(docs)


def test_edges(spark):
    rng = random.Random(8)
    base = " ".join(rng.choice("abcdefghij") * 3 for _ in range(400))
    docs = [(5, base), (3, base + " x"), (3, base + " x"), (None, base), (9, None), (8, " \n"), (1, "One"), (2, "one\t"), (4, "two words"), (7, "É é"), (6, "é É"), (None, "alone in here now")]
    df = spark.createDataFrame([(*d, 1) for d in docs], "doc_id long, text string, fp int")
    got = simhash.near_groups(df).select("doc_id", simhash.hex_digits(simhash.F.col("fp")), "component_id").collect()
    assert sorted((tuple(r) for r in got), key=str) == expected(docs)
    assert simhash.near_groups(df.limit(0)).count() == 0


def test_similar_groups_against_all_pairs(spark):
    rng = random.Random(3)
    docs = []
    for g in range(25):
        base = [rng.choice("abcdefghijklmnop") * rng.randint(1, 4) for _ in range(rng.choice([60, 200, 600]))]
        for c in range(rng.randint(1, 6)):
            own = base[:]
            for _ in range(int(len(base) * rng.choice([0, 0.005, 0.01, 0.1]))):
                own[rng.randrange(len(own))] = f"x{rng.random()}"
            docs.append((len(docs), " ".join(own)))
    docs += [(900, docs[0][1]), (901, None), (902, ""), (None, docs[3][1]), (903, "just four words here"), (903, "just four words here")]

    def grams(t):
        w = (t or "").lower().split()
        return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()

    sets = [grams(t) for _, t in docs]
    up = list(range(len(docs)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(docs)):
        for j in range(i):
            if (not sets[i] and not sets[j]) or (sets[i] | sets[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])):
                up[max(find(i), find(j))] = min(find(i), find(j))
    parts = {}
    for k, (i, _) in enumerate(docs):
        parts.setdefault(find(k), []).append(i)
    want = sorted(min((x for x in p if x is not None), default=-1) for p in parts.values())
    df = spark.createDataFrame([(*d, "s") for d in docs], "doc_id long, text string, node string")
    kept = simhash.keep_one(df)
    assert kept.columns == df.columns
    got = sorted(-1 if r.doc_id is None else r.doc_id for r in kept.collect())
    assert set(want) <= set(got) and len(set(got) - set(want)) <= 1  # a pair at the very threshold may be missed
    assert simhash.keep_one(df.limit(0)).count() == 0


def grams(t):
    w = t.lower().split()
    return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}


def similar(a, b):
    return len(a & b) >= 0.8 * len(a | b)


def parts_of(spark, texts):
    got = {r._id: r._group for r in simhash.similar_groups(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    return [got[k] for k in range(len(texts))]


@pytest.mark.parametrize("block", [5000, 300])
def test_star_of_edited_copies(spark, block, monkeypatch):
    """Copies with three words of their own each: all link with the middle, few with each other."""
    monkeypatch.setattr(simhash, "GROUP", block)
    rng = random.Random(5)
    base = [f"w{k}" for k in range(200)]
    texts = [" ".join(base)]
    for c in range(1500):
        own = base[:]
        for k in range(3):
            own[rng.randrange(5 + 65 * k, 60 + 65 * k)] = f"c{c}x{k}"
        texts.append(" ".join(own))
    sets = [grams(t) for t in texts]
    assert all(similar(sets[0], s) for s in sets) and sum(similar(sets[1], s) for s in sets) < 150
    rng.shuffle(texts)
    assert len(set(parts_of(spark, texts))) == 1


def test_link_sets_against_all_pairs():
    rng = np.random.default_rng(2)
    sets = []
    for g in range(12):
        base = rng.integers(0, 1 << 62, rng.integers(1, 60))
        sets += [np.unique(np.where(rng.random(len(base)) < rng.choice([0.02, 0.1, 0.2]), rng.integers(0, 1 << 62, len(base)), base)) for _ in range(15)]
    rng.shuffle(order := list(range(len(sets))))
    sets = [sets[k] for k in order]
    own = [set(x.tolist()) for x in sets]
    made, want = simhash.Links(len(sets)), simhash.Links(len(sets))
    pairs = simhash.link_sets(sets, 0.8)
    assert all(similar(own[a], own[b]) for a, b in pairs)
    for links, ps in ((made, pairs), (want, [(i, j) for i in range(len(sets)) for j in range(i) if similar(own[i], own[j])])):
        links.join(*np.array(ps).T)
    assert made.roots().tolist() == want.roots().tolist()


def test_short_texts_at_the_threshold(spark):
    """Pairs of few shingles that link by one word more or less, and one of 12 shared shingles in 15."""
    texts, want = [], []
    for words, less in ((9, 1), (10, 1), (11, 1), (19, 3)):
        for c in range(40):
            long = [f"p{words}x{c}x{k}" for k in range(words)]
            texts += [" ".join(long), " ".join(long[:-less])]
            want += [len(want), len(want)]
            assert similar(grams(texts[-1]), grams(texts[-2]))
    got = parts_of(spark, texts)
    assert [got.index(g) for g in got] == want


def test_long_codes_of_near_sets_are_within_the_radius():
    """The most differing bits of sets that just reach a similarity of 0.8, by their sizes; others are twice as far."""
    rng = np.random.default_rng(4)
    most, far = {}, []
    for shared in (4, 5, 6, 7, 8, 9, 10, 12, 13, 16, 20, 24, 31, 40, 80, 200, 1000):
        for one in range(shared // 4 + 1):
            two = shared // 4 - one
            for _ in range(8):
                x = rng.integers(0, 1 << 62, shared + one + two)
                codes = np.stack([simhash.long_code(x[: shared + one]), simhash.long_code(np.concatenate([x[:shared], x[shared + one :]]))])
                d = int(simhash.distance(codes, 0, 1))
                most[shared] = max(most.get(shared, 0), d)
            if one > 25:
                break
        far.append(int(simhash.distance(np.stack([simhash.long_code(rng.integers(0, 1 << 62, shared)) for _ in range(2)]), 0, 1)))
    assert max(most.values()) <= simhash.LONG_RADIUS - 30, most
    assert min(far) > simhash.LONG_RADIUS
