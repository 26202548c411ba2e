"""SimHash near-dedup: fingerprints of word shingles, joined exactly through vantage-point trees."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import Links, components, in_blocks, own, packed, saved, shared_rows, whole_runs

#: Words in a shingle, differing bits that still link, and the hash seed.
SHINGLE, RADIUS, SEED = 3, 3, 42
#: Width of the distance rings around a shard's vantage point; over RADIUS, so only neighbours overlap.
RING = 8
#: Members of a leaf that are compared directly.
LEAF = 48
#: Rows up to which a shard stays in one task; larger ones are dealt in blocks, and all pairs of blocks meet.
BLOCK = 20_000


def fingerprint(text: bytes, shingle: int = SHINGLE) -> int:
    """64 majority bits over the XXH64 hashes of a text's shingles; zero without words."""
    from xxhash import xxh64_intdigest

    words = text.lower().split()  # of bytes: A-Z and [\x20\x09-\x0D] only
    n = len(words)
    if not n:
        return 0
    if n <= shingle:
        hashes = [xxh64_intdigest(b" ".join(words), SEED)]
    else:
        hashes = [xxh64_intdigest(b"%b %b %b" % x, SEED) for x in zip(words, words[1:], words[2:], strict=False)] if shingle == 3 else [xxh64_intdigest(b" ".join(words[i : i + shingle]), SEED) for i in range(n - shingle + 1)]
    ones = np.zeros(64, np.int64)
    for k in range(0, len(hashes), 1 << 14):
        part = np.array(hashes[k : k + (1 << 14)], ">u8")
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(hashes)).tobytes(), "big")


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fp): fp as a signed 64-bit number. A null text has no words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.fromiter((fingerprint(t.as_py(), shingle) for t in b.column(1)), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce("text", F.lit("")).cast("binary").alias("text")).mapInArrow(run, "doc_id long, fp long")


def distance(fp: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Differing bits between the codes at a and at b; codes are numbers or rows of numbers."""
    d = np.bitwise_count(fp[a] ^ fp[b])
    return (d if fp.ndim == 1 else d.sum(-1)).astype(np.int64)


def _compare(fp: np.ndarray, a: np.ndarray, b: np.ndarray, links: Links, radius: int) -> None:
    """Link members of a with members of b within radius, nearest first, some at a time."""
    step = max(1, (1 << 20) // max(1, len(b) * fp[:1].size))
    for k in range(0, len(a), step):
        part = a[k : k + step]
        d = distance(fp, part[:, None], b[None, :])
        x, y = np.nonzero(d <= radius)
        order = np.argsort(d[x, y], kind="stable")
        x, y = part[x[order]], b[y[order]]
        new = links.up[x] != links.up[y]
        links.join(x[new], y[new])


def tree_join(fp: np.ndarray, a: np.ndarray, b: np.ndarray | None, links: Links, radius: int = RADIUS) -> None:
    """Link all pairs within radius among the positions a, or between a and b.

    A vantage point parts its members by their median distance. By the triangle inequality partners
    of a member differ from it by radius at most in that distance, so only members of both sides
    near the boundary can still meet across. Members within the radius of the vantage point are
    linked through it and need not be compared with each other.
    """
    todo = [(a, b)]
    while todo:
        a, b = todo.pop()
        if not len(a) or b is not None and not len(b):
            continue
        if (len(a) if b is None else min(len(a), len(b))) <= LEAF:
            _compare(fp, a, a if b is None else b, links, radius)
            continue
        v = a[len(a) // 2]
        da = distance(fp, a, v)
        if b is None:
            near = da <= radius
            links.join(a[near], np.full(int(near.sum()), v))
            if near.all():
                continue
            cut = int(np.median(da))
            low = da <= cut
            if low.all():
                low = da < cut
            if not low.any():  # all at one distance: the tree can't part them
                _compare(fp, a, a, links, radius)
                continue
            todo += [(a[~low], None), (a[low & (da >= da[~low].min() - radius)], a[~low & (da <= da[low].max() + radius)])]
            if not near[low].all():
                todo.append((a[low], None))
            continue
        db = distance(fp, b, v)
        cut = int(np.median(da))
        al, ah = da <= cut, da > cut
        parts = [(a[al], b[db <= cut + radius]), (a[ah], b[db > cut - radius])]
        if any(len(x) == len(a) and len(y) == len(b) for x, y in parts):
            _compare(fp, a, b, links, radius)
        else:
            todo += parts


def _search(batches: Iterator[pa.RecordBatch], radius: int) -> Iterator[pa.RecordBatch]:
    """Edges (fp, least linked fp) inside each shard's run of rows."""
    for size, part in whole_runs(batches):
        fp = part.column(3).to_numpy().view(np.uint64)
        links, small = Links(len(fp)), size <= LEAF
        start = np.cumsum(size) - size
        if small.any():  # every small shard at once, by the distance between places
            same = np.repeat(np.where(small, np.arange(len(size)), -1), size)
            for k in range(1, int(size[small].max())):
                i = np.flatnonzero((same[:-k] == same[k:]) & (same[:-k] >= 0))
                i = i[np.bitwise_count(fp[i] ^ fp[i + k]) <= radius]
                links.join(i, i + k)
        for s, n in zip(start[~small].tolist(), size[~small].tolist(), strict=True):
            tree_join(fp, np.arange(s, s + n), None, links, radius)
        root = links.roots()
        far = np.flatnonzero(fp != fp[root])
        yield pa.RecordBatch.from_arrays([pa.array(fp[far].view(np.int64)), pa.array(fp[root[far]].view(np.int64))], names=["a", "b"])


def links(prints: DataFrame, radius: int = RADIUS, block: int = BLOCK) -> DataFrame:
    """Edges (a, b) between the distinct numbers in prints.fp that join all within radius, and no others.

    Of four 16-bit segments two numbers within three bits share one, so each segment's value is the
    root of a vantage-point tree. Its first level is a shared vantage point, whose rings are shards: a
    number lives in its ring and visits the next one if it lies within radius of their boundary.
    The lower levels are built inside each shard by tree_join. Shards beyond `block` rows are dealt
    in blocks and every two blocks meet in a task of their own, so no group is too large for one.
    """
    if radius > 3:
        raise ValueError("four segments find pairs within three bits")
    seg = F.explode(F.array(*(F.struct(F.lit(s).cast("long").alias("s"), F.shiftrightunsigned("fp", 16 * s).bitwiseAND(0xFFFF).alias("v")) for s in range(4))))
    far = F.bit_count(F.col("fp").bitwiseXOR(F.xxhash64("_s.s", "_s.v"))).cast("long")  # the shard's vantage point is a hash of its root
    rows = prints.select("fp", seg.alias("_s")).withColumn("_d", far)
    ring = F.floor(F.col("_d") / RING)
    shard = lambda r: F.shiftleft(F.col("_s.s"), 40) + F.shiftleft(F.col("_s.v"), 8) + r
    visits = F.array(shard(ring), F.when(F.col("_d") % RING >= RING - radius, shard(ring + 1)))
    dealt = rows.select("fp", F.explode(F.filter(visits, lambda x: x.isNotNull())).alias("_shard"))
    return in_blocks(dealt, "_shard", F.xxhash64("fp"), block).select("_shard", "_lo", "_hi", "fp").mapInArrow(lambda it: _search(it, radius), "a long, b long")


def near_groups(docs: DataFrame, radius: int = RADIUS, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fp, component_id): component_id is the least doc_id reachable over links of fingerprints.

    Equal fingerprints are one node, so copies add no pairs. Null and empty texts have fingerprint
    zero and link like any other. Null doc_ids have a component like others, whose id is null only
    if it has no other id. Repeated rows stay; an empty table gives no rows; extra columns are not read.
    """
    prints = saved(fingerprints(docs, shingle), "simhash")
    nodes = saved(prints.groupBy("fp").agg(F.min("doc_id").alias("_least")), "simhash-nodes", few=True)
    roots = saved(components(links(nodes.select("fp"), radius)).select(F.col("id").alias("fp"), "root"), "simhash-roots", few=True)
    named = nodes.join(roots, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    least = named.groupBy("root").agg(F.min("_least").alias("component_id"))
    groups = saved(named.select("fp", "root").join(least, "root").select("fp", "component_id"), "simhash-groups", few=True)
    return prints.join(groups, "fp").select("doc_id", "fp", "component_id")


#: Members of a group of candidates up to which one task holds their shingles; larger groups are dealt in blocks.
GROUP = 5_000
#: Texts that tell which shingles are common, and how many of those are known to all tasks. Only speed depends on either.
SAMPLE, COMMON = 4_000, 100_000
#: Bits of the long codes, and the distance from which on two texts can't be near: two sets at a similarity of 0.8
#: differ in 77 bits on average if large and in 96 at most if small, with a deviation below ten.
LONG, LONG_RADIUS = 512, 180


def shingle_set(text: bytes, shingle: int) -> np.ndarray:
    """Hashes of a text's distinct shingles, rising; a text without words has that of the empty one."""
    from xxhash import xxh64_intdigest

    words = text.lower().split()
    return np.unique(np.fromiter((xxh64_intdigest(b" ".join(words[k : k + shingle])) for k in range(max(1, len(words) - shingle + 1))), np.uint64)).view(np.int64)


def prefix(members: np.ndarray, common: np.ndarray, rank: np.ndarray, similarity: float) -> np.ndarray:
    """The members, the rarest first, of which two sets at this Jaccard similarity have at least one in common.

    Such sets share at least `similarity` of the members of either, so leaving out one member fewer than
    that leaves a shared one in both if all sets are cut in one order: by rank among the common, then by hash.
    """
    keep = len(members) - int(np.ceil(similarity * len(members) - 1e-9)) + 1
    if not len(common):
        return np.sort(members)[:keep]
    at = np.minimum(np.searchsorted(common, members), len(common) - 1)
    return members[np.lexsort((members, np.where(common[at] == members, rank[at], -1)))[:keep]]


def _common_shingles(rows: DataFrame, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, rising; their ranks by count) of shingles that several texts of a sample hold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for t in b.column(0):
                yield pa.RecordBatch.from_arrays([pa.array(shingle_set(t.as_py(), shingle))], names=["s"])

    some = rows.where(F.pmod("_h", F.lit(max(1, rows.count() // SAMPLE))) == 0).dropDuplicates(["_h"]).select("_text")
    counts = some.mapInArrow(run, "s long").groupBy("s").agg(F.count("*").alias("c")).where("c > 1")
    top = np.array([(r["s"], r["c"]) for r in counts.orderBy(F.desc("c"), "s").limit(COMMON).collect()], np.int64).reshape(-1, 2)
    top = top[np.argsort(top[:, 0])]
    return top[:, 0].copy(), top[:, 1].copy()


def long_code(members: np.ndarray) -> np.ndarray:
    """A SimHash of LONG bits, as 64-bit numbers, of a set of shingle hashes."""
    ones = np.zeros(LONG, np.int64)
    for k in range(0, len(members), 1 << 12):
        x = members[k : k + (1 << 12)].view(np.uint64)[:, None] + np.arange(1, LONG // 64 + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ x >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ x >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
        ones += np.unpackbits((x ^ x >> np.uint64(31)).view(np.uint8), axis=1).sum(0, dtype=np.int64)
    return np.packbits(2 * ones > len(members)).view(np.uint64)


def _code_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(a, b): links that join all nodes of a shingle whose long codes are within LONG_RADIUS, found by a tree where there are many."""
    for size, part in whole_runs(batches):
        node = part.column(3).to_numpy()
        code = np.frombuffer(b"".join(part.column(4).to_pylist()), np.uint64).reshape(-1, LONG // 64)
        links, small = Links(len(node)), size <= LEAF
        same = np.repeat(np.where(small, np.arange(len(size)), -1), size)
        for k in range(1, int(size[small].max(initial=0))):
            i = np.flatnonzero((same[:-k] == same[k:]) & (same[:-k] >= 0))
            i = i[distance(code, i, i + k) <= LONG_RADIUS]
            links.join(i, i + k)
        for s, n in zip((np.cumsum(size) - size)[~small].tolist(), size[~small].tolist(), strict=True):
            tree_join(code, np.arange(s, s + n), None, links, LONG_RADIUS)
        root = links.roots()
        far = np.flatnonzero(node != node[root])
        a, b = np.unique(np.stack([node[far], node[root[far]]], 1), axis=0).T
        yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(a)), pa.array(np.ascontiguousarray(b))], names=["a", "b"])


def link_sets(sets: list[np.ndarray], similarity: float) -> list[tuple[int, int]]:
    """Pairs at this Jaccard similarity that join all such pairs' groups; each was tested itself.

    Every set meets, through an index of members, all later ones that verified pairs haven't joined it to.
    """
    n, size = len(sets), np.array([len(x) for x in sets], np.int64)
    ids = np.unique(np.concatenate(sets), return_inverse=True)[1]
    holder = np.repeat(np.arange(n), size)[np.argsort(ids, kind="stable")]
    start = np.concatenate([[0], np.cumsum(np.bincount(ids))])
    at = np.concatenate([[0], np.cumsum(size)])
    group, made, left = np.arange(n), [], n
    for x in range(n):
        if left == 1:
            break
        own = ids[at[x] : at[x + 1]]
        many = start[own + 1] - start[own]
        met = np.repeat(start[own] - np.cumsum(many) + many, many) + np.arange(int(many.sum()))
        shared = np.bincount(holder[met], minlength=n)
        for y in (np.flatnonzero(shared[x + 1 :] / (size[x + 1 :] + size[x] - shared[x + 1 :]) >= similarity) + x + 1).tolist():
            if group[y] != group[x]:
                group[group == group[y]] = group[x]
                made.append((x, y))
                left -= 1
    return made


def _verified(batches: Iterator[pa.RecordBatch], shingle: int, similarity: float) -> Iterator[pa.RecordBatch]:
    """Links (a, b) inside each group of candidates, or each two blocks of one."""
    for size, part in whole_runs(batches):
        node, texts, a, b = part.column(3).to_numpy(), part.column(4), [], []
        for s, n in zip((np.cumsum(size) - size).tolist(), size.tolist(), strict=True):
            if n > 1:
                made = np.array(link_sets([shingle_set(texts[k].as_py(), shingle) for k in range(s, s + n)], similarity), np.int64).reshape(-1, 2) + s
                a.append(node[made[:, 0]])
                b.append(node[made[:, 1]])
        if a:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(a)), pa.array(np.concatenate(b))], names=["a", "b"])


def similar_groups(docs: DataFrame, shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """(_id, _h, _group): rows' ids and text hashes with the node of their group of near copies.

    Texts link at this Jaccard similarity of their distinct shingles (lower-cased A-Z; fewer words
    than a shingle: the whole; none: all alike). Equal texts are one node. Texts that link share a
    shingle of their prefixes, and SimHashes of LONG bits tell, far beyond any doubt, which of those that share one
    can't be near; groups of the others hold every link, and inside each group texts are joined by
    links only that their whole sets of shingles have proved.
    """
    text = F.coalesce("text", F.lit(""))
    rows = docs.select(F.col("doc_id").cast("bigint").alias("_id"), F.xxhash64(text).alias("_h"), text.cast("binary").alias("_text"))
    common, rank = _common_shingles(rows, shingle)
    sent = docs.sparkSession.sparkContext.broadcast((common, rank))

    def prefixes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()  # copies in one task are one node already here
        for b in batches:
            nodes, parts = [], []
            for h, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                if h not in seen:
                    seen.add(h)
                    nodes.append(h)
                    parts.append(prefix(shingle_set(t.as_py(), shingle), *sent.value, similarity))
            if len(seen) > 200_000:
                seen.clear()
            if nodes:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(parts)), pa.array(np.repeat(np.array(nodes, np.int64), [len(x) for x in parts]))], names=["s", "node"])

    dealt = rows.select("_h", "_text").mapInArrow(prefixes, "s long, node long").repartition("s").sortWithinPartitions("s", "node")
    shared = saved(dealt.mapInArrow(shared_rows, "s long, node long"), "sim-shared")
    nodes = saved(shared.select(F.col("node").alias("_h")).distinct(), "sim-nodes", few=True)
    texts = saved(rows.select("_h", "_text").join(nodes, "_h").dropDuplicates(["_h"]), "sim-texts")

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            codes = [long_code(shingle_set(t.as_py(), shingle)).tobytes() for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(codes, pa.binary())], names=["node", "code"])

    codes = saved(texts.mapInArrow(encode, "node long, code binary"), "sim-codes", few=True)
    coded = in_blocks(shared.join(codes, "node"), "s", F.xxhash64("node"), BLOCK).select("s", "_lo", "_hi", "node", "code")
    pairs = saved(coded.mapInArrow(_code_links, "a long, b long").distinct(), "sim-pairs", few=True)
    maybe = saved(components(pairs).select(F.col("id").alias("_h"), F.col("root").alias("_maybe")), "sim-maybe", few=True)
    texts = texts.join(maybe, "_h")
    met = in_blocks(texts, "_maybe", F.xxhash64("_h"), GROUP).select("_maybe", "_lo", "_hi", "_h", "_text")
    edges = saved(met.mapInArrow(lambda it: _verified(it, shingle, similarity), "a long, b long"), "sim-links")
    roots = saved(components(edges), "sim-roots", few=True).select(F.col("id").alias("_h"), F.col("root").alias("_group"))
    return rows.drop("_text").join(roots, "_h", "left").withColumn("_group", F.coalesce("_group", "_h"))


def keep_one(docs: DataFrame, shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """docs without near copies: of each group the row with the least doc_id stays (null last, then by text hash), once."""
    groups = saved(similar_groups(docs, shingle, similarity), "sim-groups")
    first = groups.groupBy("_group").agg(F.min(F.struct(F.col("_id").isNull().alias("n"), F.col("_id").alias("i"), F.col("_h").alias("h"))).alias("_f"))
    stay = saved(first.select(F.col("_f.i").alias("_i"), F.col("_f.h").alias("_k")), "sim-stay", few=True)
    hashed = F.xxhash64(F.coalesce("_d.text", F.lit("")))
    kept = packed(docs).join(stay, F.col("_d.doc_id").cast("bigint").eqNullSafe(F.col("_i")) & (hashed == F.col("_k")), "left_semi")
    if not groups.groupBy("_id", "_h").agg(F.count("*").alias("n")).where("n > 1").isEmpty():
        kept = kept.withColumns({"_i": F.col("_d.doc_id"), "_k": hashed}).dropDuplicates(["_i", "_k"])
    return kept.select(*own(docs))


def hex_digits(c):
    return F.lower(F.lpad(F.hex(c), 16, "0"))


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return near_groups(docs).select("doc_id", hex_digits(F.col("fp")).alias("fingerprint"), "component_id")
