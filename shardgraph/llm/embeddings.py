"""Embedding near-dedup: randomised-rotation binary codes with correction factors, and exact recomputation within their bounds."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import Links, components, in_blocks, saved, shared_rows, whole_runs

COSINE = 0.98
#: Code bits in a band, bands, and the seed of the rotations. At the threshold itself a band of 20
#: bits agrees with probability (1 - acos(0.98) / pi)^20 = 0.27, so 44 bands miss one pair in a million.
BITS, BANDS, SEED = 20, 44, 20
#: Standard deviations of an estimate's error that are allowed for, and bits of a query's numbers.
EPS, PLANES = 5.0, 4
#: Rows up to which a bucket stays in one task.
BLOCK = 20_000


_ROTATIONS: dict[tuple[int, int], np.ndarray] = {}


def rotation(dim: int, k: int) -> np.ndarray:
    """The k-th random rotation of dim dimensions (rows are its directions)."""
    if (dim, k) not in _ROTATIONS:
        q, r = np.linalg.qr(np.random.default_rng([SEED, dim, k]).standard_normal((dim, dim)))
        _ROTATIONS[dim, k] = (q * np.sign(np.diag(r))).T.astype(np.float32)
    return _ROTATIONS[dim, k]


def encode(units: np.ndarray, k: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(signs, factors) of unit vectors: the sign bits of the k-th rotation, and <code, vector>.

    A code stands for the unit vector with entries +-1/sqrt(dim) in the rotated space; factor is
    its inner product with the vector it was made from, which corrects estimates.
    """
    z = units.astype(np.float32) @ rotation(units.shape[1], k).T
    return z > 0, np.abs(z).sum(1) / np.sqrt(units.shape[1])


def codes_of(units: np.ndarray, bits: int) -> np.ndarray:
    """The signs over as many rotations as `bits` take."""
    return np.concatenate([encode(units, k)[0] for k in range(-(-bits // units.shape[1]))], 1)[:, :bits]


def query_planes(rotated: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(bit planes, least number, step, sum) of rotated vectors as PLANES-bit numbers, rounded at random so that none is biased."""
    low = rotated.min(1)
    step = np.maximum((rotated.max(1) - low) / (2**PLANES - 1), 1e-12)
    dither = np.random.default_rng(SEED).random(rotated.shape[1])
    level = np.clip(np.floor((rotated - low[:, None]) / step[:, None] + dither), 0, 2**PLANES - 1).astype(np.uint8)
    return np.stack([level >> b & 1 for b in range(PLANES)], 1).astype(bool), low.astype(np.float32), step.astype(np.float32), (low * rotated.shape[1] + step * level.sum(1)).astype(np.float32)


def words(bits: np.ndarray) -> np.ndarray:
    """Bits along the last axis as 64-bit words."""
    pad = np.zeros((*bits.shape[:-1], -bits.shape[-1] % 64), bool)
    return np.packbits(np.concatenate([bits, pad], -1), axis=-1, bitorder="little").view(np.uint64)


def estimate(code: np.ndarray, factor: np.ndarray, planes: np.ndarray, low: np.ndarray, step: np.ndarray, total: np.ndarray, dim: int) -> np.ndarray:
    """Unbiased estimates, over random rotations, of <vector, query> from the vector's code words and factor and the query's planes.

    <code, query> is read off bit counts; the stored factor <code, vector> corrects it.
    """
    inside = sum(np.bitwise_count(code & planes[:, b]).sum(1, dtype=np.int64) << b for b in range(PLANES))
    ones = np.bitwise_count(code).sum(1, dtype=np.int64)
    return (2 * (low * ones + step * inside) - total) / (np.sqrt(dim) * factor)


def half_width(factor: np.ndarray, step: np.ndarray, dim: int, cosine: float, eps: float = EPS) -> np.ndarray:
    """How far an estimate may lie below a true cosine of `cosine` or more.

    code = f v + sqrt(1 - f^2) e with e orthogonal to v, and the query is off v by sqrt(1 - cosine^2), in a direction that is
    random among dim - 1: its part along e has that deviation, and never more than all of it. Rounding adds half a step.
    """
    off = np.sqrt(np.maximum(0, 1 - factor**2)) / factor * np.sqrt(1 - cosine**2)
    rounding = eps * step / (2 * factor)
    return np.hypot(off * min(1.0, eps / np.sqrt(max(1, dim - 1))), rounding) + 1e-4


def _units(v: np.ndarray) -> np.ndarray:
    """Rows of v at length 1, scaled first so that no square over- or underflows."""
    v = v / np.abs(v).max(1, keepdims=True)
    return v / np.linalg.norm(v, axis=1, keepdims=True)


def _by_dim(batch: pa.RecordBatch, column: int, kind: str) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(places, unit vectors) of a batch's vectors, for each dimension."""
    vectors = [np.array(v, kind) for v in batch.column(column).to_pylist()]
    dims = np.array([len(v) for v in vectors])
    for dim in np.unique(dims).tolist():
        own = np.flatnonzero(dims == dim)
        yield own, _units(np.stack([vectors[i] for i in own]).astype(np.float64))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ x >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ x >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
    return x ^ x >> np.uint64(31)


def band_values(signs: np.ndarray, bits: int, bands: int) -> np.ndarray:
    return (signs.reshape(len(signs), bands, bits).astype(np.uint64) << np.arange(bits, dtype=np.uint64)).sum(2, dtype=np.uint64)


def _keys(batches: Iterator[pa.RecordBatch], bits: int, bands: int, kind: str) -> Iterator[pa.RecordBatch]:
    """(s, node): a key for each band of each vector, made of label, dimension, band and the band's bits."""
    seen: set[int] = set()  # copies in one task are one node already here
    for whole in batches:
        new = [k for k, x in enumerate(whole.column(0).to_pylist()) if not (x in seen or seen.add(x))]
        if len(seen) > 200_000:
            seen.clear()
        whole = whole.take(pa.array(new, pa.int64()))
        for at in range(0, whole.num_rows, 1000):
            b = whole.slice(at, 1000)
            node, label = b.column(0).to_numpy(), b.column(1).to_numpy().view(np.uint64)
            for own, u in _by_dim(b, 2, kind):
                value = band_values(codes_of(u, bits * bands), bits, bands)
                root = _mixed(_mixed(label[own]) + np.uint64(u.shape[1]))[:, None] + np.arange(bands, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
                key = _mixed(_mixed(root) + value).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(key.T.ravel()), pa.array(np.tile(node[own], bands))], names=["s", "node"])


_CODE = "node long, label long, dim int, bits binary, code binary, factor float, planes binary, low float, step float, total float"


def _encode(batches: Iterator[pa.RecordBatch], bits: int, bands: int, kind: str) -> Iterator[pa.RecordBatch]:
    """What is stored of each vector: the bits of all bands, the first rotation's code with its correction factor, and the vector as a query."""
    for whole in batches:
        for at in range(0, whole.num_rows, 1000):
            b = whole.slice(at, 1000)
            for own, u in _by_dim(b, 2, kind):
                dim = u.shape[1]
                all_ = np.packbits(codes_of(u, bits * bands), axis=1)
                signs, factor = encode(u)
                turned = u.astype(np.float32) @ rotation(dim, 0).T
                planes, low, step, total = query_planes(turned)
                raw = lambda x: pa.array([r.tobytes() for r in x], pa.binary())
                take = lambda k: b.column(k).take(pa.array(own))  # noqa: B023, E731
                cols = [take(0), take(1), pa.array(np.full(len(own), dim, np.int32)), raw(all_), raw(words(signs)), pa.array(factor.astype(np.float32)), raw(words(planes)), pa.array(low), pa.array(step), pa.array(total)]
                yield pa.RecordBatch.from_arrays(cols, names=[x.split()[0] for x in _CODE.split(", ")])


def _pairs(size: np.ndarray, lo: np.ndarray, hi: np.ndarray, own: np.ndarray, most: int = 1 << 17) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All pairs of places inside runs, some at a time; where two blocks meet, pairs across them only."""
    start = np.cumsum(size) - size
    run = np.repeat(np.arange(len(size)), size)
    small = size <= 64
    for k in range(1, int(size[small].max(initial=0))):
        i = np.flatnonzero((run[:-k] == run[k:]) & small[run[:-k]])
        i = i[(lo[i] == hi[i]) | (own[i] != own[i + k])]
        for at in range(0, len(i), most):
            yield i[at : at + most], i[at : at + most] + k
    for s, n in zip(start[~small].tolist(), size[~small].tolist(), strict=True):
        step = max(1, most // n)
        for at in range(0, n, step):
            i, j = np.nonzero(np.arange(at, min(n, at + step))[:, None] < np.arange(n)[None, :])
            i, j = i + at + s, j + s
            keep = (lo[i] == hi[i]) | (own[i] != own[j])
            yield i[keep], j[keep]


#: Columns of the rows that meet: the bucket's three and the block, then what is stored of a vector.
_MET = ("s", "_lo", "_hi", "_own", "copies", *(x.split()[0] for x in _CODE.split(", ")))


def _candidates(sizes: np.ndarray, table: pa.Table, cosine: float, bits: int, bands: int) -> Iterator[tuple[np.ndarray, Iterator]]:
    """(places in the table, pairs of those to recompute) for each dimension.

    A pair counts in the first band that its codes share. Estimates from code and factor, with
    their confidence bound, tell which pairs may have the cosine; only those are recomputed.
    """
    table = table.append_column("_place", pa.array(np.arange(table.num_rows))).filter(pa.array(np.repeat(sizes > 1, sizes)))
    dims = table["dim"].to_numpy()
    for dim in np.unique(dims).tolist():  # one, as a rule
        part = table.filter(pa.array(dims == dim))
        s, lo, hi, own, label, factor, low, step, total = (part[c].to_numpy() for c in ("s", "_lo", "_hi", "_own", "label", "factor", "low", "step", "total"))
        change = np.flatnonzero(np.concatenate([[True], (s[1:] != s[:-1]) | (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1])]))
        size = np.diff(np.append(change, len(s)))
        read = lambda c, kind: np.frombuffer(b"".join(part[c].to_pylist()), kind).reshape(len(s), -1)  # noqa: B023, E731
        code, planes = read("code", np.uint64), read("planes", np.uint64).reshape(len(s), PLANES, -1)
        value = band_values(np.unpackbits(read("bits", np.uint8), axis=1)[:, : bits * bands].astype(bool), bits, bands)
        key = _mixed(_mixed(_mixed(_mixed(label.view(np.uint64)) + np.uint64(dim))[:, None] + np.arange(bands, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) + value)
        band = (key.view(np.int64) == s[:, None]).argmax(1)

        def pairs(size=size, lo=lo, hi=hi, own=own, label=label, value=value, band=band, code=code, planes=planes, factor=factor, low=low, step=step, total=total, dim=dim):
            for i, j in _pairs(size, lo, hi, own):
                some = (label[i] == label[j]) & ((value[i] == value[j]).argmax(1) == band[i]) & (band[i] == band[j])
                i, j = i[some], j[some]
                near = estimate(code[i], factor[i], planes[j], low[j], step[j], total[j], dim) >= cosine - half_width(factor[i], step[j], dim, cosine)
                yield i[near], j[near]

        yield part["_place"].to_numpy(), pairs()


def _undecided(batches: Iterator[pa.RecordBatch], cosine: float, bits: int, bands: int) -> Iterator[pa.RecordBatch]:
    """(s, node): of each bucket the vectors that some pair needs for its exact product."""
    for sizes, table in whole_runs(batches):
        need = np.zeros(table.num_rows, bool)
        for place, pairs in _candidates(sizes, table, cosine, bits, bands):
            for i, j in pairs:
                need[place[i]] = need[place[j]] = True
        part = table.filter(pa.array(need))
        yield pa.RecordBatch.from_arrays([part[c].combine_chunks() for c in ("s", "node")], names=["s", "node"])


def _exact(batches: Iterator[pa.RecordBatch], cosine: float, bits: int, bands: int, kind: str) -> Iterator[pa.RecordBatch]:
    """(node, least linked node, links) inside each bucket, from products in double precision of the pairs to recompute."""
    for sizes, table in whole_runs(batches):
        node, copies, vectors = table["node"].to_numpy(), table["copies"].to_numpy(), table["vector"].to_pylist()
        for place, pairs in _candidates(sizes, table, cosine, bits, bands):
            unit = _units(np.stack([np.array(vectors[k], kind) for k in place]).astype(np.float64))
            links, count = Links(len(place)), np.zeros(len(place), np.int64)
            for i, j in pairs:
                near = (unit[i] * unit[j]).sum(1) >= cosine
                i, j = i[near], j[near]
                np.add.at(count, i, copies[place[j]])
                np.add.at(count, j, copies[place[i]])
                links.join(i, j)
            some = np.flatnonzero(count)
            yield pa.RecordBatch.from_arrays([pa.array(node[place[some]]), pa.array(node[place[links.roots()[some]]]), pa.array(count[some])], names=["a", "b", "n"])


def near_vectors(vectors: DataFrame, cosine: float = COSINE, bits: int = BITS, bands: int = BANDS, block: int = BLOCK) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of vectors(vec_id, embedding, label).

    Vectors link at this cosine or more under one label. Those that are null, zero or hold null or
    non-finite numbers, and those without a label, link with nothing: their component is themselves.
    Vectors of other dimensions don't link. Equal vectors under a label are one node (a 64-bit hash) with a count,
    so copies make no pairs, and each counts as a link of the others. Buckets get ids only; what is stored of a vector,
    its code and correction factor, goes to buckets that two share, and the vector itself to those where the bound leaves a pair open. A null vec_id stays null and
    names a component only if it has no other; repeated rows are copies; an empty table gives no
    rows; extra columns are not read.
    """
    kind = "<f4" if "array<float>" == dict(vectors.dtypes)["embedding"] else "<f8"
    e = F.col("embedding")
    sound = F.col("label").isNotNull() & (F.coalesce(F.size(e), F.lit(0)) > 0) & F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(e, lambda x: x != 0)
    rows = vectors.select("vec_id", F.col("label").cast("long").alias("label"), "embedding", F.coalesce(sound, F.lit(False)).alias("_ok"), F.xxhash64("label", "embedding").alias("node"))
    sound_rows = rows.where("_ok").select("node", "label", "embedding")
    nodes = saved(rows.where("_ok").groupBy("node").agg(F.min("vec_id").alias("least"), F.count("*").alias("copies")), "vec-nodes", few=True)
    keys = sound_rows.mapInArrow(lambda it: _keys(it, bits, bands, kind), "s long, node long").repartition("s").sortWithinPartitions("s", "node")
    shared = saved(keys.mapInArrow(shared_rows, "s long, node long"), "vec-shared", few=True)
    asked = saved(shared.select("node").distinct(), "vec-asked", few=True)
    stored = sound_rows.join(asked, "node").dropDuplicates(["node"]).mapInArrow(lambda it: _encode(it, bits, bands, kind), _CODE)
    codes = saved(stored.join(nodes.select("node", "copies"), "node"), "vec-codes", few=True)
    met = in_blocks(shared.join(codes, "node"), "s", F.xxhash64("node"), block).select(*_MET)
    undecided = saved(met.mapInArrow(lambda it: _undecided(it, cosine, bits, bands), "s long, node long").distinct(), "vec-undecided", few=True)
    needed = saved(undecided.select("node").distinct(), "vec-needed", few=True)
    fetched = sound_rows.select("node", F.col("embedding").alias("vector")).join(needed, "node").dropDuplicates(["node"])
    both = in_blocks(undecided.join(codes, "node").join(fetched, "node"), "s", F.xxhash64("node"), block).select(*_MET, "vector")
    found = saved(both.mapInArrow(lambda it: _exact(it, cosine, bits, bands, kind), "a long, b long, n long"), "vec-links", few=True)
    counts = found.groupBy(F.col("a").alias("node")).agg(F.sum("n").alias("n"))
    roots = components(found.select("a", "b")).select(F.col("id").alias("node"), "root")
    named = saved(nodes.join(counts, "node", "left").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node")), "vec-named", few=True)
    least = named.groupBy("root").agg(F.min("least").alias("component"))
    known = saved(named.join(least, "root").select("node", "component", (F.coalesce("n", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.lit(True).alias("_ok")), "vec-groups", few=True)
    out = rows.select("vec_id", "node", "_ok").join(known, ["node", "_ok"], "left")
    component = F.when(F.col("_ok"), F.col("component")).otherwise(F.col("vec_id"))
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.col("vec_id").eqNullSafe(component).alias("kept"))


def query(spark, sf_dir: str) -> DataFrame:
    return near_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding", "label"))


ORACLE = """
with recursive sound as (select vec_id, label, embedding::double[] as e from embeddings
    where label is not null and embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0),
pairs as materialized (select a.vec_id as a, b.vec_id as b from sound a join sound b on a.label = b.label and a.vec_id <> b.vec_id and list_cosine_similarity(a.e, b.e) >= 0.98),
reach(id, far) as (select a, b from pairs union select r.id, p.b from reach r join pairs p on r.far = p.a),
least as (select id, min(far) as far from reach group by id),
degree as (select a, count(*) as n from pairs group by a)
select v.vec_id, coalesce(d.n, 0)::bigint as n_links, least(v.vec_id, coalesce(l.far, v.vec_id)) as component_id, v.vec_id = least(v.vec_id, coalesce(l.far, v.vec_id)) as kept
from embeddings v left join degree d on v.vec_id = d.a left join least l on v.vec_id = l.id
"""
