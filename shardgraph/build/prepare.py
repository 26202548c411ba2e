"""Preprocessing: degrees, vertex intervals, routed edge shards, CSR, mirrors, filters and metadata."""

from __future__ import annotations

import json
import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shardgraph.core.schedule import build_filters
from shardgraph.model.graph import Graph, ShardedGraph, buckets_of, interval_of
from shardgraph.session import bucketed, exists, open_bucketed, saved, scratch_path, table_name, together

#: Vertices in a block of prefix sums.
BLOCK = 1 << 16


#: What prepare makes beside shards and vertex information.
PARTS = ("csr", "mirror", "filters")


def degrees(g: Graph) -> DataFrame:
    """(id, in_deg, out_deg, out_weight), vertices without edges included: two aggregates before one join each."""
    into = g.edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("in_deg"))
    out = g.weighed().groupBy(F.col("src").alias("id")).agg(F.count("*").alias("out_deg"), F.sum("weight").alias("out_weight"))
    zero = F.lit(0).cast("long")
    return g.vertices.select("id").join(into, "id", "left").join(out, "id", "left").select("id", F.coalesce("in_deg", zero).alias("in_deg"), F.coalesce("out_deg", zero).alias("out_deg"), F.coalesce("out_weight", zero).alias("out_weight"))


def prefix(deg: DataFrame, size: int = BLOCK) -> DataFrame:
    """deg with block and before: the in-edges of all lesser ids, by block sums and a window inside each block."""
    b = deg.withColumn("block", F.floor(F.col("id") / size))
    sums = b.groupBy("block").agg(F.sum("in_deg").alias("s"))
    earlier = sums.select("block", F.coalesce(F.sum("s").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))  # one row a block
    inside = F.coalesce(F.sum("in_deg").over(Window.partitionBy("block").orderBy("id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return b.join(earlier, "block").select("id", "in_deg", "out_deg", "block", (F.col("base") + inside).alias("before"))


def cut_intervals(deg: DataFrame, threshold: int, policy: str = "greedy", bounds: list[int] | None = None, shards: int | None = None, n: int | None = None) -> list[tuple[int, int, int, int]]:
    """(shard_id, lo, hi, edges) of contiguous id ranges that cover 0..n-1.

    greedy closes a shard before the vertex that would lift it over the threshold, so a vertex with
    more in-edges stands alone with ids that have none; prefix cuts where the running sum passes a multiple of the threshold, in
    parallel; equal_vertices makes `shards` ranges of equal length; user takes the given starts.

    The greedy cut depends on all that came before it, so one task walks the sorted degrees, 16 bytes a
    vertex, in bounded memory; only starts come to the driver. prefix has no such task.
    """
    if n is None:
        n = deg.count()
    if n == 0:
        return []
    if shards is not None and shards < 1:
        raise ValueError("a graph needs a shard at least")
    if policy == "equal_vertices":
        k = min(n, shards or 1)
        starts = sorted({-(-i * n // k) for i in range(k)})
    elif policy == "user":
        starts = sorted({0, *(bounds or [])})
    elif policy == "prefix":
        rows = prefix(deg).groupBy(F.floor(F.col("before") / threshold).alias("s")).agg(F.min("id").alias("lo")).orderBy("s").collect()  # one a shard
        starts = sorted({0, *(r["lo"] for r in rows)})
    else:
        starts = _greedy(deg, threshold, n)
    edges = [0] * len(starts)
    for r in deg.groupBy(interval_of(F.col("id"), starts).alias("s")).agg(F.sum("in_deg").alias("e")).collect():
        edges[r["s"]] = r["e"]
    return [(k, lo, (starts[k + 1] if k + 1 < len(starts) else n) - 1, edges[k]) for k, lo in enumerate(starts)]


def _greedy(deg: DataFrame, threshold: int, n: int) -> list[int]:
    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, first = 0, True  # edges of the open shard; whether there is none yet
        for b in batches:
            if not b.num_rows:
                continue
            ids, total, starts = b.column(0).to_numpy(), np.cumsum(b.column(1).to_numpy()), []
            base, at = -held, 0 if first else -1  # the open shard holds total - base; its first place, if in this batch
            while (nxt := max(int(np.searchsorted(total, base + threshold, "right")), at + 1)) < len(ids):
                at, base = nxt, int(total[nxt - 1]) if nxt else 0
                starts.append(int(ids[nxt]))
            held, first = int(total[-1]) - base, False
            yield pa.RecordBatch.from_arrays([pa.array(starts, pa.int64())], names=["start"])

    rows = deg.select("id", "in_deg").repartition(1).sortWithinPartitions("id").mapInArrow(walk, "start long").collect()
    return sorted({0, *(r["start"] for r in rows)})


def assign_shards(edges: DataFrame, bounds: list[tuple[int, int, int, int]]) -> DataFrame:
    """edges with the shard of their destination: a column expression, not a range join."""
    return edges.withColumn("shard_id", interval_of(F.col("dst"), [b[1] for b in bounds]))


def to_csr(sharded: DataFrame, bounds: list[tuple[int, int, int, int]], weighted: bool = True) -> DataFrame:
    """One row a shard: row offsets per destination, source ids by (dst, src) and, where weighted, edge values.

    Shards without edges have a row too, which are made apart: those with edges are grouped where their bucket lies. Rows arrive
    sorted in their partition, so the kernel only counts; a shard's size is bounded by the interval threshold and the largest
    in-degree.
    """
    limits = {k: (lo, hi) for k, lo, hi, _ in bounds}
    cols = ["shard_id", "src", "dst", *(["weight"] if weighted else [])]

    def build(t: pa.Table) -> pa.Table:
        k = t.column("shard_id")[0].as_py()
        lo, hi = limits[k]
        src, dst = t.column("src").to_numpy(), t.column("dst").to_numpy()
        keep = dst >= 0
        src, dst = src[keep], dst[keep]
        order = np.lexsort((src, dst))
        row = np.concatenate([[0], np.cumsum(np.bincount(dst - lo, minlength=hi - lo + 1))])
        out = {"shard_id": pa.array([k], pa.int32()), "lo": [lo], "hi": [hi], "row": pa.array([row], pa.list_(pa.int64())), "col": pa.array([src[order]], pa.list_(pa.int64()))}
        if weighted:
            out["val"] = pa.array([t.column("weight").to_numpy()[keep][order]], pa.list_(pa.int64()))
        return pa.table(out)

    spark = sharded.sparkSession
    none = F.lit(-1).cast("long")
    schema = "shard_id int, lo long, hi long, row array<long>, col array<long>" + (", val array<long>" if weighted else "")
    grouped = lambda edges: edges.groupBy("shard_id").applyInArrow(build, schema)
    empty = [b[0] for b in bounds if not b[3]]
    if not empty:
        return grouped(sharded.select(*cols))
    bare = F.col("shard_id").isin(empty)
    marks = spark.range(len(bounds)).select(F.col("id").cast("int").alias("shard_id"), none.alias("src"), none.alias("dst"), *([none.alias("weight")] if weighted else [])).where(bare)
    return grouped(sharded.select(*cols).where(~bare)).unionByName(grouped(sharded.select(*cols).where(bare).unionByName(marks)))


#: Edges that from_csr passes on at once.
EDGES = 1 << 18


def from_csr(shards: DataFrame) -> DataFrame:
    """(shard_id, src, dst[, weight]): the edges that a CSR table holds, each array walked once."""
    weighted = "val" in shards.columns
    names = ["shard_id", "src", "dst", *(["weight"] if weighted else [])]

    def edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(b.num_rows):
                row, *values = (b.column(c)[k].values for c in ("row", "col", *(["val"] if weighted else [])))
                row, shard, lo = row.to_numpy(), b.column("shard_id")[k].as_py(), b.column("lo")[k].as_py()
                for at in range(0, int(row[-1]), EDGES):
                    to = min(at + EDGES, int(row[-1]))
                    dst = np.searchsorted(row, np.arange(at, to), "right") - 1 + lo
                    src, *weight = (x.slice(at, to - at) for x in values)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(to - at, shard, np.int32)), src, pa.array(dst, pa.int64()), *weight], names=names)

    wanted = shards.select("shard_id", "lo", "row", "col", *(["val"] if weighted else []))
    return wanted.mapInArrow(edges, "shard_id int, src long, dst long" + (", weight long" if weighted else ""))


def in_neighbors(shards: DataFrame, v: int, bounds: list[tuple[int, int, int, int]]) -> DataFrame:
    """(src) of one vertex: a filter on its shard, then a slice between two offsets."""
    k = next(b[0] for b in reversed(bounds) if b[1] <= v)
    at = F.lit(v) - F.col("lo")
    first, end = F.col("row")[at.cast("int")], F.col("row")[(at + 1).cast("int")]
    return shards.where(F.col("shard_id") == k).select(F.explode(F.slice("col", first.cast("int") + 1, (end - first).cast("int"))).alias("src"))


_PROPS = "num_vertices long, num_edges long, num_shards int, weighted boolean, intervals array<array<long>>, edges string, laid long"


def write_meta(path: str, g: Graph, n: int, m: int, bounds: list, vinfo: DataFrame, edges: str, laid: int) -> None:
    """Property file (counts, intervals, where and how the edges lie, JSON) and vertex information file (degrees, Parquet)."""
    spark = g.vertices.sparkSession
    props = json.dumps({"num_vertices": n, "num_edges": m, "num_shards": len(bounds), "weighted": g.weighted, "intervals": [list(b) for b in bounds], "edges": edges, "laid": laid})
    spark.range(1).coalesce(1).select(F.lit(props)).write.text(f"{path}/props")  # a list of rows would need a Python worker
    vinfo.write.parquet(f"{path}/vinfo")


def _derive(path: str, g: Graph, deg: DataFrame, n: int, m: int, bounds: list, edges: DataFrame, at: str, laid: int, parts: tuple[str, ...], spent: dict[str, float] | None = None) -> ShardedGraph:
    """Write what follows from edges that lie in their shards at `at`, and open it; spent takes the seconds of each part, which are
    made one after the other then, and at the same time where nobody asks for seconds."""
    vinfo = deg.withColumn("shard_id", interval_of(F.col("id"), [b[1] for b in bounds]))
    steps = [lambda: write_meta(path, g, n, m, bounds, vinfo, at, laid), *_parts(path, bounds, edges, laid, parts, {} if spent is None else spent)]
    if spent is None:
        together(edges.sparkSession, *steps)
    else:
        for step in steps:
            step()
    return open_sharded(edges.sparkSession, path, g)


def _parts(path: str, bounds: list, edges: DataFrame, laid: int, parts: tuple[str, ...], spent: dict[str, float]) -> list[Callable]:
    """What writes these parts, each once: steps that don't need each other."""

    def csr() -> None:
        t = time.perf_counter()
        to_csr(edges, bounds).write.parquet(f"{path}/csr")
        spent["csr"] = time.perf_counter() - t

    def mirrors() -> None:
        t = time.perf_counter()
        mirror = bucketed(edges.select("shard_id", "src").distinct(), f"{path}/mirror", "src", buckets_of(len(bounds), laid))
        spent["mirror"] = time.perf_counter() - t
        if "filters" in parts:
            t = time.perf_counter()
            build_filters(mirror).write.parquet(f"{path}/filters")
            spent["filters"] = time.perf_counter() - t

    return [step for name, step in (("csr", csr), ("mirror", mirrors)) if name in parts]


def prepare(g: Graph, threshold: int | None = None, path: str | None = None, policy: str = "greedy", shards: int = 16, parts: tuple[str, ...] = PARTS, bounds: list[int] | None = None, spent: dict[str, float] | None = None) -> ShardedGraph:
    """Cut, route and write a graph once; any program then runs on what open_sharded reads.

    parts says what is made beside the shards: other computation models need less than the engine. bounds are starts
    for the policy user. spent takes the seconds of each part, and of all the rest as "shards".

    Edges are dealt by shard and written in buckets of it, sorted by (shard, dst, src): later rounds group
    them by shard, or read the buckets of the shards they visit, and edges move no more. Edges with a null end
    or a negative destination belong to no shard and are left out; a vertex that comes twice is one.
    """
    spark, began = g.vertices.sparkSession, time.perf_counter()
    path = path or scratch_path(spark, f"sharded-{g.name}")
    edges, vertices = together(
        spark,
        lambda: saved(g.weighed().select("src", "dst", F.coalesce("weight", F.lit(1).cast("long")).alias("weight")).where("src is not null and dst >= 0"), "edges"),
        lambda: saved(g.vertices.select("id").distinct(), "vertices"),
    )
    held = Graph(edges, vertices, g.name, g.directed)
    deg = saved(degrees(held), "degrees")
    row = deg.agg(F.count("*").alias("n"), F.sum("in_deg").alias("m")).first()
    n, m = row["n"], row["m"] or 0
    bounds = cut_intervals(deg, threshold or max(1, m // shards), policy, bounds, shards, n)
    sharded = bucketed(assign_shards(edges, bounds), f"{path}/edges", "shard_id", buckets_of(len(bounds), m), ("shard_id", "dst", "src"))
    sg = _derive(path, held, deg, n, m, bounds, sharded, f"{path}/edges", m, parts, spent)
    if spent is not None:
        spent["shards"] = time.perf_counter() - began - sum(spent.get(x, 0.0) for x in PARTS)
    return sg


def refresh(sg: ShardedGraph, parts: tuple[str, ...] = PARTS) -> ShardedGraph:
    """The graph after edges were added to its shards: counts, degrees, CSR, mirrors and filters anew; edges stay where they lie."""
    spark = sg.edges.sparkSession
    spark.catalog.refreshTable(table_name(sg.edges_at))
    edges = spark.table(table_name(sg.edges_at))
    held = Graph(edges.drop("shard_id"), sg.vinfo.select("id"), sg.graph.name, sg.graph.directed)
    deg = saved(degrees(held), "degrees")
    grown = {r["shard_id"]: r["n"] for r in edges.groupBy("shard_id").agg(F.count("*").alias("n")).collect()}  # one a shard
    bounds = [(k, lo, hi, grown.get(k, 0)) for k, lo, hi, _ in sg.bounds]
    return _derive(scratch_path(spark, f"grown-{sg.graph.name}"), held, deg, sg.n, sum(grown.values()), bounds, edges, sg.edges_at, sg.laid, parts)


def with_parts(sg: ShardedGraph, parts: tuple[str, ...]) -> ShardedGraph:
    """The graph with these parts too: those that it lacks are made from its shards."""
    held = {"csr": sg.csr, "mirror": sg.mirror, "filters": sg.filters}
    lacks = [x for x in parts if held[x] is None]
    if not lacks:
        return sg
    spark = sg.edges.sparkSession
    if sg.mirror is not None and "filters" in lacks:
        build_filters(sg.mirror).write.parquet(f"{sg.path}/filters")
    together(spark, *_parts(sg.path, sg.bounds, sg.edges, sg.laid, tuple(x for x in parts if x in lacks), {}))
    return open_sharded(spark, sg.path, sg.graph)


def open_sharded(spark: SparkSession, path: str, g: Graph | None = None) -> ShardedGraph:
    """A graph that prepare wrote."""
    import os

    p = spark.read.schema(_PROPS).json(f"{path}/props").first()
    bounds = [tuple(b) for b in p["intervals"]]
    buckets = buckets_of(len(bounds), p["laid"])
    vinfo, edges = spark.read.parquet(f"{path}/vinfo"), open_bucketed(spark, p["edges"], "src long, dst long, weight long, shard_id int", "shard_id", buckets)
    g = g or Graph(edges.drop("shard_id"), vinfo.select("id"), os.path.basename(path))
    made = {x: read(f"{path}/{x}") if exists(spark, f"{path}/{x}") else None for x, read in (("csr", spark.read.parquet), ("filters", spark.read.parquet))}
    mirror = open_bucketed(spark, f"{path}/mirror", "shard_id int, src long", "src", buckets) if exists(spark, f"{path}/mirror") else None
    return ShardedGraph(g, p["num_vertices"], p["num_edges"], bounds, edges, vinfo, mirror, made["filters"], made["csr"], path, p["edges"], p["laid"])


def graph_stats(g: Graph) -> DataFrame:
    """One row: vertices, edges, average degree, greatest degrees, bytes of a raw edge record each."""
    d = degrees(g)
    return d.agg(F.count("*").alias("v"), F.sum("in_deg").alias("e"), F.round(F.sum("in_deg") / F.count("*"), 6).alias("avg_deg"), F.max("in_deg").alias("max_in"), F.max("out_deg").alias("max_out"), (F.sum("in_deg") * 8).alias("raw_bytes"))


def degree_histogram(g: Graph, side: str = "in", log: bool = False) -> DataFrame:
    """(deg, vertices), or in bins by powers of two."""
    d = degrees(g).select(F.col(f"{side}_deg").alias("deg"))
    if log:
        d = d.select(F.when(F.col("deg") == 0, -1).otherwise(F.floor(F.log2("deg"))).cast("int").alias("deg"))
    return d.groupBy("deg").agg(F.count("*").alias("vertices"))


def balance(bounds: DataFrame) -> DataFrame:
    """Shards, most and mean edges, and their ratio."""
    return bounds.agg(F.count("*").alias("shards"), F.max("edges").alias("most"), F.round(F.avg("edges"), 6).alias("mean"), F.round(F.max("edges") / F.avg("edges"), 6).alias("ratio"))


def bounds_frame(spark: SparkSession, bounds: list) -> DataFrame:
    from shardgraph.model.schema import INTERVALS

    return spark.createDataFrame(bounds, INTERVALS)
