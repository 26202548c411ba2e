"""Rounds: pull along in-edges, apply, mark, swap; and the numpy kernel for vertex arrays of checked size."""

from __future__ import annotations

import os
import pickle
import tempfile
import time
from collections.abc import Callable, Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark import RDD, StorageLevel
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from shardgraph.core.cache import EdgeCache, decode, decompress
from shardgraph.core.schedule import build_filters, edges_of_active, hashes, may_hold, pick
from shardgraph.model.graph import ArrowProgram, EngineOptions, Result, ShardedGraph, VertexProgram
from shardgraph.model.schema import EDGE_BYTES, VERTEX_BYTES
from shardgraph.session import dealt_by_one_key, forget, saved, scratch_path, together


def start(vinfo: DataFrame, program: VertexProgram, n: int) -> DataFrame:
    """state(id, shard_id, value, out_deg, active) before the first round."""
    value, active = program.init(max(1, n))
    return vinfo.select("id", "shard_id", value.alias("value"), F.col(program.degree).alias("out_deg"), active.alias("active"))


class Generations:
    """Written states: the new one replaces the old after the round, and the one two back is deleted."""

    def __init__(self, spark, label: str):
        self.spark, self.label, self.paths = spark, label, []

    def keep(self, state: DataFrame) -> tuple[DataFrame, int]:
        """(the state read back, active vertices): one job writes the round and counts."""
        seen = Observation()
        path = scratch_path(self.spark, self.label)
        with dealt_by_one_key(self.spark):
            state.observe(seen, F.coalesce(F.sum(F.col("active").cast("long")), F.lit(0)).alias("active")).write.parquet(path)
        self.paths.append(path)
        if len(self.paths) > 2:
            forget(self.spark, self.paths.pop(0))
        return self.spark.read.schema(state.schema).parquet(path), seen.get["active"]


class Meter:
    """Records that pass marked places of plans, counted while they are read or written."""

    def __init__(self):
        self.open: list[tuple[bool, int, Observation]] = []

    def _mark(self, df: DataFrame, written: bool, width: int) -> DataFrame:
        seen = Observation()
        self.open.append((written, width, seen))
        return df.observe(seen, F.count(F.lit(1)).alias("n"))

    def reads(self, df: DataFrame, width: int) -> DataFrame:
        return self._mark(df, False, width)

    def writes(self, df: DataFrame, width: int) -> DataFrame:
        return self._mark(df, True, width)

    def take(self) -> tuple[int, int, int, int]:
        """(rows read, bytes read, rows written, bytes written) since the last call; every marked plan has run by then."""
        out = [0, 0, 0, 0]
        for written, width, seen in self.open:
            n = seen.get.get("n", 0)
            out[2 * written] += n
            out[2 * written + 1] += n * width
        self.open.clear()
        return tuple(out)


def advance(state: DataFrame, combined: DataFrame, program: VertexProgram, n: int, visited: list[int] | None, buckets: int | None = None) -> DataFrame:
    """The next state: combined([shard_id,] id, msg) joins the old values; vertices of shards not visited keep theirs.

    With buckets, combined already lies by shard, and only the state is dealt to it.
    """
    new = program.apply(F.col("value"), F.col("msg"), max(1, n))
    if visited is not None:
        new = F.when(F.col("shard_id").isin(visited), new).otherwise(F.col("value"))
    old = state.drop("active")
    if buckets:
        both = old.repartition(buckets, "shard_id").join(combined.hint("shuffle_hash"), ["shard_id", "id"], "left")
    else:
        both = old.join(combined, "id", "left")
    both = both.withColumn("_new", new)
    return both.select("id", "shard_id", F.col("_new").alias("value"), "out_deg", F.coalesce(program.changed(F.col("value"), F.col("_new")), F.lit(False)).alias("active"))


def jump(state: DataFrame, program: VertexProgram, n: int, broadcast: bool) -> DataFrame:
    """The state after each vertex, whose value is an id, has taken up the value of the vertex of that id."""
    to = state.select(F.col("id").alias("value"), F.col("value").alias("msg"))
    met = state.join(F.broadcast(to) if broadcast else to, "value", "left").withColumn("_new", program.apply(F.col("value"), F.col("msg"), max(1, n)))
    moved = F.coalesce(program.changed(F.col("value"), F.col("_new")), F.lit(False))
    return met.select("id", "shard_id", F.col("_new").alias("value"), "out_deg", (F.col("active") | moved).alias("active"))


def routed_values(sg: ShardedGraph, state: DataFrame) -> DataFrame:
    """(shard_id, src, _v, _d), dealt by shard: each shard's own sources with their values."""
    src = state.select(F.col("id").alias("src"), F.col("value").alias("_v"), F.col("out_deg").alias("_d"))
    return sg.mirror.join(src, "src").repartition(sg.buckets, "shard_id")


def pull(sg: ShardedGraph, edges: DataFrame, state: DataFrame, program: VertexProgram, broadcast: bool) -> DataFrame:
    """(shard_id, id, msg): source values meet in-edges where the edges lie, and messages combine there.

    broadcast sends all vertex values to the edges. Otherwise each shard is sent the values of its
    own sources: the mirror (shard, source), in buckets of the source, meets the values, and what it finds goes to the
    shard. Edges lie in buckets of their shard, so neither the join nor the aggregation moves them.
    """
    if broadcast:
        src = state.select(F.col("id").alias("src"), F.col("value").alias("_v"), F.col("out_deg").alias("_d"))
        met = edges.join(F.broadcast(src), "src")
    else:
        met = edges.join(routed_values(sg, state).hint("shuffle_hash"), ["shard_id", "src"])
    msg = program.gather(F.col("_v"), F.col("weight"), F.col("_d"))
    return met.groupBy("shard_id", F.col("dst").alias("id")).agg(program.aggregate(msg).alias("msg"))


def _with_filters(sg: ShardedGraph, opts: EngineOptions) -> ShardedGraph:
    if opts.schedule != "selective" or sg.filters is not None:
        return sg
    return replace(sg, filters=saved(build_filters(sg.mirror), "filters"))


def run(sg: ShardedGraph, program: VertexProgram, opts: EngineOptions = EngineOptions()) -> Result:
    """Rounds until nothing is active or max_iter is reached.

    Values are broadcast while there are no more than broadcast_rows of them (16 bytes each), and routed beyond.
    """
    spark = sg.edges.sparkSession
    if opts.value_mode == "broadcast" and sg.n > opts.broadcast_rows:
        raise ValueError(f"{sg.n} vertices: more than broadcast_rows = {opts.broadcast_rows}")
    broadcast = opts.value_mode != "routed" and sg.n <= opts.broadcast_rows
    began = time.perf_counter()
    sg = _with_filters(sg, opts)
    cache = EdgeCache(sg.csr, opts.cache_bytes, opts.cache) if opts.cache is not None else None
    fill = time.perf_counter() - began  # the first round pays for the cache, and for filters that weren't there
    gens = Generations(spark, f"state-{program.name}")
    state, active = gens.keep(start(sg.vinfo, program, sg.n))
    edges_in = {b[0]: b[3] for b in sg.bounds}
    every, ledger, rounds, meter = sorted(edges_in), [], 0, Meter()
    try:
        while active and rounds < opts.max_iter:
            t0 = time.perf_counter()
            ratio = active / max(1, sg.n)
            visited = pick(sg, opts.schedule, opts.threshold, state.where("active"), ratio) if program.idempotent else None
            files, hits, held = sg.edges if visited is None else sg.edges.where(F.col("shard_id").isin(visited)), 0, None
            if cache:
                files, hits, held = cache.scan(sg.edges, visited, every)
            edges = held if files is None else meter.reads(files, EDGE_BYTES) if visited != [] else files
            edges = edges if held is None or files is None else edges.unionByName(held)
            if opts.schedule == "vertex" and program.idempotent and program.combine != "sum":
                edges = edges_of_active(edges, state.where("active"))
            state, new_active = gens.keep(advance(state, pull(sg, edges, state, program, broadcast), program, sg.n, visited, sg.buckets))
            if opts.shortcut and program.jumps and new_active:
                state, new_active = gens.keep(jump(state, program, sg.n, broadcast))
            rounds += 1
            missed = meter.take()[0]
            ledger.append({"run": opts.run, "model": "pull_window", "app": program.name, "iter": rounds, "phase": "fill" if rounds == 1 and (cache or opts.schedule == "selective") else "run", "active": active, "shards_total": len(every), "shards_read": len(every if visited is None else visited), "cache_hits": hits, "read_rows": missed, "read_bytes": missed * EDGE_BYTES, "write_rows": 0, "write_bytes": 0, "seconds": time.perf_counter() - t0 + fill})
            active, fill = new_active, 0.0
    finally:
        if cache:
            cache.close()
    return Result(state.select("id", "value"), ledger, rounds, not active)


#: Vertices up to which the kernel may hold two value arrays and the out-degrees on the driver and in each worker (24 bytes each).
KERNEL_ROWS = 1 << 24

#: Edges that pay for a task of a kernel round, and edges up to which one task holds them all (24 bytes each) and runs every
#: round itself: a round as a job of its own costs about a tenth of a second, whatever it does.
KERNEL_EDGES, ALONE = 1 << 17, 1 << 23


def unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """CSR rows as dicts of numpy arrays and numbers."""
    for b in batches:
        for k in range(b.num_rows):
            shard = {}
            for name, kind, column in zip(b.schema.names, b.schema.types, b.columns, strict=True):
                x = column[k]
                shard[name] = x.as_py() if not pa.types.is_list(kind) else x.values.to_numpy(zero_copy_only=False) if x.is_valid else np.zeros(0, np.int64)
            yield shard


def held_apart(csr: DataFrame, cache: EdgeCache) -> tuple[DataFrame, DataFrame | None]:
    """(CSR rows that a cache left out, those that it keeps: payloads in place of arrays)."""
    if not cache.cached:
        return csr, None
    kept = sorted(cache.cached)
    return csr.where(~F.col("shard_id").isin(kept)), csr.drop("row", "col", "val", "lo", "hi").join(cache.payload, "shard_id")


def unpacked_one(x: dict) -> dict:
    """A kept shard's dict with the arrays that its payload holds."""
    row, col, val = decode(decompress(x["payload"], x["codec"], x["raw_bytes"]), False)
    return {**x, "row": row, "col": col, "val": val}


def stored_one(x: dict, folder: str) -> dict:
    """A shard's dict whose arrays lie in a file of the folder."""
    with open(os.path.join(folder, str(x["shard_id"])), "wb") as f:
        for name in ("row", "col", "val"):
            if name in x:
                np.save(f, x[name])
    return {k: v for k, v in x.items() if k not in ("row", "col", "val")} | {"file": f.name, "arrays": [n for n in ("row", "col", "val") if n in x]}


def read_one(x: dict) -> dict:
    with open(x["file"], "rb") as f:
        return {**x, **{name: np.load(f) for name in x["arrays"]}}


def resident(csr: DataFrame, tasks: int) -> RDD:
    """CSR rows as dicts of numpy arrays and numbers, kept in executors in as many partitions: a round on them is a bare job,
    which nothing is planned, compiled or converted for."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for shard in unpacked(batches):
            yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(shard, 5)], pa.binary())], names=["shard"])

    packed = csr.repartitionByRange(tasks, "shard_id").mapInArrow(pack, "shard binary")
    return packed.rdd.map(lambda r: pickle.loads(r["shard"])).persist(StorageLevel.MEMORY_AND_DISK)


def run_kernel(sg: ShardedGraph, program: VertexProgram | ArrowProgram, opts: EngineOptions = EngineOptions()) -> Result:
    """The same rounds over CSR shards with vertex arrays in memory: each worker writes the values of its own shards only,
    and asks a shard's filter, or its sources, itself before it works on it. Up to ALONE edges, and without at_once, one task
    runs all rounds; beyond, a round is a job over shards that stay in the executors.

    For graphs whose vertex arrays fit, checked against KERNEL_ROWS; larger ones take run().
    """
    if sg.n > KERNEL_ROWS:
        raise ValueError(f"{sg.n} vertices: more than the kernel's arrays may hold")
    spark = sg.edges.sparkSession
    sg = _with_filters(sg, opts)
    v, on = program.init(max(1, sg.n))
    first = sg.vinfo.select("id", v.alias("value"), F.col(getattr(program, "degree", "out_deg")).alias("out_deg"), on.alias("active")).toArrow().sort_by("id")
    whole = pa.types.is_integer(first.schema.field("value").type)
    far = np.iinfo(np.int64).max // 4
    old = first.column("value").fill_null(far).to_numpy() if whole else first.column("value").to_numpy()
    deg = first.column("out_deg").to_numpy()
    on = first.column("active").to_numpy()
    active = int(np.count_nonzero(on))
    update: Callable = program.update if isinstance(program, ArrowProgram) else program.kernel
    n, ledger, outgoing = sg.n, [], getattr(program, "outgoing", None)
    idempotent = getattr(program, "idempotent", True)
    csr = sg.csr
    if opts.schedule == "selective" and idempotent:
        csr = csr.join(sg.filters, "shard_id", "left")  # a shard without edges has no filter
    elif opts.schedule == "exact" and idempotent:
        csr = csr.join(sg.mirror.groupBy("shard_id").agg(F.collect_list("src").alias("sources")), "shard_id", "left")
    by_filter = opts.schedule == "selective"
    began = time.perf_counter()
    cache = EdgeCache(sg.csr, opts.cache_bytes, opts.cache) if opts.cache is not None else None
    fill = time.perf_counter() - began  # the first round pays for the cache
    kept = {b[1] for b in sg.bounds if cache and b[0] in cache.cached}

    every_hash: list[np.ndarray] = []  # of all ids, once many are asked about in a round

    def hashed(on: np.ndarray, active: int) -> np.ndarray:
        if 8 * active < n and not every_hash:
            return hashes(np.flatnonzero(on))
        if not every_hash:
            every_hash.append(hashes(np.arange(n)))
        return every_hash[0][on]

    def asked_for(on: np.ndarray, active: int) -> np.ndarray | None:
        """What the shards are asked about in a round, or None where all are visited."""
        asks = idempotent and (opts.schedule == "exact" or by_filter and active / max(1, n) <= opts.threshold)
        return (hashed(on, active) if by_filter else on) if asks else None

    def visit(shards: Iterable[dict], old: np.ndarray, deg: np.ndarray, asked: np.ndarray | None, sent: tuple = ()) -> Iterator[tuple[int, np.ndarray]]:
        """(first vertex, new values) of each shard that must be read; sent is what vertices pass on, if that was worked out for all of them."""
        for x in shards:
            if asked is None or (x["m"] is not None and may_hold(asked, x["m"], x["k"], x["places"], x["words"]) if by_filter else asked[x["sources"]].any()):
                if cached:
                    x = unpacked_one(x) if x.get("payload") is not None else read_one(x) if "file" in x else x
                yield x["lo"], np.ascontiguousarray(update(x["row"], x["col"], x.get("val"), old, deg, x["lo"], n, *sent))

    cached = cache is not None  # what tasks may know of it
    changed = program.changed if isinstance(program, ArrowProgram) else np.not_equal
    edges_in = {b[1]: b[3] for b in sg.bounds}

    def loop(visited: Callable, old: np.ndarray, on: np.ndarray) -> Iterator[tuple[int, int, int, int, float, np.ndarray, int]]:
        """(active before, shards visited, those of them in memory, edges read from files, or from memory without a cache, seconds, values, active after) of each round."""
        active, rounds = int(np.count_nonzero(on)), 0
        while active and rounds < opts.max_iter:
            t0 = time.perf_counter()
            new, many, hits, read = old.copy(), 0, 0, 0
            for lo, part in visited(old, asked_for(on, active)):
                new[lo : lo + len(part)] = part
                hit = not cached or lo in kept
                many, hits, read = many + 1, hits + hit, read + edges_in[lo] * (not cached or not hit)
            on = changed(old, new)
            old, before, active, rounds = new, active, int(np.count_nonzero(on)), rounds + 1
            yield before, many, hits, read, time.perf_counter() - t0, old, active

    def entered(before: int, many: int, hits: int, read: int, seconds: float) -> None:
        first = cached and not ledger
        ledger.append({"run": opts.run, "model": "pull_window", "app": program.name, "iter": len(ledger) + 1, "phase": "fill" if first else "kernel", "active": before, "shards_total": sg.shards, "shards_read": many, "cache_hits": hits, "read_rows": read, "read_bytes": read * EDGE_BYTES, "write_rows": 0, "write_bytes": 0, "seconds": seconds + fill * first})

    files, packed = held_apart(csr, cache) if cached else (csr, None)
    tasks = opts.at_once or max(1, min(sg.shards, sg.m // KERNEL_EDGES))

    def alone() -> tuple[np.ndarray, int]:
        first_round = spark.sparkContext.broadcast((old, deg, on))

        def every_round(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            old, deg, on = first_round.value
            rows, left = [], int(np.count_nonzero(on))
            with tempfile.TemporaryDirectory() as folder:
                laid = (stored_one(x, folder) if cached and x.get("payload") is None else x for x in unpacked(batches))
                shards = sorted(laid, key=lambda x: x["lo"])
                for *told, old, left in loop(lambda old, asked: visit(shards, old, deg, asked, (outgoing(old, deg),) if outgoing else ()), old, on):  # noqa: B007
                    rows.append((*told, None))
            rows.append((left, 0, 0, 0, 0.0, np.ascontiguousarray(old).tobytes()))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["active", "many", "hits", "read", "seconds", "values"])

        held = files if packed is None else files.unionByName(packed, allowMissingColumns=True)
        one = held.repartition(1) if opts.schedule == "exact" and idempotent else held.coalesce(1)  # sources are gathered by many tasks, the rest is only read
        told = one.mapInArrow(every_round, "active long, many long, hits long, read long, seconds double, values binary").collect()  # a row a round, and one array of at most KERNEL_ROWS values
        *done, last = told or [r for b in every_round(iter(())) for r in b.to_pylist()]  # a table without rows may have no task
        for r in done:
            entered(r["active"], r["many"], r["hits"], r["read"], r["seconds"])
        first_round.destroy()
        return np.frombuffer(last["values"], old.dtype), last["active"]

    def dealt() -> tuple[np.ndarray, int]:
        inside = resident(packed if cached else files, tasks) if packed is not None or not cached else None
        out = spark.sparkContext.broadcast(deg)

        def visited(old: np.ndarray, asked: np.ndarray | None) -> Iterator[tuple[int, np.ndarray]]:
            sent = spark.sparkContext.broadcast((old, asked))
            told = lambda shards: ((lo, own.tobytes()) for lo, own in visit(shards, sent.value[0], out.value, sent.value[1]))

            def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for lo, own in told(unpacked(batches)):
                    yield pa.RecordBatch.from_arrays([pa.array([lo], pa.int64()), pa.array([own], pa.binary())], names=["lo", "own"])

            steps = [lambda: inside.mapPartitions(told).collect()] if inside is not None else []  # one array of at most KERNEL_ROWS values, by shard; none of those skipped
            if cached:
                steps.append(lambda: files.mapInArrow(read, "lo long, own binary").collect())  # shards go from their files straight to the workers that read them
            for part in together(spark, *steps):
                for lo, own in part:
                    yield lo, np.frombuffer(own, old.dtype)
            sent.destroy()

        last, left = old, active
        try:
            for *told, last, left in loop(visited, old, on):  # noqa: B007
                entered(*told)
        finally:
            if inside is not None:
                inside.unpersist()
            out.destroy()
        return last, left

    try:
        old, active = alone() if opts.at_once is None and sg.m <= ALONE else dealt()
    finally:
        if cached:
            cache.close()
    rounds = len(ledger)
    values = lambda: spark.createDataFrame(pa.table({"id": np.arange(n), "value": pa.array(old, mask=old >= far) if whole else pa.array(old)}))
    return Result(values, ledger, rounds, not active)


def pagerank(sg: ShardedGraph, opts: EngineOptions = EngineOptions(), damping: float = 0.85, dangling: str = "drop") -> Result:
    """PageRank; dangling='redistribute' deals the value of vertices without out-edges to all, each round."""
    from shardgraph import programs

    if dangling == "drop":
        return run(sg, programs.pagerank(damping), opts)
    program = programs.pagerank(damping)
    gens = Generations(sg.edges.sparkSession, "state-pagerank")
    state, active = gens.keep(start(sg.vinfo, program, sg.n))
    rounds = 0
    while active and rounds < opts.max_iter:
        lost = state.where("out_deg = 0").agg(F.coalesce(F.sum("value"), F.lit(0.0)).alias("s")).first()["s"]
        base = (1 - damping) / sg.n + damping * lost / sg.n
        msg = pull(sg, sg.edges, state, program, sg.n <= opts.broadcast_rows)
        both = state.repartition(sg.buckets, "shard_id").join(msg.hint("shuffle_hash"), ["shard_id", "id"], "left").withColumn("_new", F.lit(base) + F.lit(damping) * F.coalesce("msg", F.lit(0.0)))
        state, active = gens.keep(both.select("id", "shard_id", F.col("_new").alias("value"), "out_deg", (F.col("_new") != F.col("value")).alias("active")))
        rounds += 1
    return Result(state.select("id", "value"), [], rounds, not active)


def sssp_parents(sg: ShardedGraph, dist: DataFrame, weighted: bool = True) -> DataFrame:
    """(id, parent): for each reached vertex but sources, the least in-neighbour on a shortest path."""
    d = dist.where("value is not null")
    src = d.select(F.col("id").alias("src"), F.col("value").alias("_v"))
    met = sg.edges.join(src, "src").join(d.select(F.col("id").alias("dst"), F.col("value").alias("_d")), "dst")
    step = F.col("weight") if weighted else F.lit(1)
    return met.where(F.col("_v") + step == F.col("_d")).groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent"))


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """(vertices, differ, max_abs, l1) of two results."""
    both = a.select("id", F.col("value").alias("x")).join(b.select("id", F.col("value").alias("y")), "id", "full")
    d = F.abs(F.coalesce(F.col("x").cast("double"), F.lit(0.0)) - F.coalesce(F.col("y").cast("double"), F.lit(0.0)))
    return both.agg(F.count("*").alias("vertices"), F.sum((~F.col("x").eqNullSafe(F.col("y"))).cast("long")).alias("differ"), F.max(d).alias("max_abs"), F.sum(d).alias("l1"))


def memory_bytes(sg: ShardedGraph, workers: int) -> int:
    """What the model holds by its formula: two value arrays, the out-degrees and one shard a worker."""
    return 3 * VERTEX_BYTES * sg.n + workers * EDGE_BYTES * sg.m // max(1, sg.shards)


def stored_bytes(df: DataFrame) -> int:
    """Bytes of memory and disk that a persisted table's blocks take, as the block managers report them."""
    spark = df.sparkSession
    before = {r.id(): r.memSize() + r.diskSize() for r in spark.sparkContext._jsc.sc().getRDDStorageInfo()}
    df = df.persist()
    try:
        df.count()
        now = {r.id(): r.memSize() + r.diskSize() for r in spark.sparkContext._jsc.sc().getRDDStorageInfo()}
        return sum(size for k, size in now.items() if k not in before)
    finally:
        df.unpersist(True)


def hits(sg: ShardedGraph, rounds: int = 10) -> DataFrame:
    """(id, hub, authority) after so many rounds: authorities sum their in-neighbours' hub values, hubs their
    out-neighbours' authorities, and each has length 1 after a round. All are 1 at first."""
    state = saved(sg.vinfo.select("id", F.lit(1.0).alias("hub"), F.lit(1.0).alias("authority")), "hits")

    def summed(values: DataFrame, out: str, near: str, far: str) -> DataFrame:
        met = sg.edges.select("src", "dst").join(values.select(F.col("id").alias(near), F.col("_x")), near)
        return met.groupBy(F.col(far).alias("id")).agg(F.sum("_x").alias(out))

    def scaled(df: DataFrame, c: str) -> DataFrame:
        length = df.agg(F.sqrt(F.sum(F.col(c) * F.col(c))).alias("s")).first()["s"] or 1.0
        return df.withColumn(c, F.col(c) / F.lit(length))

    for _ in range(rounds):
        a = summed(state.withColumn("_x", F.col("hub")), "_a", "src", "dst")
        new = saved(state.select("id").join(a, "id", "left").select("id", F.coalesce("_a", F.lit(0.0)).alias("authority")), "hits-a")
        new = scaled(new, "authority")
        h = summed(new.withColumn("_x", F.col("authority")), "_h", "dst", "src")
        state = scaled(saved(new.join(h, "id", "left").select("id", F.coalesce("_h", F.lit(0.0)).alias("hub"), "authority"), "hits-h"), "hub")
    return state.select("id", "hub", "authority")
