"""The computation models and engine styles that the pull-window model is compared with, on one substrate.

Every model runs the same programs and gives the same values. What differs is where its edges lie, how
messages get from sources to destinations in a round, and so what is read, written and shuffled. Each model
lays its edges out in buckets of its own key, so that in a round only what the model says moves
does move. The ledger counts the records that really pass a model's scans and writes.
"""

from __future__ import annotations

import math
import time
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.core.engine import Generations, Meter, advance, routed_values, start
from shardgraph.core.engine import run as run_pull
from shardgraph.core.engine import run_kernel
from shardgraph.model.graph import EngineOptions, Graph, Result, ShardedGraph, VertexProgram
from shardgraph.model.schema import EDGE_BYTES as D
from shardgraph.model.schema import VERTEX_BYTES as C
from shardgraph.session import bucketed, drop_bucketed, saved, scratch_path

_EDGE = ("src", "dst", "weight")


@dataclass
class Model:
    """One model over a prepared graph; prepare() lays its own edge tables out, gather() runs a round's messages."""

    sg: ShardedGraph
    program: VertexProgram
    opts: EngineOptions
    made: dict = field(default_factory=dict)
    meter: Meter = field(default_factory=Meter)
    tables: list = field(default_factory=list)

    name = ""
    #: Whether a round's old and new vertex values are read and written as files.
    stored = True

    def prepare(self, state: DataFrame) -> None: ...

    def gather(self, state: DataFrame) -> DataFrame:
        raise NotImplementedError

    def after(self, state: DataFrame) -> None: ...

    def close(self) -> None:
        for path in self.tables:
            drop_bucketed(self.sg.edges.sparkSession, path)

    def lay(self, df: DataFrame, key: str, buckets: int | None = None, sort: tuple[str, ...] = ()) -> DataFrame:
        """df in buckets of key, until the model is closed."""
        self.tables.append(scratch_path(df.sparkSession, f"{self.name}-{key}"))
        return bucketed(df, self.tables[-1], key, buckets or self.sg.buckets, sort)

    @property
    def edges(self) -> DataFrame:
        return self.sg.edges.select(*_EDGE)

    def message(self) -> F:
        return self.program.gather(F.col("_v"), F.col("weight"), F.col("_d"))

    def sources(self, state: DataFrame) -> DataFrame:
        return state.select(F.col("id").alias("src"), F.col("value").alias("_v"), F.col("out_deg").alias("_d"))

    def senders(self, state: DataFrame) -> DataFrame:
        """Vertices whose messages can matter: a sum needs all, a least or greatest only those that changed."""
        return self.sources(state.where("active") if self.program.combine in ("min", "max") and self.program.idempotent else state)

    def combine(self, edges: DataFrame, *by: str) -> DataFrame:
        return edges.groupBy(*by, F.col("dst").alias("id")).agg(self.program.aggregate(F.col("_m")).alias("msg")).drop(*by)


class SlidingWindows(Model):
    """Shards by destination, sorted by source, whose edges carry their source's value. A round loads each shard's in-edges,
    updates its vertices and puts the shard back; then the windows of out-edges in all shards are loaded, take the new values and are put back."""

    name = "psw"

    def prepare(self, state):
        local = routed_values(self.sg, state)
        self.made["edges"] = self.lay(self.sg.edges.join(local.hint("shuffle_hash"), ["shard_id", "src"]), "shard_id", sort=("shard_id", "src"))

    def gather(self, state):
        return self.combine(self.meter.reads(self.made["edges"], C + D).withColumn("_m", self.message()), "shard_id")

    def after(self, state):
        shards = self.lay(self.meter.writes(self.made["edges"], C + D), "shard_id", sort=("shard_id", "src"))
        local = routed_values(self.sg, state)
        windows = self.meter.reads(shards, C + D).drop("_v", "_d").join(local.hint("shuffle_hash"), ["shard_id", "src"])
        self.made["edges"] = self.lay(self.meter.writes(windows, C + D), "shard_id", sort=("shard_id", "src"))
        for path in self.tables[:-1]:
            drop_bucketed(self.sg.edges.sparkSession, path)
        del self.tables[:-1]


class StreamedEdges(Model):
    """Partitions by source stream their edges and write one update an edge; a second phase reads the updates and applies them."""

    name = "esg"

    def spread(self):
        return (F.col("src") * self.sg.shards / F.lit(max(1, self.sg.n))).cast("int")

    def prepare(self, state):
        self.made["edges"] = self.lay(self.edges.withColumn("src_part", self.spread()), "src_part")

    def gather(self, state):
        own = self.meter.reads(self.sources(state), C).withColumn("src_part", self.spread()).repartition(self.sg.buckets, "src_part")
        met = self.meter.reads(self.made["edges"], D).join(own.hint("shuffle_hash"), ["src_part", "src"])
        updates = saved(self.meter.writes(met.select("dst", self.message().alias("_m")), C), f"{self.name}-updates")
        return self.combine(self.meter.reads(updates, C))

    stored = False  # sources are what it reads of the vertices; what it writes is counted by the loop


class ClusterStreamedEdges(StreamedEdges):
    """The same with partitions spread over workers by hash."""

    name = "esg_cluster"

    def spread(self):
        return F.pmod(F.xxhash64("src"), F.lit(self.opts.workers)).cast("int")


class StreamedVertices(Model):
    """Shards of equally many destinations: each loads the vertices that occur in it, streams its edges against them and writes its own vertices."""

    name = "vsp"

    def prepare(self, state):
        part = (F.col("dst") * self.sg.shards / F.lit(max(1, self.sg.n))).cast("int")
        self.made["edges"] = self.lay(self.edges.withColumn("part", part), "part")
        self.made["mirror"] = self.lay(self.made["edges"].select("part", "src").distinct(), "src")

    def gather(self, state):
        local = self.meter.reads(self.made["mirror"].join(self.sources(state), "src"), C).repartition(self.sg.buckets, "part")
        met = self.meter.reads(self.made["edges"], D).join(local.hint("shuffle_hash"), ["part", "src"])
        return self.combine(met.withColumn("_m", self.message()), "part")


class Grid(Model):
    """Edges in a grid of source and destination chunks. Each column loads every source chunk, and each block's sums are written as a
    part of its destination chunk, which the next block reads."""

    name = "dsw"
    stored = False

    def prepare(self, state):
        self.side = max(1, round(math.sqrt(self.sg.shards)))
        at = lambda c: (F.col(c) * self.side / F.lit(max(1, self.sg.n))).cast("int")
        self.made["edges"] = self.lay(self.edges.select(*_EDGE, at("src").alias("bi"), at("dst").alias("bj")), "bj", self.side)

    def gather(self, state):
        columns = F.explode(F.sequence(F.lit(0), F.lit(self.side - 1))).alias("bj")
        chunks = self.meter.reads(self.sources(state).select("*", columns), C).repartition(self.side, "bj")
        met = self.meter.reads(self.made["edges"], D).join(chunks.hint("shuffle_hash"), ["bj", "src"]).withColumn("_m", self.message())
        if self.program.combine == "mode":
            return self.combine(met, "bj")
        blocks = met.groupBy("bj", "bi", "dst").agg(self.program.aggregate(F.col("_m")).alias("_m"))
        return self.combine(self.meter.reads(saved(self.meter.writes(blocks, C), "dsw-blocks"), C))


class SparseMatrix(Model):
    """All edges sorted by destination and source and held in memory; a round is a product of the matrix and the value vector over the program's semiring."""

    name = "spmv_mem"
    stored = False

    def prepare(self, state):
        matrix = self.edges.repartitionByRange(self.sg.buckets, "dst", "src").sortWithinPartitions("dst", "src")
        self.made["edges"] = matrix.persist(StorageLevel.MEMORY_AND_DISK)
        self.made["edges"].count()

    def gather(self, state):
        return self.combine(self.made["edges"].join(self.sources(state), "src").withColumn("_m", self.message()))

    def close(self):
        self.made["edges"].unpersist()


class MessagePassing(Model):
    """Vertices live with their out-edges; changed ones send messages, which combine before and after the shuffle."""

    name = "bsp_push"
    stored = False

    def prepare(self, state):
        self.made["edges"] = self.edges.repartition(self.sg.buckets, "src").persist(StorageLevel.MEMORY_AND_DISK)

    def gather(self, state):
        return self.combine(self.made["edges"].join(self.senders(state), "src").withColumn("_m", self.message()))

    def close(self):
        if "edges" in self.made:
            self.made["edges"].unpersist()


class StoredMessagePassing(MessagePassing):
    """The same from files: edges are read again and messages written and read each round."""

    name = "bsp_ooc"

    def prepare(self, state):
        self.made["files"] = self.lay(self.edges, "src")

    def gather(self, state):
        met = self.meter.reads(self.made["files"], D).join(self.senders(state), "src")
        msgs = saved(self.meter.writes(met.select("dst", self.message().alias("_m")), C + D), "bsp-messages")
        return self.combine(self.meter.reads(msgs, C + D))

    def close(self):
        Model.close(self)


class VertexCut(Model):
    """Edges are spread over workers; each worker is sent copies of the sources it holds, gathers in part where the edges are, and parts meet at the vertex."""

    name = "gas_cut"
    stored = False

    def parts(self) -> DataFrame:
        return self.edges.withColumn("part", F.pmod(F.xxhash64("src", "dst"), F.lit(self.opts.workers)).cast("int"))

    def prepare(self, state):
        self.made["edges"] = self.lay(self.parts(), "part", self.opts.workers)
        self.made["at"] = self.lay(self.made["edges"].select("part", "src").distinct(), "src")
        both = self.made["edges"].select("part", F.explode(F.array("src", "dst")).alias("id")).distinct()
        self.made["copies"] = both.count()

    @property
    def replication(self) -> float:
        """Copies of a vertex, on average."""
        return self.made["copies"] / max(1, self.sg.n)

    def gather(self, state):
        copies = self.made["at"].join(self.sources(state), "src").repartition(self.opts.workers, "part")
        met = self.made["edges"].join(copies.hint("shuffle_hash"), ["part", "src"]).withColumn("_m", self.message())
        if self.program.combine == "mode":
            return self.combine(met)
        return self.combine(met.groupBy("part", "dst").agg(self.program.aggregate(F.col("_m")).alias("_m")))


class HybridCut(VertexCut):
    """Edges of destinations with few in-edges stay together; those of hubs, with more than hub_degree, are spread by source.

    Without a number, hubs are the hundredth part of the vertices that has most in-edges.
    """

    name = "gas_hybrid"
    hub_degree: int | None = None

    def limit(self) -> float:
        if self.hub_degree is not None:
            return self.hub_degree
        return self.sg.vinfo.agg(F.percentile("in_deg", 0.99).alias("q")).first()["q"] or 0

    def parts(self):
        hubs = self.sg.vinfo.where(F.col("in_deg") > self.limit()).select(F.col("id").alias("dst"), F.lit(True).alias("hub"))
        self.made["hubs"] = hubs.count()
        key = F.when(F.col("hub"), F.xxhash64("src")).otherwise(F.xxhash64("dst"))
        return self.edges.join(hubs, "dst", "left").withColumn("part", F.pmod(key, F.lit(self.opts.workers)).cast("int")).drop("hub")


MODELS: dict[str, type[Model]] = {m.name: m for m in (SlidingWindows, StreamedEdges, StreamedVertices, Grid, SparseMatrix, MessagePassing, VertexCut, HybridCut, StoredMessagePassing, ClusterStreamedEdges)}


def run_model(name: str, sg: ShardedGraph, program: VertexProgram, opts: EngineOptions = EngineOptions()) -> Result:
    """Values and ledger of a program under a model; 'pull_window' is the engine itself."""
    if name == "pull_window":
        return run_pull(sg, program, opts)
    model = MODELS[name](sg, program, opts)
    spark = sg.edges.sparkSession
    gens = Generations(spark, f"state-{name}")
    t0 = time.perf_counter()
    state, active = gens.keep(start(sg.vinfo, program, sg.n))
    model.prepare(state)
    model.meter.take()
    ledger = [{"run": opts.run, "model": name, "app": program.name, "iter": 0, "phase": "load", "active": active, "shards_total": sg.shards, "shards_read": sg.shards, "cache_hits": 0, "read_rows": sg.m, "read_bytes": D * sg.m, "write_rows": 0, "write_bytes": 0, "seconds": time.perf_counter() - t0}]
    rounds = 0
    files = not isinstance(model, SparseMatrix | MessagePassing | VertexCut)
    try:
        while active and rounds < opts.max_iter:
            t0 = time.perf_counter()
            old = model.meter.reads(state, C) if model.stored else state
            new = advance(old, model.gather(state), program, sg.n, None)
            state, new_active = gens.keep(model.meter.writes(new, C) if files else new)
            model.after(state)
            rounds += 1
            rr, rb, wr, wb = model.meter.take()
            ledger.append({"run": opts.run, "model": name, "app": program.name, "iter": rounds, "phase": "run", "active": active, "shards_total": sg.shards, "shards_read": sg.shards, "cache_hits": 0, "read_rows": rr, "read_bytes": rb, "write_rows": wr, "write_bytes": wb, "seconds": time.perf_counter() - t0})
            active = new_active
    finally:
        model.close()
    return Result(state.select("id", "value"), ledger, rounds, not active)


def sorted_blocks(edges: DataFrame, parts: int) -> DataFrame:
    """The matrix in so many ranges of destinations, sorted by destination and source: one row a range, offsets from its first to
    its last destination."""

    def block(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(batches, pa.schema([(c, pa.int64()) for c in _EDGE]))
        if not t.num_rows:
            return
        dst = t.column("dst").to_numpy()
        lo, hi = int(dst[0]), int(dst[-1])
        row = np.concatenate([[0], np.cumsum(np.bincount(dst - lo, minlength=hi - lo + 1))])
        lists = (pa.array([x], pa.list_(pa.int64())) for x in (row, t.column("src").to_numpy(), t.column("weight").to_numpy()))
        yield pa.RecordBatch.from_arrays([pa.array([lo]), pa.array([lo]), pa.array([hi]), *lists], names=["shard_id", "lo", "hi", "row", "col", "val"])

    matrix = edges.select(*_EDGE).repartitionByRange(parts, "dst").sortWithinPartitions("dst", "src")
    return matrix.mapInArrow(block, "shard_id long, lo long, hi long, row array<long>, col array<long>, val array<long>")


def run_matrix(sg: ShardedGraph, program: VertexProgram, opts: EngineOptions = EngineOptions()) -> Result:
    """The model spmv_mem with vertex arrays in memory too: the load sorts all edges into blocks that are held, and rounds multiply
    them by the value vector. Destinations between blocks, which have no in-edges, are rows without entries.

    For what the kernel holds, and programs with a numpy form; larger graphs take run_model.
    """
    spark, t0 = sg.edges.sparkSession, time.perf_counter()
    blocks = sorted_blocks(sg.edges, sg.buckets).persist(StorageLevel.MEMORY_AND_DISK)
    try:
        ends = sorted(tuple(r) for r in blocks.select("lo", "hi", F.size("col")).collect())  # one a block
        gaps, at = [], 0
        for lo, hi, _ in [*ends, (sg.n, sg.n, 0)]:
            if at < lo:
                gaps.append((at, lo - 1, 0))
            at = hi + 1
        none = F.lit(None).cast("array<long>")
        rest = spark.createDataFrame(gaps, "lo long, hi long, e int").select(F.col("lo").alias("shard_id"), "lo", "hi", F.array_repeat(F.lit(0).cast("long"), (F.col("hi") - F.col("lo") + 2).cast("int")).alias("row"), none.alias("col"), none.alias("val"))
        bounds = [(k, *b) for k, b in enumerate(sorted([*ends, *gaps]))]
        load = time.perf_counter() - t0
        r = run_kernel(replace(sg, csr=blocks.unionByName(rest), bounds=bounds), program, replace(opts, schedule="all", cache=None))
    finally:
        blocks.unpersist()
    own = {"model": "spmv_mem", "shards_total": sg.shards, "shards_read": sg.shards, "cache_hits": 0, "read_rows": 0, "read_bytes": 0}
    first = {**own, "run": opts.run, "app": program.name, "iter": 0, "phase": "load", "active": r.ledger[0]["active"] if r.ledger else 0, "read_rows": sg.m, "read_bytes": D * sg.m, "write_rows": 0, "write_bytes": 0, "seconds": load}
    return replace(r, ledger=[first, *({**x, **own, "phase": "run"} for x in r.ledger)])


def spmv(g: Graph, x: DataFrame, semiring: str, rounds: int = 1) -> DataFrame:
    """(id, value): the transposed adjacency matrix applied `rounds` times over 'plus_times', 'min_plus' or 'min_first'."""
    mul = {"plus_times": lambda v, w: v * w, "min_plus": lambda v, w: v + w, "min_first": lambda v, w: v}[semiring]
    add = F.sum if semiring == "plus_times" else F.min
    for _ in range(rounds):
        x = saved(g.weighed().join(x.select(F.col("id").alias("src"), "value"), "src").groupBy(F.col("dst").alias("id")).agg(add(mul(F.col("value"), F.col("weight"))).alias("value")), "spmv")
    return x
