"""Graphs, programs, options and results as plain declarations; the work is in DataFrames."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import cached_property

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Graph:
    """A static graph: edges(src, dst[, weight]) over vertices(id), ids dense from 0. Without a weight column each edge weighs 1."""

    edges: DataFrame
    vertices: DataFrame
    name: str = "graph"
    directed: bool = True

    @property
    def weighted(self) -> bool:
        return "weight" in self.edges.columns

    def weighed(self) -> DataFrame:
        """Edges with a weight column."""
        return self.edges if self.weighted else self.edges.withColumn("weight", F.lit(1).cast("long"))

    def unweighted(self) -> Graph:
        return replace(self, edges=self.edges.select("src", "dst"))

    def register(self, prefix: str | None = None) -> None:
        """Temp views <name>_edges and <name>_vertices for SQL users."""
        p = prefix or self.name
        self.edges.createOrReplaceTempView(f"{p}_edges")
        self.vertices.createOrReplaceTempView(f"{p}_vertices")


@dataclass(frozen=True)
class VertexProgram:
    """A pull program in Catalyst expressions.

    init(n) gives (value, active) columns from id, in_deg, out_deg; gather(value, weight, out_deg)
    the message along an in-edge; combine is an aggregate of messages; apply(old, combined, n) the
    new value; changed(old, new) whether the vertex is active next. Nulls are "no value".
    kernel names the numpy form of gather, combine and apply, if there is one.
    """

    name: str
    init: Callable[[int], tuple[Column, Column]]
    gather: Callable[[Column, Column, Column], Column]
    combine: str
    apply: Callable[[Column, Column, int], Column]
    changed: Callable[[Column, Column], Column]
    kernel: Callable | None = None
    #: The numpy forms of gather and of apply apart, for programs that combine by sum or min.
    pieces: tuple[Callable, Callable] | None = None
    #: What each vertex passes on by (values, degrees), if that is the same along all its out-edges: the kernel may be given it as well.
    outgoing: Callable | None = None
    #: Whether unchanged inputs leave a vertex as it is, so that shards may be skipped without loss.
    idempotent: bool = True
    #: The column of the vertex information that gather is given as out_deg: out_deg, or out_weight for the sum of out-edges' values.
    degree: str = "out_deg"
    #: Whether a value is the id of a vertex whose own value holds for this one too, so that values may jump to it.
    jumps: bool = False

    def aggregate(self, message: Column) -> Column:
        return {"sum": F.sum, "min": F.min, "max": F.max, "mode": lambda c: F.mode(c, deterministic=True)}[self.combine](message)


@dataclass(frozen=True)
class ArrowProgram:
    """A program over whole CSR shards: update(row, col, val, old, out_deg, lo) gives the new values of the shard's own vertices."""

    name: str
    init: Callable
    update: Callable
    changed: Callable


@dataclass(frozen=True)
class EngineOptions:
    """max_iter rounds at most; schedule one of all, selective, exact, vertex; threshold the activation ratio below which
    selective scheduling asks the filters; cache a mode 0..4, 'auto' or None; value_mode broadcast, routed or auto; at_once the tasks that kernel rounds are dealt to, at most; shortcut lets values that are ids
    jump to their vertex' value after a round, which leads to the same end in fewer rounds."""

    max_iter: int = 10
    schedule: str = "all"
    threshold: float = 0.001
    cache: int | str | None = None
    cache_bytes: int = 1 << 30
    value_mode: str = "auto"
    broadcast_rows: int = 4_000_000
    workers: int = 4
    at_once: int | None = None
    run: str = "run"
    shortcut: bool = False


@dataclass
class Result:
    """values(id, value), or what makes them once they are asked for; ledger rows as dicts; rounds run; whether nothing was active at the end."""

    found: DataFrame | Callable[[], DataFrame]
    ledger: list[dict] = field(default_factory=list)
    rounds: int = 0
    converged: bool = False

    @cached_property
    def values(self) -> DataFrame:
        return self.found if isinstance(self.found, DataFrame) else self.found()

    def ledger_frame(self) -> DataFrame:
        from shardgraph.model.schema import LEDGER

        names = [x.split()[0] for x in LEDGER.split(", ")]
        return self.values.sparkSession.createDataFrame([tuple(r.get(n) for n in names) for r in self.ledger], LEDGER)


@dataclass(frozen=True)
class ShardedGraph:
    """A prepared graph: shards of in-edges by destination interval, with what each application needs.

    edges(shard_id, src, dst, weight) in buckets of shard_id; intervals(shard_id, lo, hi, edges);
    vinfo(id, shard_id, in_deg, out_deg, out_weight); mirror(shard_id, src) in buckets of src; filters(shard_id, m, k, places,
    words); csr, one row a shard.
    bounds is the intervals on the driver: one row a shard. laid is how many edges there were when they were laid out.
    """

    graph: Graph
    n: int
    m: int
    bounds: list[tuple[int, int, int, int]]
    edges: DataFrame
    vinfo: DataFrame
    mirror: DataFrame | None
    filters: DataFrame | None
    csr: DataFrame | None
    path: str
    edges_at: str
    laid: int

    @property
    def shards(self) -> int:
        return len(self.bounds)

    @property
    def buckets(self) -> int:
        return buckets_of(self.shards, self.laid)

    def shard_of(self, c: Column) -> Column:
        return interval_of(c, [b[1] for b in self.bounds])


#: Edges that one bucket of a graph's tables holds at least, and buckets at least and at most.
BUCKET_EDGES, FEWEST, MOST = 1 << 20, 8, 4096


def buckets_of(shards: int, edges: int) -> int:
    """Buckets of the tables of a graph: no more than shards, enough for a cluster's cores, not so many that small graphs pay for tasks."""
    return max(1, min(shards, MOST, max(FEWEST, edges // BUCKET_EDGES)))


def interval_of(c: Column, starts: list[int]) -> Column:
    """The interval that holds id c; null for a null or negative id.

    By a balanced tree of comparisons in generated code up to 256 intervals; above, by halving steps
    over one literal array: as many steps as the number of intervals has bits.
    """
    held = c >= 0
    if len(starts) > 256:
        all_ = F.split(F.lit(",".join(map(str, starts))), ",").cast("array<bigint>")
        steps = F.array(*(F.lit(1 << k) for k in reversed(range(len(starts).bit_length()))))
        return F.when(held, F.aggregate(steps, F.lit(0), lambda at, h: F.when(F.coalesce(F.get(all_, at + h) <= c, F.lit(False)), at + h).otherwise(at)))

    def half(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi + 1) // 2
        return F.when(c < starts[mid], half(lo, mid - 1)).otherwise(half(mid, hi))

    return F.when(held, half(0, len(starts) - 1)).cast("int")
