"""One query for each method, variant, baseline and measure; the graph is prepared once for each session and table folder."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardgraph import cost, programs
from shardgraph.baselines import MODELS, HybridCut, run_model, spmv
from shardgraph.build import graphs, prepare
from shardgraph.core import cache, engine, schedule
from shardgraph.functions import facade
from shardgraph.model.graph import EngineOptions, Graph, ShardedGraph
from shardgraph.session import table, together
from shardgraph.workloads import oracles as o

Query = Callable[[SparkSession, str], DataFrame]
SHARDS = 16
MAIN = ("part_next", "word_next", "event_chain")
#: Bytes that a supplier's raw edges, 4,800 as a rule, are tried to be cached in.
ROOMS = (5000.0, 3000.0, 1500.0, 1000.0)
_READY: dict[tuple, ShardedGraph] = {}


def graph(spark: SparkSession, sf: str, name: str) -> Graph:
    return graphs.BUILDERS[name](spark, sf)


def sharded(spark: SparkSession, sf: str, name: str, symmetric: bool = False, parts: tuple[str, ...] = prepare.PARTS) -> ShardedGraph:
    """Prepared once, used by every program: later queries read the same shards, and add the parts that they need beside. Edges
    that lie in shards already are not made again for both directions."""
    key = (spark.sparkContext.applicationId, sf, name, symmetric)
    if key not in _READY:
        plain = _READY.get((*key[:3], False))
        g = Graph(plain.edges.drop("shard_id"), plain.vinfo.select("id"), name) if plain else graph(spark, sf, name)
        _READY[key] = prepare.prepare(graphs.symmetrize(g) if symmetric else g, shards=SHARDS, parts=parts)
    _READY[key] = prepare.with_parts(_READY[key], parts)
    return _READY[key]


def ready(spark: SparkSession, sf: str, names: tuple[str, ...], symmetric: tuple[bool, ...] = (False, True)) -> None:
    """These graphs prepared at the same time, in one or both directions: a graph's many short jobs leave most cores free."""
    together(spark, *(lambda g=g: [sharded(spark, sf, g, both) for both in symmetric] for g in names))


def shards_only(spark: SparkSession, sf: str, name: str) -> DataFrame:
    """The CSR shards of a graph: of the prepared one, or of one that has no mirrors and filters."""
    key = (spark.sparkContext.applicationId, sf, name)
    if (*key, False) in _READY:
        return _READY[*key, False].csr
    if (*key, "csr") not in _READY:
        _READY[*key, "csr"] = prepare.prepare(graph(spark, sf, name), shards=SHARDS, parts=("csr",))
    return _READY[*key, "csr"].csr


def _csr(spark: SparkSession, sf: str, name: str, symmetric: bool = False) -> tuple[ShardedGraph, DataFrame]:
    sg = sharded(spark, sf, name, symmetric)
    return sg, sg.csr


def _rounded(df: DataFrame) -> DataFrame:
    return df.select("id", F.round("value", 10).alias("value"))


def _run(model: str, app: str, sg: ShardedGraph, rounds: int, **opts) -> engine.Result:
    program = {"pagerank": programs.pagerank(), "sssp": programs.sssp((0,)), "bfs": programs.bfs(0), "cc": programs.components()}[app]
    return run_model(model, sg, program, EngineOptions(max_iter=rounds, **opts))


def _fitting(sg: ShardedGraph, program, rounds: int) -> engine.Result:
    """By the kernel where its arrays fit, and by rounds over tables beyond."""
    run = engine.run if sg.n > engine.KERNEL_ROWS else engine.run_kernel
    return run(sg, program, EngineOptions(max_iter=rounds))


def _kernel(spark, sf, name, program, rounds, symmetric=False) -> DataFrame:
    return _fitting(sharded(spark, sf, name, symmetric), program, rounds).values


def _settled(spark, sf, name, program, symmetric=False) -> DataFrame:
    """Values once nothing changes any more, by rounds over tables: paths have fewer edges than there are vertices.

    Labels that are ids jump to their vertex' label after each round, so long paths take few rounds.
    """
    sg = sharded(spark, sf, name, symmetric)
    r = engine.run(sg, program, EngineOptions(max_iter=sg.n + 1, shortcut=True))
    if not r.converged:
        raise RuntimeError(f"{program.name} did not settle in {r.rounds} rounds")
    return r.values


def _cuts(spark, sf, g):
    return prepare.bounds_frame(spark, sharded(spark, sf, g).bounds)


def _counted_cuts(spark, sf, g):
    """The same with the edges of each shard counted in the tables."""
    sg = sharded(spark, sf, g)
    n = prepare.assign_shards(graph(spark, sf, g).edges.select("dst"), sg.bounds).groupBy("shard_id").agg(F.count("*").alias("n"))
    return _cuts(spark, sf, g).join(n, "shard_id", "left").select("shard_id", "lo", "hi", F.coalesce("n", F.lit(0)).alias("edges"))


def _csr_rows(spark, sf, g):
    """(id, offset): where each vertex' in-edges begin in its shard."""
    _, csr = _csr(spark, sf, g)
    return csr.select("lo", F.posexplode(F.slice("row", 1, F.size("row") - 1)).alias("p", "offset")).select((F.col("lo") + F.col("p")).alias("id"), "offset")


def _lookup(spark, sf):
    sg, csr = _csr(spark, sf, "part_next")
    return prepare.in_neighbors(csr, 7, sg.bounds)


def _exact(spark, sf):
    """Shards with an active source when vertices below 5 are active."""
    sg = sharded(spark, sf, "event_chain")
    return schedule.active_shards_exact(sg.mirror, sg.vinfo.where("id < 5"))


def _bloom(spark, sf, g):
    """For each shard alone, its least source being active: shards that must be read, those that filters miss, and whether
    they add a twentieth of all at most."""
    sg = sharded(spark, sf, g)
    tried = sg.mirror.groupBy("shard_id").agg(F.min("src").alias("id"))
    rows = []
    for r in tried.orderBy("shard_id").collect():  # one a shard
        active = spark.createDataFrame([(r["id"],)], "id long")
        exact, found = ({x["shard_id"] for x in f(t, active).collect()} for f, t in ((schedule.active_shards_exact, sg.mirror), (schedule.active_shards_bloom, sg.filters)))
        rows.append((r["shard_id"], len(exact), len(exact - found), len(found - exact) <= max(1, sg.shards // 20)))
    return spark.createDataFrame(rows, "shard_id int, needed long, missed long, few_more boolean")


def _visits(spark, sf, g, how):
    """Shards that each round of unit-weight distances reads when scheduling is always on; with filters, whether it read
    what it must and a twentieth of all more at most."""
    sg = sharded(spark, sf, g)
    rows = {k: [(x["iter"], x["shards_read"]) for x in engine.run_kernel(sg, programs.bfs(0), EngineOptions(max_iter=1000, schedule=k, threshold=1.0)).ledger] for k in {"exact", how}}
    if how == "exact":
        return spark.createDataFrame(rows["exact"], "iter int, shards_read long")
    more = sum(b - a for (_, a), (_, b) in zip(rows["exact"], rows[how], strict=True))
    enough = all(a <= b for (_, a), (_, b) in zip(rows["exact"], rows[how], strict=True))
    needed = sum(a for _, a in rows["exact"])
    return spark.createDataFrame([(needed, enough, more <= max(2, len(rows[how]) * sg.shards // 20))], "needed long, enough boolean, few_more boolean")


def _mirrors(spark, sf, g):
    return sharded(spark, sf, g).mirror.groupBy("shard_id").agg(F.count("*").alias("sources"))


def _choices(spark, sf):
    """The mode that a cache of each capacity takes for the raw edges out of each supplier."""
    sizes = table(spark, sf, "lineitem").groupBy(F.col("l_suppkey").alias("id")).agg((F.count("*") * 8).cast("double").alias("size"))
    rooms = F.explode(F.array(*map(F.lit, ROOMS))).alias("capacity")
    return sizes.select("id", "size", rooms).withColumn("mode", cache.mode_of(F.col("size"), F.col("capacity")))


def _admission(spark, sf):
    sizes = _counted_cuts(spark, sf, "part_next").select("shard_id", (F.col("edges") * 8).alias("bytes"))
    return cache.admission(sizes, sharded(spark, sf, "part_next").m * 8 // 2)


def _hits(spark, sf):
    """Cached shards and edges read from files in each of three rounds, with room for two fifths of the raw shards."""
    sg = sharded(spark, sf, "part_next")
    raw = 8 * (sg.n + sg.shards + 2 * sg.m + 3 * sg.shards)
    r = _run("pull_window", "pagerank", sg, 3, cache=1, cache_bytes=raw * 2 // 5)
    return spark.createDataFrame([(x["iter"], x["cache_hits"], x["read_rows"]) for x in r.ledger], "iter int, hits long, read_rows long")


def _analytic(spark, sf, g):
    sg = sharded(spark, sf, g)
    return cost.analytic_frame(spark, 8, 8, sg.n, sg.m, SHARDS, 4, 1.0)


def _ledger(spark, sf, model, g):
    """Bytes of the records that one round under a model read and wrote, as counted, scheduling and cache off."""
    sg = sharded(spark, sf, g)
    return _run(model, "pagerank", sg, 1).ledger_frame().where("iter = 1").select("model", "read_bytes", "write_bytes")


def _activity(spark, sf, g, app="bfs"):
    """Vertices that the round before left changed, for each round."""
    program = {"bfs": programs.bfs(0), "cc": programs.components(), "pagerank": programs.pagerank()}[app]
    r = _fitting(sharded(spark, sf, g, app == "cc"), program, 200 if app == "pagerank" else 100_000)
    rows = [(x["iter"], x["active"]) for x in r.ledger]
    return spark.createDataFrame(rows, "iter int, active long")


def _topk(spark, sf, k=10):
    """Greatest ranks after ten rounds; ids break ties."""
    return _rounded(_run("pull_window", "pagerank", sharded(spark, sf, "part_next"), 10).values).orderBy(F.desc("value"), "id").limit(k)


def _parents(spark, sf):
    sg = sharded(spark, sf, "part_next")
    return engine.sssp_parents(sg, _settled(spark, sf, "part_next", programs.sssp((0,))))


def _cc_sizes(spark, sf, g):
    return _settled(spark, sf, g, programs.components(), True).groupBy(F.col("value").alias("component")).agg(F.count("*").alias("size"))


def _agree(spark, sf, model, app, g="part_next"):
    sym = app == "cc"
    out = _run(model, app, sharded(spark, sf, g, sym), 10 if app == "pagerank" else 200).values
    return _rounded(out) if app == "pagerank" else out.select("id", "value")


def _schedule_same(spark, sf, how):
    """Distances with shards skipped equal distances with every shard read: differing vertices, by schedule."""
    sg = sharded(spark, sf, "part_next")
    a = _run("pull_window", "sssp", sg, 200).values
    b = _run("pull_window", "sssp", sg, 200, schedule=how, threshold=1.0).values
    return engine.compare(a, b).select("vertices", "differ")


def _cached(spark, sf, mode):
    sg = sharded(spark, sf, "part_next")
    return _rounded(_run("pull_window", "pagerank", sg, 10, cache=mode, cache_bytes=sg.m * 8 // 5).values)


def _facade(spark, sf, g, statement):
    """An application as one SQL statement over the views of a prepared graph."""
    facade.register(sharded(spark, sf, g), f"sg_{g}")
    out = facade.run_sql(spark, statement)
    return _rounded(out) if "double" in dict(out.dtypes)["value"] else out


def _facade_state(spark, sf):
    facade.register_result(sharded(spark, sf, "part_next", True), programs.components(), "sg_components", EngineOptions(max_iter=200))
    return spark.sql("select value as component, count(*) as size from sg_components group by value")


def _hubs(spark, sf, g):
    """Vertices whose in-edges the hybrid cut spreads, and those edges."""
    sg = sharded(spark, sf, g)
    limit = HybridCut(sg, programs.pagerank(), EngineOptions()).limit()
    return sg.vinfo.where(F.col("in_deg") > limit).agg(F.count("*").alias("hubs"), F.sum("in_deg").alias("hub_edges"))


def _redistributed(spark, sf):
    return _rounded(engine.pagerank(sharded(spark, sf, "event_chain"), EngineOptions(max_iter=10), dangling="redistribute").values)


def _spmv(spark, sf, ring):
    g = graph(spark, sf, "part_next")
    return spmv(g, g.vertices.select("id", F.col("id").alias("value")), ring)


def _reach(spark, sf, program):
    return _kernel_free(spark, sf, program)


def _kernel_free(spark, sf, program, rounds=None):
    """Values after so many rounds, or once nothing changes any more: paths have fewer edges than there are vertices."""
    sg = sharded(spark, sf, "part_next")
    r = engine.run(sg, program, EngineOptions(max_iter=rounds or sg.n + 1))
    if rounds is None and not r.converged:
        raise RuntimeError(f"{program.name} did not settle in {r.rounds} rounds")
    return r.values


#: Bytes that one round under a model reads and writes, from the sizes of a graph and of a model's own layout.
COUNTED = {"pull_window": ("8 * m", "0"), "psw": ("8 * n + 32 * m", "8 * n + 32 * m"), "esg": ("8 * n + 16 * m", "8 * n + 8 * m"), "vsp": ("8 * (n + mir) + 8 * m", "8 * n"), "dsw": ("8 * 4 * n + 8 * m + 8 * blk", "8 * blk + 8 * n"), "spmv_mem": ("0", "0"), "bsp_ooc": ("8 * m + 16 * m", "16 * m"), "esg_cluster": ("8 * n + 16 * m", "8 * n + 8 * m")}


def _sizes(g: str) -> str:
    """k(m, n, p, mir, blk): edges, vertices, shards, sources by equal destination ranges, destinations by source chunks of a grid."""
    return o.intervals(g, SHARDS) + """, k0 as (select (select count(*) from e) as m, (select count(*) from v) as n, (select count(*) from iv) as p),
        k as (select m, n, p, (select count(*) from (select distinct dst * p // n, src from e)) as mir, (select count(*) from (select distinct src * 4 // n, dst from e)) as blk from k0) """


def analytic_oracle() -> str:
    """Formulas and counts of one round on the three graphs."""
    x = "(1 - exp(-m::double / n / p)) * p"
    formulas = {"psw": ("8 * n + 32 * m", "8 * n + 32 * m"), "esg": ("8 * n + 16 * m", "8 * n + 8 * m"), "vsp": (f"8 * (1 + {x}) * n + 8 * m", "8 * n"), "dsw": ("8 * sqrt(p) * n + 8 * m", "8 * sqrt(p) * n"), "pull_window": ("8 * m", "0")}
    parts = []
    for g in MAIN:
        rows = " union all ".join(f"select '{g}' as graph, '{m}' as model, round(({r})::double, 4) as read_b, round(({w})::double, 4) as write_b, ({COUNTED[m][0]})::bigint as read_bytes, ({COUNTED[m][1]})::bigint as write_bytes from k" for m, (r, w) in formulas.items())
        parts.append(f"select * from ({_sizes(g)} {rows})")
    return " union all ".join(parts)


def build() -> tuple[dict[str, Query], dict[str, str]]:
    q: dict[str, Query] = {}
    sql: dict[str, str] = {}

    def add(name: str, f: Query, oracle: str | None = None) -> None:
        q[name] = f
        if oracle:
            sql[name] = oracle

    for g in graphs.BUILDERS:
        add(f"stats_{g}", lambda s, d, g=g: prepare.graph_stats(graph(s, d, g)), o.stats(g))
        add(f"deg_hist_{g}", lambda s, d, g=g: prepare.degree_histogram(graph(s, d, g)), o.histogram(g, "in"))
    add("deg_hist_out_word_next", lambda s, d: prepare.degree_histogram(graph(s, d, "word_next"), "out"), o.histogram("word_next", "out"))
    add("deg_hist_log_word_next", lambda s, d: prepare.degree_histogram(graph(s, d, "word_next"), "in", True), o.head("word_next", o.DEGREES) + " select case when in_deg = 0 then -1 else floor(log2(in_deg))::int end as deg, count(*) as vertices from deg group by 1")
    for g in MAIN:
        iv = o.intervals(g, SHARDS)
        add(f"intervals_{g}", lambda s, d, g=g: _cuts(s, d, g), iv + " select shard_id, lo, hi, (select sum(in_deg)::bigint from deg where id between lo and hi) as edges from iv")
        add(f"shard_balance_{g}", lambda s, d, g=g: prepare.balance(_counted_cuts(s, d, g)), iv + ", k as (select (select sum(in_deg)::bigint from deg where id between lo and hi) as edges from iv) select count(*) as shards, max(edges) as most, round(avg(edges), 6) as mean, round(max(edges) / avg(edges), 6) as ratio from k")
        add(f"csr_rows_{g}", lambda s, d, g=g: _csr_rows(s, d, g), iv + " select d.id, coalesce(sum(in_deg) over (partition by shard_id order by d.id rows between unbounded preceding and 1 preceding), 0)::bigint as \"offset\" from deg d join iv on d.id between lo and hi")
        add(f"mirror_sources_{g}", lambda s, d, g=g: _mirrors(s, d, g), iv + " select shard_id, count(distinct src) as sources from e join iv on dst between lo and hi group by shard_id")
        add(f"symmetrize_{g}", lambda s, d, g=g: graphs.symmetrize(graph(s, d, g)).edges, o.head(g, o.SYMMETRIC) + " select src, dst, weight from s")
        add(f"pagerank10_{g}", lambda s, d, g=g: _rounded(_run("pull_window", "pagerank", sharded(s, d, g), 10).values), o.pagerank(g) + " select id, round(value, 10) as value from r10")
        add(f"pagerank10_kernel_{g}", lambda s, d, g=g: _rounded(_kernel(s, d, g, programs.pagerank(), 10)), o.pagerank(g) + " select id, round(value, 10) as value from r10")
        add(f"pagerank10_routed_{g}", lambda s, d, g=g: _rounded(_run("pull_window", "pagerank", sharded(s, d, g), 10, broadcast_rows=0).values), o.pagerank(g) + " select id, round(value, 10) as value from r10")
        for way, run, routed in (("", _settled, False), ("_kernel", _kernel, True)):
            more = (100_000,) if routed else ()
            add(f"sssp{way}_{g}", lambda s, d, g=g, run=run, more=more: run(s, d, g, programs.bfs(0), *more), o.sssp(g, False) + " select id, value from dist")
            add(f"sssp_weighted{way}_{g}", lambda s, d, g=g, run=run, more=more: run(s, d, g, programs.sssp((0,)), *more), o.sssp(g) + " select id, value from dist")
            add(f"cc{way}_{g}", lambda s, d, g=g, run=run, more=more: run(s, d, g, programs.components(), *more, symmetric=True), o.components(g) + " select id, label as value from c")
        add(f"shards_read_exact_{g}", lambda s, d, g=g: _visits(s, d, g, "exact"), o.visits(g, SHARDS) + " select iter, shards_read from k")
        add(f"shards_read_bloom_{g}", lambda s, d, g=g: _visits(s, d, g, "selective"), o.visits(g, SHARDS) + " select sum(shards_read)::bigint as needed, true as enough, true as few_more from k")
        add(f"shards_active_bloom_{g}", lambda s, d, g=g: _bloom(s, d, g), o.intervals(g, SHARDS) + ", h as materialized (select distinct shard_id, src from e join iv on dst between lo and hi), f as (select shard_id, min(src) as src from h group by 1) select f.shard_id, (select count(*) from h where h.src = f.src) as needed, 0::bigint as missed, true as few_more from f")
        add(f"active_ratio_cc_{g}", lambda s, d, g=g: _activity(s, d, g, "cc"), o.label_rounds(g, {"part_next": 10, "word_next": 20, "event_chain": 110}[g]))
        add(f"active_ratio_pagerank_{g}", lambda s, d, g=g: _activity(s, d, g, "pagerank"))
        add(f"active_ratio_sssp_{g}", lambda s, d, g=g: _activity(s, d, g), o.sssp(g, False) + " select (value + 1)::int as iter, count(*) as active from dist where value is not null group by 1")
        x = f"(1 - exp(-m / v / {SHARDS}.0)) * {SHARDS}.0"
        add(f"analytic_t3_{g}", lambda s, d, g=g: _analytic(s, d, g), o.head(g) + f""", k as (select (select count(*) from e)::double as m, (select count(*) from v)::double as v)
            select 'psw' as model, round(8 * v + 32 * m, 4) as read_b, round(8 * v + 32 * m, 4) as write_b, round((8 * v + 32 * m) / {SHARDS}, 4) as mem_b, round(48 * m, 4) as prep_b from k
            union all select 'esg', round(8 * v + 16 * m, 4), round(8 * v + 8 * m, 4), round(8 * v / {SHARDS}, 4), round(16 * m, 4) from k
            union all select 'vsp', round(8 * (1 + {x}) * v + 8 * m, 4), round(8 * v, 4), round(8 * (2 + {x}) * v / {SHARDS}, 4), round(32 * m, 4) from k
            union all select 'dsw', round(8 * 4.0::double * v + 8 * m, 4), round(8 * 4.0::double * v, 4), round(16 * v / 4.0::double, 4), round(48 * m, 4) from k
            union all select 'pull_window', round(8 * m, 4), 0.0::double, round(16 * v + 32 * m / {SHARDS}, 4), round(40 * m, 4) from k""")
    for g in ("doc_dup", "vec_knn", "geo_tree", "turn_chain"):
        add(f"cc_sizes_{g}", lambda s, d, g=g: _cc_sizes(s, d, g), o.components(g) + " select label as component, count(*) as size from c group by label")
    add("csr_lookup", _lookup, o.head("part_next") + " select src from e where dst = 7")
    add("pagerank_topk", _topk, o.pagerank("part_next") + " select id, round(value, 10) as value from r10 order by round(value, 10) desc, id limit 10")
    parts = [o.DEGREES, "nv as (select count(*)::double as n from v)", "r0 as materialized (select id, 1.0::double / n as value from v, nv)"]
    for k in range(1, 11):
        parts.append(f"r{k} as materialized (select v.id, 0.15::double / n + 0.85::double * (select coalesce(sum(r.value), 0) from r{k - 1} r join deg on deg.id = r.id where out_deg = 0) / n + 0.85::double * coalesce(m.s, 0) as value from v cross join nv left join (select dst, sum(value / out_deg) as s from e join r{k - 1} r on r.id = e.src join deg on deg.id = e.src group by dst) m on m.dst = v.id)")
    add("pagerank_dangling", _redistributed, o.head("event_chain", *parts) + " select id, round(value, 10) as value from r10")
    add("sssp_parents", _parents, o.sssp("part_next") + " select b.id, min(e.src) as parent from e join dist a on a.id = e.src join dist b on b.id = e.dst where a.value + e.weight = b.value group by b.id")
    add("shards_active_exact", _exact, o.intervals("event_chain", SHARDS) + " select distinct shard_id from e join iv on dst between lo and hi where src < 5")
    for how in ("selective", "exact", "vertex"):
        add(f"schedule_lossless_{how}", lambda s, d, how=how: _schedule_same(s, d, how), o.head("part_next") + " select count(*) as vertices, 0::bigint as differ from v")
    for mode in range(5):
        add(f"cache_mode{mode}_pagerank10", lambda s, d, mode=mode: _cached(s, d, mode), o.pagerank("part_next") + " select id, round(value, 10) as value from r10")
    add("cache_choice", _choices, f"select id, size, capacity, case when size <= capacity then 1 when size / 2 <= capacity then 2 when size / 4 <= capacity then 3 else 4 end as mode from (select l_suppkey as id, (8 * count(*))::double as size from lineitem group by 1) cross join (select unnest([{', '.join(map(str, ROOMS))}])::double as capacity)")
    sized = o.intervals("part_next", SHARDS) + ", k as materialized (select shard_id, (select sum(in_deg)::bigint from deg where id between lo and hi) as edges, hi - lo + 1 as own from iv), room as (select sum(edges) * 8 // 2 as half, (8 * (sum(own) + 4 * count(*) + 2 * sum(edges))) * 2 // 5 as raw from k), "
    walk = "a(shard_id, bytes, used, cached) as (select -1, 0::bigint, 0::bigint, false union all select k.shard_id, {b}, a.used + case when a.used + {b} <= {room} then {b} else 0 end, a.used + {b} <= {room} from a join k on k.shard_id = a.shard_id + 1, room)"
    add("cache_admission", _admission, sized + walk.format(b="(k.edges * 8)::bigint", room="half") + " select shard_id, bytes, cached from a where shard_id >= 0")
    add("cache_hits_raw", _hits, sized + walk.format(b="(8 * (k.own + 4 + 2 * k.edges))::bigint", room="raw") + " select unnest([1, 2, 3])::int as iter, count(*) filter (cached) as hits, sum(edges) filter (not cached)::bigint as read_rows from a join k using (shard_id)")
    add("compression", lambda s, d: cache.compression_report(_csr(s, d, "part_next")[1]))
    add("compression_delta", lambda s, d: cache.compression_report(_csr(s, d, "part_next")[1], delta=True))
    flat = {"pagerank": o.pagerank("part_next") + " select id, round(value, 10) as value from r10", "sssp": o.sssp("part_next") + " select id, value from dist", "cc": o.components("part_next") + " select id, label as value from c"}
    for model in ("pull_window", *MODELS):
        for app, want in flat.items():
            add(f"{model}_{'pagerank10' if app == 'pagerank' else app}", lambda s, d, m=model, a=app: _agree(s, d, m, a), want)
    for g in MAIN:
        for model, (r, w) in COUNTED.items():
            add(f"ledger_{model}_{g}", lambda s, d, m=model, g=g: _ledger(s, d, m, g), _sizes(g) + f"select '{model}' as model, ({r})::bigint as read_bytes, ({w})::bigint as write_bytes from k")
    for ring, (f, a) in {"plus_times": ("sum(src * weight)::bigint", ""), "min_plus": ("min(src + weight)", ""), "min_first": ("min(src)", "")}.items():
        add(f"spmv_{ring}", lambda s, d, ring=ring: _spmv(s, d, ring), o.head("part_next") + f" select dst as id, {f} as value from e group by dst")
    add("in_degree_program", lambda s, d: _kernel_free(s, d, programs.in_degree(), 1), o.head("part_next", o.DEGREES) + " select id, in_deg as value from deg")
    add("reachability", lambda s, d: _kernel_free(s, d, programs.reachability((0,))), o.sssp("part_next", False) + " select id, (value is not null)::bigint as value from dist")
    add("max_propagation", lambda s, d: engine.run(sharded(s, d, "part_next", True), programs.max_propagation(), EngineOptions(max_iter=200)).values, o.components("part_next") + ", k as (select label, max(id) as value from c group by label) select c.id, k.value from c join k using (label)")
    add("cc_unsymmetrised", lambda s, d: _kernel(s, d, "event_chain", programs.components(), 10000), o.head("event_chain") + ", c(id, label) using key (id) as (select id, id from v union (select e.dst, min(c.label) from c join e on e.src = c.id join recurring.c r on r.id = e.dst where c.label < r.label group by e.dst)) select id, label as value from c")
    add("pagerank_decimal", lambda s, d: engine.run(sharded(s, d, "part_next"), programs.pagerank(decimal=True), EngineOptions(max_iter=10)).values.select("id", F.round("value", 10).alias("value")), o.pagerank("part_next") + " select id, round(value, 10) as value from r10")
    votes = ["l0 as materialized (select id, id as label from v)"]
    for k in range(1, 4):
        votes.append(f"l{k} as materialized (select v.id, coalesce(m.label, p.label) as label from v join l{k - 1} p on p.id = v.id left join (select dst, label, row_number() over (partition by dst order by count(*) desc, label) as best from e join l{k - 1} p on p.id = e.src group by dst, label) m on m.dst = v.id and m.best = 1)")
    add("label_propagation", lambda s, d: _kernel_free(s, d, programs.label_propagation(), 3), o.head("part_next", *votes) + " select id, label as value from l3")
    add("widest_path", lambda s, d: _kernel_free(s, d, programs.widest_path(0)), o.head("part_next") + """, w(id, width) using key (id) as (select 0::bigint, (2::hugeint ** 62)::bigint union
        (select e.dst, max(least(w.width, e.weight))::bigint from w join e on e.src = w.id left join recurring.w r on r.id = e.dst where r.width is null or least(w.width, e.weight) > r.width group by e.dst)) select v.id, w.width as value from v left join w on w.id = v.id""")
    add("multi_source_sssp", lambda s, d: _settled(s, d, "part_next", programs.sssp((0, 1, 2))), o.sssp("part_next", source="unnest([0, 1, 2])") + " select id, value from dist")
    add("multi_source_sssp_kernel", lambda s, d: _kernel(s, d, "part_next", programs.sssp((0, 1, 2)), 1000), o.sssp("part_next", source="unnest([0, 1, 2])") + " select id, value from dist")
    for g in ("part_next", "word_next"):
        add(f"pagerank_weighted_{g}", lambda s, d, g=g: _rounded(engine.run(sharded(s, d, g), programs.pagerank(weighted=True), EngineOptions(max_iter=10)).values), o.pagerank(g, weighted=True) + " select id, round(value, 10) as value from r10")
    add("pagerank_personalised", lambda s, d: _rounded(engine.run(sharded(s, d, "part_next"), programs.pagerank(seeds={0, 7, 11}), EngineOptions(max_iter=10)).values), o.pagerank("part_next", seeds=(0, 7, 11)) + " select id, round(value, 10) as value from r10")
    add("influence", lambda s, d: _rounded(engine.run(sharded(s, d, "event_chain"), programs.influence(), EngineOptions(max_iter=10)).values), o.influence("event_chain", 10) + " select id, round(value, 10) as value from r10")
    add("hits", lambda s, d: engine.hits(sharded(s, d, "part_next"), 5).select("id", F.round("hub", 9).alias("hub"), F.round("authority", 9).alias("authority")), o.hits("part_next", 5) + " select id, round(hub, 9) as hub, round(authority, 9) as authority from h5")
    add("facade_pagerank", lambda s, d: _facade(s, d, "part_next", facade.pagerank_sql("sg_part_next", 3)), o.pagerank("part_next", 3) + " select id, round(value, 10) as value from r3")
    add("facade_sssp", lambda s, d: _facade(s, d, "event_chain", facade.sssp_sql("sg_event_chain", 0)), o.sssp("event_chain") + " select id, value from dist")
    add("facade_reached", lambda s, d: _facade(s, d, "geo_tree", facade.reached_sql("sg_geo_tree")), o.head("geo_tree", "p(root, id) as (select id, id from v union all select p.root, e.dst from p join e on e.src = p.id)") + " select id, min(root) as value from p group by id")
    add("facade_state", lambda s, d: _facade_state(s, d), o.components("part_next") + " select label as component, count(*) as size from c group by label")
    for g in MAIN:
        add(f"hybrid_hubs_{g}", lambda s, d, g=g: _hubs(s, d, g), o.head(g, o.DEGREES) + ", q as (select quantile_cont(in_deg, 0.99) as q from deg) select count(*) as hubs, sum(in_deg)::bigint as hub_edges from deg, q where in_deg > q")
    return q, sql
