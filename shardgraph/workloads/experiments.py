"""The experiments as result tables: each returns one row a run or round, with logical bytes beside seconds.

Rounds and graphs are parameters; the defaults finish in minutes on one machine. At the published
scale they are called with prepared graphs of that size.
"""

from __future__ import annotations

import functools
import os
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardgraph import cost, programs, sources
from shardgraph.baselines import MODELS, alone, run_matrix, run_model
from shardgraph.baselines.alone import run_alone
from shardgraph.build import graphs, prepare
from shardgraph.core import cache, engine
from shardgraph.model.graph import EngineOptions, Graph, ShardedGraph
from shardgraph.model.schema import EDGE_BYTES, VERTEX_BYTES
from shardgraph.session import exists, saved, scratch_path
from shardgraph.workloads import oracles
from shardgraph.workloads.queries import MAIN, SHARDS, graph, ready, sharded, shards_only

APPS = ("pagerank", "sssp", "cc")
FOUR = ("part_next", "user_next", "supp_part", "word_next")


def program(app: str):
    return {"pagerank": programs.pagerank(), "sssp": programs.sssp((0,)), "cc": programs.components()}[app]


def _graph(spark: SparkSession, sf: str, g: str, app: str) -> ShardedGraph:
    return sharded(spark, sf, g, app == "cc")


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def scheduling(spark: SparkSession, sf: str, g: str = "part_next", rounds: int = 200, thresholds=(1e-3, 1.0), beside: tuple[str, ...] = ()) -> DataFrame:
    """Selective scheduling off and on at several thresholds: activation ratio, shards read and seconds of every round.

    Vertex arrays are in memory and shards as CSR, as far as the kernel holds them; beyond, rounds run over tables. Graphs that
    later calls ask for may be prepared beside this one.
    """
    rows = []
    ready(spark, sf, beside or (g,))
    for app in APPS:
        sg = _graph(spark, sf, g, app)
        run = engine.run_kernel if sg.n <= engine.KERNEL_ROWS else engine.run
        for how, limit in [("all", 0.0), *(("selective", t) for t in thresholds), ("exact", 1.0)]:
            r = run(sg, program(app), EngineOptions(max_iter=rounds, schedule=how, threshold=limit))
            rows += [(app, how, float(limit), x["iter"], x["active"] / max(1, sg.n), x["shards_read"], x["shards_total"], x["seconds"]) for x in r.ledger]
    return spark.createDataFrame(rows, "app string, schedule string, threshold double, iter int, ratio double, shards_read int, shards_total int, seconds double")


def cache_modes(spark: SparkSession, sf: str, g: str = "part_next", rounds: int = 10, share: float = 0.2, apps=APPS) -> DataFrame:
    """Cache modes 0 to 4 and auto with room for a share of the raw edges: cached shards, hits, bytes missed, seconds.

    Vertex arrays are in memory, as in `scheduling`; shards that the cache leaves out are read from files in every round.
    """
    rows = []
    for app in apps:
        sg = sharded(spark, sf, g, app == "cc", parts=("csr",))  # nothing else is read by the kernel
        run = engine.run_kernel
        if sg.n > engine.KERNEL_ROWS:
            sg, run = _graph(spark, sf, g, app), engine.run
        for mode in (0, 1, 2, 3, 4, "auto"):
            x = run(sg, program(app), EngineOptions(max_iter=rounds, cache=mode, cache_bytes=int(sg.m * EDGE_BYTES * share))).ledger
            hit = max(r["cache_hits"] / r["shards_total"] for r in x)
            rows.append((app, str(mode), hit, 1 - hit, sum(r["read_bytes"] for r in x), x[0]["seconds"], float(sum(r["seconds"] for r in x[1:]))))
    return spark.createDataFrame(rows, "app string, mode string, cached_ratio double, miss_ratio double, missed_bytes long, first_round double, later_rounds double")


def in_memory(spark: SparkSession, sf: str, g: str = "part_next", rounds=(120, 15, 25)) -> DataFrame:
    """The in-memory sparse-matrix engine, whose load sorts all edges, against the pull-window engine: load and run seconds, without and with preprocessing.

    Both hold vertex arrays in memory as far as the kernel does; beyond, rounds run over tables. Edges are made from the tables
    once, and shards of a direction once; their seconds count for every application that needs them.
    """
    t = time.perf_counter()
    base = graph(spark, sf, g)
    base = Graph(saved(base.weighed().select("src", "dst", "weight"), f"edges-{g}"), saved(base.vertices.select("id").distinct(), f"vertices-{g}"), g)
    fits = base.vertices.count() <= engine.KERNEL_ROWS
    made, ready, rows = time.perf_counter() - t, {}, []
    runs = {"spmv_mem": run_matrix, "pull_window": engine.run_kernel} if fits else {m: functools.partial(run_model, m) for m in ("spmv_mem", "pull_window")}
    for app, k in zip(APPS, rounds, strict=True):
        both = app == "cc"
        if both not in ready:
            t = time.perf_counter()
            sg = prepare.prepare(graphs.symmetrize(base) if both else base, shards=SHARDS, parts=("csr",) if fits else ("mirror",))
            ready[both] = sg, made + time.perf_counter() - t
        sg, prep = ready[both]
        for model, run in runs.items():
            for x in run(sg, program(app), EngineOptions(max_iter=k)).ledger:
                rows.append((app, model, "load" if x["phase"] == "load" else "run", x["iter"], x["seconds"], prep if model == "pull_window" else 0.0))
    return spark.createDataFrame(rows, "app string, model string, phase string, iter int, seconds double, preprocessing double")


def pull_options(sg: ShardedGraph) -> dict[str, dict]:
    """The engine without and with what it may switch on: scheduling by filters, and a cache that all raw edges would fit in."""
    both = {"schedule": "selective", "cache": 1, "cache_bytes": 4 * EDGE_BYTES * (sg.m + sg.n)}
    return {"pull_window": {}, "pull_window+cache+scheduling": both}


def models(spark: SparkSession, sf: str, names=("psw", "esg", "vsp", "dsw"), gs=("part_next",), rounds: int = 10, apps=APPS) -> DataFrame:
    """Totals of the first rounds under each model, and of the engine with and without cache and scheduling; the model's
    own layout is timed apart.

    Graphs that one task holds are run by one task under every model and the engine alike, from files of its own where a model has
    files; beyond, all rounds run over tables.
    """
    rows = []
    ready(spark, sf, gs, sorted({app == "cc" for app in apps}))
    for g in gs:
        for app in apps:
            sg = _graph(spark, sf, g, app)
            run = run_alone if alone.fits(sg, program(app)) else run_model
            runs = [(m, m, {}) for m in names] + [("pull_window", label, more) for label, more in pull_options(sg).items()]
            for m, label, more in runs:
                x = run(m, sg, program(app), EngineOptions(max_iter=rounds, **more)).ledger
                own = [r for r in x if r["phase"] != "load"]
                rows.append((g, app, label, len(own), sg.m, float(sum(r["seconds"] for r in x if r["phase"] == "load")), float(sum(r["seconds"] for r in own)), sum(r["read_bytes"] for r in own), sum(r["write_bytes"] for r in own)))
    totals = spark.createDataFrame(rows, "graph string, app string, model string, rounds int, edges long, load double, seconds double, read_bytes long, write_bytes long")
    return cost.speed_ups(cost.edges_per_second(totals))


def replication(spark: SparkSession, sf: str, gs=MAIN) -> DataFrame:
    """Copies of vertices that the two cuts spread over workers, and the hubs that one of them tells apart."""
    rows = []
    for g in gs:
        sg = sharded(spark, sf, g)
        for name in ("gas_cut", "gas_hybrid"):
            model = MODELS[name](sg, programs.pagerank(), EngineOptions())
            model.prepare(engine.start(sg.vinfo, programs.pagerank(), sg.n))
            rows.append((g, name, model.made["copies"], model.replication, model.made.get("hubs", 0)))
            model.close()
    return spark.createDataFrame(rows, "graph string, model string, copies long, replication double, hubs long")


def clusters(spark: SparkSession, sf: str, **kw) -> DataFrame:
    return models(spark, sf, names=("bsp_push", "gas_cut", "gas_hybrid", "bsp_ooc", "esg_cluster"), **kw)


def preprocessing(spark: SparkSession, sf: str, gs=("part_next", "event_chain")) -> DataFrame:
    """Seconds from an edge list in CSV to what each model runs on: every step that it needs, none that it doesn't.

    Steps that models share are run and measured once and count for each of them.
    """
    rows = []
    for g in gs:
        base = graph(spark, sf, g)
        at = scratch_path(spark, f"csv-{g}")
        sources.write_edges(base.weighed().select("src", "dst", "weight"), at, "csv")
        vertices = saved(base.vertices.select("id"), "vertices")
        needs = {"pull_window": prepare.PARTS, "psw": ("mirror",), "esg": (), "vsp": (), "dsw": ()}
        spent: dict[str, float] = {}
        sg = prepare.prepare(Graph(sources.read_edges(spark, at, "csv"), vertices, g), shards=SHARDS, spent=spent)
        for m, parts in needs.items():
            t = time.perf_counter()
            if m != "pull_window":
                model = MODELS[m](sg, programs.pagerank(), EngineOptions())
                model.prepare(engine.start(sg.vinfo, programs.pagerank(), sg.n))
                model.close()
            own = time.perf_counter() - t if m != "pull_window" else 0.0
            formula = {"pull_window": 5 * EDGE_BYTES, "psw": VERTEX_BYTES + 5 * EDGE_BYTES, "dsw": 6 * EDGE_BYTES, "esg": 2 * EDGE_BYTES, "vsp": 4 * EDGE_BYTES}[m]
            rows.append((g, m, spent["shards"] + sum(spent[x] for x in parts) + own, formula * sg.m))
    return spark.createDataFrame(rows, "graph string, model string, seconds double, formula_bytes long")


def memory(spark: SparkSession, sf: str, g: str = "part_next", workers: int = 4) -> DataFrame:
    """Bytes that each model must hold by its formula, and bytes that block managers report of what engines really hold."""
    sg = sharded(spark, sf, g)
    rows = [(m, "formula", float(b)) for m, _, _, b, _ in cost.analytic(VERTEX_BYTES, EDGE_BYTES, sg.n, sg.m, sg.shards, workers, 1.0)]
    rows.append(("pull_window", "arrays and one shard a worker", float(engine.memory_bytes(sg, workers))))
    edges = sg.edges.select("src", "dst", "weight")
    held = {
        ("spmv_mem", "sorted matrix"): edges.repartitionByRange(sg.buckets, "dst", "src").sortWithinPartitions("dst", "src"),
        ("bsp_push", "vertices with out-edges"): edges.repartition(sg.buckets, "src"),
        ("pull_window", "vertex state"): engine.start(sg.vinfo, programs.pagerank(), sg.n),
        ("pull_window", "CSR of all shards"): sg.csr,
        ("pull_window", "cache of all shards, mode 4"): cache.payloads(sg.csr, cache.CODECS[4]).select("shard_id", "payload"),
    }
    rows += [(*k, float(engine.stored_bytes(df))) for k, df in held.items()]
    return spark.createDataFrame(rows, "model string, what string, bytes double")


def datasets(spark: SparkSession, sf: str) -> DataFrame:
    """One row a graph: sizes and degrees. Each graph's edges are made once and read for both ends' degrees."""
    return _union([prepare.graph_stats(held(graph(spark, sf, g))).withColumn("graph", F.lit(g)) for g in graphs.BUILDERS])


def held(g: Graph) -> Graph:
    """The graph without weights, as written tables."""
    return Graph(saved(g.edges.select("src", "dst"), f"edges-{g.name}"), saved(g.vertices.select("id"), f"vertices-{g.name}"), g.name)


def datasets_oracle() -> str:
    return " union all ".join(f"select *, '{g}' as graph from ({oracles.stats(g)})" for g in graphs.BUILDERS)


def compressors(spark: SparkSession, sf: str, gs=("part_next", "event_chain")) -> DataFrame:
    """Sizes and speeds of the codecs on each graph's CSR shards, without and with differences; nothing else is prepared for it."""
    reports = [cache.compression_reports(shards_only(spark, sf, g)).withColumn("graph", F.lit(g)) for g in gs]
    return _union(reports).select("codec", "raw_bytes", "bytes", "ratio", "mb_s", "graph", "delta")


def analytic(spark: SparkSession, sf: str, gs=MAIN, workers: int = 4) -> DataFrame:
    """Formulas beside the bytes of the records that one round under each model really read and wrote."""
    rows = []
    for g in gs:
        sg = sharded(spark, sf, g)
        for m, r, w, _, _ in cost.analytic(VERTEX_BYTES, EDGE_BYTES, sg.n, sg.m, sg.shards, workers, 1.0):
            x = run_model(m, sg, programs.pagerank(), EngineOptions(max_iter=1)).ledger[-1]
            rows.append((g, m, round(float(r), 4), round(float(w), 4), x["read_bytes"], x["write_bytes"]))
    return spark.createDataFrame(rows, "graph string, model string, read_b double, write_b double, read_bytes long, write_bytes long")


def reuse(spark: SparkSession, sf: str, g: str = "part_next", rounds: int = 10) -> DataFrame:
    """One preparation serves every application; the sliding-window model lays its edges out for each."""
    rows = []
    for app in APPS:
        sg = _graph(spark, sf, g, app)
        for m in ("pull_window", "psw"):
            r = run_model(m, sg, program(app), EngineOptions(max_iter=rounds))
            rows.append((app, m, *(float(sum(x["seconds"] for x in r.ledger if (x["phase"] == "load") == own)) for own in (True, False))))
    return spark.createDataFrame(rows, "app string, model string, own_preparation double, run double")


def scale(spark: SparkSession, sf: str, g: str = "part_next", rounds: int = 10) -> DataFrame:
    """Vertices, edges, seconds of preparation and of ten rounds, at each table size there is up to this one."""
    folder, own = os.path.split(sf.rstrip("/"))
    sizes = [x for x in ("sf0.001", "sf0.01", "sf0.1") if x != own and exists(spark, f"{folder}/{x}") and x < own] if own.startswith("sf") else []
    rows = []
    for x in (*sizes, own):
        t = time.perf_counter()
        sg = prepare.prepare(graph(spark, f"{folder}/{x}", g), shards=SHARDS)
        prep = time.perf_counter() - t
        r = engine.run(sg, programs.pagerank(), EngineOptions(max_iter=rounds))
        spent = sum(k["seconds"] for k in r.ledger)
        rows.append((x, sg.n, sg.m, prep, spent, rounds * sg.m / spent))
    return spark.createDataFrame(rows, "tables string, v long, e long, preparation double, seconds double, edges_s double")


def workers(spark: SparkSession, sf: str, g: str = "word_next", counts=(1, 2, 4, 8), shards=(16, 64), rounds: int = 5) -> DataFrame:
    """Seconds of kernel rounds by the number of tasks that work at once, and by shards, which bound it; medians of the rounds after the first."""
    rows = []
    base = graph(spark, sf, g)
    for p in shards:
        sg = prepare.prepare(base, shards=p, parts=("csr",))
        for k in counts:
            r = engine.run_kernel(sg, programs.pagerank(), EngineOptions(max_iter=rounds + 1, at_once=k))
            rows.append((sg.shards, k, float(np.median([x["seconds"] for x in r.ledger[1:]]))))
    return spark.createDataFrame(rows, "shards int, workers int, seconds_a_round double")


def surveyed_scheduling(spark: SparkSession, sf: str) -> DataFrame:
    gs = ("word_next", "event_chain")
    return _union([scheduling(spark, sf, g, thresholds=(1e-4, 1e-3, 1e-2, 1.0), beside=gs).withColumn("graph", F.lit(g)) for g in gs])


#: Registered with the rounds, graphs and applications of the survey, on whole tables.
EXPERIMENTS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "w01_scheduling": surveyed_scheduling, "w02_cache_modes": lambda s, d: cache_modes(s, d, "word_next"), "w03_in_memory": in_memory,
    "w04_out_of_core": lambda s, d: models(s, d, gs=FOUR), "w05_preprocessing": lambda s, d: preprocessing(s, d, MAIN), "w06_memory": memory, "w07_clusters": lambda s, d: clusters(s, d, gs=FOUR),
    "w08_datasets": datasets, "w09_compression": lambda s, d: compressors(s, d, tuple(graphs.BUILDERS)), "w10_analytic": analytic, "w11_reuse": reuse, "w12_scale": scale, "w13_workers": workers, "replication": replication,
}
