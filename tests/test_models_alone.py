"""One task runs all rounds of a model, with the values and the counted records of rounds over tables."""

import pytest

from shardgraph import programs
from shardgraph.baselines import run_model
from shardgraph.baselines.alone import ALONE, run_alone
from shardgraph.build import graphs, prepare
from shardgraph.core import engine
from shardgraph.model import EngineOptions, Graph
from shardgraph.workloads import experiments


@pytest.fixture(scope="module")
def sg(spark, data):
    return prepare.prepare(graphs.part_next(spark, data), shards=5)


def seen(r):
    names = ("iter", "phase", "active", "shards_read", "read_rows", "read_bytes", "write_rows", "write_bytes")
    return r.converged, r.rounds, [tuple(x[n] for n in names) for x in r.ledger], {v.id: v.value for v in r.values.collect()}


@pytest.mark.parametrize("model", sorted(ALONE))
def test_as_rounds_over_tables(sg, model):
    for program, rounds in ((programs.sssp((0,)), 2), (programs.pagerank(), 1)):
        got, want = (seen(run(model, sg, program, EngineOptions(max_iter=rounds))) for run in (run_alone, run_model))
        assert got[:3] == want[:3] and got[3] == pytest.approx(want[3])


@pytest.mark.parametrize("edges", [[(5, 6, 2), (6, 5, 1), (0, 6, 9), (2, 5, 1), (2, 5, 7)], []])
def test_vertices_without_edges_and_parallel_edges(spark, edges):
    few = prepare.prepare(Graph(spark.createDataFrame(edges, "src long, dst long, weight long"), spark.range(10).select("id"), "few"), shards=3, parts=("csr",))
    for program in (programs.pagerank(), programs.sssp((0, 2)), programs.components()):
        want = engine.run_kernel(few, program, EngineOptions(max_iter=9))
        values = {v.id: v.value for v in want.values.collect()}
        for model in ALONE:
            got = run_alone(model, few, program, EngineOptions(max_iter=9))
            assert {v.id: v.value for v in got.values.collect()} == pytest.approx(values)
            assert [x["active"] for x in got.ledger[1:]] == [x["active"] for x in want.ledger] and got.converged == want.converged


def test_pulled_windows_are_read_from_files_too(sg, monkeypatch):
    asked, real = [], engine.run_kernel
    monkeypatch.setattr(engine, "run_kernel", lambda g, p, o: asked.append(o.cache) or real(g, p, o))
    for more in ({}, {"cache": 1, "cache_bytes": 1 << 30}):
        opts = EngineOptions(max_iter=2, **more)
        got, want = (run("pull_window", sg, programs.pagerank(), opts).ledger for run in (run_alone, run_model))
        assert [(x["read_bytes"], x["cache_hits"]) for x in got] == [(x["read_bytes"], x["cache_hits"]) for x in want]
    assert asked == [0, 1]


@pytest.mark.parametrize("run,many", [(experiments.models, 6), (experiments.clusters, 7)])
def test_rounds_of_experiments_are_no_jobs(spark, data, run, many):
    run(spark, data, gs=("part_next",), rounds=1, apps=("sssp",)).collect()
    jobs = []
    for rounds in (1, 10):
        spark.sparkContext.setJobGroup(f"models-alone-{many}-{rounds}", "")
        rows = run(spark, data, gs=("part_next",), rounds=rounds, apps=("sssp",)).collect()
        jobs.append(len(spark.sparkContext.statusTracker().getJobIdsForGroup(f"models-alone-{many}-{rounds}")))
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(rows) == many and {r.rounds for r in rows} == {4} and jobs[1] <= jobs[0] + 3  # rounds are no jobs


def test_larger_graphs_run_over_tables(spark, data, monkeypatch):
    monkeypatch.setattr(engine, "ALONE", 10)
    monkeypatch.setattr(experiments, "run_alone", None)
    assert experiments.models(spark, data, ("esg",), rounds=1, apps=("sssp",)).count() == 3
