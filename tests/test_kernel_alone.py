"""One task runs all kernel rounds of a graph that it holds, with the values and the ledger of rounds that are jobs."""

import pytest

from shardgraph import programs
from shardgraph.build import prepare
from shardgraph.core import engine
from shardgraph.model import EngineOptions, Graph


def path(spark, n, edges=None, **cut):
    edges = spark.createDataFrame([(k, k + 1, 1) for k in range(n - 1)] if edges is None else edges, "src long, dst long, weight long")
    return prepare.prepare(Graph(edges, spark.range(n).select("id"), "path"), **cut)


def seen(r):
    return r.converged, r.rounds, [(x["iter"], x["active"], x["shards_read"], x["read_rows"]) for x in r.ledger], sorted(map(tuple, r.values.collect()))


@pytest.mark.parametrize("how,limit", [("all", 0.0), ("selective", 0.05), ("selective", 1.0), ("exact", 1.0)])
def test_one_task_does_what_jobs_do(spark, monkeypatch, how, limit):
    sg = path(spark, 40, shards=4)
    for program in (programs.pagerank(), programs.sssp((0,))):
        opts = EngineOptions(max_iter=60, schedule=how, threshold=limit)
        alone = seen(engine.run_kernel(sg, program, opts))
        monkeypatch.setattr(engine, "ALONE", 0)
        assert seen(engine.run_kernel(sg, program, opts)) == alone and alone[1] >= 40
        monkeypatch.undo()


def test_many_rounds_take_few_jobs(spark):
    sg = path(spark, 40, shards=4)
    spark.sparkContext.setJobGroup("kernel-alone", "")
    r = engine.run_kernel(sg, programs.sssp((0,)), EngineOptions(max_iter=60))
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert r.rounds == 40 and len(spark.sparkContext.statusTracker().getJobIdsForGroup("kernel-alone")) < 20


@pytest.mark.parametrize("alone", [1 << 20, 0])
def test_shards_without_edges_are_visited(spark, monkeypatch, alone):
    """Vertices that have no in-edges fall to the restart value too."""
    monkeypatch.setattr(engine, "ALONE", alone)
    for edges in ([(5, 6, 1), (6, 5, 1)], []):
        sg = path(spark, 8, edges, policy="user", bounds=[0, 4])
        want = seen(engine.run_kernel(sg, programs.pagerank(), EngineOptions(max_iter=3)))[3]
        assert seen(engine.run_kernel(sg, programs.pagerank(), EngineOptions(max_iter=3, schedule="selective", threshold=0.0)))[3] == want
        assert want[0][1] == pytest.approx(0.15 / 8)
