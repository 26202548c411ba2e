"""Kernel rounds with an edge cache: the values, hits and missed edges of rounds over tables, in few jobs."""

import pytest

from shardgraph import programs
from shardgraph.build import graphs, prepare
from shardgraph.core import engine
from shardgraph.model import EngineOptions
from shardgraph.workloads import experiments


@pytest.fixture(scope="module")
def sg(spark, data):
    return prepare.prepare(graphs.part_next(spark, data), shards=5)


def seen(r):
    return [(x["iter"], x["active"], x["shards_read"], x["cache_hits"], x["read_rows"]) for x in r.ledger], {v.id: v.value for v in r.values.collect()}


@pytest.mark.parametrize("mode", [0, 1, "auto"])
@pytest.mark.parametrize("alone", [1 << 20, 0])
def test_as_rounds_over_tables(sg, monkeypatch, mode, alone):
    monkeypatch.setattr(engine, "ALONE", alone)
    opts = EngineOptions(max_iter=3, cache=mode, cache_bytes=sg.m * 10)  # blocks are of 24 bytes an edge and more
    for program in (programs.sssp((0,)), programs.pagerank()):
        (kernel, got), (table, want) = seen(engine.run_kernel(sg, program, opts)), seen(engine.run(sg, program, opts))
        assert kernel == table and (kernel[0][3] > 0) == (mode != 0) and (kernel[0][4] > 0) == (mode in (0, 1))
        assert got == pytest.approx(want)


def test_skipped_shards_are_neither_hit_nor_missed(sg, monkeypatch):
    for alone in (1 << 20, 0):
        monkeypatch.setattr(engine, "ALONE", alone)
        opts = EngineOptions(max_iter=4, cache=2, cache_bytes=sg.m * 10, schedule="exact", threshold=1.0)
        assert seen(engine.run_kernel(sg, programs.sssp((0,)), opts)) == seen(engine.run(sg, programs.sssp((0,)), opts))


def test_cache_modes_take_few_jobs(spark, data):
    experiments.cache_modes(spark, data, rounds=1, apps=("sssp",)).collect()
    spark.sparkContext.setJobGroup("cache-modes", "")
    rows = experiments.cache_modes(spark, data, rounds=10, apps=("sssp",)).collect()
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(rows) == 6 and all(r.first_round > 0 and r.later_rounds > 0 for r in rows)
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("cache-modes")) < 120
