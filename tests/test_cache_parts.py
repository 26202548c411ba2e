"""The cache experiment prepares what its kernel reads; other parts are added when a query needs them, and files are read in one step."""

import pytest
from pyspark import RDD

from shardgraph import programs
from shardgraph.build import graphs, prepare
from shardgraph.core import cache, engine
from shardgraph.model import EngineOptions
from shardgraph.workloads import experiments
from shardgraph.workloads import queries as w


def test_only_shards_are_prepared_for_cache_modes(spark, data, monkeypatch):
    monkeypatch.setattr(w, "_READY", {})
    made, real = [], prepare.prepare
    monkeypatch.setattr(prepare, "prepare", lambda g, **kw: made.append(kw.get("parts")) or real(g, **kw))
    rows = experiments.cache_modes(spark, data, "event_chain", rounds=1, apps=("sssp",)).collect()
    assert made == [("csr",)] and len(rows) == 6
    whole = w.sharded(spark, data, "event_chain")
    assert len(made) == 1 and whole.filters.count() > 0 and w.sharded(spark, data, "event_chain") is whole
    want = real(graphs.event_chain(spark, data), shards=w.SHARDS)
    assert sorted(map(tuple, whole.mirror.collect())) == sorted(map(tuple, want.mirror.collect()))


def test_admitted_on_the_driver(spark, monkeypatch):
    sizes = spark.createDataFrame([(2, 50), (0, 60), (1, 50), (3, 40)], "shard_id int, bytes long")
    want = [tuple(r) for r in cache.admission(sizes, 100).orderBy("shard_id").collect()]
    monkeypatch.setattr(type(spark), "createDataFrame", None)
    assert cache.admitted(sizes, 100) == want == [(0, 60, True), (1, 50, False), (2, 50, False), (3, 40, True)]


@pytest.mark.parametrize("mode", [0, 1])
def test_shards_in_files_pass_no_worker_but_the_round_s(spark, data, monkeypatch, mode):
    sg = prepare.prepare(graphs.part_next(spark, data), shards=5, parts=("csr",))
    opts = EngineOptions(max_iter=3, cache=mode, cache_bytes=sg.m * 10)
    want = engine.run_kernel(sg, programs.pagerank(), opts)
    monkeypatch.setattr(engine, "ALONE", 0)
    asked, real = [], RDD.mapPartitions
    monkeypatch.setattr(RDD, "mapPartitions", lambda self, *a, **k: asked.append(self.is_cached) or real(self, *a, **k))
    got = engine.run_kernel(sg, programs.pagerank(), opts)
    assert got.values.collect() == want.values.collect() and [x["cache_hits"] for x in got.ledger] == [x["cache_hits"] for x in want.ledger]
    assert asked == [True] * 3 * mode
