"""Preparation leaves no core idle that has work, and kernel rounds do for each vertex once what they need once."""

import threading

import pytest

from shardgraph import programs, session
from shardgraph.build import graphs, prepare
from shardgraph.core import engine
from shardgraph.model import EngineOptions
from shardgraph.workloads import experiments, queries

KEY = "spark.sql.requireAllClusterKeysForCoPartition"


def test_one_file_is_dealt_to_all_cores(spark, tmp_path):
    cores = spark.sparkContext.defaultParallelism
    for files, many in ((1, cores), (3 * cores, None)):
        at = str(tmp_path / str(files))
        spark.range(1000).repartition(files).write.parquet(at)
        df = spark.read.parquet(at)
        out = session.spread(df)
        assert out.rdd.getNumPartitions() == (many or df.rdd.getNumPartitions()) and sorted(r.id for r in out.collect()) == list(range(1000))
        assert (out is df) == (many is None)


def test_words_of_one_file_are_found_by_all_cores(spark, data, monkeypatch):
    seen = []
    monkeypatch.setattr(graphs, "saved", lambda df, label: (seen.append((label, df)), session.saved(df, label))[1])
    graphs.word_next(spark, data)
    assert "Repartition" in dict(seen)["word-pairs"]._jdf.queryExecution().logical().toString()


def test_a_setting_shared_by_threads_is_put_back(spark):
    old, first, second = spark.conf.get(KEY, None), threading.Event(), threading.Event()

    def holds():
        with session.dealt_by_one_key(spark):
            first.set()
            assert second.wait(20)

    t = threading.Thread(target=holds)
    t.start()
    assert first.wait(20)
    with session.dealt_by_one_key(spark):
        second.set()
        t.join()
        assert spark.conf.get(KEY) == "false"  # the one that entered later is still inside
    assert spark.conf.get(KEY, None) == old


def test_graphs_are_prepared_at_the_same_time(spark, data, monkeypatch):
    both = threading.Barrier(2)
    monkeypatch.setattr(queries, "sharded", lambda s, d, g, symmetric: both.wait(20))
    queries.ready(spark, data, ("part_next", "word_next"))
    met = []
    monkeypatch.setattr(experiments, "ready", lambda s, d, gs, *more: met.append(tuple(gs)))
    monkeypatch.setattr(experiments, "APPS", ())
    experiments.surveyed_scheduling(spark, data)
    experiments.models(spark, data, (), gs=experiments.FOUR, apps=())
    assert met[0] == ("word_next", "event_chain") and met[-1] == experiments.FOUR


@pytest.mark.parametrize("spent", [None, {}])
def test_parts_made_together_are_the_parts(spark, data, spent):
    sg = prepare.prepare(graphs.event_chain(spark, data), shards=3, spent=spent)
    assert {r.shard_id for r in sg.csr.collect()} == {b[0] for b in sg.bounds} and sum(b[3] for b in sg.bounds) == sg.m == sg.edges.count()
    assert sorted(map(tuple, sg.mirror.collect())) == sorted(map(tuple, sg.edges.select("shard_id", "src").distinct().collect())) and sg.filters.count() > 0
    again = prepare.open_sharded(spark, sg.path)
    assert (again.n, again.m, again.bounds, again.laid) == (sg.n, sg.m, sg.bounds, sg.laid)


def test_values_passed_on_are_worked_out_once_a_round(spark, data, monkeypatch):
    sg = prepare.prepare(graphs.part_next(spark, data), shards=5, parts=("csr",))
    opts = EngineOptions(max_iter=4)
    want = engine.run_kernel(sg, programs.pagerank(), opts).values.collect()
    monkeypatch.setattr(programs, "_shares", None)  # what a shard would work out by itself
    got = engine.run_kernel(sg, programs.pagerank(), opts)
    assert got.rounds == 4 and got.values.collect() == want
    monkeypatch.undo()
    monkeypatch.setattr(engine, "ALONE", 0)
    assert engine.run_kernel(sg, programs.pagerank(), opts).values.collect() == want


def test_values_that_nobody_asks_for_are_no_table(spark, data, monkeypatch):
    sg = prepare.prepare(graphs.part_next(spark, data), shards=5, parts=("csr",))
    made, real = [], type(spark).createDataFrame
    monkeypatch.setattr(type(spark), "createDataFrame", lambda *a, **k: made.append(1) or real(*a, **k))
    r = engine.run_kernel(sg, programs.sssp((0,)))
    assert not made and r.values.count() == sg.n and r.values is r.values and made
