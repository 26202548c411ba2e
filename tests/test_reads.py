"""Queries read tables of their own, whatever was prepared before."""

import pytest

from shardgraph.core import cache
from shardgraph.workloads import queries as w


def test_cache_choice_reads_a_table(spark, data):
    out = w._choices(spark, data)
    assert any("lineitem.parquet" in f for f in out.inputFiles())
    rows = out.collect()
    assert all(r.mode == cache.choose_mode(r.size, r.capacity) for r in rows) and {r.mode for r in rows} == {1, 2, 3, 4}


@pytest.mark.parametrize("g,file", [("part_next", "lineitem"), ("event_chain", "events")])
def test_shards_are_counted_in_the_tables(spark, data, g, file):
    w.sharded(spark, data, g)
    out = w._counted_cuts(spark, data, g)
    assert any(f"{file}.parquet" in f for f in out.inputFiles())
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, w._cuts(spark, data, g).collect()))


def test_admission_reads_a_table(spark, data, monkeypatch):
    seen = []
    monkeypatch.setattr(cache, "admission", lambda sizes, room: seen.extend(sizes.inputFiles()))
    w._admission(spark, data)
    assert any("lineitem.parquet" in f for f in seen)
