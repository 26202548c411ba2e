"""Sizes of all graphs come from edges that are made once."""

from shardgraph.build import graphs
from shardgraph.workloads import experiments


def test_edges_are_made_once(spark, data, monkeypatch):
    monkeypatch.setattr(graphs, "BUILDERS", {k: graphs.BUILDERS[k] for k in ("event_chain", "geo_tree")})
    out = experiments.datasets(spark, data)
    assert not any("testdata" in f for f in out.inputFiles())
    assert {r.graph: r.e for r in out.collect()} == {k: f(spark, data).edges.count() for k, f in graphs.BUILDERS.items()}
