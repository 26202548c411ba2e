"""Labels that jump lead to the same components in fewer rounds."""

import pytest

from shardgraph import programs
from shardgraph.build import graphs, prepare
from shardgraph.core import engine
from shardgraph.model import EngineOptions, Graph


@pytest.mark.parametrize("more", [{}, {"broadcast_rows": 0}, {"schedule": "exact", "threshold": 1.0}])
@pytest.mark.parametrize("pick", ["min", "max"])
def test_long_paths_take_few_rounds(spark, more, pick):
    edges = [(i, i + 1, 1) for i in range(0, 59)] + [(70, 60, 1), (60, 80, 1), (80, 65, 1)]
    g = Graph(spark.createDataFrame(edges, "src long, dst long, weight long"), spark.range(82).select("id"), "path")
    sg = prepare.prepare(graphs.symmetrize(g), shards=4)
    r = engine.run(sg, programs.components(pick), EngineOptions(max_iter=12, shortcut=True, **more))
    low, high = (0, 60) if pick == "min" else (59, 80)
    want = [low if i < 60 else high if i in (60, 65, 70, 80) else i for i in range(82)]
    assert r.converged and [x.value for x in r.values.orderBy("id").collect()] == want


def test_values_that_are_no_ids_do_not_jump(spark):
    g = Graph(spark.createDataFrame([(0, 1, 2), (1, 2, 2)], "src long, dst long, weight long"), spark.range(3).select("id"), "three")
    r = engine.run(prepare.prepare(g, shards=2), programs.sssp((0,)), EngineOptions(max_iter=9, shortcut=True))
    assert [x.value for x in r.values.orderBy("id").collect()] == [0, 2, 4]
