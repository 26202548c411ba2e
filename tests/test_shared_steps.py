"""Experiments make what their runs share once, and count its seconds for each run that needs it."""

import pytest

from shardgraph import programs
from shardgraph.baselines import run_matrix
from shardgraph.build import prepare
from shardgraph.core import engine
from shardgraph.model import EngineOptions, Graph
from shardgraph.workloads import experiments


@pytest.fixture()
def prepared(monkeypatch):
    seen, real = [], prepare.prepare
    monkeypatch.setattr(experiments.prepare, "prepare", lambda g, **kw: seen.append((g.name, kw)) or real(g, **kw))
    return seen


def test_preprocessing_prepares_once(spark, data, prepared):
    rows = {r.model: r.seconds for r in experiments.preprocessing(spark, data, ("event_chain",)).collect()}
    assert len(prepared) == 1
    spent = prepared[0][1]["spent"]
    assert set(spent) == {"shards", "csr", "mirror", "filters"} and all(x > 0 for x in spent.values())
    assert rows["pull_window"] == pytest.approx(sum(spent.values())) and rows["psw"] > spent["shards"] + spent["mirror"]
    assert set(rows) == {"pull_window", "psw", "esg", "vsp", "dsw"} and all(rows[m] > spent["shards"] for m in ("esg", "vsp", "dsw"))


def test_in_memory_prepares_each_direction_once(spark, data, prepared):
    rows = experiments.in_memory(spark, data, rounds=(3, 2, 2)).collect()
    assert [n for n, _ in prepared] == ["part_next", "part_next_sym"]
    assert {(r.app, r.model, r.phase, r.iter) for r in rows} == {(a, m, "run" if i else "load", i) for a, k in (("pagerank", 3), ("sssp", 2), ("cc", 2)) for m in ("spmv_mem", "pull_window") for i in range(m == "pull_window", k + 1)}
    assert all((r.preprocessing > 0) == (r.model == "pull_window") for r in rows)


@pytest.mark.parametrize("edges", [[(5, 6, 2), (6, 5, 1), (0, 6, 9), (2, 5, 1)], [(0, 3, 2), (3, 9, 1)], []])
@pytest.mark.parametrize("alone", [1 << 20, 0])
def test_matrix_gives_the_engine_s_values(spark, monkeypatch, edges, alone):
    monkeypatch.setattr(engine, "ALONE", alone)
    sg = prepare.prepare(Graph(spark.createDataFrame(edges, "src long, dst long, weight long"), spark.range(10).select("id"), "few"), shards=3, parts=("csr",))
    for program in (programs.pagerank(), programs.sssp((0,)), programs.components()):
        r, want = run_matrix(sg, program, EngineOptions(max_iter=4)), engine.run_kernel(sg, program, EngineOptions(max_iter=4))
        assert {v.id: v.value for v in r.values.collect()} == pytest.approx({v.id: v.value for v in want.values.collect()})
        assert [x["phase"] for x in r.ledger] == ["load", *["run"] * r.rounds] and r.rounds == want.rounds
