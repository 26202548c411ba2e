import duckdb
import pytest

import __spark_entry__ as entry
from shardgraph import operators, plans, sources
from shardgraph.build import graphs, prepare
from shardgraph.workloads import experiments
from shardgraph.workloads import queries as workload

OPS, OPS_SQL = operators.build()
GRAPH, GRAPH_SQL = workload.build()


@pytest.fixture(scope="module")
def con(data):
    c = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "conversations"):
        c.execute(f"create view {t} as select * from read_parquet('{data}/{t}.parquet')")
    return c


def same(df, relation):
    def rows(names, values):
        order = sorted(range(len(names)), key=lambda k: names[k])
        return [names[k] for k in order], sorted((tuple(r[k] for k in order) for r in values), key=str)

    assert rows(df.columns, [tuple(r) for r in df.collect()]) == rows(relation.columns, relation.fetchall())


@pytest.mark.parametrize("name", sorted(OPS_SQL))
def test_operator_equals_sql(spark, data, con, name):
    same(OPS[name](spark, data), con.sql(OPS_SQL[name]))


FAST = [n for n in GRAPH_SQL if n.split("_")[0] in ("stats", "intervals", "shard", "csr", "mirror", "symmetrize", "analytic", "cache", "spmv") and "word_next" not in n]


@pytest.mark.parametrize("name", sorted(FAST))
def test_graph_query_equals_sql(spark, data, con, name):
    same(GRAPH[name](spark, data), con.sql(GRAPH_SQL[name]))


def test_scan_reads_only_what_it_needs(spark, data):
    df = OPS["op_scan_prune"](spark, data)
    assert set(plans.read_columns(df)) == {"l_orderkey", "l_partkey", "l_shipdate"}
    assert any("GreaterThanOrEqual(l_shipdate" in p for p in plans.pushed(df)) and not plans.has_python(df)


def test_join_strategies(spark, data):
    assert plans.joins(OPS["op_join_broadcast"](spark, data)).count("BroadcastHashJoin") == 2
    assert "CartesianProduct" not in plans.joins(OPS["op_triangles"](spark, data))


def test_bucketed_table_groups_without_exchange(spark, data):
    assert plans.exchanges(OPS["op_bucketed"](spark, data)) == 0


def test_csr_data_source(spark, data, tmp_path):
    sg = prepare.prepare(graphs.user_next(spark, data), shards=4)
    sources.write_csr_files(sg.csr, str(tmp_path / "csr"))
    sources.register(spark)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    df = spark.read.format("csr_shards").load(path=str(tmp_path / "csr"))
    want = sorted((r.shard_id, r.src, r.dst) for r in sg.edges.collect())
    assert sorted((r.shard_id, r.src, r.dst) for r in df.collect()) == want
    one = df.where("shard_id = 1")
    assert one.rdd.getNumPartitions() == 1 and sorted((r.shard_id, r.src, r.dst) for r in one.collect()) == [w for w in want if w[0] == 1]


def test_text_edges(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# comment\n1 2\n3\t4\n\n")
    assert sorted(tuple(r) for r in sources.read_edges(spark, str(tmp_path / "e.txt"), "text", "src long, dst long").collect()) == [(1, 2), (3, 4)]


def test_ablations_move_as_published(spark, data):
    rows = experiments.scheduling(spark, data, "event_chain", rounds=5).collect()
    read = {}
    for r in rows:
        if r.app == "sssp":
            read[r.schedule, r.threshold] = read.get((r.schedule, r.threshold), 0) + r.shards_read
    assert read["exact", 1.0] <= read["selective", 1.0] < read["all", 0.0]
    modes = {r.mode: r for r in experiments.cache_modes(spark, data, rounds=2).collect()}
    assert modes["0"].cached_ratio == 0 and modes["0"].missed_bytes >= modes["1"].missed_bytes >= modes["4"].missed_bytes
    for r in experiments.analytic(spark, data).collect():
        if r.model != "vsp":
            assert r.read_b == pytest.approx(r.read_bytes, rel=0.02)  # a grid has a whole number of columns


def test_entry_and_registry(spark):
    assert entry.entry(spark).count() == 10
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_registered_experiments_run_the_surveyed_job(monkeypatch):
    seen = []
    for name in ("scheduling", "cache_modes", "in_memory", "models", "shards_and_workers"):
        monkeypatch.setattr(experiments, name, lambda s, d, *a, name=name, **kw: seen.append((name, a, kw)) or _Frame())
    monkeypatch.setattr(experiments.F, "lit", lambda v: v)
    for name in ("w01_scheduling", "w02_cache_modes", "w03_in_memory", "w04_out_of_core", "w07_clusters"):
        experiments.EXPERIMENTS[name](None, "")
    by = {}
    for name, a, kw in seen:
        by.setdefault(name, []).append((a, kw))
    assert [(a[0], kw["rounds"], kw["thresholds"]) for a, kw in by["scheduling"]] == [(g, 200, (1e-4, 1e-3, 1e-2, 1.0)) for g in ("word_next", "event_chain")]
    assert by["cache_modes"] == [(("word_next",), {"rounds": 10, "apps": experiments.APPS})] and by["in_memory"] == [((), {"rounds": (120, 15, 25)})]
    disk, cluster = (kw for _, kw in by["models"])
    assert disk["gs"] == cluster["gs"] == experiments.FOUR and disk["rounds"] == cluster["rounds"] == 10 and cluster["apps"] == experiments.APPS


class _Frame:
    def withColumn(self, *_):
        return self

    def unionByName(self, _):
        return self


def test_queries_beyond_the_kernel(spark, data, monkeypatch):
    from shardgraph.core import engine
    from shardgraph.workloads import queries

    q, _ = queries.build()
    names = ("cc_part_next", "sssp_weighted_part_next", "active_ratio_sssp_part_next")
    want = {n: sorted(map(tuple, q[n](spark, data).collect()), key=str) for n in names}
    monkeypatch.setattr(engine, "KERNEL_ROWS", 10)
    assert {n: sorted(map(tuple, q[n](spark, data).collect()), key=str) for n in names} == want
    monkeypatch.setattr(engine, "run_kernel", None)
    assert q["cc_sizes_doc_dup"](spark, data).count() > 0


def test_reachability_of_a_long_path(spark, data, monkeypatch):
    from shardgraph.build import prepare
    from shardgraph.model.graph import Graph
    from shardgraph.workloads import queries

    n = 56
    edges = spark.createDataFrame([(k, k + 1, 1) for k in range(n - 1)], "src long, dst long, weight long")
    path = prepare.prepare(Graph(edges, spark.range(n).select("id"), "path"), shards=2)
    monkeypatch.setattr(queries, "sharded", lambda *_: path)
    q, _ = queries.build()
    assert q["reachability"](spark, data).where("value = 1").count() == n
