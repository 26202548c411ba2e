import duckdb
import numpy as np
import pytest

from shardgraph import cost, plans, programs
from shardgraph.baselines import MODELS, run_model
from shardgraph.build import graphs, prepare
from shardgraph.core import cache, engine, schedule
from shardgraph.model import EngineOptions, Graph
from shardgraph.model.graph import ArrowProgram
from shardgraph.session import dealt_by_one_key


def tiny(spark, edges, n, name="tiny"):
    return Graph(spark.createDataFrame(edges, "src long, dst long, weight long"), spark.range(n).select("id"), name)


EDGES = [(0, 1, 2), (1, 2, 1), (2, 0, 4), (0, 2, 7), (3, 4, 1), (4, 3, 1), (4, 4, 3), (5, 0, 1), (5, 0, 2)]


def ref_pagerank(edges, n, rounds):
    out = np.zeros(n)
    for s, _, _ in edges:
        out[s] += 1
    v = np.full(n, 1 / n)
    for _ in range(rounds):
        new = np.full(n, 0.15 / n)
        for s, d, _ in edges:
            new[d] += 0.85 * v[s] / out[s]
        v = new
    return v


def ref_sssp(edges, n, source=0, weighted=True):
    d = [None] * n
    d[source] = 0
    for _ in range(n):
        for s, t, w in edges:
            if d[s] is not None and (d[t] is None or d[s] + (w if weighted else 1) < d[t]):
                d[t] = d[s] + (w if weighted else 1)
    return d


def values(result):
    return {r["id"]: r["value"] for r in result.values.collect()}


@pytest.fixture(scope="module")
def sharded(spark):
    return prepare.prepare(tiny(spark, EDGES, 7), threshold=3)


@pytest.fixture(scope="module")
def chain(spark, data):
    return prepare.prepare(graphs.event_chain(spark, data))


def literal_cut(deg, threshold):
    starts, s = [0], 0
    for v, d in enumerate(deg):
        if s + d > threshold and v > starts[-1]:
            starts.append(v)
            s = d
        else:
            s += d
    return starts


@pytest.mark.parametrize("deg,threshold", [([1] * 10, 3), ([9, 0, 0, 1, 2], 3), ([0, 0, 9, 0, 1, 1, 1, 1], 3), ([5], 3), ([0] * 5, 3), ([1, 2, 3, 4, 5, 6], 6), (list(range(40)) * 5, 77)])
def test_greedy_cut(spark, deg, threshold):
    df = spark.createDataFrame([(i, d, 0) for i, d in enumerate(deg)], "id long, in_deg long, out_deg long")
    for batch in (10000, 3):
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", batch)
        got = prepare.cut_intervals(df, threshold)
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
        assert [b[1] for b in got] == literal_cut(deg, threshold)
        assert sum(b[3] for b in got) == sum(deg) and got[-1][2] == len(deg) - 1


def test_interval_policies(spark):
    deg = [1, 5, 0, 2, 2, 9, 0, 0, 1, 3]
    df = spark.createDataFrame([(i, d, 0) for i, d in enumerate(deg)], "id long, in_deg long, out_deg long")
    starts = lambda **k: [b[1] for b in prepare.cut_intervals(df, 6, **k)]
    assert starts(policy="equal_vertices", shards=4) == [0, 3, 5, 8]
    assert starts(policy="user", bounds=[3, 7]) == [0, 3, 7]
    before = np.cumsum([0, *deg[:-1]])
    assert starts(policy="prefix") == [0, *(i for i in range(1, 10) if before[i] // 6 > before[i - 1] // 6)]
    for policy in ("equal_vertices", "user", "prefix"):
        got = prepare.cut_intervals(df, 6, policy, bounds=[3, 7], shards=4)
        assert sum(b[3] for b in got) == sum(deg) and got[-1][2] == 9 and [a[2] + 1 for a in got[:-1]] == [b[1] for b in got[1:]]


def test_five_thousand_shards(spark):
    n = 20_000
    g = Graph(spark.range(n).selectExpr("id as src", "(id * 7 + 1) % 20000 as dst", "1L as weight"), spark.range(n).select("id"), "many")
    sg = prepare.prepare(g, threshold=4)
    assert sg.shards == 5000 and [b[3] for b in sg.bounds] == [4] * 5000
    assert sg.edges.where("shard_id <> dst div 4").count() == 0
    assert sg.vinfo.where("shard_id <> id div 4").count() == 0
    assert values(engine.run(sg, programs.in_degree(), EngineOptions(max_iter=1))) == dict.fromkeys(range(n), 1)


def test_ids_out_of_range_belong_to_no_shard(spark):
    rows = [(0, 1, 1), (None, 1, 1), (1, None, 1), (1, -4, 1), (2, 2, None)]
    g = Graph(spark.createDataFrame(rows, "src long, dst long, weight long"), spark.createDataFrame([(0,), (1,), (1,), (2,)], "id long"), "odd")
    sg = prepare.prepare(g, threshold=1)
    assert (sg.n, sg.m) == (3, 2) and sorted((r.src, r.dst) for r in sg.edges.collect()) == [(0, 1), (2, 2)]


def test_shards_hold_each_edge_once(spark, sharded):
    got = sorted((r.src, r.dst, r.weight) for r in sharded.edges.collect())
    assert got == sorted(EDGES)
    csr = prepare.to_csr(sharded.edges, sharded.bounds)
    assert csr.count() == sharded.shards
    assert sorted((r.src, r.dst, r.weight) for r in prepare.from_csr(csr).collect()) == sorted(EDGES)
    assert sorted(r.src for r in prepare.in_neighbors(csr, 0, sharded.bounds).collect()) == [2, 5, 5]
    assert sharded.edges.groupBy("dst").agg({"shard_id": "count"}).count() == len({d for _, d, _ in EDGES})
    again = prepare.open_sharded(spark, sharded.path)
    assert again.bounds == sharded.bounds and again.n == 7 and again.m == 9


def test_csr_offsets_by_hand(spark):
    edges = [(0, 0, 1), (2, 0, 1), (3, 0, 1), (1, 1, 1), (0, 2, 1), (1, 2, 1), (2, 2, 1), (0, 3, 1), (3, 3, 1)]
    row = prepare.to_csr(tiny(spark, edges, 4).edges.withColumn("shard_id", graphs.F.lit(0)), [(0, 0, 3, 9)], weighted=False).first()
    assert row.row == [0, 3, 4, 7, 9] and row.col == [0, 2, 3, 1, 0, 1, 2, 0, 3]


@pytest.mark.parametrize("model", ["pull_window", *MODELS])
def test_every_model_gives_the_same_values(sharded, model):
    opts = EngineOptions(max_iter=10, workers=3)
    pr = values(run_model(model, sharded, programs.pagerank(), opts))
    assert [pr[i] for i in range(7)] == pytest.approx(ref_pagerank(EDGES, 7, 10), abs=1e-12)
    for weighted in (True, False):
        d = values(run_model(model, sharded, programs.sssp((0,), weighted), opts))
        assert [d[i] for i in range(7)] == ref_sssp(EDGES, 7, 0, weighted)


def test_components_and_kernels(spark, sharded):
    sym = prepare.prepare(graphs.symmetrize(sharded.graph), threshold=4)
    want = [0, 0, 0, 3, 3, 0, 6]
    for model in ("pull_window", "bsp_push"):
        got = values(run_model(model, sym, programs.components(), EngineOptions(max_iter=20)))
        assert [got[i] for i in range(7)] == want
    got = values(engine.run_kernel(sym, programs.components(), EngineOptions(max_iter=20)))
    assert [got[i] for i in range(7)] == want
    pr = values(engine.run_kernel(sharded, programs.pagerank(), EngineOptions(max_iter=10)))
    assert [pr[i] for i in range(7)] == pytest.approx(ref_pagerank(EDGES, 7, 10), abs=1e-12)
    d = values(engine.run_kernel(sharded, programs.sssp((0,)), EngineOptions(max_iter=10)))
    assert [d[i] for i in range(7)] == ref_sssp(EDGES, 7)


def test_other_programs(sharded):
    run = lambda p, k=10: values(engine.run(sharded, p, EngineOptions(max_iter=k)))
    assert run(programs.in_degree(), 1) == {0: 3, 1: 1, 2: 2, 3: 1, 4: 2, 5: 0, 6: 0}
    assert run(programs.reachability((3,))) == {0: 0, 1: 0, 2: 0, 3: 1, 4: 1, 5: 0, 6: 0}
    assert run(programs.widest_path(0))[2] == 7
    assert run(programs.label_propagation(), 3)[3] == 3
    assert sum(values(engine.pagerank(sharded, EngineOptions(max_iter=30), dangling="redistribute")).values()) == pytest.approx(1)
    assert values(engine.run(sharded, programs.pagerank(decimal=True), EngineOptions(max_iter=5)))[0] == pytest.approx(ref_pagerank(EDGES, 7, 5)[0], abs=1e-15)
    d = engine.run(sharded, programs.sssp((0,))).values
    assert {r.id: r.parent for r in engine.sssp_parents(sharded, d).collect()} == {1: 0, 2: 1}


def test_scheduling_is_lossless_and_skips(chain):
    full = engine.run(chain, programs.sssp((0,)), EngineOptions(max_iter=12))
    for s in ("selective", "exact", "vertex"):
        r = engine.run(chain, programs.sssp((0,)), EngineOptions(max_iter=12, schedule=s, threshold=1.0))
        assert values(r) == values(full)
        if s != "vertex":
            assert sum(x["shards_read"] for x in r.ledger) < sum(x["shards_read"] for x in full.ledger)
    active = chain.vinfo.where("id < 5")
    exact = {r.shard_id for r in schedule.active_shards_exact(chain.mirror, active).collect()}
    bloom = {r.shard_id for r in schedule.active_shards_bloom(chain.filters, active).collect()}
    assert exact <= bloom


def test_routed_edges_stay_where_they_are(spark, data):
    """No exchange above the edge scan in either mode: what moves are values, by mirror, and the state."""
    sg = prepare.prepare(graphs.part_next(spark, data))
    state = engine.start(sg.vinfo, programs.pagerank(), sg.n)
    for broadcast in (True, False):
        with dealt_by_one_key(spark):
            tree = plans.text(engine.advance(state, engine.pull(sg, sg.edges, state, programs.pagerank(), broadcast), programs.pagerank(), sg.n, None, sg.buckets)).splitlines()
        scan = next(k for k, line in enumerate(tree) if "FileScan" in line and "dst#" in line)
        assert "Bucketed: true" in tree[scan]
        depth, above = tree[scan].index("FileScan"), []
        for line in reversed(tree[:scan]):  # the path from the scan to the root
            at = len(line) - len(line.lstrip(" :+-*()0123456789"))
            if at < depth:
                depth = at
                above.append(line)
        assert not any("Exchange" in line for line in above), above


@pytest.mark.parametrize("name", ["part_next", "event_chain"])
def test_routed_rounds_on_tables(spark, data, name):
    sg = prepare.prepare(graphs.BUILDERS[name](spark, data))
    a, b = (engine.run(sg, programs.pagerank(), EngineOptions(broadcast_rows=k)).values for k in (0, 1 << 20))
    assert engine.compare(a, b).first().max_abs < 1e-12
    with pytest.raises(ValueError):
        engine.run(sg, programs.pagerank(), EngineOptions(broadcast_rows=1, value_mode="broadcast"))


def test_filters_miss_nothing_and_add_little(spark):
    mirror = spark.range(40_000).selectExpr("cast(id % 8 as int) as shard_id", "id as src")
    filters = schedule.build_filters(mirror)
    rows = filters.collect()
    h = spark.range(80_000).selectExpr("id", "xxhash64(id) as h").toPandas()
    for r in rows:
        hit = schedule.probe(h["h"].to_numpy(), r.m, r.k, np.array(r.places), np.array(r.words))
        own = (h["id"] < 40_000) & (h["id"] % 8 == r.shard_id)
        assert hit[own].all() and hit[~own].mean() < 0.02
    assert (schedule.hashes(h["id"].to_numpy()) == h["h"].to_numpy()).all()
    active = spark.range(50_000, 50_003)
    assert schedule.active_shards_bloom(filters, active).count() <= 2
    monkey = schedule.CHUNK
    schedule.CHUNK = 7
    try:
        assert schedule.active_shards_bloom(filters, spark.range(0, 40, 8)).collect()[0].shard_id == 0
    finally:
        schedule.CHUNK = monkey


def test_kernel_skips_shards_without_loss(chain):
    full = engine.run_kernel(chain, programs.sssp((0,)), EngineOptions(max_iter=12))
    for s in ("selective", "exact"):
        r = engine.run_kernel(chain, programs.sssp((0,)), EngineOptions(max_iter=12, schedule=s, threshold=1.0))
        assert values(r) == values(full) and sum(x["shards_read"] for x in r.ledger) < sum(x["shards_read"] for x in full.ledger)


def test_routed_values_equal_broadcast(sharded):
    a = values(engine.run(sharded, programs.pagerank(), EngineOptions(value_mode="routed")))
    assert a == pytest.approx(values(engine.run(sharded, programs.pagerank(), EngineOptions(value_mode="broadcast"))))


@pytest.mark.parametrize("mode", [0, 1, 2, 3, 4, "auto"])
def test_cache_modes(sharded, mode):
    r = engine.run(sharded, programs.pagerank(), EngineOptions(cache=mode, cache_bytes=220))
    assert [values(r)[i] for i in range(7)] == pytest.approx(ref_pagerank(EDGES, 7, 10), abs=1e-12)
    assert all(x["cache_hits"] <= x["shards_read"] for x in r.ledger)


def test_cache_choice_and_codecs():
    assert [cache.choose_mode(s, c) for s, c in ((6.5, 100), (196, 100), (362, 100), (362, 80), (362, 50))] == [1, 2, 3, 4, 4]
    raw = np.arange(1000).tobytes()
    for codec in (*cache.CODECS.values(), *cache.EXTRA):
        assert cache.decompress(cache.compress(raw, codec), codec, len(raw)) == raw
    row, col, val = np.array([0, 2, 3]), np.array([4, 9, 1]), np.array([1, 1, 5])
    for delta in (False, True):
        assert [x.tolist() for x in cache.decode(cache.encode(row, col, val, delta), delta)] == [[0, 2, 3], [4, 9, 1], [1, 1, 5]]


def test_admission_never_exceeds(spark):
    sizes = spark.createDataFrame([(0, 50), (1, 60), (2, 40), (3, 20)], "shard_id int, bytes long")
    assert [r.cached for r in cache.admission(sizes, 100).orderBy("shard_id").collect()] == [True, False, True, False]


def test_visited_shards_prune_buckets(sharded):
    pruned = sharded.edges.where("shard_id in (1)").groupBy("shard_id").count()
    assert f"SelectedBucketsCount: 1 out of {sharded.buckets}" in plans.text(pruned)


def test_edge_graphs(spark):
    for edges, n in (([], 3), ([(0, 0, 1)], 1)):
        sg = prepare.prepare(tiny(spark, edges, n), threshold=5)
        assert len(values(engine.run(sg, programs.pagerank()))) == n
        assert values(engine.run(sg, programs.sssp((0,))))[0] == 0


def test_builders_have_dense_ids(spark, data):
    for name, build in graphs.BUILDERS.items():
        g = build(spark, data)
        n = g.vertices.count()
        row = g.edges.selectExpr("min(src)", "max(src)", "min(dst)", "max(dst)").first()
        assert row[0] is None or (min(row[0], row[2]) >= 0 and max(row[1], row[3]) < n), name
    want = {"part_next": (200, 4276), "word_next": (22646, 56904), "event_chain": (1000, 985), "user_next": (15, 207), "cust_part": (350, 5382), "supp_part": (210, 1905), "page_link": (329, 279)}
    for name, (v, e) in want.items():
        g = graphs.BUILDERS[name](spark, data)
        assert (g.vertices.count(), g.edges.count()) == (v, e), name


def test_weighted_and_personal_pagerank(spark, sharded):
    out = np.zeros(7)
    for s, _, w in EDGES:
        out[s] += w
    v, p = np.full(7, 1 / 7), np.full(7, 1 / 7)
    deg = np.bincount([s for s, _, _ in EDGES], minlength=7)
    for _ in range(10):
        nv, np_ = np.full(7, 0.15 / 7), np.where(np.isin(range(7), [3, 5]), 0.075, 0.0)
        for s, d, w in EDGES:
            nv[d] += 0.85 * v[s] * w / out[s]
            np_[d] += 0.85 * p[s] / deg[s]
        v, p = nv, np_
    got = values(engine.run(sharded, programs.pagerank(weighted=True)))
    assert [got[i] for i in range(7)] == pytest.approx(v.tolist(), abs=1e-12) and sum(got.values()) <= 1 + 1e-12
    got = values(engine.run(sharded, programs.pagerank(seeds={3, 5})))
    assert [got[i] for i in range(7)] == pytest.approx(p.tolist(), abs=1e-12)


def test_tolerance_ends_a_run(sharded):
    r = engine.run(sharded, programs.pagerank(tol=1e-3), EngineOptions(max_iter=200))
    assert r.converged and r.rounds < 60
    assert max(abs(a - b) for a, b in zip(ref_pagerank(EDGES, 7, 300), (values(r)[i] for i in range(7)), strict=True)) < 0.01


def test_greatest_label(spark, sharded):
    sym = prepare.prepare(graphs.symmetrize(sharded.graph), threshold=4)
    got = values(engine.run(sym, programs.components("max"), EngineOptions(max_iter=20)))
    assert [got[i] for i in range(7)] == [5, 5, 5, 4, 4, 5, 6]


def test_a_program_over_arrays(sharded):
    """A user's own update over whole shards: the greatest edge value into each vertex."""

    def update(row, col, val, old, out, lo, n):
        new = old[lo : lo + len(row) - 1].copy()
        for k in range(len(new)):
            new[k] = max([new[k], *val[row[k] : row[k + 1]]])
        return new

    F = graphs.F
    program = ArrowProgram("greatest", lambda n: (F.lit(0).cast("long"), F.lit(True)), update, lambda old, new: new != old)
    r = engine.run_kernel(sharded, program, EngineOptions(max_iter=5))
    assert r.converged and values(r) == {0: 4, 1: 2, 2: 7, 3: 1, 4: 3, 5: 0, 6: 0}


def test_hits(sharded):
    a = np.zeros((7, 7))
    for s, d, _ in EDGES:
        a[s, d] += 1
    hub = np.ones(7)
    for _ in range(4):
        auth = a.T @ hub
        auth /= np.linalg.norm(auth)
        hub = a @ auth
        hub /= np.linalg.norm(hub)
    got = {r.id: (r.hub, r.authority) for r in engine.hits(sharded, 4).collect()}
    assert [got[i][0] for i in range(7)] == pytest.approx(hub.tolist()) and [got[i][1] for i in range(7)] == pytest.approx(auth.tolist())


def test_one_owner_for_each_destination(sharded):
    assert sharded.edges.groupBy("dst").agg(graphs.F.countDistinct("shard_id").alias("k")).where("k > 1").isEmpty()


def test_hybrid_cut_has_hubs(spark, data):
    sg = prepare.prepare(graphs.word_next(spark, data))
    model = MODELS["gas_hybrid"](sg, programs.pagerank(), EngineOptions())
    model.prepare(None)
    plain = MODELS["gas_cut"](sg, programs.pagerank(), EngineOptions())
    plain.prepare(None)
    assert model.made["hubs"] > 0 and 1 < model.replication < plain.replication
    model.close(), plain.close()


def test_counted_records_match_the_formulas_order(sharded):
    """What models read in a round, as counted: sliding windows most, pulled windows least."""
    read = {m: run_model(m, sharded, programs.pagerank(), EngineOptions(max_iter=1)).ledger[-1]["read_bytes"] for m in ("psw", "esg", "vsp", "pull_window")}
    assert read["psw"] == 8 * 7 + 32 * 9 and read["esg"] == 8 * 7 + 16 * 9 and read["pull_window"] == 8 * 9
    assert read["psw"] > read["esg"] > read["vsp"] > read["pull_window"]


def test_filters_are_made_in_the_first_round_where_there_are_none(spark, data):
    g = graphs.event_chain(spark, data)
    plain = prepare.prepare(g, parts=("csr", "mirror"))
    assert plain.filters is None
    r = engine.run(plain, programs.sssp((0,)), EngineOptions(max_iter=4, schedule="selective", threshold=1.0))
    assert r.ledger[0]["phase"] == "fill" and all(x["shards_read"] <= 3 for x in r.ledger)


def test_measures(spark):
    t = spark.createDataFrame([("g", "a", "pull_window", 10, 100, 2.0), ("g", "a", "psw", 10, 100, 5.0)], "graph string, app string, model string, rounds int, edges long, seconds double")
    got = {r.model: (r.edges_s, r.speed_up) for r in cost.speed_ups(cost.edges_per_second(t)).collect()}
    assert got == {"pull_window": (500.0, 1.0), "psw": (200.0, 2.5)}
    ledger = spark.createDataFrame([("r", "m", "a", 1, 5, 4, 1)], "run string, model string, app string, iter int, active long, shards_read int, cache_hits int")
    assert cost.activation(ledger, 10).select("ratio", "miss_ratio").first() == (0.5, 0.75)
