import math

import numpy as np
import pytest

from shardgraph.llm import embeddings as em


def brute(rows):
    def sound(label, e):
        return label is not None and e and all(x is not None and math.isfinite(x) for x in e) and any(e)

    ok = [k for k, (_, e, lab) in enumerate(rows) if sound(lab, e)]
    up, n = list(range(len(rows))), [0] * len(rows)

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for x, i in enumerate(ok):
        for j in ok[:x]:
            a, b = (np.array(rows[k][1], np.float64) for k in (i, j))
            if rows[i][2] == rows[j][2] and len(a) == len(b) and a @ b / np.linalg.norm(a) / np.linalg.norm(b) >= 0.98:
                n[i] += 1
                n[j] += 1
                up[max(find(i), find(j))] = min(find(i), find(j))
    least = {}
    for k, (v, _, _) in enumerate(rows):
        least[find(k)] = min((x for x in (v, least.get(find(k))) if x is not None), default=None)
    return sorted(((v, n[k], least[find(k)], v == least[find(k)]) for k, (v, _, _) in enumerate(rows)), key=str)


@pytest.mark.parametrize("dim,cosine", [(64, 0.9), (64, 0.98), (100, 0.98), (3, 0.98)])
def test_estimates_are_unbiased_and_bounded(dim, cosine):
    rng = np.random.default_rng(1)
    v, q = (x / np.linalg.norm(x) for x in rng.standard_normal((2, dim)))
    q = cosine * v + np.sqrt(1 - cosine**2) * (q - (q @ v) * v) / np.linalg.norm(q - (q @ v) * v)
    est = []
    for k in range(400):
        signs, f = em.encode(v[None], k)
        turned = q[None].astype(np.float32) @ em.rotation(dim, k).T
        planes, low, step, total = em.query_planes(turned)
        est.append(float(em.estimate(em.words(signs), f, em.words(planes), low, step, total, dim)[0]))
        assert est[-1] >= cosine - em.half_width(f, step, dim, cosine)[0]
    assert np.mean(est) == pytest.approx(cosine, abs=4 * np.std(est) / 20 + 0.01)


def planted(groups=60, dim=64):
    """Groups around a centre, with cosines between members on both sides of the threshold."""
    rng = np.random.default_rng(7)
    rows = []
    for g in range(groups):
        c = rng.standard_normal(dim)
        for _ in range(6):
            x = rng.standard_normal(dim)
            x -= (x @ c) / (c @ c) * c
            rows.append((len(rows), (c / np.linalg.norm(c) + rng.uniform(0.05, 0.2) * x / np.linalg.norm(x)).tolist(), g % 3))
    return rows


def test_planted_pairs_are_found(spark):
    rows = planted()
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    want = brute(rows)
    assert sum(r[1] for r in want) > 500 and any(r[1] == 0 for r in want)
    assert sorted((tuple(r) for r in em.near_vectors(df).collect()), key=str) == want


def test_the_bound_spares_exact_products(spark, monkeypatch):
    rng = np.random.default_rng(3)
    rows = [(k, rng.standard_normal(64).tolist(), 0) for k in range(3000)] + [(3000 + i, e, 0) for i, e, _ in planted(3)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    u = em._units(np.array([r[1] for r in rows]))
    signs, f = em.encode(u)
    planes, low, step, total = em.query_planes(u.astype(np.float32) @ em.rotation(64, 0).T)
    i, j = np.triu_indices(len(rows), 1)
    i, j = i[::50], j[::50]
    open_ = em.estimate(em.words(signs)[i], f[i], em.words(planes)[j], low[j], step[j], total[j], 64) >= 0.98 - em.half_width(f[i], step[j], 64, 0.98)
    assert open_.mean() < 0.001  # nearly no pair of strangers is recomputed
    assert len([r for r in em.near_vectors(df, bits=8, bands=20).collect() if r.n_links]) == len([r for r in brute([r for r in rows if r[0] >= 3000]) if r[1]])


@pytest.mark.parametrize("block", [20000, 16])
def test_whole_table(spark, data, block):
    t = spark.read.parquet(f"{data}/embeddings.parquet")
    rows = [(r.vec_id, r.embedding, r.label) for r in t.collect()]
    assert sorted((tuple(r) for r in em.near_vectors(t, block=block).collect()), key=str) == brute(rows)


def test_edges(spark):
    rng = np.random.default_rng(2)
    v = rng.standard_normal(8).tolist()
    near = (np.array(v) * 3 + 0.01).tolist()
    far = (-np.array(v)).tolist()
    rows = [(1, v, 0), (2, v, 0), (2, v, 0), (3, near, 0), (4, far, 0), (5, v, 1), (6, v, None), (7, None, 0), (8, [0.0] * 8, 0), (9, [], 0), (10, [float("nan")] * 8, 0), (11, [None, *v[1:]], 0), (12, [float("inf"), *v[1:]], 0), (None, near, 0), (13, v[:4], 0), (14, v[:4], 0), (15, [1e300] * 8, 2), (16, [1e-300] * 8, 2)]
    df = spark.createDataFrame([(*r, 5) for r in rows], "vec_id long, embedding array<double>, label int, node int")
    assert sorted((tuple(r) for r in em.near_vectors(df).collect()), key=str) == brute([r if r[0] not in (15, 16) else (r[0], [1.0] * 8, 2) for r in rows])
    assert em.near_vectors(df.limit(0)).count() == 0


def test_query_equals_sql(spark, data):
    import duckdb

    con = duckdb.connect()
    con.execute(f"create view embeddings as select * from read_parquet('{data}/embeddings.parquet')")
    r = con.sql(em.ORACLE)
    assert r.columns == ["vec_id", "n_links", "component_id", "kept"]
    assert sorted((tuple(x) for x in em.query(spark, data).collect()), key=str) == sorted(r.fetchall(), key=str)
