"""Vectors of a label meet block by block."""

import numpy as np

from shardgraph.build import graphs


def test_near_vectors_meet_in_blocks(spark, tmp_path, monkeypatch):
    rng = np.random.default_rng(3)
    x = np.round(rng.normal(size=(90, 4)), 1)
    x[7] = 0
    rows = [(i, i % 2 if i % 11 else None, [float(a) for a in v]) for i, v in enumerate(x)]
    rows += [(90, 0, None), (91, 0, [1.0, None, 0.0, 2.0]), (92, 0, [1.0, 2.0]), (93, 0, [2.0, 4.0]), (94, 1, [float("nan")] * 4)]
    spark.createDataFrame(rows, "vec_id long, label int, embedding array<double>").write.parquet(f"{tmp_path}/embeddings.parquet")
    want = set()
    for i, la, a in rows:
        for j, lb, b in rows:
            if i < j and la is not None and la == lb and a and b and len(a) == len(b) and None not in a + b:
                dot = lambda p, q: float(sum((m * n for m, n in zip(p, q)), 0.0))
                if not dot(a, b) < 0.4 * dot(a, a) ** 0.5 * dot(b, b) ** 0.5:
                    want.add((i, j, 1))
    monkeypatch.setattr(graphs, "VECTORS", 8)
    g = graphs.vec_knn(spark, str(tmp_path))
    assert sorted(map(tuple, g.edges.collect())) == sorted(want)
    assert "zip_with" not in g.edges._jdf.queryExecution().toString() and g.vertices.count() == len(rows)
