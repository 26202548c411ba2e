"""Edges of CSR shards."""

from shardgraph.build import prepare


def test_edges_of_a_shard_are_walked_once(spark, monkeypatch):
    """No plan slices a shard's arrays for each vertex; parts, empty rows and shards come out whole."""
    monkeypatch.setattr(prepare, "EDGES", 3)
    rows = [(0, 0, 3, [0, 2, 2, 7, 8], [5, 6, 0, 1, 2, 3, 4, 9]), (1, 4, 5, [0, 0, 0], []), (2, 6, 6, [0, 1], [0])]
    csr = spark.createDataFrame(rows, "shard_id int, lo long, hi long, row array<long>, col array<long>")
    out = prepare.from_csr(csr)
    assert "slice" not in out._jdf.queryExecution().toString()
    want = [(s, c, lo + r) for s, lo, _, row, col in rows for r in range(len(row) - 1) for c in col[row[r] : row[r + 1]]]
    assert sorted(map(tuple, out.collect())) == sorted(want)
