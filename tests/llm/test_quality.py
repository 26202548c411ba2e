import numpy as np

from shardgraph.llm import quality


def test_votes_model_finds_accuracies():
    rng = np.random.default_rng(1)
    bad = rng.random(4000) < 0.2
    k = len(quality.LABELLERS)
    v = np.where(rng.random((4000, k)) < 0.1, 0, np.where(rng.random((4000, k)) < np.where(bad, 0.4, 0.01)[:, None], 2, 1))
    patterns, counts = np.unique((v * 3 ** np.arange(k)).sum(1), return_counts=True)
    post, prob, prior = quality.fit_votes(patterns, counts.astype(float))
    assert abs(prior - 0.2) < 0.03
    assert np.abs(prob[1, :, 2] - 0.36).max() < 0.06 and prob[0, :, 2].max() < 0.03
    got = dict(zip(patterns.tolist(), post, strict=True))
    assert np.mean((np.array([got[x] for x in (v * 3 ** np.arange(k)).sum(1)]) > 0.5) == bad) > 0.95


def test_whole_table_against_labels(spark):
    data = "/root/testdata/sf0.01"
    got = {r.doc_id: r for r in quality.query(spark, data).collect()}
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{data}/labels.parquet").collect() if r.quality is not None}
    good = [got[i].keep for i, q in labels.items() if q == 1]
    bad = [got[i].keep for i, q in labels.items() if q == 0]
    assert np.mean(good) > 0.98 and np.mean(bad) < 0.1


def test_query_equals_scoring_each_text(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    w = quality.fit(quality.read_features(docs))
    want = {r.doc_id: quality.score(r.text, w) for r in docs.collect()}
    got = {r.doc_id: r.score for r in quality.query(spark, data).collect()}
    assert got.keys() == want.keys() and all(abs(got[i] - want[i]) < 1e-9 for i in want)


def test_edges(spark):
    rows = [(1, None, 1), (None, "fine words are here", 2), (2, "", 3), (3, "a b c " * 5000, 4), (3, "a b c " * 5000, 4), (4, "|", 5)]
    df = spark.createDataFrame(rows, "doc_id long, text string, score int")
    out = quality.classify(df).collect()
    assert len(out) == 6 and all(0 <= r._score <= 1 for r in out)
    assert quality.classify(df.limit(0)).count() == 0
    clash = df.withColumnRenamed("score", "_score").selectExpr("*", "'x' as _keep", "1 as _s", "2 as _d")
    kept = quality.good(clash)
    assert kept.columns == clash.columns and {r._score for r in kept.collect()} == {r["score"] for r in out if r._keep}
    assert quality.classify(clash).columns == ["doc_id", "text", "_s", "_d", "_score", "_keep"]
