import zlib

import numpy as np
import pytest

from shardgraph.llm import toxicity


def test_trees_learn_an_interaction():
    rng = np.random.default_rng(0)
    x = rng.random((3000, 4))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.3)).astype(float)
    t = toxicity.Trees(trees=80).fit(x[:2000], y[:2000])
    assert np.mean((t.margin(x[2000:]) > 0) == y[2000:]) > 0.95


def test_isotonic_is_the_best_rising_fit():
    rng = np.random.default_rng(2)
    m = np.sort(rng.random(60))
    y = (rng.random(60) < m).astype(float)
    at, p = toxicity.isotonic(m, y)
    assert (np.diff(p) > 0).all() and (np.diff(at) > 0).all()
    # min-max formula of isotonic regression
    want = [max(min(y[i : j + 1].mean() for j in range(k, 60)) for i in range(k + 1)) for k in range(60)]
    assert sorted(set(np.round(want, 9))) == np.round(p, 9).tolist()


def test_disguises():
    r = toxicity.Reader({"idiot": 5.0, "lowe*": 4.0})
    assert r.weight("Idiot!") == 5.0 and r.weight("loweisch") == 4.0 and r.weight("low") == 0
    assert r.describe("1d!ot")[0] == 5.0 and r.describe("i.d.i.o.t")[1] in (0, False)


def test_whole_table_held_out(spark):
    data = "/root/testdata/sf0.1"
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{data}/labels.parquet").collect() if r.toxic is not None}
    rows = toxicity.query(spark, data).collect()
    assert len(rows) == spark.read.parquet(f"{data}/documents.parquet").count()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) and r.predicted == (r.score >= 0.7) and 0 <= r.score <= 1 for r in rows)
    held = [(r.score, r.predicted, labels[r.doc_id]) for r in rows if r.held_out and r.doc_id in labels]
    hit = sum(p for _, p, t in held if t)
    assert hit / sum(t for *_, t in held) > 0.8 and hit / sum(p for _, p, _ in held) > 0.95


def test_query_equals_scoring_each_text(spark, data):
    docs, labels = spark.read.parquet(f"{data}/documents.parquet"), spark.read.parquet(f"{data}/labels.parquet")
    model = toxicity.Model(toxicity.training_rows(docs, labels))
    texts = docs.orderBy("doc_id").collect()
    got = {r.doc_id: r.score for r in toxicity.query(spark, data).collect()}
    assert [got[r.doc_id] for r in texts] == pytest.approx(model.scores([r.text for r in texts]).tolist(), abs=1e-12)


def test_edges(spark):
    docs = spark.createDataFrame([(1, None, 1), (None, "you moron", 1), (2, "", 0), (2, "", 0), (5, "word " * 20000, 0)], "doc_id long, text string, toxic int")
    none = spark.createDataFrame([(None, 1, 1), (7, None, 1)], "doc_id long, toxic int, score int")
    out = toxicity.classify(docs, toxicity.Model(toxicity.training_rows(docs, none))).collect()
    assert len(out) == 5 and all(r.score == 0 and r.predicted == 0 for r in out)
    assert toxicity.classify(docs.limit(0), toxicity.Model([])).count() == 0
