import os
import sys

import duckdb
import pytest

sys.path.insert(0, os.path.dirname(__file__))
from test_packing import check  # noqa: E402

import corpus_pipeline  # noqa: E402
from shardgraph.llm import line_dedup, mixing, quality  # noqa: E402


def grams(t):
    w = (t or "").encode().lower().split()
    return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()


def groups(rows):
    sets = [grams(r.text) for r in rows]
    up = list(range(len(rows)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] == sets[j] or len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                up[max(find(i), find(j))] = min(find(i), find(j))
    return [find(i) for i in range(len(rows))]


def test_each_stage_against_brute_force(spark, data, tmp_path):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    seen = {}
    at = docs
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, at, data).write.parquet(f"{tmp_path}/{name}")
        seen[name] = (at, at := spark.read.parquet(f"{tmp_path}/{name}"))
    assert all(out.columns == docs.columns for name, (_, out) in seen.items() if name != "packing")

    before, after = seen["quality_classifier"]
    w = quality.fit(quality.read_features(before))
    assert {r.doc_id for r in after.collect()} == {r.doc_id for r in before.collect() if quality.score(r.text, w) >= quality.KEEP}

    before, after = seen["line_dedup"]
    con = duckdb.connect()
    con.register("documents", before.toPandas())
    want = {r[0]: r[3] for r in con.sql(line_dedup.ORACLE).fetchall()}
    import hashlib

    assert {r.doc_id: hashlib.sha256(r.text.encode()).hexdigest() for r in after.collect()} == want
    assert all(r.n_chars == len(r.text) for r in after.collect())

    before, after = seen["simhash_dedup"]
    rows = before.orderBy("doc_id").collect()
    least = {g: r.doc_id for r, g in reversed(list(zip(rows, groups(rows), strict=True)))}
    assert {r.doc_id for r in after.collect()} == set(least.values())

    before, after = seen["source_mixing"]
    copies = {r.doc_id: r._copies for r in mixing.mix(before).collect()}
    got = {r.doc_id: r["count"] for r in after.groupBy("doc_id").count().collect()}
    assert got == {i: n for i, n in copies.items() if n}

    before, after = seen["packing"]
    assert check([(r.doc_id, r.text) for r in before.collect()], after.collect(), 4096) == 0


def test_run_is_the_stages_in_turn(spark, data):
    assert corpus_pipeline.run(spark, data).count() > 0


@pytest.mark.parametrize("rows", [[], [(None, None, None, None, None), (1, "a b", "en", None, 3), (1, "a b", "en", None, 3)]])
def test_edges(spark, rows):
    at = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES:
        at = stage(spark, at, "")
    at.collect()
