"""All codecs are measured in one pass over shards that nothing else was prepared for."""

from pyspark.sql import functions as F

from shardgraph import plans
from shardgraph.build import prepare
from shardgraph.core import cache
from shardgraph.workloads import experiments
from shardgraph.workloads import queries as w


def test_codecs_are_measured_in_one_pass(spark, data, monkeypatch):
    monkeypatch.setattr(w, "_READY", {})
    made, real = [], prepare.prepare
    monkeypatch.setattr(prepare, "prepare", lambda g, **kw: made.append(kw.get("parts")) or real(g, **kw))
    out = experiments.compressors(spark, data, ("geo_tree",))
    assert made == [("csr",)] and plans.text(out).count("MapInArrow") == plans.text(cache.payloads(w.shards_only(spark, data, "geo_tree"), "raw")).count("MapInArrow")
    got = {(r.codec, r.delta): (r.raw_bytes, r.bytes, r.ratio) for r in out.collect()}
    assert len(got) == 12
    for (codec, delta), x in got.items():
        one = cache.payloads(w.shards_only(spark, data, "geo_tree"), codec, delta).agg(F.sum("raw_bytes"), F.sum("bytes")).first()
        assert x == (one[0], one[1], round(one[0] / one[1], 4))
    assert {r.codec: r.bytes for r in cache.compression_report(w.shards_only(spark, data, "geo_tree"), delta=True).collect()} == {c: x[1] for (c, d), x in got.items() if d}
