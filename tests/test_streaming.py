from pyspark.sql import functions as F

from shardgraph import programs, streaming
from shardgraph.build import graphs, prepare
from shardgraph.core import engine
from shardgraph.model import EngineOptions, Graph


def test_grown_shards_are_those_of_one_preparation(spark, data):
    """No edge prepared, all of them streamed: owners, counts, filters and skipping are as if all had been there."""
    whole = graphs.event_chain(spark, data)
    user = prepare.prepare(Graph(whole.edges, whole.vertices, "chain"), threshold=300)
    empty = prepare.prepare(Graph(whole.edges.where("src < 0"), whole.vertices, "chain"), threshold=300, bounds=[b[1] for b in user.bounds], policy="user")
    chain = streaming.chain_edges(streaming.events(spark, data)).selectExpr("src", "dst", "1L as weight")
    grown = streaming.grow_shards(chain, empty)
    assert grown.bounds == user.bounds and (grown.n, grown.m) == (user.n, user.m)
    rows = lambda df: sorted(tuple(r) for r in df.collect())
    assert rows(grown.edges.select("shard_id", "src", "dst")) == rows(user.edges.select("shard_id", "src", "dst"))
    assert rows(grown.mirror.select("shard_id", "src")) == rows(user.mirror.select("shard_id", "src"))
    assert rows(grown.vinfo) == rows(user.vinfo)
    full = engine.run(user, programs.sssp((0,)), EngineOptions(max_iter=12)).values
    skipped = engine.run(grown, programs.sssp((0,)), EngineOptions(max_iter=12, schedule="selective", threshold=1.0)).values
    assert engine.compare(full, skipped).first().differ == 0


def test_closed_windows_are_those_of_the_batch(spark, data):
    batch = {(r.start, r.event_type): r.n for r in spark.read.parquet(f"{data}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.window("ts", "1 hour").start.alias("start"), "event_type").agg(F.count("*").alias("n")).collect()}
    got = {(r.start, r.event_type): r.n for r in streaming.drained(streaming.tumbling(streaming.events(spark, data)), "append", "t").collect()}
    assert got and all(batch[k] == n for k, n in got.items()) and len(batch) - len(got) <= 10


def test_sessions_and_sliding_run(spark, data):
    for f in (streaming.sessions, streaming.sliding):
        assert streaming.drained(f(streaming.events(spark, data)), "append", "s").count() > 0
