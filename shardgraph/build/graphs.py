"""Graphs made from the given tables. Every builder returns dense ids from 0."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shardgraph.build.ids import densify
from shardgraph.model.graph import Graph
from shardgraph.session import saved, spread, table


def _counted(pairs: DataFrame) -> DataFrame:
    return pairs.where("src <> dst").groupBy("src", "dst").agg(F.count("*").alias("weight"))


def part_next(spark: SparkSession, sf: str) -> Graph:
    """Part of a line to the part of its order's next line, weighted by how often."""
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey")
    pairs = table(spark, sf, "lineitem").select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(w).alias("dst"))
    return Graph(_counted(pairs), table(spark, sf, "part").select(F.col("p_partkey").alias("id")), "part_next")


def words(spark: SparkSession, sf: str) -> DataFrame:
    """(doc_id, pos, word) of every document."""
    found = F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), 0)
    return table(spark, sf, "documents").select("doc_id", F.posexplode(found).alias("pos", "word"))


def word_next(spark: SparkSession, sf: str) -> Graph:
    """Word to the next, different word of its document; ids are ranks, in binary order, of words in such pairs."""
    found = F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), 0)
    pairs = spread(table(spark, sf, "documents").select("text")).select(F.explode(F.arrays_zip(F.slice(found, 1, F.greatest(F.size(found) - 1, F.lit(0))).alias("a"), F.slice(found, 2, F.size(found)).alias("b"))).alias("p"))
    counted = saved(pairs.select("p.a", "p.b").where("a <> b").groupBy("a", "b").agg(F.count("*").alias("weight")), "word-pairs")
    ids = densify(counted.select(F.explode(F.array("a", "b")).alias("key")))
    a, b = ids.select(F.col("key").alias("a"), F.col("id").alias("src")), ids.select(F.col("key").alias("b"), F.col("id").alias("dst"))
    return Graph(counted.join(a, "a").join(b, "b").select("src", "dst", "weight"), ids, "word_next")


def event_chain(spark: SparkSession, sf: str, gaps: bool = False) -> Graph:
    """Event to the same user's next event; weight 1 or, with gaps, the seconds between."""
    e = table(spark, sf, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    nxt = e.select(F.col("event_id").alias("src"), F.lead("event_id").over(w).alias("dst"), F.timestamp_diff("SECOND", F.col("ts"), F.lead("ts").over(w)).alias("weight")).where("dst is not null")
    return Graph(nxt if gaps else nxt.withColumn("weight", F.lit(1).cast("long")), e.select(F.col("event_id").alias("id")), "event_chain")


def user_next(spark: SparkSession, sf: str) -> Graph:
    """User of an event to the user of the next event; event ids are dense in time order, so the next is an equi-join."""
    e = table(spark, sf, "events").select("event_id", "user_id")
    nxt = e.select((F.col("event_id") - 1).alias("event_id"), F.col("user_id").alias("dst"))
    ids = densify(e.select(F.col("user_id").alias("key")))
    a, b = ids.select(F.col("key").alias("user_id"), F.col("id").alias("src")), ids.select(F.col("key").alias("dst_key"), F.col("id").alias("dst"))
    pairs = e.join(nxt.withColumnRenamed("dst", "dst_key"), "event_id").join(a, "user_id").join(b, "dst_key").select("src", "dst")
    return Graph(_counted(pairs), ids, "user_next")


def cust_part(spark: SparkSession, sf: str) -> Graph:
    """Customer to part bought; parts come after the customers."""
    c, p = table(spark, sf, "customer"), table(spark, sf, "part")
    off = c.agg(F.count("*").alias("off"))
    bought = table(spark, sf, "orders").join(table(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    pairs = bought.crossJoin(F.broadcast(off)).select(F.col("o_custkey").alias("src"), (F.col("l_partkey") + F.col("off")).alias("dst"))
    ids = c.select(F.col("c_custkey").alias("id")).union(p.crossJoin(F.broadcast(off)).select(F.col("p_partkey") + F.col("off")))
    return Graph(_counted(pairs), ids, "cust_part")


def supp_part(spark: SparkSession, sf: str) -> Graph:
    """Supplier to part; parts come after the suppliers."""
    s, p = table(spark, sf, "supplier"), table(spark, sf, "part")
    off = s.agg(F.count("*").alias("off"))
    pairs = table(spark, sf, "lineitem").crossJoin(F.broadcast(off)).select(F.col("l_suppkey").alias("src"), (F.col("l_partkey") + F.col("off")).alias("dst"))
    ids = s.select(F.col("s_suppkey").alias("id")).union(p.crossJoin(F.broadcast(off)).select(F.col("p_partkey") + F.col("off")))
    return Graph(_counted(pairs), ids, "supp_part")


def page_urls(spark: SparkSession, sf: str) -> DataFrame:
    """(url, target): each link of each page, a relative one completed with the page's scheme and host."""
    href = F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), 1)).alias("href")
    host = F.regexp_extract("url", r"^(https?://[^/]+)", 1)
    links = table(spark, sf, "pages").select("url", host.alias("host"), href)
    full = F.when(F.col("href").rlike("^https?://"), F.col("href")).when(F.col("href").startswith("/"), F.concat("host", "href")).otherwise(F.concat("host", F.lit("/"), "href"))
    return links.select("url", full.alias("target"))


def page_link(spark: SparkSession, sf: str) -> Graph:
    """Page to the urls it links to; ids are ranks of the urls in binary order."""
    links = page_urls(spark, sf)
    ids = densify(table(spark, sf, "pages").select(F.col("url").alias("key")).union(links.select("target")))
    a, b = ids.select(F.col("key").alias("url"), F.col("id").alias("src")), ids.select(F.col("key").alias("target"), F.col("id").alias("dst"))
    return Graph(_counted(links.join(a, "url").join(b, "target").select("src", "dst")), ids, "page_link")


def geo_tree(spark: SparkSession, sf: str) -> Graph:
    """Region to nation to customer and supplier: a forest whose ids follow each other table by table."""
    r, n, c, s = (table(spark, sf, t) for t in ("region", "nation", "customer", "supplier"))
    offs = r.agg(F.count("*").alias("nr")).crossJoin(n.agg(F.count("*").alias("nn"))).crossJoin(c.agg(F.count("*").alias("nc")))
    at = lambda df: df.crossJoin(F.broadcast(offs))
    nat, cus, sup = at(n), at(c), at(s)
    nation_id = F.col("nr") + F.col("n_nationkey")
    edges = (
        nat.select(F.col("n_regionkey").cast("long").alias("src"), nation_id.alias("dst"))
        .union(cus.select(F.col("nr") + F.col("c_nationkey"), F.col("nr") + F.col("nn") + F.col("c_custkey")))
        .union(sup.select(F.col("nr") + F.col("s_nationkey"), F.col("nr") + F.col("nn") + F.col("nc") + F.col("s_suppkey")))
    )
    ids = r.select(F.col("r_regionkey").cast("long").alias("id")).union(edges.select("dst"))
    return Graph(edges.withColumn("weight", F.lit(1).cast("long")), ids, "geo_tree")


def turn_chain(spark: SparkSession, sf: str) -> Graph:
    """Turn to the next turn of its conversation; ids are ranks by conversation and turn."""
    c = table(spark, sf, "conversations").select("conv_id", "turn").distinct()
    ids = densify(c.select(F.struct("conv_id", "turn").alias("key")))
    own = ids.select(F.col("key.conv_id").alias("conv_id"), F.col("key.turn").alias("turn"), "id")
    w = Window.partitionBy("conv_id").orderBy("turn")
    edges = own.select(F.col("id").alias("src"), F.lead("id").over(w).alias("dst")).where("dst is not null").withColumn("weight", F.lit(1).cast("long"))
    return Graph(edges, own.select("id"), "turn_chain")


def doc_dup(spark: SparkSession, sf: str) -> Graph:
    """Documents that share a normalised line of 40 characters or more, as stars around the least of them."""
    d = table(spark, sf, "documents")
    lines = d.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.lower(F.trim("line")).alias("line")).where(F.length("line") >= 40)
    least = lines.groupBy("line").agg(F.min("doc_id").alias("src"))
    edges = lines.join(least, "line").where("doc_id <> src").select("src", F.col("doc_id").alias("dst")).distinct().withColumn("weight", F.lit(1).cast("long"))
    return Graph(edges, d.select(F.col("doc_id").alias("id")), "doc_dup")


#: Vectors of a label that meet as one block, about.
VECTORS = 2000


def _lengths(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Row by row x * y, added up from left to right: what decides where the product of matrices is too near a bound to tell."""
    out = np.zeros(len(x))
    for k in range(x.shape[1]):
        out = x[:, k] * y[:, k] + out
    return out


def _near(t: pa.Table, cosine: float) -> pa.Table:
    """(src, dst) of the pairs of two blocks, or inside one, whose cosine reaches the bound."""
    lo, hi = t["lo"][0].as_py(), t["hi"][0].as_py()
    flat, own, ids = t["e"].combine_chunks().flatten().to_numpy(), t["block"].to_numpy(), t["vec_id"].to_numpy()
    x = flat.reshape(len(ids), t["size"][0].as_py())
    norm = np.sqrt(_lengths(x, x))
    left, right = np.flatnonzero(own == lo), np.flatnonzero(own == hi)
    pairs = []
    for at in range(0, len(left), VECTORS):  # a block of a hot hash is no larger a matrix
        i = left[at : at + VECTORS]
        for to in range(0, len(right), VECTORS):
            j = right[to : to + VECTORS]
            with np.errstate(invalid="ignore", over="ignore"):
                dot, size = x[i] @ x[j].T, norm[i][:, None] * norm[j]
                p, q = np.nonzero(~(dot < (cosine - 1e-9) * size))
            p, q = i[p], j[q]
            ordered = ids[p] < ids[q] if lo == hi else ids[p] != ids[q]
            p, q = p[ordered], q[ordered]
            with np.errstate(invalid="ignore", over="ignore"):
                exact = _lengths(x[p], x[q])
                keep = ~(exact < cosine * norm[p] * norm[q])
            pairs.append((np.minimum(ids[p], ids[q])[keep], np.maximum(ids[p], ids[q])[keep]))
    src, dst = (np.concatenate(c) if pairs else np.zeros(0, np.int64) for c in (zip(*pairs, strict=True) if pairs else ((), ())))
    return pa.table({"src": pa.array(src, pa.int64()), "dst": pa.array(dst, pa.int64())})


def vec_knn(spark: SparkSession, sf: str, cosine: float = 0.4) -> Graph:
    """Vectors of one label whose cosine reaches a bound, one that occurs in the given tables.

    Every pair inside a label is compared: its vectors are dealt to blocks, of which every two meet in a task as a product
    of matrices; pairs that reach the bound, or come near it, are computed again in one order of additions.
    """
    v = table(spark, sf, "embeddings").select("vec_id", "label", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    whole = v.where("vec_id is not null and label is not null and e is not null and forall(e, x -> x is not null)").withColumn("size", F.size("e"))
    blocks = whole.groupBy("label", "size").agg(F.ceil(F.count("*") / VECTORS).alias("blocks"))
    dealt = whole.join(F.broadcast(blocks), ["label", "size"]).withColumn("block", F.pmod(F.xxhash64("vec_id"), "blocks"))
    met = dealt.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    met = met.select("label", "size", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), "block", "vec_id", "e")
    near = met.groupBy("label", "size", "lo", "hi").applyInArrow(lambda t: _near(t, cosine), "src long, dst long")
    return Graph(near.withColumn("weight", F.lit(1).cast("long")), v.select(F.col("vec_id").alias("id")), "vec_knn")


BUILDERS = {f.__name__: f for f in (part_next, word_next, event_chain, user_next, cust_part, supp_part, page_link, geo_tree, turn_chain, doc_dup, vec_knn)}


def symmetrize(g: Graph) -> Graph:
    """Both directions of every edge, once, with the lesser weight."""
    e = g.weighed()
    both = e.select("src", "dst", "weight").union(e.select(F.col("dst"), F.col("src"), "weight"))
    return Graph(both.groupBy("src", "dst").agg(F.min("weight").alias("weight")), g.vertices, f"{g.name}_sym", directed=False)
