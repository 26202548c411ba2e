"""Analytic costs of five computation models and measures of runs."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def delta(v: float, e: float, p: float) -> float:
    """Expected copies of a source over p shards when neighbours are random."""
    return (1 - math.exp(-e / v / p)) * p if v else 0.0


def analytic(c: float, d: float, v: float, e: float, p: float, n: float, theta: float) -> list[tuple[str, float, float, float, float]]:
    """(model, read, write, memory, preprocessing) in bytes a round: c and d are the vertex and edge records,
    p shards, n workers, theta the cache's miss ratio."""
    x, r = delta(v, e, p), math.sqrt(p)
    return [
        ("psw", c * v + 2 * (c + d) * e, c * v + 2 * (c + d) * e, (c * v + 2 * (c + d) * e) / p, (c + 5 * d) * e),
        ("esg", c * v + (c + d) * e, c * v + c * e, c * v / p, 2 * d * e),
        ("vsp", c * (1 + x) * v + d * e, c * v, c * (2 + x) * v / p, 4 * d * e),
        ("dsw", c * r * v + d * e, c * r * v, 2 * c * v / r, 6 * d * e),
        ("pull_window", theta * d * e, 0.0, 2 * c * v + n * d * e / p, 5 * d * e),
    ]


def analytic_frame(spark: SparkSession, *args: float) -> DataFrame:
    rows = [(m, *(round(float(x), 4) for x in xs)) for m, *xs in analytic(*args)]
    return spark.createDataFrame(rows, "model string, read_b double, write_b double, mem_b double, prep_b double")


def totals(ledger: DataFrame) -> DataFrame:
    """(run, model, app, rounds, seconds, read_bytes, write_bytes, shards_read, hits)."""
    return ledger.groupBy("run", "model", "app").agg(F.count("*").alias("rounds"), F.sum("seconds").alias("seconds"), F.sum("read_bytes").alias("read_bytes"), F.sum("write_bytes").alias("write_bytes"), F.sum("shards_read").alias("shards_read"), F.sum("cache_hits").alias("hits"))


def speed_ups(totals: DataFrame, base: str = "pull_window") -> DataFrame:
    """totals(graph, app, model, seconds, ...) with speed_up: how many times the seconds of model `base` each takes."""
    own = totals.where(F.col("model") == base).select("graph", "app", F.col("seconds").alias("_base"))
    return totals.join(own, ["graph", "app"], "left").withColumn("speed_up", F.col("seconds") / F.greatest("_base", F.lit(1e-9))).drop("_base")


def edges_per_second(totals: DataFrame) -> DataFrame:
    """totals(rounds, edges, seconds, ...) with edges_s: edges that rounds pass over in a second."""
    return totals.withColumn("edges_s", F.col("rounds") * F.col("edges") / F.greatest("seconds", F.lit(1e-9)))


def activation(ledger: DataFrame, vertices: int) -> DataFrame:
    """(run, model, app, iter, ratio, shards_read, miss_ratio) by round."""
    return ledger.select("run", "model", "app", "iter", (F.col("active") / F.lit(vertices)).alias("ratio"), "shards_read", ((F.col("shards_read") - F.col("cache_hits")) / F.greatest("shards_read", F.lit(1))).alias("miss_ratio"))
