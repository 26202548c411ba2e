"""Prepared graphs for SQL users: views, and each application as one statement, to cross-check small graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardgraph.build.prepare import bounds_frame
from shardgraph.core import engine
from shardgraph.model.graph import EngineOptions, ShardedGraph, VertexProgram


def register(sg: ShardedGraph, name: str) -> None:
    """Temp views <name>_edges, _vertices (with degrees), _shards (intervals) and _sources (distinct sources of each shard)."""
    sg.edges.createOrReplaceTempView(f"{name}_edges")
    sg.vinfo.createOrReplaceTempView(f"{name}_vertices")
    bounds_frame(sg.vinfo.sparkSession, sg.bounds).createOrReplaceTempView(f"{name}_shards")
    sg.mirror.createOrReplaceTempView(f"{name}_sources")


def register_result(sg: ShardedGraph, program: VertexProgram, view: str, opts: EngineOptions = EngineOptions()) -> DataFrame:
    """Run a program and offer its values as a temp view (id, shard_id, value)."""
    out = engine.run(sg, program, opts).values.join(sg.vinfo.select("id", "shard_id"), "id").select("id", "shard_id", "value")
    out.createOrReplaceTempView(view)
    return out


def pagerank_sql(name: str, rounds: int, damping: float = 0.85) -> str:
    """PageRank as one statement: a common table expression a round."""
    parts = [f"n as (select cast(count(*) as double) as n from {name}_vertices)", f"r0 as (select id, out_deg, 1D / n as value from {name}_vertices, n)"]
    for k in range(1, rounds + 1):
        sums = f"select e.dst, sum(r.value / r.out_deg) as s from {name}_edges e join r{k - 1} r on r.id = e.src group by e.dst"
        parts.append(f"r{k} as (select v.id, v.out_deg, {1 - damping!r}D / n + {damping!r}D * coalesce(m.s, 0D) as value from {name}_vertices v cross join n left join ({sums}) m on m.dst = v.id)")
    return "with " + ", ".join(parts) + f" select id, value from r{rounds}"


def sssp_sql(name: str, source: int, weighted: bool = True) -> str:
    """Distances by recursion over paths: for graphs with few paths, such as chains and trees."""
    step = "e.weight" if weighted else "1"
    return f"""with recursive p(id, dist) as (select {source}L, 0L union all select e.dst, cast(p.dist + {step} as bigint) from p join {name}_edges e on e.src = p.id)
        select v.id, d.value from {name}_vertices v left join (select id, min(dist) as value from p group by id) d on d.id = v.id"""


def reached_sql(name: str) -> str:
    """The least id that leads to a vertex, by recursion over paths from each: for forests."""
    return f"""with recursive p(root, id) as (select id, id from {name}_vertices union all select p.root, e.dst from p join {name}_edges e on e.src = p.id)
        select id, min(root) as value from p group by id"""


def run_sql(spark: SparkSession, statement: str) -> DataFrame:
    """The statement's rows; recursion ends where no row is left, not at the session's limits of rows and levels, which
    are read when the rows are asked for."""
    for limit in ("Row", "Level"):
        spark.conf.set(f"spark.sql.cteRecursion{limit}Limit", "-1")
    return spark.sql(statement).select("id", F.col("value"))
