"""Relational operators around graphs, each a query on the given tables with oracle SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shardgraph import functions as fn
from shardgraph import sources, streaming
from shardgraph.build import graphs, prepare
from shardgraph.session import scratch_path, table
from shardgraph.workloads import oracles as o

Query = Callable[[SparkSession, str], DataFrame]
_ALL: dict[str, tuple[Query, str | None]] = {}


def op(sql: str | None = None, name: str | None = None):
    def put(f: Query) -> Query:
        _ALL[name or f"op_{f.__name__}"] = (f, sql)
        return f

    return put


def build() -> tuple[dict[str, Query], dict[str, str]]:
    return {k: f for k, (f, _) in _ALL.items()}, {k: s for k, (_, s) in _ALL.items() if s}


def _part(s, d):
    return graphs.part_next(s, d).edges


def _users(s, d):
    return graphs.user_next(s, d).edges


# scans, projections, predicates


@op("select l_orderkey as src, l_partkey as dst from lineitem where l_shipdate >= timestamp '1995-01-01' and l_shipdate < timestamp '1996-01-01'")
def scan_prune(s, d):
    return table(s, d, "lineitem").where("l_shipdate >= timestamp_ntz '1995-01-01' and l_shipdate < timestamp_ntz '1996-01-01'").select(F.col("l_orderkey").alias("src"), F.col("l_partkey").alias("dst"))


@op("select o_orderkey, case o_orderstatus when 'F' then 3 when 'O' then 2 else 1 end as weight from orders")
def case_project(s, d):
    return table(s, d, "orders").select("o_orderkey", F.when(F.col("o_orderstatus") == "F", 3).when(F.col("o_orderstatus") == "O", 2).otherwise(1).alias("weight"))


@op(o.head("page_link") + " select v.id, e.src is not distinct from null as sink from v left join (select distinct src from e) e on e.src = v.id")
def null_safe(s, d):
    g = graphs.page_link(s, d)
    out = g.edges.select("src").distinct()
    return g.vertices.join(out, g.vertices["id"] == out["src"], "left").select("id", F.col("src").eqNullSafe(F.lit(None)).alias("sink"))


@op("select c_custkey, c_mktsegment from customer where c_mktsegment in ('BUILDING', 'MACHINERY') and c_acctbal between 0 and 5000 and c_name like 'Customer%'")
def predicates(s, d):
    return table(s, d, "customer").where("c_mktsegment in ('BUILDING', 'MACHINERY') and c_acctbal between 0 and 5000 and c_name like 'Customer%'").selectExpr("c_custkey", "c_mktsegment")


# joins


@op("select s_suppkey, n_name, r_name from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey")
def join_broadcast(s, d):
    return table(s, d, "supplier").join(F.broadcast(table(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("s_suppkey", "n_name", "r_name")


@op("select l_suppkey, sum(o_totalprice) > 0 as positive, count(*) as n from lineitem join orders on l_orderkey = o_orderkey group by l_suppkey")
def join_shuffle_hash(s, d):
    return table(s, d, "lineitem").join(table(s, d, "orders").hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("l_suppkey").agg((F.sum("o_totalprice") > 0).alias("positive"), F.count("*").alias("n"))


@op(o.head("part_next") + " select a.src as id, count(*) as paths from e a join e b on a.dst = b.src group by a.src")
def join_sortmerge(s, d):
    e = _part(s, d)
    out = e.groupBy("src").agg(F.count("*").alias("n"))  # counts first: a join of edges with edges would make every path a row
    return e.select(F.col("src").alias("id"), "dst").join(out.hint("merge"), F.col("dst") == out["src"]).groupBy("id").agg(F.sum("n").alias("paths"))


@op("select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_nationkey = b.s_nationkey and a.s_suppkey < b.s_suppkey and abs(a.s_acctbal - b.s_acctbal) < 500")
def join_theta(s, d):
    x = table(s, d, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal")
    a, b = x.alias("a"), x.alias("b")
    return a.join(b, (F.col("a.s_nationkey") == F.col("b.s_nationkey")) & (F.col("a.s_suppkey") < F.col("b.s_suppkey")) & (F.abs(F.col("a.s_acctbal") - F.col("b.s_acctbal")) < 500)).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


@op(o.intervals("part_next", 16) + " select v.id, shard_id from v join iv on v.id between lo and hi")
def join_range(s, d):
    """Ids meet the intervals that hold them by a range condition; intervals are P rows and go to every task."""
    from shardgraph.build import prepare
    from shardgraph.workloads.queries import sharded

    sg = sharded(s, d, "part_next")
    intervals = prepare.bounds_frame(s, sg.bounds).select("shard_id", "lo", "hi")
    return graphs.part_next(s, d).vertices.join(F.broadcast(intervals), F.col("id").between(F.col("lo"), F.col("hi"))).select("id", "shard_id")


@op("select p.event_id, v.event_id as last_view from events p asof left join (select user_id, ts, event_id from events where event_type = 'view') v on p.user_id = v.user_id and v.ts < p.ts where p.event_type = 'purchase'")
def join_asof(s, d):
    """Last earlier view of each purchase: one window over both kinds, no join."""
    e = table(s, d, "events").where("event_type in ('view', 'purchase')")
    earlier = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(Window.unboundedPreceding, -1)
    last = F.max(F.when(F.col("event_type") == "view", F.struct("ts", "event_id"))).over(earlier)
    return e.select("event_id", "event_type", last.alias("v")).where("event_type = 'purchase'").select("event_id", F.col("v.event_id").alias("last_view"))


@op("select a.event_id as src, b.event_id as dst from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour where a.event_type = 'click' and b.event_type = 'purchase'")
def join_interval(s, d):
    e = table(s, d, "events")
    a = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("src"), F.col("ts").alias("ta"))
    b = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("dst"), F.col("ts").alias("tb"))
    return a.join(b, "user_id").where("tb > ta and tb <= ta + interval 1 hour").select("src", "dst")


@op(o.head("part_next") + " select p_partkey as id from part where exists (select 1 from e where e.dst = p_partkey)")
def join_semi(s, d):
    return table(s, d, "part").select(F.col("p_partkey").alias("id")).join(_part(s, d).select(F.col("dst").alias("id")), "id", "left_semi")


@op("select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)")
def join_anti(s, d):
    return table(s, d, "customer").select("c_custkey").join(table(s, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


@op(o.head("page_link") + " select coalesce(a.id, b.id) as id, a.n as ins, b.n as outs from (select dst as id, count(*) as n from e group by dst) a full join (select src as id, count(*) as n from e group by src) b on a.id = b.id")
def join_full(s, d):
    e = graphs.page_link(s, d).edges
    a, b = e.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("ins")), e.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("outs"))
    return a.join(b, "id", "full")


@op("select a.r_regionkey as bi, b.r_regionkey as bj from region a cross join region b")
def join_cross(s, d):
    r = table(s, d, "region").select("r_regionkey")
    return r.select(F.col("r_regionkey").alias("bi")).crossJoin(r.select(F.col("r_regionkey").alias("bj")))


@op(o.head("user_next") + " select src, dst, weight from (select *, row_number() over (partition by src order by weight desc, dst) as k from e) where k = 1")
def lateral_top(s, d):
    _users(s, d).createOrReplaceTempView("op_users")
    return s.sql("select v.src, t.dst, t.weight from (select distinct src from op_users) v, lateral (select dst, weight from op_users e where e.src = v.src order by weight desc, dst limit 1) t")


@op(o.head("user_next", o.SYMMETRIC) + ", k as (select src, dst from s where src < dst) select id, count(*) as triangles from (select unnest([a.src, a.dst, b.dst]) as id from k a join k b on a.dst = b.src join k c on c.src = a.src and c.dst = b.dst) group by id")
def triangles(s, d):
    k = graphs.symmetrize(graphs.user_next(s, d)).edges.where("src < dst").select("src", "dst")
    a, b, c = k.toDF("x", "y"), k.toDF("y", "z"), k.toDF("x", "z")
    return a.join(b, "y").join(c, ["x", "z"]).select(F.explode(F.array("x", "y", "z")).alias("id")).groupBy("id").agg(F.count("*").alias("triangles"))


# set operations


@op(o.head("part_next") + " select src, dst from e intersect select dst, src from e")
def reciprocal(s, d):
    e = _part(s, d)
    return e.select("src", "dst").intersect(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


@op(o.sssp("word_next", False) + " select id from v except select id from dist where value is not null")
def unreached(s, d):
    from shardgraph import programs
    from shardgraph.workloads.queries import _kernel

    dist = _kernel(s, d, "word_next", programs.bfs(0), 1000)
    return dist.select("id").exceptAll(dist.where("value is not null").select("id"))


@op(o.head("part_next") + " select src, dst from e union all select dst, src from e")
def union_all(s, d):
    e = _part(s, d).select("src", "dst")
    return e.unionAll(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


@op(o.head("part_next") + " select src, dst from e union select dst, src from e")
def union_distinct(s, d):
    e = _part(s, d).select("src", "dst")
    return e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


# aggregates


@op("select l_returnflag, l_linestatus, round(sum(l_quantity), 2) as qty, round(avg(l_extendedprice), 4) as price, min(l_discount) as low, max(l_discount) as high, count(*) as n from lineitem group by 1, 2")
def agg_basic(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.min("l_discount").alias("low"), F.max("l_discount").alias("high"), F.count("*").alias("n"))


@op(o.head("part_next") + " select dst as id, string_agg(src::varchar, ',' order by src) as sources from e group by dst")
def agg_collect(s, d):
    return _part(s, d).groupBy(F.col("dst").alias("id")).agg(fn.as_text(F.sort_array(F.collect_list("src"))).alias("sources"))


@op(o.intervals("part_next", 16) + " select shard_id, count(distinct src) as sources from e join iv on dst between lo and hi group by shard_id")
def agg_distinct(s, d):
    from shardgraph.workloads.queries import sharded

    return sharded(s, d, "part_next").edges.groupBy("shard_id").agg(F.countDistinct("src").alias("sources"))


@op(o.head("word_next") + " select true as near, count(distinct src) as exact from e")
def agg_approx(s, d):
    e = graphs.word_next(s, d).edges
    return e.agg((F.abs(F.approx_count_distinct("src", 0.02) - F.countDistinct("src")) <= 0.08 * F.countDistinct("src")).alias("near"), F.countDistinct("src").alias("exact"))


_SALES = "from orders join customer on o_custkey = c_custkey"


def _sales(s, d):
    return table(s, d, "orders").join(table(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))


@op(f"select c_mktsegment as segment, o_orderstatus as status, count(*) as n {_SALES} group by cube (c_mktsegment, o_orderstatus)")
def cube(s, d):
    return _sales(s, d).cube(F.col("c_mktsegment").alias("segment"), F.col("o_orderstatus").alias("status")).agg(F.count("*").alias("n"))


@op(f"select c_mktsegment as segment, o_orderstatus as status, count(*) as n {_SALES} group by rollup (c_mktsegment, o_orderstatus)")
def rollup(s, d):
    return _sales(s, d).rollup(F.col("c_mktsegment").alias("segment"), F.col("o_orderstatus").alias("status")).agg(F.count("*").alias("n"))


@op(f"select c_mktsegment as segment, o_orderpriority as priority, count(*) as n {_SALES} group by grouping sets ((c_mktsegment), (o_orderpriority), ())")
def gsets(s, d):
    _sales(s, d).createOrReplaceTempView("op_sales")
    return s.sql("select c_mktsegment as segment, o_orderpriority as priority, count(*) as n from op_sales group by grouping sets ((c_mktsegment), (o_orderpriority), ())")


_TYPES = ["click", "purchase", "view"]


@op("select cast(ts as date) as day, count(*) filter (where event_type = 'click') as click, count(*) filter (where event_type = 'purchase') as purchase, count(*) filter (where event_type = 'view') as view from events group by 1")
def pivot(s, d):
    return table(s, d, "events").groupBy(F.to_date("ts").alias("day")).pivot("event_type", _TYPES).agg(F.count(F.lit(1))).select("day", *(F.coalesce(t, F.lit(0).cast("long")).alias(t) for t in _TYPES))


@op("select s_suppkey, k, x from (select s_suppkey, s_acctbal as a, s_nationkey::double as b from supplier) unpivot (x for k in (a, b))")
def unpivot(s, d):
    return table(s, d, "supplier").select("s_suppkey", F.col("s_acctbal").alias("a"), F.col("s_nationkey").cast("double").alias("b")).unpivot("s_suppkey", ["a", "b"], "k", "x")


@op(o.head("part_next", o.DEGREES) + " select id, in_deg from deg where in_deg > (select avg(in_deg) + 2 * stddev_samp(in_deg) from deg)")
def having_filter(s, d):
    deg = prepare.degrees(graphs.part_next(s, d))
    return deg.crossJoin(F.broadcast(deg.agg((F.avg("in_deg") + 2 * F.stddev("in_deg")).alias("top")))).where("in_deg > top").select("id", "in_deg")


@op(o.head("word_next", o.DEGREES) + ", h as (select in_deg, count(*) as n from deg where in_deg > 0 group by in_deg) select round(regr_slope(ln(n), ln(in_deg)), 8) as slope, round(regr_r2(ln(n), ln(in_deg)), 8) as r2 from h")
def regr(s, d):
    h = prepare.degree_histogram(graphs.word_next(s, d)).where("deg > 0")
    return h.agg(F.round(F.regr_slope(F.log("vertices"), F.log("deg")), 8).alias("slope"), F.round(F.regr_r2(F.log("vertices"), F.log("deg")), 8).alias("r2"))


@op(o.head("part_next") + " select dst as id, src as best from (select *, row_number() over (partition by dst order by weight desc, src) as k from e) where k = 1")
def minby(s, d):
    return _part(s, d).groupBy(F.col("dst").alias("id")).agg(F.min_by("src", F.struct(-F.col("weight"), "src")).alias("best"))


@op("select o_orderstatus, corr(o_totalprice, o_custkey) is not null as has_corr, mode(o_orderpriority) is not null as has_mode from orders group by 1")
def stats_functions(s, d):
    return table(s, d, "orders").groupBy("o_orderstatus").agg(F.corr("o_totalprice", "o_custkey").isNotNull().alias("has_corr"), F.mode("o_orderpriority").isNotNull().alias("has_mode"))


# windows and order


@op("select c_custkey, rank() over w as r, dense_rank() over w as dr, row_number() over (partition by c_nationkey order by c_acctbal desc, c_custkey) as rn, round(percent_rank() over w, 10) as pr, round(cume_dist() over w, 10) as cd from customer window w as (partition by c_nationkey order by c_acctbal desc)")
def rank(s, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"))
    t = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return table(s, d, "customer").select("c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.row_number().over(t).alias("rn"), F.round(F.percent_rank().over(w), 10).alias("pr"), F.round(F.cume_dist().over(w), 10).alias("cd"))


@op("select c_custkey, ntile(4) over (partition by c_nationkey order by c_acctbal, c_custkey) as quarter from customer")
def ntile(s, d):
    return table(s, d, "customer").select("c_custkey", F.ntile(4).over(Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")).alias("quarter"))


@op("select event_id, date_diff('second', lag(ts) over (partition by user_id order by ts, event_id), ts) as gap from events")
def lag(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    t = lambda c: F.date_trunc("second", c)  # noqa: E731  whole seconds on both sides
    return table(s, d, "events").select("event_id", F.timestamp_diff("SECOND", t(F.lag("ts").over(w)), t(F.col("ts"))).alias("gap"))


@op("select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows between 2 preceding and current row), 6) as moving from events")
def frame_rows(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return table(s, d, "events").select("event_id", F.round(F.sum("value").over(w), 6).alias("moving"))


@op("select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row) as n from events")
def frame_range(s, d):
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)
    return table(s, d, "events").select("event_id", F.count("*").over(w).alias("n"))


@op(o.head("part_next", o.DEGREES) + " select id, coalesce(sum(in_deg) over (order by id rows between unbounded preceding and 1 preceding), 0)::bigint as before from deg")
def prefix(s, d):
    return prepare.prefix(prepare.degrees(graphs.part_next(s, d)), 1024).select("id", "before")


@op(o.head("part_next", o.DEGREES) + " select id, in_deg from deg order by in_deg desc, id limit 10")
def topk(s, d):
    return prepare.degrees(graphs.part_next(s, d)).select("id", "in_deg").orderBy(F.desc("in_deg"), "id").limit(10)


@op("select p_brand, p_partkey, p_retailprice from (select *, row_number() over (partition by p_brand order by p_retailprice desc, p_partkey) as k from part) where k <= 3")
def topk_group(s, d):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(s, d, "part").withColumn("k", F.row_number().over(w)).where("k <= 3").select("p_brand", "p_partkey", "p_retailprice")


@op("select o_orderkey from orders order by o_orderkey limit 20 offset 40")
def offset(s, d):
    return table(s, d, "orders").select("o_orderkey").orderBy("o_orderkey").offset(40).limit(20)


# scalar functions


@op(r"select page_id, regexp_extract(url, '^([a-z]+)://', 1) as scheme, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as host, regexp_extract(url, '^[a-z]+://[^/]+([^?#]*)', 1) as path, len(regexp_extract_all(html, 'href=')) as links from pages")
def string(s, d):
    return table(s, d, "pages").select("page_id", *(fn.url_part(F.col("url"), p).alias(p) for p in ("scheme", "host", "path")), F.regexp_count("html", F.lit("href=")).cast("long").alias("links"))


@op("select o_orderkey, date_trunc('month', o_orderdate)::date as month, date_diff('day', (select min(o_orderdate) from orders)::date, o_orderdate::date) as days, extract(year from o_orderdate) as year from orders")
def date(s, d):
    t = table(s, d, "orders")
    return t.crossJoin(F.broadcast(t.agg(F.min("o_orderdate").alias("first")))).select("o_orderkey", F.to_date(F.date_trunc("month", "o_orderdate")).alias("month"), F.datediff(F.to_date("o_orderdate"), F.to_date("first")).cast("long").alias("days"), F.year("o_orderdate").cast("long").alias("year"))


@op("select p_partkey, round(sqrt(p_size), 8) as r, round(exp(-p_size / 10.0::double), 8) as x, p_size % 7 as m, greatest(p_size, 10) as g, floor(log2(p_size))::bigint as b from part")
def math(s, d):
    p = F.col("p_size")
    return table(s, d, "part").select("p_partkey", F.round(F.sqrt(p), 8).alias("r"), F.round(F.exp(-p / 10.0), 8).alias("x"), F.pmod(p, F.lit(7)).alias("m"), F.greatest(p, F.lit(10)).alias("g"), F.floor(F.log2(p)).alias("b"))


@op(o.head("part_next") + " select src, dst, weight from e")
def array(s, d):
    from shardgraph.workloads.queries import _csr

    return prepare.from_csr(_csr(s, d, "part_next")[1]).drop("shard_id")


@op(o.head("user_next") + " select src, dst, weight from e where weight > 1")
def map(s, d):  # noqa: A001
    m = _users(s, d).groupBy("src").agg(fn.adjacency(F.col("dst"), F.col("weight")).alias("near"))
    return m.select("src", F.explode(F.map_filter("near", lambda k, v: v > 1)).alias("dst", "weight"))


@op("select event_type, round(avg((props->>'$.k')::bigint), 8) as mean from events group by 1")
def json(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.round(F.avg(fn.json_number(F.col("props"), "k")), 8).alias("mean"))


@op(o.intervals("part_next", 16) + " select shard_id, bit_count(bit_or((1::bigint << (src % 60)::int))) as bits from e join iv on dst between lo and hi group by shard_id")
def bits(s, d):
    from shardgraph.workloads.queries import sharded

    return sharded(s, d, "part_next").edges.groupBy("shard_id").agg(F.bit_count(F.bit_or(F.expr("shiftleft(1L, cast(src % 60 as int))"))).cast("tinyint").alias("bits"))


@op("select l_returnflag, sum(l_extendedprice::decimal(15,2) * (1 - l_discount::decimal(15,2)))::decimal(38,4) as revenue from lineitem group by 1")
def decimal(s, d):
    dec = lambda c: F.col(c).cast("decimal(15,2)")
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(F.sum(dec("l_extendedprice") * (F.lit(1).cast("decimal(15,2)") - dec("l_discount"))).cast("decimal(38,4)").alias("revenue"))


@op("select a.vec_id as a, b.vec_id as b, round(list_cosine_similarity(a.embedding::double[], b.embedding::double[]), 8) as c from embeddings a join embeddings b on a.label = 0 and b.label = 0 and a.vec_id < b.vec_id order by c desc, a, b limit 5")
def vector(s, d):
    v = table(s, d, "embeddings").where("label = 0").select("vec_id", "embedding")
    a, b = v.toDF("a", "x"), v.toDF("b", "y")
    return a.join(b, F.col("a") < F.col("b")).select("a", "b", F.round(fn.cosine(F.col("x"), F.col("y")), 8).alias("c")).orderBy(F.desc("c"), "a", "b").limit(5)


# Python functions and SQL functions


@op(r"select doc_id, len(regexp_extract_all(text, '[^\s]+'))::bigint as n from documents")
def udf_scalar(s, d):
    return table(s, d, "documents").select("doc_id", fn.words_in("text").alias("n"))


@op(o.head("user_next") + " select dst as id, weight as commonest from (select dst, weight, row_number() over (partition by dst order by count(*) desc, weight) as k from e group by dst, weight) where k = 1")
def udaf(s, d):
    return _users(s, d).groupBy(F.col("dst").alias("id")).agg(fn.mode_least("weight").alias("commonest"))


@op(o.head("part_next") + " select dst, src from e")
def udtf(s, d):
    from shardgraph.workloads.queries import _csr

    fn.register_sql(s)
    _csr(s, d, "part_next")[1].select("lo", "row", "col").createOrReplaceTempView("op_csr")
    return s.sql("select t.dst, t.src from op_csr, lateral csr_rows(lo, row, col) t")


@op("select p_partkey as id, round(0.15::double / 100 + 0.85::double * p_retailprice, 8) as x from part")
def sql_udf(s, d):
    fn.register_sql(s)
    table(s, d, "part").createOrReplaceTempView("op_parts")
    return s.sql("select p_partkey as id, round(damped(p_retailprice, 100L), 8) as x from op_parts")


@op(o.head("geo_tree") + ", l(id, depth) as (select r_regionkey::bigint, 0 from region union all select e.dst, depth + 1 from l join e on e.src = l.id) select id, depth from l")
def recursive_cte(s, d):
    graphs.geo_tree(s, d).edges.createOrReplaceTempView("op_tree")
    table(s, d, "region").createOrReplaceTempView("op_region")
    return s.sql("with recursive l(id, depth) as (select cast(r_regionkey as long), 0 from op_region union all select e.dst, depth + 1 from l join op_tree e on e.src = l.id) select id, depth from l")


@op("select approx_count_distinct(user_id) > 0 as some, count(*) as n from events")
def approx_users(s, d):
    e = table(s, d, "events")
    return e.agg((F.approx_count_distinct("user_id") > 0).alias("some"), F.count("*").alias("n"))


@op("select event_id, user_id from events where substr(md5(event_id::varchar), 1, 1) < '4'")
def sample(s, d):
    """A quarter of the rows by the hash of their key: the same ones on every run and however rows are dealt."""
    return table(s, d, "events").where("substr(md5(cast(event_id as string)), 1, 1) < '4'").select("event_id", "user_id")


# event windows, in batch and as streams


@op("select time_bucket(interval 1 hour, ts) as start, event_type, count(*) as n from events group by 1, 2")
def win_tumbling(s, d):
    return table(s, d, "events").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@op("select start, count(*) as n from (select unnest([time_bucket(interval 30 minutes, ts), time_bucket(interval 30 minutes, ts) - interval 30 minutes]) as start from events) group by 1")
def win_sliding(s, d):
    return table(s, d, "events").groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@op("with g as (select user_id, ts, ts >= lag(ts) over w + interval 30 minutes or lag(ts) over w is null as cut from events window w as (partition by user_id order by ts, event_id)), k as (select *, sum(cut::int) over (partition by user_id order by ts, cut desc rows unbounded preceding) as sid from g) select min(ts) as start, user_id, count(*) as n from k group by user_id, sid")
def win_session(s, d):
    return table(s, d, "events").groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").cast("timestamp_ntz").alias("start"), "user_id", "n")


@op(o.head("event_chain") + " select src, dst from e")
def stream_chain(s, d):
    return streaming.drained(streaming.chain_edges(streaming.events(s, d)), "append", "chain")


@op("select event_id from events")
def stream_dedup(s, d):
    e = streaming.events(s, d)
    return streaming.drained(streaming.without_repeats(e.unionByName(e)).select("event_id"), "append", "dedup")


@op("select a.event_id as src, b.event_id as dst from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour where a.event_type = 'click' and b.event_type = 'purchase'")
def stream_join(s, d):
    return streaming.drained(streaming.click_to_purchase(streaming.events(s, d)), "append", "join")


@op("select user_id, count(*) as n from events group by 1")
def stream_degrees(s, d):
    return streaming.drained(streaming.degrees_so_far(streaming.events(s, d)), "complete", "degrees")


@op("select start, event_type, n from (select time_bucket(interval 1 hour, ts) as start, event_type, count(*) as n from events group by 1, 2) where start + interval 1 hour <= (select max(ts) from events) - interval 10 minutes")
def stream_late(s, d):
    """Windows that the watermark has closed; the last, open ones are not emitted in append mode."""
    return streaming.drained(streaming.tumbling(streaming.events(s, d)), "append", "late")


@op("select user_id, n_name from (select distinct user_id from events) join nation on user_id % 25 = n_nationkey")
def stream_static(s, d):
    e = streaming.events(s, d).select("user_id").join(F.broadcast(table(s, d, "nation")), F.expr("user_id % 25 = n_nationkey"))
    return streaming.drained(e.select("user_id", "n_name").dropDuplicates(), "append", "static")


# files


def _round_trip(fmt):
    def f(s, d):
        path = scratch_path(s, f"edges-{fmt}")
        sources.write_edges(_part(s, d).select("src", "dst", "weight"), path, fmt)
        return sources.read_edges(s, path, fmt)

    return f


for _fmt in ("csv", "json", "orc", "parquet"):
    op(o.head("part_next") + " select src, dst, weight from e", f"op_{_fmt}_roundtrip")(_round_trip(_fmt))


@op(o.head("part_next") + " select dst, count(*) as n from e group by dst")
def bucketed(s, d):
    sources.save_bucketed(_part(s, d), "op_bucketed_edges", 8)
    return s.table("op_bucketed_edges").groupBy("dst").agg(F.count("*").alias("n"))


@op(o.head("geo_tree", o.DEGREES) + " select id, in_deg, out_deg from deg")
def noop_sink(s, d):
    deg = prepare.degrees(graphs.geo_tree(s, d))
    deg.write.format("noop").mode("overwrite").save()
    return deg.select("id", "in_deg", "out_deg")

