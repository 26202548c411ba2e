"""Mixing sources to target weights: repetition rates and hash-seeded Bernoulli copies."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import own, packed, saved, with_index

WORD = r"[^\x20\x09-\x0D]+"
#: How often a source may repeat at most, and how many hash seeds a source chooses from.
MAX_RATE, SEEDS = 3, 16


def draw(doc_id: Column, seed: int) -> Column:
    """A uniform number in [0, 1) that depends on the document's id and the seed only."""
    text = F.concat_ws(":", F.coalesce(doc_id.cast("string"), F.lit("null")), F.lit(str(seed // 4)))
    return F.conv(F.substring(F.md5(text), 1 + 8 * (seed % 4), 8), 16, 10).cast("bigint") / F.lit(4294967296.0)


def water_level(sources: DataFrame, total: int) -> float:
    """The words a weight of 1 gets once sources at their limit have left the sharing.

    sources has size and weight. A source is at its limit when MAX_RATE * size < level * weight;
    the level only rises, so each round is one aggregate over the sources and one row to the driver.
    """
    level = 0.0
    while True:
        full = F.lit(MAX_RATE) * F.col("size") < F.lit(level) * F.col("weight")
        row = sources.agg(F.sum(F.when(full, MAX_RATE * F.col("size"))).alias("fixed"), F.sum(F.when(~full, F.col("weight"))).alias("w")).first()
        if not row["w"]:
            return level
        new = (total - (row["fixed"] or 0)) / row["w"]
        if new <= level:
            return level
        level = new


def mix(docs: DataFrame) -> DataFrame:
    """docs plus _size, _source_size, _target, _copies: how often the mix takes each document.

    Sources in code point order, null last (a source of its own), weigh 1, 2, 3, 1, 2, 3, ...; they
    share the corpus' words by weight, none above MAX_RATE times its own. A document comes
    floor(rate) times and once more if its draw is below the fraction. Each source uses the seed, of
    SEEDS, whose total is nearest its target (ties: the least seed), so small sources come near too.
    Null texts have no words; a null doc_id draws as one id; equal rows draw alike; an empty table
    gives no rows. Columns of docs stay, whatever their names, but for one named as an added one.
    """
    t = packed(docs).withColumn("_size", F.coalesce(F.regexp_count("_d.text", F.lit(WORD)).cast("bigint"), F.lit(0)))
    sized = saved(t.select("_d.doc_id", "_d.source", "_size"), "mix-sizes")
    by = sized.groupBy("source").agg(F.sum("_size").alias("size"))
    src = saved(with_index(by, [F.col("source").asc_nulls_last()], "_i").select("source", "size", (F.col("_i") % 3 + 1).alias("weight")), "mix-sources", few=True)
    total = src.agg(F.sum("size")).first()[0] or 0
    level = water_level(src, total)
    target = F.least(F.lit(MAX_RATE) * F.col("size").cast("double"), F.lit(level) * F.col("weight"))
    rates = src.select(F.col("source").alias("_source"), F.col("size").alias("_source_size"), target.alias("_target"))
    rates = rates.withColumn("_rate", F.when(F.col("_source_size") > 0, F.col("_target") / F.col("_source_size")).otherwise(0.0))
    rates = rates.withColumn("_times", F.floor("_rate")).withColumn("_part", F.col("_rate") - F.floor("_rate"))
    same = F.col("source").eqNullSafe(F.col("_source"))
    drawn = sized.join(rates, same)
    sums = drawn.groupBy("_source").agg(F.first("_target").alias("t"), F.first(F.col("_times") * F.col("_source_size")).alias("base"), *(F.coalesce(F.sum(F.when(draw(F.col("doc_id"), k) < F.col("_part"), F.col("_size"))), F.lit(0)).alias(f"s{k}") for k in range(SEEDS)))
    off = F.array(*(F.abs(F.col("base") + F.col(f"s{k}") - F.col("t")) for k in range(SEEDS)))
    seeds = sums.select("_source", (F.array_position(off, F.array_min(off)) - 1).alias("_seed"))
    chosen = saved(rates.join(seeds.withColumnRenamed("_source", "_s"), F.col("_source").eqNullSafe(F.col("_s"))).drop("_s"), "mix-rates", few=True)
    u = F.coalesce(*(F.when(F.col("_seed") == k, draw(F.col("_d.doc_id"), k)) for k in range(SEEDS)))
    out = t.join(chosen, F.col("_d.source").eqNullSafe(F.col("_source"))).withColumn("_copies", (F.col("_times") + F.when(u < F.col("_part"), 1).otherwise(0)).cast("bigint"))
    added = ("_size", "_source_size", "_target", "_copies")
    return out.select(*own(docs, added), *added)


def mixed(docs: DataFrame) -> DataFrame:
    """The documents of the mix themselves, each as often as it is taken."""
    n = docs.columns
    taken = mix(packed(docs).select("_d.doc_id", "_d.text", "_d.source", "_d")).where("_copies > 0")
    return taken.select("_d", F.explode(F.sequence(F.lit(1), F.col("_copies").cast("int"))).alias("_copy")).select(*own(docs)).select(*n)


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source")
    return mix(docs).select("doc_id", F.col("_size").alias("size"), F.col("_source_size").alias("source_size"), F.col("_target").alias("target"), (F.col("_copies") * F.col("_size")).alias("taken"))


_U = "cast('0x' || substr(md5(coalesce(cast(doc_id as varchar), 'null') || ':' || '{b}'), {o}, 8) as bigint) / 4294967296.0::double"
_DRAWS = ", ".join(_U.format(b=k // 4, o=1 + 8 * (k % 4)) + f" as u{k}" for k in range(SEEDS))
_SUMS = ", ".join(f"abs(any_value(times * source_size) + coalesce(sum(case when u{k} < part then size end), 0) - any_value(target)) as d{k}" for k in range(SEEDS))
ORACLE = rf"""
with sized as (select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size from documents),
by_source as (select source, sum(size)::bigint as source_size from sized group by source),
weighed as (select *, (row_number() over (order by source nulls last) - 1) % 3 + 1 as weight from by_source),
filling as (select *, sum(source_size) over () as total,
    sum(3 * source_size) over w as fixed_before, sum(weight) over () - coalesce(sum(weight) over w, 0) as weight_left, row_number() over (order by 3 * source_size / weight, source) as k
    from weighed window w as (order by 3 * source_size / weight, source rows between unbounded preceding and 1 preceding)),
levels as (select min_by((total - coalesce(fixed_before, 0))::double / weight_left::double, k) as lvl from filling where (total - coalesce(fixed_before, 0))::double / weight_left::double * weight <= 3 * source_size),
rates as (select source, source_size, least(3.0::double * source_size, lvl * weight) as target from weighed, levels),
parts as (select *, case when source_size > 0 then floor(target / source_size) else 0 end as times, case when source_size > 0 then target / source_size - floor(target / source_size) else 0 end as part from rates),
drawn as (select s.doc_id, s.size, p.*, {_DRAWS} from sized s join parts p on s.source is not distinct from p.source),
sums as (select source, {_SUMS} from drawn group by source),
seeds as (select source, list_position([{", ".join(f"d{k}" for k in range(SEEDS))}], least({", ".join(f"d{k}" for k in range(SEEDS))})) as seed from sums)
select d.doc_id, d.size, d.source_size::bigint as source_size, d.target,
    (d.size * (d.times + case when [{", ".join(f"u{k}" for k in range(SEEDS))}][seed] < d.part then 1 else 0 end))::bigint as taken
from drawn d join seeds on d.source is not distinct from seeds.source
"""
