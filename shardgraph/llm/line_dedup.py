"""Line dedup: lines that many documents share stay in one document only. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import SPACE, ascii_lower, packed, saved

MIN_CHARS, MIN_DOCS = 40, 5


def _rows(docs: DataFrame) -> DataFrame:
    """doc_id, _text and _row, which tells apart different texts under one id."""
    text = F.coalesce("text", F.lit(""))
    return docs.select("doc_id", text.alias("_text"), F.xxhash64(text).alias("_row"))


def shared_lines(docs: DataFrame, min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS) -> tuple[DataFrame, DataFrame]:
    """(lines, shared): every long line's place and 128-bit key, and the keys in min_docs documents or more with the last of these."""
    split = _rows(docs).select("doc_id", "_row", F.posexplode(F.split("_text", "\n")).alias("_pos", "_line"))
    keyed = split.select("doc_id", "_row", "_pos", ascii_lower(F.btrim("_line", F.lit(SPACE))).alias("_key")).where(F.length("_key") >= min_chars)
    lines = saved(keyed.select("doc_id", "_row", "_pos", F.xxhash64("_key").alias("_h"), F.xxhash64(F.lit(1), "_key").alias("_g")), "lines")
    each = lines.groupBy("_h", "_g", "doc_id").agg(F.lit(1).alias("_one"))
    counted = each.groupBy("_h", "_g").agg(F.count("*").alias("_docs"), F.max("doc_id").alias("_last"))
    return lines, saved(counted.where(F.col("_docs") >= min_docs), "shared-lines", few=True)


def dedup_lines(docs: DataFrame, min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS) -> DataFrame:
    """docs with text cleaned, plus _n_lines and _n_dropped.

    A null or empty text is one empty line. A null doc_id counts as one document before all others.
    Rows that repeat are cleaned alike; a document whose lines all go keeps an empty text; an empty
    table gives no rows. Columns of docs stay, whatever their names, but for one named as an added one.

    Line keys and shared keys are written tables, so texts are split once and AQE can split a hot key's join.
    The lines go to their key's counter without text and a shared line's places come back to its
    document, so a text moves once; dropped places cut the line array into runs that are sliced.
    """
    lines, shared = shared_lines(docs, min_chars, min_docs)
    out = lines.join(shared, ["_h", "_g"]).where(~F.col("doc_id").eqNullSafe(F.col("_last")))
    drops = out.groupBy(F.col("doc_id").alias("_id"), F.col("_row").alias("_r")).agg(F.sort_array(F.collect_set("_pos")).alias("_drops"))
    text = F.coalesce("_d.text", F.lit(""))
    both = packed(docs).join(drops, F.col("_d.doc_id").eqNullSafe(F.col("_id")) & (F.xxhash64(text) == F.col("_r")), "left")
    parts = F.split(text, "\n")
    cuts = F.concat(F.array(F.lit(-1)), F.col("_drops"), F.array(F.size(parts)))
    runs = F.transform(F.sequence(F.lit(0), F.size("_drops")), lambda i: F.slice(F.col("_parts"), F.col("_cuts")[i] + 2, F.col("_cuts")[i + 1] - F.col("_cuts")[i] - 1))
    clean = F.when(F.col("_drops").isNull(), text).otherwise(F.array_join(F.flatten(runs), "\n"))
    columns = [clean.alias("text") if c == "text" else F.col(f"_d.`{c}`").alias(c) for c in docs.columns if c not in ("_n_lines", "_n_dropped")]
    return both.withColumns({"_parts": parts, "_cuts": cuts}).select(*columns, F.size("_parts").cast("bigint").alias("_n_lines"), F.coalesce(F.size("_drops"), F.lit(0)).cast("bigint").alias("_n_dropped"))


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return dedup_lines(docs).select("doc_id", F.col("_n_lines").alias("n_lines"), F.col("_n_dropped").alias("n_dropped"), F.sha2("text", 256).alias("kept_sha256"))


ORACLE = r"""
with docs as (select doc_id, coalesce(text, '') as text from documents),
lines as (select doc_id, unnest(string_split(text, chr(10))) as line, generate_subscripts(string_split(text, chr(10)), 1) as pos from docs),
keyed as (select *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as k from lines),
hot as (select k, max(doc_id) as last_id from keyed where length(k) >= 40 group by k having count(distinct doc_id) >= 5),
flagged as (select keyed.doc_id, keyed.pos, keyed.line, hot.k is not null and keyed.doc_id <> hot.last_id as gone from keyed left join hot on keyed.k = hot.k)
select doc_id, count(*) as n_lines, count(*) filter (where gone) as n_dropped,
    sha256(coalesce(string_agg(line, chr(10) order by pos) filter (where not gone), '')) as kept_sha256
from flagged group by doc_id
"""
