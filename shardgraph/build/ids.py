"""Dense ids without a single-task sort."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shardgraph.session import saved


def densify(keys: DataFrame) -> DataFrame:
    """(key, id) for the distinct values of keys.key, ids their ranks from 0.

    Keys are dealt by range and written, which fixes the ranges; a rank is the count of keys in
    earlier ranges (one row a range is summed in one task) plus the row number inside its own.
    """
    ranged = saved(keys.select("key").distinct().repartitionByRange("key").withColumn("_p", F.spark_partition_id()), "keys")
    before = Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    offsets = ranged.groupBy("_p").agg(F.count("*").alias("_n")).select("_p", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_off"))
    inside = F.row_number().over(Window.partitionBy("_p").orderBy("key")) - 1
    return saved(ranged.join(F.broadcast(offsets), "_p").select("key", (F.col("_off") + inside).alias("id")), "ids")
