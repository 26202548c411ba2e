"""Statements end where no row is left."""

from shardgraph.functions import facade
from shardgraph.workloads import queries as w


def test_recursion_has_no_limit_of_rows(spark, data):
    spark.conf.set("spark.sql.cteRecursionRowLimit", "50")
    try:
        assert w._facade(spark, data, "geo_tree", facade.reached_sql("sg_geo_tree")).count() == w.sharded(spark, data, "geo_tree").n
    finally:
        spark.conf.unset("spark.sql.cteRecursionRowLimit")
