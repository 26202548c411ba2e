"""Spark-native iterative graph analytics: interval shards, pull rounds, baselines and their costs."""
