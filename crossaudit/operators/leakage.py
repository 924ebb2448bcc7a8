"""Hits of several leakage methods, their union and strength of evidence, and re-runs without what they name."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def test_hits(pairs: DataFrame, items: DataFrame, method: str) -> DataFrame:
    """``domain, item_id, method, cross_group``: test items of pairs that cross train and test inside one domain."""
    side = lambda k: items.select(F.col("item_id").alias(f"{k}_id"), *[F.col(c).alias(f"{k}_{c}") for c in ("domain", "split", "group_id")])
    rows = pairs.select("left_id", "right_id").join(side("left"), "left_id").join(side("right"), "right_id").where("left_domain = right_domain")
    rows = rows.where("(left_split = 'train' and right_split = 'test') or (left_split = 'test' and right_split = 'train')")
    test = F.when(F.col("left_split") == "test", F.col("left_id")).otherwise(F.col("right_id"))
    hits = rows.select(F.col("left_domain").alias("domain"), test.alias("item_id"), F.lit(method).alias("method"), (F.col("left_group_id") != F.col("right_group_id")).alias("cross"))
    return hits.groupBy("domain", "item_id", "method").agg(F.bool_or("cross").alias("cross_group"))


def leak_union(*hits: DataFrame) -> DataFrame:
    """``domain, item_id, n_methods, methods``: every suspicious test item once, with its evidence; one method alone is weak."""
    every = reduce(DataFrame.unionByName, hits)
    return every.groupBy("domain", "item_id").agg(F.count_distinct("method").alias("n_methods"), F.array_join(F.array_sort(F.collect_set("method")), ",").alias("methods"))


def leak_by_method(*hits: DataFrame) -> DataFrame:
    """``domain, method, n_test_items, cross_group_items``."""
    every = reduce(DataFrame.unionByName, hits)
    return every.groupBy("domain", "method").agg(F.count_distinct("item_id").alias("n_test_items"), F.sum(F.col("cross_group").cast("int")).alias("cross_group_items"))


def rerun_without(items: DataFrame, exclusions: DataFrame, scope: str = "all") -> DataFrame:
    """Items without the excluded ones: everywhere, or in the test split only."""
    marked = items.join(exclusions.select("item_id", F.lit(True).alias("out")).distinct(), "item_id", "left")
    gone = F.coalesce("out", F.lit(False)) & (F.lit(scope == "all") | (F.col("split") == "test"))
    return marked.where(~gone).drop("out")
