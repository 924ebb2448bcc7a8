"""Group-stratified splits."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crossaudit.operators.ranks import running


def group_split(items: DataFrame, fractions: tuple[float, float] = (0.69, 0.845), seed: int = 42) -> DataFrame:
    """Items with ``split``; a group is never cut.

    Inside (domain, majority class) groups are ordered by a hash, and a group falls where the share of items before it lies.
    Sums run over groups, not items, in two levels.
    """
    per = items.groupBy("domain", "group_id", "class").agg(F.count(F.lit(1)).alias("n"))
    groups = per.groupBy("domain", "group_id").agg(F.sum("n").alias("n"), F.min(F.struct((-F.col("n")).alias("m"), "class"))["class"].alias("cls"))
    digest = F.md5(F.concat_ws(":", F.lit(str(seed)), "domain", "group_id").cast("binary"))
    groups = running(groups, ["domain", "cls"], digest, "group_id", F.col("n")).withColumn("share", F.col("before") / F.col("total"))
    split = F.when(F.col("share") < fractions[0], "train").when(F.col("share") < fractions[1], "val").otherwise("test")
    return items.join(groups.select("domain", "group_id", split.alias("split")), ["domain", "group_id"])


def split_violations(items: DataFrame) -> DataFrame:
    """Groups that stand in several splits."""
    return items.groupBy("domain", "group_id").agg(F.count_distinct("split").alias("n_splits")).where("n_splits > 1")


def group_profile(items: DataFrame) -> DataFrame:
    """``domain, n_groups, n_items, max_size, median_size, multi_share``."""
    sizes = items.groupBy("domain", "group_id").agg(F.count(F.lit(1)).alias("n"))
    return sizes.groupBy("domain").agg(
        F.count(F.lit(1)).alias("n_groups"), F.sum("n").alias("n_items"), F.max("n").alias("max_size"),
        F.percentile("n", 0.5).alias("median_size"), F.round(F.avg((F.col("n") > 1).cast("double")), 6).alias("multi_share"),
    )
