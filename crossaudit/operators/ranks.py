"""Running sums in the order of a hash, in two levels, so that no task holds all rows of a key."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def running(rows: DataFrame, keys: list[str], digest: Column, tie: str, value: Column | None = None, digits: int = 3) -> DataFrame:
    """Rows with ``before``, the sum of ``value`` (default: 1) of the rows of the same keys ahead of them, and ``total``, that of all.

    The order is by ``digest``, a hex string, then ``tie``. Sums of the cells of its first digits come first (16 to the power of ``digits`` rows a key
    at most), then each cell is ordered by itself. Keys must not be null.
    """
    value = F.lit(1) if value is None else value
    marked = rows.withColumns({"digest_": digest, "value_": value}).withColumn("cell_", F.substring("digest_", 1, digits))
    cells = marked.groupBy(*keys, "cell_").agg(F.sum("value_").alias("sum_"))
    by = Window.partitionBy(*keys)
    ahead = by.orderBy("cell_").rowsBetween(Window.unboundedPreceding, -1)
    cells = cells.select(*keys, "cell_", F.coalesce(F.sum("sum_").over(ahead), F.lit(0)).alias("ahead_"), F.sum("sum_").over(by).alias("total"))
    inside = Window.partitionBy(*keys, "cell_").orderBy("digest_", tie).rowsBetween(Window.unboundedPreceding, -1)
    out = marked.join(cells, [*keys, "cell_"]).withColumn("before", F.col("ahead_") + F.coalesce(F.sum("value_").over(inside), F.lit(0)))
    return out.drop("digest_", "value_", "cell_", "ahead_")
