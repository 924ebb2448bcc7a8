"""Connected components of a graph given as an edge table, without ever holding the graph on the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crossaudit.functions.storage import discard, materialize


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Smallest reachable node of every node that has an edge.

    ``edges`` has the columns ``src`` and ``dst`` (any comparable type). Rounds alternate two star operations:
    first each node hands its larger neighbours to its smallest one, then each node hands its smaller neighbours
    to the smallest; both keep connectivity, and at the fixed point every node hangs on its component's minimum.
    Each round is a group-by with map-side combining and a join that Spark may split on skew. Only a row count
    and a checksum reach the driver. Null ends, loops and repeated edges are ignored; an empty table gives an
    empty result.

    Returns ``node, component``.
    """
    pairs = edges.select("src", "dst").where("src is not null and dst is not null and src <> dst")
    stars = materialize(pairs.select(F.greatest("src", "dst").alias("u"), F.least("src", "dst").alias("v")).distinct(), "cc")
    before = None
    for _ in range(max_rounds):
        both = stars.select("u", "v").unionAll(stars.select(F.col("v").alias("u"), F.col("u").alias("v")))
        lowest = both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"))
        large = (
            both.where("v > u").join(lowest, "u")
            .select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        )
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = (
            large.join(low, "u")
            .select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u"), F.col("m").alias("v")))).alias("e"))
            .select("e.u", "e.v").where("u <> v").distinct()
        )
        last, stars = stars, materialize(small, "cc")
        discard(last)
        now = stars.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if before == (now["n"], now["h"]):
            break
        before = (now["n"], now["h"])
    else:
        raise RuntimeError(f"no fixed point after {max_rounds} rounds")
    roots = stars.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return stars.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
