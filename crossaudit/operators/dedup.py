"""Exact copies across domains: removal, residue, overlap and exclusion lists. Only digests are shuffled, never content."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from crossaudit.operators.components import connected_components


def exact_dedup(items: DataFrame, key_mode: str = "hash", priority: Column | None = None, name: str = "name") -> tuple[DataFrame, DataFrame]:
    """Keep one item of each set of copies: the one of least ``priority``, then of least id.

    ``key_mode``: copies have the same ``digest`` (``hash``), the same ``name``, ``both``, or either of them, directly
    or through others (``either``). Returns the kept items, and ``item_id, kept_id, domain, reason`` of the removed.
    """
    order = priority if priority is not None else F.lit(0)
    place = F.struct(order.alias("p"), F.col("item_id").alias("i"))
    if key_mode == "either":
        by = lambda c: items.groupBy(c).agg(F.min("item_id").alias("first"))
        links = [items.join(by(c), c).select(F.col("item_id").alias("src"), F.col("first").alias("dst")) for c in ("digest", name)]
        groups = connected_components(links[0].unionByName(links[1])).withColumnRenamed("node", "item_id")
        keyed = items.join(groups, "item_id", "left").withColumn("copy_key", F.coalesce("component", "item_id")).drop("component")
    else:
        columns = {"hash": ["digest"], "name": [name], "both": ["digest", name]}[key_mode]
        keyed = items.withColumn("copy_key", F.struct(*columns))
    best = keyed.groupBy("copy_key").agg(F.min(place).alias("best"))
    marked = keyed.join(best, "copy_key").withColumn("kept_id", F.col("best.i"))
    kept = marked.where("item_id = kept_id").select(*items.columns)
    removed = marked.where("item_id <> kept_id").select("item_id", "kept_id", "domain", F.lit(key_mode).alias("reason"))
    return kept, removed


def cross_domain_exact(items: DataFrame) -> DataFrame:
    """Digests that occur in several domains: ``digest, n_domains, n_items``."""
    seen = items.groupBy("digest", "domain").agg(F.count(F.lit(1)).alias("n"))
    return seen.groupBy("digest").agg(F.count(F.lit(1)).alias("n_domains"), F.sum("n").alias("n_items")).where("n_domains > 1")


def overlap_matrix(items: DataFrame) -> DataFrame:
    """``domain_a, domain_b, shared, share_of_a`` over distinct digests, for every ordered pair that shares any."""
    per = items.groupBy("digest").agg(F.collect_set("domain").alias("domains"))  # at most K entries
    pairs = per.select(F.explode("domains").alias("domain_a"), "domains").select("domain_a", F.explode("domains").alias("domain_b"))
    counts = pairs.groupBy("domain_a", "domain_b").agg(F.count(F.lit(1)).alias("shared"))
    own = counts.where("domain_a = domain_b").select("domain_a", F.col("shared").alias("own"))
    return counts.where("domain_a <> domain_b").join(F.broadcast(own), "domain_a").select("domain_a", "domain_b", "shared", F.round(F.col("shared") / F.col("own"), 6).alias("share_of_a"))


def apply_exclusions(items: DataFrame, exclusions: DataFrame) -> DataFrame:
    """Items that the list does not name."""
    return items.join(exclusions.select("item_id").distinct(), "item_id", "left_anti")


def within_exact(items: DataFrame) -> DataFrame:
    """Digests that stand in several splits of one domain: ``domain, digest, n_splits, n_items``."""
    seen = items.groupBy("domain", "digest", "split").agg(F.count(F.lit(1)).alias("n"))
    return seen.groupBy("domain", "digest").agg(F.count(F.lit(1)).alias("n_splits"), F.sum("n").alias("n_items")).where("n_splits > 1")


def incremental_first(items: DataFrame) -> DataFrame:
    """Copies numbered by order of arrival within their digest."""
    return items.withColumn("copy", F.row_number().over(Window.partitionBy("digest").orderBy("item_id")))
