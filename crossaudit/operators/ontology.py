"""Mapping raw labels to shared classes, and what the raw labels disagree about."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def apply_ontology(items: DataFrame, ontology: DataFrame, on_missing: str = "keep", restricted: tuple[str, ...] = ()) -> DataFrame:
    """Items with ``class`` (null: left out on purpose) and ``restricted``.

    A raw label that the ontology lacks is an error of the ontology, not an exclusion: ``on_missing='error'`` raises
    when such a row is reached; otherwise `validate_ontology` reports it.
    """
    onto = F.broadcast(ontology.select("domain", "raw_label", "class", F.lit(True).alias("mapped")))
    out = items.join(onto, ["domain", "raw_label"], "left")
    if on_missing == "error":
        out = out.withColumn("mapped", F.coalesce("mapped", F.raise_error(F.concat(F.lit("no map for "), "domain", F.lit("::"), "raw_label")).cast("boolean")))
        out = out.where("mapped")
    flag = F.coalesce(F.col("class").isin(*restricted), F.lit(False)) if restricted else F.lit(False)
    return out.withColumn("restricted", flag).drop("mapped")


def validate_ontology(ontology: DataFrame, items: DataFrame) -> DataFrame:
    """``domain, raw_label, problem, n``: labels without a map, and labels with several classes."""
    missing = items.groupBy("domain", "raw_label").agg(F.count(F.lit(1)).alias("n")).join(F.broadcast(ontology), ["domain", "raw_label"], "left_anti")
    several = ontology.groupBy("domain", "raw_label").agg(F.count_distinct(F.coalesce("class", F.lit(""))).alias("n")).where("n > 1")
    return missing.select("domain", "raw_label", F.lit("unmapped").alias("problem"), "n").unionByName(several.select("domain", "raw_label", F.lit("ambiguous").alias("problem"), "n"))


def coverage(items: DataFrame, domains: list[str], classes: list[str]) -> DataFrame:
    """Count of every domain and class, with zeros kept visible."""
    spark = items.sparkSession
    grid = spark.createDataFrame([(d, c) for d in domains for c in classes], "domain string, class string")
    counted = items.where("class is not null").groupBy("domain", "class").agg(F.count(F.lit(1)).alias("n"))
    return grid.join(counted, ["domain", "class"], "left").select("domain", "class", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def label_conflicts(items: DataFrame, key: list[Column], label: Column) -> DataFrame:
    """Content keys whose copies lie in several domains and carry several labels across them.

    A key whose several labels all sit inside one domain is no conflict. Counting happens per (key, domain, label)
    first, so a hot key is combined before it is shuffled. Returns the key, sorted labels and domains, and counts.
    """
    names = [f"key_{i}" for i in range(len(key))]
    rows = items.select(*[k.alias(n) for k, n in zip(key, names, strict=True)], "domain", label.alias("label")).where("label is not null")
    per = rows.groupBy(*names, "domain", "label").agg(F.count(F.lit(1)).alias("n"))
    groups = per.groupBy(*names).agg(
        F.array_sort(F.collect_set("label")).alias("labels"), F.array_sort(F.collect_set("domain")).alias("domains"), F.sum("n").alias("n_items"),
    )
    return groups.where((F.size("labels") > 1) & (F.size("domains") > 1))


def conflict_pairs(conflicts: DataFrame, focal: str) -> DataFrame:
    """``label_a, label_b, n, share, focal_share``: conflicts by unordered pair of labels, and the share that touches ``focal``."""
    total = conflicts.agg(F.count(F.lit(1)).alias("total"), F.sum(F.array_contains("labels", focal).cast("int")).alias("touching"))
    pairs = conflicts.select(F.explode("labels").alias("label_a"), "labels").select("label_a", F.explode("labels").alias("label_b")).where("label_a < label_b")
    counted = pairs.groupBy("label_a", "label_b").agg(F.count(F.lit(1)).alias("n"))
    return counted.join(F.broadcast(total)).select("label_a", "label_b", "n", F.round(F.col("n") / F.col("total"), 6).alias("share"), F.round(F.col("touching") / F.col("total"), 6).alias("focal_share"))


def ontology_variants(ontology: DataFrame, kind: str) -> DataFrame:
    """``variant, domain, raw_label, class``: the ontology as given, each map left out in turn, or label names only."""
    base = ontology.withColumn("variant", F.lit("as given"))
    if kind == "names":
        return ontology.select(F.lit("names").alias("variant"), "domain", "raw_label", F.lower(F.regexp_replace("raw_label", "[^A-Za-z]", "")).alias("class"))
    out = base.select("variant", "domain", "raw_label", "class")
    if kind == "leave_one_out":
        named = ontology.where("class is not null").select(F.concat_ws("::", "domain", "raw_label").alias("left_out"))
        pairs = ontology.join(F.broadcast(named))  # both sides are the ontology: a few rows
        here = F.concat_ws("::", "domain", "raw_label") == F.col("left_out")
        out = out.unionByName(pairs.select(F.concat(F.lit("without "), "left_out").alias("variant"), "domain", "raw_label", F.when(~here, F.col("class")).alias("class")))
    return out
