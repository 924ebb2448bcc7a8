"""The experiment relations on the given tables: items with domains, raw labels, groups and splits."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from crossaudit.operators.dedup import exact_dedup
from crossaudit.operators.ontology import apply_ontology
from crossaudit.operators.split import group_split
from crossaudit.sources import table

ROLES = ("NOISY", "LARGE", "CLEAN", "TINY")
CLASSES = ("brief", "burst", "extended", "medium", "neutral")
#: (domain, raw label, class); no class means that the label is left out on purpose.
ONTOLOGY = (
    ("LARGE", "Brief", "brief"), ("LARGE", "Medium", "medium"), ("LARGE", "Long", "extended"),
    ("NOISY", "short", "brief"), ("NOISY", "mid", "medium"), ("NOISY", "long", "extended"), ("NOISY", "dk", None),
    ("CLEAN", "noise", "neutral"), ("CLEAN", "snippet", "brief"), ("CLEAN", "article", "extended"),
    ("TINY", "brief", "brief"), ("TINY", "burst", "burst"), ("TINY", "long", "extended"),
)
RESTRICTED = ("burst",)


def role_of(source: Column) -> Column:
    """Fold twenty sources into four domains."""
    k = F.substring(source, 4, 9).cast("int")
    return F.when(k < 10, "LARGE").when(k < 16, "NOISY").when(k < 19, "CLEAN").otherwise("TINY")


def raw_label_of(domain: Column, n: Column) -> Column:
    """Each domain's own label convention on text length."""
    return (
        F.when(domain == "LARGE", F.when(n < 600, "Brief").when(n < 2500, "Medium").otherwise("Long"))
        .when(domain == "NOISY", F.when(n < 1000, "short").when(n < 2500, "mid").when(n < 6000, "long").otherwise("dk"))
        .when(domain == "CLEAN", F.when(n < 300, "noise").when(n < 600, "snippet").otherwise("article"))
        .otherwise(F.when(n < 1000, "brief").when(n < 3000, "burst").otherwise("long"))
    )


def group_of(domain: Column, item: Column) -> Column:
    """Handmade group rules: blocks of eight, four or two items, or the item itself."""
    size = F.when(domain == "LARGE", 8).when(domain == "NOISY", 4).when(domain == "TINY", 2).otherwise(1)
    return F.concat(F.substring(domain, 1, 1), F.floor(item / size).cast("string"))


def ontology_frame(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(ONTOLOGY), "domain string, raw_label string, class string")


def raw_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``item_id, domain, raw_label, group_id, digest, source, lang, n_chars`` of all documents, before de-duplication."""
    d = table(spark, sf_dir, "documents").withColumn("domain", role_of(F.col("source")))
    return d.select(
        F.col("doc_id").alias("item_id"), "domain", raw_label_of(F.col("domain"), F.col("n_chars")).alias("raw_label"),
        group_of(F.col("domain"), F.col("doc_id")).alias("group_id"), F.sha2(F.col("text").cast("binary"), 256).alias("digest"), "source", "lang", "n_chars",
    )


def priority_of(domain: Column) -> Column:
    return F.when(domain == "NOISY", 0).when(domain == "LARGE", 1).when(domain == "CLEAN", 2).otherwise(3)


def clean_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items after exact de-duplication, with ``class`` and ``restricted``; excluded labels stay with a null class."""
    raw = raw_items(spark, sf_dir)
    kept, _ = exact_dedup(raw, priority=priority_of(F.col("domain")))
    return apply_ontology(kept, ontology_frame(spark), restricted=RESTRICTED)


def split_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mapped items with their split."""
    return group_split(clean_items(spark, sf_dir).where("class is not null"))


#: SQL twins, as common table expressions in order.
SQL_ITEMS = """
rawi AS (SELECT doc_id AS item_id, domain, CASE domain
    WHEN 'LARGE' THEN CASE WHEN n_chars < 600 THEN 'Brief' WHEN n_chars < 2500 THEN 'Medium' ELSE 'Long' END
    WHEN 'NOISY' THEN CASE WHEN n_chars < 1000 THEN 'short' WHEN n_chars < 2500 THEN 'mid' WHEN n_chars < 6000 THEN 'long' ELSE 'dk' END
    WHEN 'CLEAN' THEN CASE WHEN n_chars < 300 THEN 'noise' WHEN n_chars < 600 THEN 'snippet' ELSE 'article' END
    ELSE CASE WHEN n_chars < 1000 THEN 'brief' WHEN n_chars < 3000 THEN 'burst' ELSE 'long' END END AS raw_label,
  substr(domain, 1, 1) || CAST(doc_id // CASE domain WHEN 'LARGE' THEN 8 WHEN 'NOISY' THEN 4 WHEN 'TINY' THEN 2 ELSE 1 END AS VARCHAR) AS group_id,
  sha256(text) AS digest, source, lang, n_chars, text
  FROM (SELECT *, CASE WHEN k < 10 THEN 'LARGE' WHEN k < 16 THEN 'NOISY' WHEN k < 19 THEN 'CLEAN' ELSE 'TINY' END AS domain
        FROM (SELECT *, CAST(substr(source, 4) AS INT) AS k FROM documents))),
ranked AS (SELECT *, row_number() OVER (PARTITION BY digest ORDER BY CASE domain WHEN 'NOISY' THEN 0 WHEN 'LARGE' THEN 1 WHEN 'CLEAN' THEN 2 ELSE 3 END, item_id) AS copy FROM rawi),
onto(domain, raw_label, class) AS (VALUES """ + ", ".join(f"('{d}', '{r}', {'NULL' if c is None else repr(c)})" for d, r, c in ONTOLOGY) + """),
clean AS (SELECT r.*, o.class, coalesce(o.class = 'burst', false) AS restricted FROM ranked r LEFT JOIN onto o USING (domain, raw_label) WHERE copy = 1)"""

SQL_SPLIT = """,
gc AS (SELECT domain, group_id, class, count(*) AS n FROM clean WHERE class IS NOT NULL GROUP BY domain, group_id, class),
gm AS (SELECT domain, group_id, sum(n) AS n, min_by(class, (-n, class)) AS cls FROM (SELECT *, n AS n2 FROM gc) GROUP BY domain, group_id),
go AS (SELECT domain, group_id, coalesce(sum(n) OVER (PARTITION BY domain, cls ORDER BY md5('42:' || domain || ':' || group_id), group_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)
      / sum(n) OVER (PARTITION BY domain, cls) AS share FROM gm),
items AS (SELECT c.*, CASE WHEN share < 0.69 THEN 'train' WHEN share < 0.845 THEN 'val' ELSE 'test' END AS split FROM clean c JOIN go USING (domain, group_id) WHERE class IS NOT NULL)"""
