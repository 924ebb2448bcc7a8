"""Corpus preparation, ontology, conflicts, de-duplication and splits on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from crossaudit.operators import dedup, encode, ontology, split, transfer
from crossaudit.plans.registry import query
from crossaudit.plans.workloads import CLASSES, ROLES, SQL_ITEMS, SQL_SPLIT, clean_items, ontology_frame, priority_of, raw_items, split_items
from crossaudit.sources import table

WITH = f"WITH {SQL_ITEMS}"
WITH_SPLIT = f"WITH {SQL_ITEMS}{SQL_SPLIT}"


def hourly(spark, sf_dir):
    """Mean value of each user in each of 24 hours."""
    e = table(spark, sf_dir, "events")
    return e.groupBy("user_id", F.hour("ts").alias("h")).agg(F.round(F.avg("value"), 6).alias("v"))


SQL_HOURLY = "hourly AS (SELECT user_id, CAST(hour(ts) AS INT) AS h, round(avg(value), 6) AS v FROM events GROUP BY 1, 2)"


@query("prep_standardize", f"""
WITH {SQL_HOURLY}, a AS (SELECT user_id, list(coalesce(v, 0) ORDER BY h) AS s FROM hourly GROUP BY user_id),
b AS (SELECT user_id, list_slice(list_concat(s, list_transform(range(24), lambda x: 0.0::DOUBLE)), 1, 24) AS s FROM a),
c AS (SELECT user_id, unnest(range(24)) AS k, unnest(s) AS v, list_max(list_transform(s, lambda x: abs(x))) AS top FROM b)
SELECT user_id, k, round(CASE WHEN top > 0 THEN v / top ELSE v END, 6) AS v, true AS ok FROM c""")
def prep_standardize(spark, sf_dir):
    out = encode.standardize(hourly(spark, sf_dir), "user_id", "h", "v", 24)
    return out.select("user_id", F.posexplode("series").alias("k", "v"), "ok").select("user_id", F.col("k").cast("long").alias("k"), F.round("v", 6).alias("v"), "ok")


@query("corpus_audit", WITH + """,
m AS (SELECT domain, max(n) / sum(n) AS p, count(*) AS m FROM (SELECT domain, class, count(*) AS n FROM clean WHERE class IS NOT NULL GROUP BY 1, 2) GROUP BY 1)
SELECT s.domain, scanned, removed, mapped, m AS n_classes, round(2 * p / (1 + p) / m, 6) AS majority_caf1, median_chars, n_groups
FROM (SELECT domain, count(*) AS scanned, count(*) FILTER (copy > 1) AS removed FROM ranked GROUP BY 1) s
JOIN (SELECT domain, count(class) AS mapped, median(n_chars) AS median_chars, count(DISTINCT group_id) AS n_groups FROM clean GROUP BY 1) c USING (domain) JOIN m USING (domain)""")
def corpus_audit(spark, sf_dir):
    raw, clean = raw_items(spark, sf_dir), clean_items(spark, sf_dir)
    scanned = raw.groupBy("domain").agg(F.count(F.lit(1)).alias("scanned"))
    kept = clean.groupBy("domain").agg(F.count(F.lit(1)).alias("kept"), F.count("class").alias("mapped"), F.percentile("n_chars", 0.5).alias("median_chars"), F.count_distinct("group_id").alias("n_groups"))
    votes = transfer.majority_baseline(clean.where("class is not null")).select("domain", "n_classes", F.col("caf1").alias("majority_caf1"))
    return scanned.join(kept, "domain").join(votes, "domain").select("domain", "scanned", (F.col("scanned") - F.col("kept")).alias("removed"), "mapped", "n_classes", "majority_caf1", "median_chars", "n_groups")


@query("size_gate", WITH + """
SELECT domain, count(class) AS mapped, count(class) >= 80 AS kept, CASE WHEN count(class) >= 80 THEN '' ELSE 'fewer than 80 mapped items' END AS reason FROM clean GROUP BY domain""")
def size_gate(spark, sf_dir, min_items: int = 80):
    n = clean_items(spark, sf_dir).groupBy("domain").agg(F.count("class").alias("mapped"))
    ok = F.col("mapped") >= min_items
    return n.select("domain", "mapped", ok.alias("kept"), F.when(ok, "").otherwise(f"fewer than {min_items} mapped items").alias("reason"))


@query("group_rules", WITH + " SELECT item_id, domain, group_id FROM rawi")
def group_rules(spark, sf_dir):
    return raw_items(spark, sf_dir).select("item_id", "domain", "group_id")


@query("group_profile", WITH + """
SELECT domain, count(*) AS n_groups, CAST(sum(n) AS BIGINT) AS n_items, max(n) AS max_size, median(n) AS median_size, round(avg(CASE WHEN n > 1 THEN 1.0::DOUBLE ELSE 0 END), 6) AS multi_share
FROM (SELECT domain, group_id, count(*) AS n FROM rawi GROUP BY 1, 2) GROUP BY domain""")
def group_profile(spark, sf_dir):
    return split.group_profile(raw_items(spark, sf_dir))


@query("ontology_apply", WITH + " SELECT item_id, domain, raw_label, class, restricted FROM clean")
def ontology_apply(spark, sf_dir):
    return clean_items(spark, sf_dir).select("item_id", "domain", "raw_label", "class", "restricted")


@query("ontology_violations", WITH + """, bad AS (SELECT * FROM onto WHERE raw_label <> 'mid' UNION ALL VALUES ('LARGE', 'Brief', 'medium'))
SELECT domain, raw_label, 'unmapped' AS problem, count(*) AS n FROM rawi ANTI JOIN bad USING (domain, raw_label) GROUP BY 1, 2
UNION ALL SELECT domain, raw_label, 'ambiguous', count(DISTINCT coalesce(class, '')) FROM bad GROUP BY 1, 2 HAVING count(DISTINCT coalesce(class, '')) > 1""")
def ontology_violations(spark, sf_dir):
    """A damaged ontology: one map missing, one label mapped twice."""
    bad = ontology_frame(spark).where("raw_label <> 'mid'").union(spark.createDataFrame([("LARGE", "Brief", "medium")], "a string, b string, c string"))
    return ontology.validate_ontology(bad, raw_items(spark, sf_dir))


@query("ontology_coverage", WITH + f"""
SELECT g.domain, g.class, CAST(count(c.item_id) AS BIGINT) AS n FROM (SELECT unnest({list(ROLES)!r}) AS domain) d CROSS JOIN (SELECT unnest({list(CLASSES)!r}) AS class) k
CROSS JOIN LATERAL (SELECT d.domain, k.class) g LEFT JOIN clean c ON c.domain = g.domain AND c.class = g.class GROUP BY 1, 2""")
def ontology_coverage(spark, sf_dir):
    return ontology.coverage(clean_items(spark, sf_dir), list(ROLES), list(CLASSES))


CONFLICTS = """, conf AS (
  SELECT digest, space, list_sort(list_distinct(list(label))) AS labels, list_sort(list_distinct(list(domain))) AS domains, CAST(count(*) AS BIGINT) AS n_items
  FROM (SELECT digest, domain, 'raw' AS space, lower(raw_label) AS label FROM rawi UNION ALL SELECT digest, domain, 'mapped', class FROM rawi LEFT JOIN onto USING (domain, raw_label)) WHERE label IS NOT NULL
  GROUP BY digest, space HAVING count(DISTINCT label) > 1 AND count(DISTINCT domain) > 1)"""


def document_conflicts(spark, sf_dir, space: str):
    rows = raw_items(spark, sf_dir)
    if space == "mapped":
        rows = ontology.apply_ontology(rows, ontology_frame(spark))
    return ontology.label_conflicts(rows, [F.col("digest")], F.lower("raw_label") if space == "raw" else F.col("class"))


@query("label_conflicts_docs", WITH + CONFLICTS + " SELECT digest, space, array_to_string(labels, ',') AS labels, array_to_string(domains, ',') AS domains, n_items FROM conf")
def label_conflicts_docs(spark, sf_dir):
    both = [document_conflicts(spark, sf_dir, s).withColumn("space", F.lit(s)) for s in ("raw", "mapped")]
    return both[0].unionByName(both[1]).select(F.col("key_0").alias("digest"), "space", F.array_join("labels", ",").alias("labels"), F.array_join("domains", ",").alias("domains"), "n_items")


@query("label_conflicts_lineitem", """
SELECT l_orderkey, CAST(l_linenumber AS BIGINT) AS l_linenumber, string_agg(DISTINCT l_returnflag, ',' ORDER BY l_returnflag) AS labels, CAST(count(*) AS BIGINT) AS n_items
FROM lineitem GROUP BY 1, 2 HAVING count(DISTINCT l_linestatus) > 1 AND count(DISTINCT l_returnflag) > 1""")
def label_conflicts_lineitem(spark, sf_dir):
    rows = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", F.col("l_linestatus").alias("domain"), "l_returnflag")
    out = ontology.label_conflicts(rows, [F.col("l_orderkey"), F.col("l_linenumber").cast("long")], F.col("l_returnflag"))
    return out.select(F.col("key_0").alias("l_orderkey"), F.col("key_1").alias("l_linenumber"), F.array_join("labels", ",").alias("labels"), "n_items")


@query("conflict_pairs", WITH + CONFLICTS + """, c AS (SELECT * FROM conf WHERE space = 'raw'), t AS (SELECT count(*) AS total, count(*) FILTER (list_contains(labels, 'medium')) AS touching FROM c)
SELECT label_a, label_b, count(*) AS n, round(count(*) / any_value(total), 6) AS share, round(any_value(touching) / any_value(total), 6) AS focal_share
FROM (SELECT unnest(labels) AS label_a, labels FROM c), LATERAL (SELECT unnest(labels) AS label_b), t WHERE label_a < label_b GROUP BY 1, 2""")
def conflict_pairs(spark, sf_dir):
    return ontology.conflict_pairs(document_conflicts(spark, sf_dir, "raw"), "medium")


@query("ontology_variants", WITH + """, names AS (SELECT domain || '::' || raw_label AS left_out FROM onto WHERE class IS NOT NULL),
v AS (SELECT 'as given' AS variant, * FROM onto UNION ALL SELECT 'without ' || left_out, domain, raw_label, CASE WHEN domain || '::' || raw_label <> left_out THEN class END FROM onto, names
  UNION ALL SELECT 'names', domain, raw_label, lower(regexp_replace(raw_label, '[^A-Za-z]', '', 'g')) FROM onto)
SELECT variant, class, count(*) AS n FROM (SELECT domain, raw_label FROM ranked WHERE copy = 1) JOIN v USING (domain, raw_label) GROUP BY 1, 2""")
def ontology_variants(spark, sf_dir):
    onto = ontology_frame(spark)
    variants = ontology.ontology_variants(onto, "leave_one_out").unionByName(ontology.ontology_variants(onto, "names"))
    items = clean_items(spark, sf_dir).groupBy("domain", "raw_label").agg(F.count(F.lit(1)).alias("n"))
    return items.join(F.broadcast(variants), ["domain", "raw_label"]).groupBy("variant", "class").agg(F.sum("n").alias("n"))


@query("group_split", WITH_SPLIT + " SELECT item_id, domain, group_id, class, split FROM items")
def group_split(spark, sf_dir):
    return split_items(spark, sf_dir).select("item_id", "domain", "group_id", "class", "split")


@query("split_violations", WITH_SPLIT + """, broken AS (SELECT domain, group_id, CASE WHEN item_id % 16 = 1 THEN 'test' ELSE split END AS split, 'planted' AS kind FROM items UNION ALL SELECT domain, group_id, split, 'real' FROM items)
SELECT kind, domain, group_id, count(DISTINCT split) AS n_splits FROM broken GROUP BY 1, 2, 3 HAVING count(DISTINCT split) > 1""")
def split_violations(spark, sf_dir):
    """None in the split as made; some in one with items moved on purpose."""
    items = split_items(spark, sf_dir)
    planted = items.withColumn("split", F.when(F.col("item_id") % 16 == 1, "test").otherwise(F.col("split")))
    both = [split.split_violations(x).withColumn("kind", F.lit(k)) for k, x in (("real", items), ("planted", planted))]
    return both[0].unionByName(both[1]).select("kind", "domain", "group_id", "n_splits")


@query("exact_dedup_manifest", WITH + """, k AS (SELECT digest, item_id AS kept_id FROM ranked WHERE copy = 1)
SELECT item_id, kept_id, domain, 'hash' AS reason FROM ranked JOIN k USING (digest) WHERE copy > 1""")
def exact_dedup_manifest(spark, sf_dir):
    return dedup.exact_dedup(raw_items(spark, sf_dir), priority=priority_of(F.col("domain")))[1]


@query("exact_dedup_summary", WITH + " SELECT domain, count(*) AS scanned, count(*) FILTER (copy > 1) AS removed, count(*) FILTER (copy = 1) AS kept FROM ranked GROUP BY domain")
def exact_dedup_summary(spark, sf_dir):
    raw = raw_items(spark, sf_dir)
    kept, _ = dedup.exact_dedup(raw, priority=priority_of(F.col("domain")))
    a = raw.groupBy("domain").agg(F.count(F.lit(1)).alias("scanned")).join(kept.groupBy("domain").agg(F.count(F.lit(1)).alias("kept")), "domain", "left").fillna(0, ["kept"])
    return a.select("domain", "scanned", (F.col("scanned") - F.col("kept")).alias("removed"), "kept")


@query("exact_dedup_either", WITH.replace("WITH ", "WITH RECURSIVE ", 1) + """, nm AS (SELECT item_id, domain, digest, lang || ':' || (item_id // 3) AS name, CASE domain WHEN 'NOISY' THEN 0 WHEN 'LARGE' THEN 1 WHEN 'CLEAN' THEN 2 ELSE 3 END AS prio FROM rawi),
ed AS (SELECT a.item_id AS a, b.item_id AS b FROM nm a JOIN nm b USING (digest) UNION SELECT a.item_id, b.item_id FROM nm a JOIN nm b USING (name)),
rc AS (SELECT item_id, item_id AS other FROM nm UNION SELECT rc.item_id, ed.b FROM rc JOIN ed ON rc.other = ed.a),
cm AS (SELECT item_id, min(other) AS c FROM rc GROUP BY 1), bt AS (SELECT c, arg_min(item_id, (prio, item_id)) AS kept_id FROM cm JOIN nm USING (item_id) GROUP BY c)
SELECT item_id, kept_id, domain, 'either' AS reason FROM cm JOIN bt USING (c) JOIN nm USING (item_id) WHERE item_id <> kept_id""")
def exact_dedup_either(spark, sf_dir):
    """Copies by digest or by name (here the block of the id), directly or through others."""
    named = raw_items(spark, sf_dir).withColumn("name", F.concat_ws(":", "lang", F.floor(F.col("item_id") / 3).cast("string")))
    return dedup.exact_dedup(named, key_mode="either", priority=priority_of(F.col("domain")))[1]


@query("exact_dup_residual", WITH + " SELECT digest, count(DISTINCT domain) AS n_domains, count(*) AS n_items FROM clean GROUP BY digest HAVING count(DISTINCT domain) > 1")
def exact_dup_residual(spark, sf_dir):
    return dedup.cross_domain_exact(clean_items(spark, sf_dir))


@query("domain_overlap", WITH + """, p AS (SELECT DISTINCT digest, domain FROM rawi)
SELECT a.domain AS domain_a, b.domain AS domain_b, count(*) AS shared, round(count(*) / any_value(n), 6) AS share_of_a
FROM p a JOIN p b USING (digest) JOIN (SELECT domain, count(*) AS n FROM p GROUP BY 1) o ON o.domain = a.domain WHERE a.domain <> b.domain GROUP BY 1, 2""")
def domain_overlap(spark, sf_dir):
    return dedup.overlap_matrix(raw_items(spark, sf_dir))


@query("apply_exclusions", WITH + " SELECT domain, count(*) AS n FROM rawi WHERE item_id NOT IN (SELECT item_id FROM ranked WHERE copy > 1) GROUP BY domain")
def apply_exclusions(spark, sf_dir):
    raw = raw_items(spark, sf_dir)
    _, removed = dedup.exact_dedup(raw, priority=priority_of(F.col("domain")))
    return dedup.apply_exclusions(raw, removed).groupBy("domain").agg(F.count(F.lit(1)).alias("n"))


RAW_SPLIT = """, s AS (SELECT *, CASE WHEN h < 0.69 THEN 'train' WHEN h < 0.845 THEN 'val' ELSE 'test' END AS split
  FROM (SELECT *, CAST('0x' || substr(md5('7:' || group_id), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE AS h FROM rawi))"""


def raw_split(spark, sf_dir):
    """Items before de-duplication under a plain split by a hash of the group: what the within-domain audits look at."""
    h = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit("7"), "group_id").cast("binary")), 1, 8), 16, 10).cast("double") / 4294967296.0
    return raw_items(spark, sf_dir).withColumn("split", F.when(h < 0.69, "train").when(h < 0.845, "val").otherwise("test"))


@query("within_exact", WITH + RAW_SPLIT + " SELECT domain, digest, count(DISTINCT split) AS n_splits, count(*) AS n_items FROM s GROUP BY 1, 2 HAVING count(DISTINCT split) > 1")
def within_exact(spark, sf_dir):
    return dedup.within_exact(raw_split(spark, sf_dir))


@query("majority_baseline", WITH + """, c AS (SELECT domain, class, count(*) AS n FROM clean WHERE class IS NOT NULL GROUP BY 1, 2)
SELECT domain, min_by(class, (-n, class)) AS majority, round(max(n) / sum(n), 6) AS share, count(*) AS n_classes, round(2 * (max(n) / sum(n)) / (1 + max(n) / sum(n)) / count(*), 6) AS caf1 FROM c GROUP BY domain""")
def majority_baseline(spark, sf_dir):
    return transfer.majority_baseline(clean_items(spark, sf_dir).where("class is not null"))
