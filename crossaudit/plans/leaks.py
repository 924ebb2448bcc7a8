"""Near-duplicate and leakage audits on the given tables, and the matrix without what they find."""

from __future__ import annotations

from pyspark.sql import functions as F

from crossaudit.functions.storage import materialize
from crossaudit.operators import encode, leakage, neardup, transfer
from crossaudit.plans.corpus import CONFLICTS, RAW_SPLIT, SQL_HOURLY, document_conflicts, hourly, raw_split
from crossaudit.plans.matrix import CHAR3, SQL_FEATS, SQL_NTR, TASK_SQL, WORD, base_items, char3, sql_probe, sql_scores, task_matrix, task_predictions
from crossaudit.plans.registry import query
from crossaudit.plans.workloads import SQL_ITEMS, SQL_SPLIT, clean_items
from crossaudit.sources import table

TAU, TAU2, TAU_CONFIRM, TAU_WITHIN = 0.98, 0.99, 0.926, 0.995
WITH = f"WITH {SQL_ITEMS}"
VECS = f", {CHAR3}, vec AS (SELECT item_id, list(x ORDER BY d) AS f FROM char3 GROUP BY item_id)"
CROSS = VECS + """, cv AS (SELECT item_id, domain, class, f FROM clean JOIN vec USING (item_id)),
cp AS (SELECT a.item_id AS left_id, b.item_id AS right_id, least(a.domain, b.domain) AS domain_a, greatest(a.domain, b.domain) AS domain_b, list_cosine_similarity(a.f, b.f) AS cos, a.class AS la, b.class AS lb
  FROM cv a JOIN cv b ON a.item_id < b.item_id AND a.domain <> b.domain)"""


def vectors(spark, sf_dir):
    """Trigram vectors of the de-duplicated items, with their domains."""
    return materialize(clean_items(spark, sf_dir).select("item_id", "domain", "class").join(char3(spark, sf_dir), "item_id"), "vectors")


@query("cosine_audit", WITH + CROSS + " SELECT domain_a, domain_b, round(max(cos), 6) AS max_cos, count(*) FILTER (cos > 0.95) AS n950, count(*) FILTER (cos > 0.98) AS n980, count(*) FILTER (cos > 0.99) AS n990 FROM cp GROUP BY 1, 2")
def cosine_audit(spark, sf_dir):
    return neardup.cosine_audit(vectors(spark, sf_dir).drop("class"))


@query("near_pairs", WITH + CROSS + f" SELECT left_id, right_id, round(cos, 6) AS cos FROM cp WHERE cos >= {TAU}")
def near_pairs(spark, sf_dir):
    return neardup.blocked_cosines(vectors(spark, sf_dir).drop("class"), TAU).withColumn("cos", F.round("cos", 6))


@query("near_pair_summary", WITH + CROSS + f""" SELECT (SELECT count(*) FROM cp WHERE cos >= {TAU}) AS n_pairs,
(SELECT count(*) FROM (SELECT left_id FROM cp WHERE cos >= {TAU} UNION SELECT right_id FROM cp WHERE cos >= {TAU})) AS n_items, (SELECT round(avg(coalesce((la = lb)::INT::DOUBLE, 0)), 6) FROM cp WHERE cos >= {TAU}) AS agreement""")
def near_pair_summary(spark, sf_dir):
    return neardup.near_summary(vectors(spark, sf_dir).withColumnRenamed("class", "label"), TAU)


@query("near_pairs_lsh", WITH + CROSS + f" SELECT left_id, right_id, round(cos, 6) AS cos FROM cp WHERE cos >= {TAU}")
def near_pairs_lsh(spark, sf_dir):
    """The banded search; at this threshold it misses a pair once in a million, so it equals the exact one."""
    return neardup.near_pairs_lsh(vectors(spark, sf_dir).drop("class"), TAU).withColumn("cos", F.round("cos", 6))


@query("mutual_best_pairs", WITH + CROSS + f""", np AS (SELECT left_id, right_id, round(cos, 6) AS cos FROM cp WHERE cos >= {TAU2}),
bt AS (SELECT left_id, right_id, cos FROM (SELECT *, left_id AS me, right_id AS other FROM np UNION ALL SELECT *, right_id, left_id FROM np) QUALIFY row_number() OVER (PARTITION BY me ORDER BY cos DESC, other) = 1)
SELECT left_id, right_id, max(cos) AS cos FROM bt GROUP BY 1, 2 HAVING count(*) = 2""")
def mutual_best_pairs(spark, sf_dir):
    return neardup.best_cosines(vectors(spark, sf_dir).drop("class"), TAU2)


@query("confirm_pairs", WITH + CROSS + f", {WORD}, wvec AS (SELECT item_id, list(x ORDER BY d) AS f FROM wordv GROUP BY item_id)" + f"""
SELECT left_id, right_id, round(list_cosine_similarity(a.f, b.f), 6) AS cos2, round(list_cosine_similarity(a.f, b.f), 6) >= {TAU_CONFIRM} AS confirmed FROM cp JOIN wvec a ON a.item_id = left_id JOIN wvec b ON b.item_id = right_id WHERE cos >= {TAU2}""")
def confirm_pairs(spark, sf_dir):
    """Pairs above the higher threshold, under word counts as a second encoder."""
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), "lang", "text")
    second = encode.hashed(docs, "word", 64, center="lang")
    pairs = neardup.blocked_cosines(vectors(spark, sf_dir).drop("class"), TAU2).select("left_id", "right_id")
    return neardup.confirm(pairs, second, TAU_CONFIRM)


def text_hashes(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), "text")
    return neardup.simhash(docs)


def _vote(c: str, k: int) -> str:
    return f"CASE WHEN sum(CASE WHEN ({c} >> {k}) & 1 = 1 THEN n ELSE -n END) > 0 THEN {1 << k}::BIGINT ELSE 0 END"


SIM = rf""" sw AS (SELECT item_id, w, count(*) AS n FROM (SELECT doc_id AS item_id, unnest(regexp_split_to_array(lower(text), '[^\p{{L}}0-9]+')) AS w FROM documents) WHERE w <> '' GROUP BY 1, 2),
sd AS (SELECT item_id, n, CAST('0x' || substr(md5(w), 1, 8) AS BIGINT) AS h, CAST('0x' || substr(md5(w), 9, 8) AS BIGINT) AS l FROM sw),
sh AS (SELECT doc_id AS item_id, coalesce(hi, 0) AS hi, coalesce(lo, 0) AS lo FROM documents LEFT JOIN (SELECT item_id AS doc_id, {' + '.join(_vote('h', k) for k in range(32))} AS hi, {' + '.join(_vote('l', k) for k in range(32))} AS lo FROM sd GROUP BY 1) USING (doc_id)),
sp AS (SELECT a.item_id AS left_id, b.item_id AS right_id, CAST(bit_count(xor(a.hi, b.hi)) + bit_count(xor(a.lo, b.lo)) AS INT) AS hamming FROM sh a JOIN sh b ON a.item_id < b.item_id)"""


@query("simhash_pairs", f"WITH {SIM} SELECT left_id, right_id, hamming FROM sp WHERE hamming <= 1")
def simhash_pairs(spark, sf_dir):
    return neardup.hamming_pairs(materialize(text_hashes(spark, sf_dir), "simhash"))


@query("simhash_min_hist", f"WITH {SIM} SELECT distance, count(*) AS n FROM (SELECT item_id, min(hamming) AS distance FROM (SELECT left_id AS item_id, hamming FROM sp UNION ALL SELECT right_id, hamming FROM sp) GROUP BY 1) GROUP BY 1")
def simhash_min_hist(spark, sf_dir):
    return neardup.min_distance_hist(materialize(text_hashes(spark, sf_dir), "simhash"))


WITHIN = RAW_SPLIT + VECS + """, wt AS (SELECT item_id, domain, split, f FROM s JOIN vec USING (item_id)),
nn AS (SELECT a.item_id AS test_id, b.item_id AS train_id, round(list_cosine_similarity(a.f, b.f), 9) AS cos FROM wt a JOIN wt b ON a.domain = b.domain AND a.split = 'test' AND b.split = 'train'
  QUALIFY row_number() OVER (PARTITION BY a.item_id ORDER BY cos DESC, b.item_id) = 1)"""


def within_vectors(spark, sf_dir):
    return materialize(raw_split(spark, sf_dir).select("item_id", "domain", "split", "group_id", "raw_label").join(char3(spark, sf_dir), "item_id"), "within")


@query("nn_train_test", WITH + WITHIN + f""" SELECT test_id, train_id, round(cos, 6) AS cos, round(cos, 6) > {TAU_WITHIN} AS flagged, a.raw_label = b.raw_label AS label_equal FROM nn JOIN rawi a ON a.item_id = test_id JOIN rawi b ON b.item_id = train_id""")
def nn_train_test(spark, sf_dir):
    v = within_vectors(spark, sf_dir)
    near = neardup.nearest_train(v.select("item_id", "domain", "split", "features"))
    a, b = (v.select(F.col("item_id").alias(f"{k}_id"), F.col("raw_label").alias(f"{k}_label")) for k in ("test", "train"))
    return near.join(a, "test_id").join(b, "train_id").select("test_id", "train_id", "cos", (F.col("cos") > TAU_WITHIN).alias("flagged"), (F.col("test_label") == F.col("train_label")).alias("label_equal"))


@query("shift_match", f"""WITH {SQL_HOURLY},
a AS (SELECT user_id AS id, list(coalesce(v, 0) ORDER BY h) AS s FROM hourly GROUP BY 1), f AS (SELECT id, list_slice(list_concat(s, list_transform(range(24), lambda x: 0.0::DOUBLE)), 1, 24) AS s FROM a),
g AS (SELECT id, s FROM f UNION ALL SELECT id + 1000000, list_concat(list_slice(s, id % 3 + 1, 24), list_slice(s, 1, id % 3)) FROM f),
p AS (SELECT id AS left_id, id + 1000000 AS right_id FROM f UNION ALL SELECT id, id + 1 FROM f WHERE id + 1 IN (SELECT id FROM f)),
l AS (SELECT left_id, right_id, a.s AS sa, b.s AS sb, lag, 24 - abs(lag) AS n FROM p JOIN g a ON a.id = left_id JOIN g b ON b.id = right_id, (SELECT unnest(range(-4, 5)) AS lag)),
x AS (SELECT left_id, right_id, lag, unnest(list_slice(sa, greatest(0, lag) + 1, greatest(0, lag) + n)) AS x, unnest(list_slice(sb, greatest(0, -lag) + 1, greatest(0, -lag) + n)) AS y FROM l),
r AS (SELECT left_id, right_id, lag, round(covar_pop(x, y) / nullif(stddev_pop(x) * stddev_pop(y), 0), 6) AS r FROM x GROUP BY 1, 2, 3)
SELECT left_id, right_id, CAST(lag AS INT) AS best_lag, r AS xcorr, r >= 0.8 AS match FROM r WHERE r IS NOT NULL QUALIFY row_number() OVER (PARTITION BY left_id, right_id ORDER BY r DESC, abs(lag), lag) = 1""")
def shift_match(spark, sf_dir):
    """Hourly series of users against copies shifted by up to two hours, and against the next user."""
    s = encode.standardize(hourly(spark, sf_dir), "user_id", "h", "v", 24, peak=False).select(F.col("user_id").alias("item_id"), "series")
    k = F.pmod(F.col("item_id"), F.lit(3)).cast("int")
    planted = s.select((F.col("item_id") + 1_000_000).alias("item_id"), F.concat(F.slice("series", k + 1, 24 - k), F.slice("series", F.lit(1), k)).alias("series"))
    pairs = s.select(F.col("item_id").alias("left_id"), (F.col("item_id") + 1_000_000).alias("right_id")).unionByName(
        s.select(F.col("item_id").alias("left_id"), (F.col("item_id") + 1).alias("right_id")).join(s.select(F.col("item_id").alias("right_id")), "right_id", "left_semi").select("left_id", "right_id"))
    return neardup.shift_match(pairs, s.unionByName(planted), 4)


HITS = WITHIN + f""", {SIM},
pr AS (SELECT 'hash' AS method, a.item_id AS left_id, b.item_id AS right_id FROM s a JOIN s b ON a.digest = b.digest AND a.item_id < b.item_id
  UNION ALL SELECT 'fingerprint', left_id, right_id FROM sp WHERE hamming <= 1 UNION ALL SELECT 'embedding', test_id, train_id FROM nn WHERE cos > {TAU_WITHIN}),
ht AS (SELECT a.domain, method, CASE WHEN a.split = 'test' THEN left_id ELSE right_id END AS item_id, bool_or(a.group_id <> b.group_id) AS cross_group
  FROM pr JOIN s a ON a.item_id = left_id JOIN s b ON b.item_id = right_id WHERE a.domain = b.domain AND a.split || b.split IN ('traintest', 'testtrain') GROUP BY 1, 2, 3)"""


def hits(spark, sf_dir):
    """Test items that each method finds again in train, of the items before de-duplication."""
    v = within_vectors(spark, sf_dir)
    items = v.select("item_id", "domain", "split", "group_id")
    raw = raw_split(spark, sf_dir).select("item_id", "digest", "domain", "split")
    same = raw.alias("a").join(raw.alias("b"), ["digest", "domain"]).where("a.split = 'train' and b.split = 'test'").select(F.col("a.item_id").alias("left_id"), F.col("b.item_id").alias("right_id"))
    prints = neardup.hamming_pairs(materialize(text_hashes(spark, sf_dir), "simhash"))
    near = neardup.nearest_train(v.select("item_id", "domain", "split", "features")).where(F.col("cos") > TAU_WITHIN).select(F.col("test_id").alias("left_id"), F.col("train_id").alias("right_id"))
    return [leakage.test_hits(p, items, m) for p, m in ((same, "hash"), (prints, "fingerprint"), (near, "embedding"))]


@query("leak_by_method", WITH + HITS + " SELECT domain, method, count(*) AS n_test_items, count(*) FILTER (cross_group) AS cross_group_items FROM ht GROUP BY 1, 2")
def leak_by_method(spark, sf_dir):
    return leakage.leak_by_method(*hits(spark, sf_dir))


@query("leak_test_items", WITH + HITS + " SELECT DISTINCT domain, item_id FROM ht")
def leak_test_items(spark, sf_dir):
    return leakage.leak_union(*hits(spark, sf_dir)).select("domain", "item_id")


@query("leak_evidence", WITH + HITS + " SELECT domain, item_id, count(DISTINCT method) AS n_methods, string_agg(method, ',' ORDER BY method) AS methods FROM ht GROUP BY 1, 2")
def leak_evidence(spark, sf_dir):
    return leakage.leak_union(*hits(spark, sf_dir))


@query("contamination", r"""WITH t AS (SELECT doc_id AS item_id, list_filter(regexp_split_to_array(lower(text), '[^\p{L}0-9]+'), lambda w: w <> '') AS w FROM documents),
b AS (SELECT item_id AS passage_id, list_filter(regexp_split_to_array(lower(text), '[^\p{L}0-9]+'), lambda w: w <> '') AS w FROM benchmark),
tg AS (SELECT DISTINCT item_id, array_to_string(list_slice(w, k, k + 7), ' ') AS g FROM (SELECT item_id, w, unnest(range(1, len(w) - 6)) AS k FROM t WHERE len(w) >= 8)),
bg AS (SELECT DISTINCT passage_id, array_to_string(list_slice(w, k, k + 7), ' ') AS g FROM (SELECT passage_id, w, unnest(range(1, len(w) - 6)) AS k FROM b WHERE len(w) >= 8))
SELECT item_id, passage_id, count(*) AS shared FROM tg JOIN bg USING (g) GROUP BY 1, 2""")
def contamination(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), "text")
    return neardup.contamination(docs, table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("passage_id"), "text"))


def _robust_sql(extra: str, excluded: str, test_only: bool = False) -> str:
    gone = f"item_id IN ({excluded})" + " AND split = 'test'" * test_only
    return f"""WITH {SQL_ITEMS}{SQL_SPLIT}{SQL_FEATS}{extra},
base AS (SELECT i.item_id, i.domain, i.group_id, i.class, i.split, f.* EXCLUDE (item_id) FROM items i JOIN feats f USING (item_id) WHERE i.domain <> 'TINY'),
ta AS ({TASK_SQL['binary']}), tb AS (SELECT * FROM ta WHERE NOT ({gone})),
tra AS (SELECT * FROM ta WHERE split = 'train'), tea AS (SELECT * FROM ta WHERE split = 'test'), trb AS (SELECT * FROM tb WHERE split = 'train'), teb AS (SELECT * FROM tb WHERE split = 'test')""" + sql_probe("pa", "tra", "tea") + sql_probe("pb", "trb", "teb") + sql_scores("ma", "pa") + sql_scores("mb", "pb") + f"""
SELECT (SELECT ntr FROM {SQL_NTR.format(m='ma')}) AS ntr_before, (SELECT ntr FROM {SQL_NTR.format(m='mb')}) AS ntr_after, (SELECT count(*) FROM ta) - (SELECT count(*) FROM tb) AS removed,
 (SELECT round(min(b.caf1 - a.caf1), 6) FROM ma a JOIN mb b USING (train_domain, test_domain) WHERE train_domain = test_domain) AS diag_drop, (SELECT round(max(b.caf1 - a.caf1), 6) FROM ma a JOIN mb b USING (train_domain, test_domain) WHERE train_domain = test_domain) AS diag_rise"""


def robust(spark, sf_dir, exclusions, scope="all"):
    """Ratio before and after leaving items out, and the range of the diagonal's change."""
    items = base_items(spark, sf_dir)
    rest = materialize(leakage.rerun_without(items, exclusions, scope), "rest")
    a, b = (materialize(task_matrix(spark, sf_dir, "binary", x), "matrix") for x in (items, rest))
    n = items.agg(F.count(F.lit(1)).alias("n1")).join(F.broadcast(rest.agg(F.count(F.lit(1)).alias("n2")))).select((F.col("n1") - F.col("n2")).alias("removed"))
    both = a.where("train_domain = test_domain").select("test_domain", F.col("caf1").alias("x")).join(b.where("train_domain = test_domain").select("test_domain", F.col("caf1").alias("y")), "test_domain")
    diag = both.agg(F.round(F.min(F.col("y") - F.col("x")), 6).alias("diag_drop"), F.round(F.max(F.col("y") - F.col("x")), 6).alias("diag_rise"))
    before = transfer.negative_transfer_ratio(a).select(F.col("ntr").alias("ntr_before"))
    after = transfer.negative_transfer_ratio(b).select(F.col("ntr").alias("ntr_after"))
    return before.join(F.broadcast(after)).join(F.broadcast(n)).join(F.broadcast(diag))


@query("robust_neardup", _robust_sql(CROSS, f"SELECT left_id FROM cp WHERE cos >= {TAU} UNION SELECT right_id FROM cp WHERE cos >= {TAU}"))
def robust_neardup(spark, sf_dir):
    pairs = neardup.blocked_cosines(vectors(spark, sf_dir).drop("class"), TAU)
    return robust(spark, sf_dir, materialize(pairs.select(F.explode(F.array("left_id", "right_id")).alias("item_id")), "out"))


@query("robust_conflict", _robust_sql(CONFLICTS, "SELECT item_id FROM rawi WHERE digest IN (SELECT digest FROM conf WHERE space = 'raw')"))
def robust_conflict(spark, sf_dir):
    from crossaudit.plans.workloads import raw_items

    keys = document_conflicts(spark, sf_dir, "raw").select(F.col("key_0").alias("digest"))
    return robust(spark, sf_dir, materialize(raw_items(spark, sf_dir).join(keys, "digest", "left_semi").select("item_id"), "out"))


@query("robust_within", _robust_sql(HITS, "SELECT item_id FROM ht", test_only=True))
def robust_within(spark, sf_dir):
    return robust(spark, sf_dir, materialize(leakage.leak_union(*hits(spark, sf_dir)).select("item_id"), "out"), scope="test")
