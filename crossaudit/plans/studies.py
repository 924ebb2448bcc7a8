"""Label budgets, joint training, quality and zero-shot studies, and probes of Spark ML, on the given tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from crossaudit.functions.storage import materialize
from crossaudit.operators import adapt, encode, probe, stats, transfer, zeroshot
from crossaudit.operators.encode import HANDCRAFTED
from crossaudit.plans.matrix import SQL_FEATS, features, sql_probe, sql_scores, sql_task, task_predictions
from crossaudit.plans.registry import query
from crossaudit.plans.workloads import SQL_ITEMS, SQL_SPLIT, split_items
from crossaudit.sources import table

#: Labels a class; the last one is all there are.
BUDGETS = [1, 5, 10, 50, 1_000_000]
WITH = f"""WITH {SQL_ITEMS}{SQL_SPLIT}{SQL_FEATS},
base AS (SELECT i.item_id, i.domain, i.raw_label, i.group_id, i.class, i.class AS y, i.split, i.n_chars, f.* EXCLUDE (item_id) FROM items i JOIN feats f USING (item_id)),
lt AS (SELECT * FROM base WHERE domain = 'LARGE' AND split = 'train'), le AS (SELECT * FROM base WHERE domain = 'LARGE' AND split = 'test')"""


def studied(spark, sf_dir):
    items = split_items(spark, sf_dir).select("item_id", "domain", "raw_label", "group_id", "class", F.col("class").alias("y"), "split", "n_chars")
    return materialize(items.join(features(spark, sf_dir), "item_id"), "studied")


def _shots_sql(draws: list[int], prefix: str) -> str:
    return f""", sr AS (SELECT draw, item_id, y, row_number() OVER (PARTITION BY draw, y ORDER BY md5('{prefix}:' || draw || ':' || item_id), item_id) AS r FROM lt, (SELECT unnest({draws}) AS draw)),
sb AS (SELECT draw, budget, item_id, y, count(*) OVER (PARTITION BY draw, budget, y) AS actual_n FROM sr, (SELECT unnest({BUDGETS}) AS budget) WHERE r <= budget)"""


@query("shots_fixed", WITH + _shots_sql([42], "fs") + " SELECT draw, budget, item_id, y, actual_n FROM sb")
def shots_fixed(spark, sf_dir):
    return adapt.draw_shots(studied(spark, sf_dir).where("domain = 'LARGE' and split = 'train'"), [42], BUDGETS, "fs")


EPISODES = list(range(1, 21))


@query("episode_counts", WITH + _shots_sql(EPISODES, "ep") + " SELECT draw, budget, y, count(*) AS n, CAST(sum(item_id) AS BIGINT) AS checksum FROM sb GROUP BY 1, 2, 3")
def episode_counts(spark, sf_dir):
    shots = adapt.draw_shots(studied(spark, sf_dir).where("domain = 'LARGE' and split = 'train'"), EPISODES, BUDGETS, "ep")
    return shots.groupBy("draw", "budget", "y").agg(F.count(F.lit(1)).alias("n"), F.sum("item_id").alias("checksum"))


ARMS = WITH + _shots_sql(EPISODES, "ep") + """, et AS (SELECT b.* REPLACE (draw || ':' || budget AS domain) FROM sb JOIN base b USING (item_id))""" + sql_probe("ea", "et", "le") + sql_scores("sa", "ea")


def _arm(spark, sf_dir, arm: str):
    """Scores of an arm over episodes and budgets: one distributed fit of all tiny training sets.

    Arm A scales by its own shots, arm C by the unlabelled pool of all train splits.
    """
    items = studied(spark, sf_dir)
    shots = adapt.draw_shots(items.where("domain = 'LARGE' and split = 'train'"), EPISODES, BUDGETS, "ep").drop("y", "actual_n")
    train = items.join(shots, "item_id").withColumn("domain", F.concat_ws(":", "draw", "budget"))
    models = transfer.fit_centroid(train)
    if arm == "C":
        pool = items.where("split = 'train'").agg(*[F.avg(f).alias(f"pm_{f}") for f in HANDCRAFTED], *[F.stddev_pop(f).alias(f"ps_{f}") for f in HANDCRAFTED])
        means = train.groupBy(F.col("domain").alias("model"), F.col("y").alias("pred")).agg(*[F.avg(f).alias(f"a_{f}") for f in HANDCRAFTED]).join(F.broadcast(pool))
        z = [F.coalesce(F.try_divide(F.col(f"a_{f}") - F.col(f"pm_{f}"), F.col(f"ps_{f}")), F.lit(0.0)).alias(f"c_{f}") for f in HANDCRAFTED]
        models = means.select("model", "pred", *[F.col(f"pm_{f}").alias(f"m_{f}") for f in HANDCRAFTED], *[F.col(f"ps_{f}").alias(f"s_{f}") for f in HANDCRAFTED], *z)
    test = items.where("domain = 'LARGE' and split = 'test'").select("item_id", "domain", F.col("y").alias("truth"), *HANDCRAFTED)
    preds = transfer.score_all(test, models).select("item_id", F.col("model").alias("train_domain"), F.col("domain").alias("test_domain"), "truth", "pred")
    parts = F.split("train_domain", ":")
    return transfer.transfer_matrix(preds).select(F.lit(arm).alias("arm"), parts[0].cast("int").alias("episode"), parts[1].cast("int").alias("budget"), F.col("caf1").alias("score"))


SQL_ARM_A = "SELECT 'A' AS arm, CAST(split_part(train_domain, ':', 1) AS INT) AS episode, CAST(split_part(train_domain, ':', 2) AS INT) AS budget, caf1 AS score FROM sa"


@query("arm_frozen", ARMS + " " + SQL_ARM_A)
def arm_frozen(spark, sf_dir):
    return _arm(spark, sf_dir, "A")


def _pool_arm_sql() -> str:
    f = HANDCRAFTED
    apart = " + ".join(f"power(coalesce((t.{x} - m_{x}) / nullif(s_{x}, 0), 0) - c_{x}, 2)" for x in f)
    return f""", ps AS (SELECT {', '.join(f'avg({x}) AS m_{x}, stddev_pop({x}) AS s_{x}' for x in f)} FROM base WHERE split = 'train'),
cm AS (SELECT domain AS model, y AS pred, {', '.join(f'any_value(m_{x}) AS m_{x}, any_value(s_{x}) AS s_{x}, coalesce((avg({x}) - any_value(m_{x})) / nullif(any_value(s_{x}), 0), 0) AS c_{x}' for x in f)} FROM et, ps GROUP BY domain, y),
ec AS (SELECT t.item_id, model AS train_domain, t.domain AS test_domain, t.y AS truth, pred FROM le t, cm QUALIFY row_number() OVER (PARTITION BY t.item_id, model ORDER BY round({apart}, 6), pred) = 1)""" + sql_scores("sc", "ec")


SQL_ARM_C = SQL_ARM_A.replace("'A'", "'C'").replace("FROM sa", "FROM sc")
#: Fixed value: the 97.5th percentile of t with 19 degrees of freedom, for twenty episodes.
SQL_CONTRAST = ARMS + _pool_arm_sql() + f""", ac AS (SELECT budget, c.score - a.score AS d FROM ({SQL_ARM_A}) a JOIN ({SQL_ARM_C}) c USING (episode, budget)),
ct AS (SELECT budget, count(d) AS n, round(avg(d), 6) AS mean, round(avg(d) - 2.093024 * stddev_samp(d) / sqrt(count(d)), 6) AS ci_lo, round(avg(d) + 2.093024 * stddev_samp(d) / sqrt(count(d)), 6) AS ci_hi FROM ac GROUP BY budget)"""


@query("arm_adapted", ARMS + _pool_arm_sql() + " " + SQL_ARM_C)
def arm_adapted(spark, sf_dir):
    return _arm(spark, sf_dir, "C")


@query("episode_means", ARMS + f", a AS ({SQL_ARM_A}) SELECT budget, CAST(count(*) AS BIGINT) AS n_runs, round(avg(score), 6) AS mean, round(stddev_samp(score), 6) AS std, count(DISTINCT score) AS n_distinct, count(DISTINCT score) = 1 AS deterministic FROM a GROUP BY budget")
def episode_means(spark, sf_dir):
    return stats.seed_summary(_arm(spark, sf_dir, "A"), ["budget"])


@query("paired_contrast", SQL_CONTRAST + " SELECT *, ci_lo > 0 OR ci_hi < 0 AS significant FROM ct")
def paired_contrast(spark, sf_dir):
    """Arm C minus arm A over shared episodes."""
    both = materialize(_arm(spark, sf_dir, "A").unionByName(_arm(spark, sf_dir, "C")), "arms")
    return adapt.paired_contrast(both, "C", "A")


@query("adapt_crossover", SQL_CONTRAST + """, cr AS (SELECT min(budget) FILTER (ci_lo > 0) AS sure, min(budget) FILTER (mean > 0) AS maybe, min(budget) AS first FROM ct)
SELECT CASE WHEN sure > first THEN sure WHEN maybe > first THEN maybe END AS crossover, CASE WHEN sure > first THEN 'crossover' WHEN maybe > first THEN 'trend' ELSE 'none' END AS kind FROM cr""")
def adapt_crossover(spark, sf_dir):
    both = materialize(_arm(spark, sf_dir, "A").unionByName(_arm(spark, sf_dir, "C")), "arms")
    return adapt.crossover(adapt.paired_contrast(both, "C", "A"))


@query("adapt_pool", WITH + """ SELECT protocol, origin, count(*) AS n FROM (SELECT 'inductive' AS protocol, 'items' AS origin FROM base WHERE split = 'train' UNION ALL SELECT 'transductive', 'items' FROM base
UNION ALL SELECT p, 'extra' FROM pages, (SELECT unnest(['inductive', 'transductive']) AS p)) GROUP BY 1, 2""")
def adapt_pool(spark, sf_dir):
    items, extra = studied(spark, sf_dir), table(spark, sf_dir, "pages").select(F.col("page_id").alias("item_id"))
    both = [adapt.build_pool(items, extra, p).withColumn("protocol", F.lit(p)) for p in ("inductive", "transductive")]
    return both[0].unionByName(both[1]).groupBy("protocol", "origin").agg(F.count(F.lit(1)).alias("n"))


@query("pool_violations", WITH + " SELECT 'transductive' AS protocol, split, count(*) AS n FROM base WHERE split <> 'train' GROUP BY 1, 2")
def pool_violations(spark, sf_dir):
    items, extra = studied(spark, sf_dir), table(spark, sf_dir, "pages").select(F.col("page_id").alias("item_id"))
    both = [adapt.pool_violations(adapt.build_pool(items, extra, p), items).withColumn("protocol", F.lit(p)) for p in ("inductive", "transductive")]
    return both[0].unionByName(both[1]).groupBy("protocol", "split").agg(F.count(F.lit(1)).alias("n"))


@query("exposure", WITH + """, t AS (SELECT count(*) AS labelled FROM lt), p AS (SELECT (SELECT count(*) FROM base WHERE split = 'train') + (SELECT count(*) FROM pages) AS unlabelled)
SELECT 'A' AS arm, labelled, 0 AS unlabelled, 0 AS steps FROM t UNION ALL SELECT 'C', labelled, unlabelled, unlabelled // 16 FROM t, p""")
def exposure(spark, sf_dir):
    """Labelled and unlabelled items each arm sees, and steps of one pass in batches of 16."""
    items, extra = studied(spark, sf_dir), table(spark, sf_dir, "pages").select(F.col("page_id").alias("item_id"))
    labelled = items.where("domain = 'LARGE' and split = 'train'").agg(F.count(F.lit(1)).alias("labelled"))
    pool = adapt.build_pool(items, extra).agg(F.count(F.lit(1)).alias("unlabelled"))
    a = labelled.select(F.lit("A").alias("arm"), "labelled", F.lit(0).cast("long").alias("unlabelled"), F.lit(0).cast("long").alias("steps"))
    return a.unionByName(labelled.join(F.broadcast(pool)).select(F.lit("C").alias("arm"), "labelled", "unlabelled", F.floor(F.col("unlabelled") / 16).alias("steps")))


TARGETS = ("LARGE", "NOISY")
PAIR = ("brief", "extended")
JOINT = WITH + """, jb AS (SELECT * REPLACE (class AS y) FROM base WHERE domain IN ('LARGE', 'NOISY') AND class IN ('brief', 'extended')),
js AS (SELECT * FROM jb WHERE split = 'train'), je AS (SELECT * FROM jb WHERE split = 'test'),
jn AS (SELECT * REPLACE ('naive' AS domain, domain || '::' || raw_label AS y) FROM js), jm AS (SELECT * REPLACE ('mapped' AS domain) FROM js),
jz AS (SELECT * REPLACE ('normalized' AS domain, lower(regexp_replace(raw_label, '[^A-Za-z]', '', 'g')) AS y) FROM js)""" + sql_probe("p1", "js", "je") + sql_probe("p2", "jm", "je") + sql_probe("p3", "jn", "je") + sql_probe("p4", "jz", "je") + """,
nm AS (SELECT DISTINCT domain || '::' || raw_label AS raw, lower(regexp_replace(raw_label, '[^A-Za-z]', '', 'g')) AS norm, class FROM js), nz AS (SELECT norm, min(class) AS class FROM nm GROUP BY norm),
jp AS (SELECT item_id, train_domain, test_domain, truth, pred FROM p1 UNION ALL SELECT item_id, train_domain, test_domain, truth, pred FROM p2
  UNION ALL SELECT item_id, train_domain, test_domain, truth, class FROM p3 JOIN nm ON pred = raw UNION ALL SELECT item_id, train_domain, test_domain, truth, class FROM p4 JOIN nz ON pred = norm)""" + sql_scores("jm2", "jp") + """,
jt AS (SELECT test_domain AS target, CASE WHEN train_domain = test_domain THEN 'single' WHEN train_domain IN ('LARGE', 'NOISY') THEN 'best cross' ELSE train_domain END AS condition, max(caf1) AS caf1, any_value(n) AS n_test FROM jm2 GROUP BY 1, 2)"""


def joint_rows(spark, sf_dir):
    """``target, condition, caf1, n_test``: single-domain, best cross-domain, naive merge, names only and mapped joint.

    The three joint fits share one pool and differ only in what they are told to predict; raw and normalised predictions
    are mapped to classes after the fact, for scoring alone. All conditions score the same test items.
    """
    items = studied(spark, sf_dir).where(F.col("domain").isin(*TARGETS) & F.col("class").isin(*PAIR))
    train = items.where("split = 'train'")
    test = items.where("split = 'test'").select("item_id", "domain", F.col("class").alias("truth"), *HANDCRAFTED)
    raw, name = F.concat_ws("::", "domain", "raw_label"), F.lower(F.regexp_replace("raw_label", "[^A-Za-z]", ""))

    def scored(model, back=None):
        out = transfer.score_all(test, model).select("item_id", F.col("model").alias("train_domain"), F.col("domain").alias("test_domain"), "truth", "pred")
        return out if back is None else out.join(F.broadcast(back), "pred").select("item_id", "train_domain", "test_domain", "truth", F.col("class").alias("pred"))

    def pooled(label, condition):
        return transfer.fit_centroid(train.withColumn("y", label).withColumn("domain", F.lit(condition)))

    preds = scored(transfer.fit_centroid(train)).unionByName(scored(pooled(F.col("class"), "mapped")))
    preds = preds.unionByName(scored(pooled(raw, "naive"), train.select(raw.alias("pred"), "class").distinct()))
    preds = preds.unionByName(scored(pooled(name, "normalized"), train.groupBy(name.alias("pred")).agg(F.min("class").alias("class"))))
    condition = F.when(F.col("train_domain") == F.col("test_domain"), "single").when(F.col("train_domain").isin(*TARGETS), "best cross").otherwise(F.col("train_domain"))
    return transfer.transfer_matrix(preds).groupBy(F.col("test_domain").alias("target"), condition.alias("condition")).agg(F.max("caf1").alias("caf1"), F.max("n").alias("n_test"))


@query("joint_table", JOINT + " SELECT target, condition, caf1, n_test FROM jt")
def joint_table(spark, sf_dir):
    return joint_rows(spark, sf_dir)


@query("joint_winner", JOINT + """ SELECT target, arg_max(condition, (caf1, condition)) AS winner, round(max(caf1) FILTER (condition = 'mapped') - max(caf1) FILTER (condition = 'naive'), 6) AS naive_loss, count(DISTINCT n_test) = 1 AS same_tests FROM jt GROUP BY target""")
def joint_winner(spark, sf_dir):
    """The winner is computed, never assumed."""
    of = lambda c: F.max(F.when(F.col("condition") == c, F.col("caf1")))
    return joint_rows(spark, sf_dir).groupBy("target").agg(F.max_by("condition", F.struct("caf1", "condition")).alias("winner"), F.round(of("mapped") - of("naive"), 6).alias("naive_loss"), (F.count_distinct("n_test") == 1).alias("same_tests"))


for _name, _keep in (("joint_baselines", ("single", "best cross")), ("joint_naive", ("naive",)), ("joint_mapped", ("mapped",)), ("joint_normalized", ("normalized",))):

    @query(_name, JOINT + f" SELECT target, condition, caf1, n_test FROM jt WHERE condition IN ({', '.join(repr(c) for c in _keep)})")
    def _joint(spark, sf_dir, keep=_keep):
        return joint_rows(spark, sf_dir).where(F.col("condition").isin(*keep))


@query("small_case", WITH + """, sst AS (SELECT 'without' AS domain, * EXCLUDE (domain) FROM base WHERE domain = 'NOISY' AND split = 'train' UNION ALL SELECT 'with', * EXCLUDE (domain) FROM base WHERE domain IN ('NOISY', 'TINY') AND split = 'train'),
sse AS (SELECT * FROM base WHERE domain IN ('NOISY', 'TINY') AND split = 'test')""" + sql_probe("p1", "sst", "sse") + sql_scores("m1", "p1") + " SELECT train_domain AS condition, test_domain AS target, n, caf1, n < 20 AS underpowered FROM m1")
def small_case(spark, sf_dir):
    """The smallest domain added to another one's training, scored on both."""
    items = studied(spark, sf_dir).where("domain in ('NOISY', 'TINY')")
    train = items.where("split = 'train'")
    both = train.where("domain = 'NOISY'").withColumn("domain", F.lit("without")).unionByName(train.withColumn("domain", F.lit("with")))
    test = items.where("split = 'test'").select("item_id", "domain", F.col("y").alias("truth"), *HANDCRAFTED)
    preds = transfer.score_all(test, transfer.fit_centroid(both)).select("item_id", F.col("model").alias("train_domain"), F.col("domain").alias("test_domain"), "truth", "pred")
    return transfer.transfer_matrix(preds).select(F.col("train_domain").alias("condition"), F.col("test_domain").alias("target"), "n", "caf1", (F.col("n") < 20).alias("underpowered"))


@query("snr_events", """WITH q AS (SELECT user_id, quantile_cont(value * value, 0.9) AS hi, quantile_cont(value * value, 0.1) AS lo FROM events GROUP BY user_id)
SELECT user_id, round(CASE WHEN lo > 0 AND hi > 0 THEN least(100.0::DOUBLE, 10 * log10(hi / lo)) END, 6) AS snr_db, coalesce(10 * log10(nullif(hi, 0) / nullif(lo, 0)) >= 100, lo = 0) AS saturated FROM q""")
def snr_events(spark, sf_dir, cap: float = 100.0):
    """Signal quality of each user's series: 10 log10 of the 90th over the 10th percentile of energy, capped and flagged."""
    q = table(spark, sf_dir, "events").groupBy("user_id").agg(F.percentile(F.col("value") * F.col("value"), 0.9).alias("hi"), F.percentile(F.col("value") * F.col("value"), 0.1).alias("lo"))
    db = 10 * F.log10(F.try_divide(F.nullif("hi", F.lit(0.0)), F.nullif("lo", F.lit(0.0))))
    return q.select("user_id", F.round(F.when((F.col("lo") > 0) & (F.col("hi") > 0), F.least(F.lit(cap), db)), 6).alias("snr_db"), F.coalesce(db >= cap, F.col("lo") == 0).alias("saturated"))


SQL_QUALITY = "quality AS (SELECT item_id, round(fresh_mean - punct_mean - digits_mean, 6) AS quality FROM feats)"


def quality_of(feats):
    """Text quality: distinct words, less punctuation and digits, averaged over lines."""
    return feats.select("item_id", F.round(F.col("fresh_mean") - F.col("punct_mean") - F.col("digits_mean"), 6).alias("quality"))


@query("text_quality", f"WITH {SQL_ITEMS}{SQL_FEATS}, {SQL_QUALITY} SELECT * FROM quality")
def text_quality(spark, sf_dir):
    return quality_of(features(spark, sf_dir))


SQL_QC = sql_task("multi") + f", {SQL_QUALITY}" + """, qc AS (SELECT train_domain, test_domain, quality, (truth = pred)::INT::DOUBLE AS c FROM preds JOIN quality USING (item_id)),
qr AS (SELECT {k}, count(*) AS n, round(covar_pop(quality, c) / nullif(stddev_pop(quality) * stddev_pop(c), 0), 6) AS r FROM qc WHERE {w} GROUP BY {k})
SELECT {k}, n, r, round(r * sqrt(n - 2.0::DOUBLE) / nullif(sqrt(1 - r * r), 0), 6) AS t FROM qr"""


def quality_rows(spark, sf_dir):
    return task_predictions(spark, sf_dir, "multi").join(quality_of(features(spark, sf_dir)), "item_id").withColumn("correct", F.col("truth") == F.col("pred"))


@query("quality_corr_pairs", SQL_QC.format(k="train_domain, test_domain", w="train_domain <> test_domain"))
def quality_corr_pairs(spark, sf_dir):
    return stats.point_biserial(quality_rows(spark, sf_dir).where("train_domain <> test_domain").withColumn("correct", F.col("correct").cast("int")), ["train_domain", "test_domain"])


@query("quality_corr_within", SQL_QC.format(k="test_domain", w="train_domain = test_domain"))
def quality_corr_within(spark, sf_dir):
    return stats.point_biserial(quality_rows(spark, sf_dir).where("train_domain = test_domain").withColumn("correct", F.col("correct").cast("int")), ["test_domain"])


@query("quality_confound", sql_task("multi") + f", {SQL_QUALITY}" + """ SELECT domain AS test_domain, round(median(quality), 6) AS median_quality, round((SELECT avg(caf1) FROM mat WHERE test_domain = domain AND train_domain <> domain), 6) AS incoming
FROM (SELECT domain, quality FROM base JOIN quality USING (item_id)) GROUP BY domain""")
def quality_confound(spark, sf_dir):
    """Median quality of each domain beside the mean score of transfer into it."""
    items = studied(spark, sf_dir).where("domain <> 'TINY'")
    q = items.join(quality_of(items), "item_id").groupBy(F.col("domain").alias("test_domain")).agg(F.round(F.percentile("quality", 0.5), 6).alias("median_quality"))
    m = transfer.transfer_matrix(task_predictions(spark, sf_dir, "multi")).where("train_domain <> test_domain").groupBy("test_domain").agg(F.round(F.avg("caf1"), 6).alias("incoming"))
    return q.join(m, "test_domain", "left")


ZS = WITH + """, zt AS (SELECT item_id, domain, class AS truth, n_chars FROM base WHERE split = 'test'),
zc AS (SELECT domain, truth, count(*) AS c, any_value(t) AS t FROM zt JOIN (SELECT domain, count(*) AS t FROM zt GROUP BY 1) USING (domain) GROUP BY 1, 2),
zx AS (SELECT *, c * least(20, t) / t::DOUBLE AS x, floor(c * least(20, t) / t::DOUBLE) AS b FROM zc),
zq AS (SELECT domain, truth, b + CASE WHEN row_number() OVER (PARTITION BY domain ORDER BY round(x - b, 9) DESC, truth) <= least(20, t) - sum(b) OVER (PARTITION BY domain) THEN 1 ELSE 0 END AS quota FROM zx),
zs AS (SELECT z.* FROM zt z JOIN zq USING (domain, truth) QUALIFY row_number() OVER (PARTITION BY domain, truth ORDER BY md5('42:' || item_id), item_id) <= quota),
za AS (SELECT *, CASE WHEN n_chars < 700 THEN 'this is brief' WHEN n_chars < 2600 THEN 'medium' WHEN n_chars < 9000 THEN 'Extended.' ELSE 'brief or extended?' END AS answer FROM zs),
zp AS (SELECT *, CASE WHEN len(f) = 1 THEN f[1] ELSE 'UNPARSED' END AS pred FROM (SELECT *, list_filter(['brief', 'burst', 'extended', 'medium', 'neutral'], lambda k: contains(lower(answer), k)) AS f FROM za))"""


def zs_items(spark, sf_dir):
    test = studied(spark, sf_dir).where("split = 'test'").select("item_id", "domain", F.col("class").alias("truth"), "n_chars")
    return zeroshot.stratified_subsample(test, 20)


def zs_predictions(spark, sf_dir):
    answer = zeroshot.rule_answer(F.col("n_chars"))
    return zs_items(spark, sf_dir).withColumn("answer", answer).withColumn("pred", zeroshot.parse_answer(F.col("answer"), ["brief", "burst", "extended", "medium", "neutral"]))


@query("zs_sample", ZS + " SELECT item_id, domain, truth FROM zs")
def zs_sample(spark, sf_dir):
    return zs_items(spark, sf_dir).select("item_id", "domain", "truth")


@query("zs_predict", ZS + " SELECT item_id, domain, truth, answer, pred FROM zp")
def zs_predict(spark, sf_dir):
    return zs_predictions(spark, sf_dir).select("item_id", "domain", "truth", "answer", "pred")


def rule_call(text: str) -> str:
    """The rule predictor as a foreign call would be: from the text alone."""
    n = len(text or "")
    return "this is brief" if n < 700 else "medium" if n < 2600 else "Extended." if n < 9000 else "brief or extended?"


@query("zs_calls", ZS + " SELECT item_id, answer, pred, CAST(NULL AS VARCHAR) AS error FROM zp")
def zs_calls(spark, sf_dir):
    """The sample through the caller: one call an item, retries, errors kept; its seconds are left out, for they differ."""
    texts = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), "text")
    calls = zeroshot.zero_shot(zs_items(spark, sf_dir).join(texts, "item_id"), rule_call, ["brief", "burst", "extended", "medium", "neutral"])
    return calls.select("item_id", "answer", "pred", "error")


@query("zs_report", ZS + sql_scores("zm", "zp", "domain") + """, tp AS (SELECT domain, max(c) AS top, CAST(coalesce(sum(c) FILTER (pred = 'UNPARSED'), 0) AS BIGINT) AS unparsed, CAST(sum(c) AS BIGINT) AS calls FROM (SELECT domain, pred, count(*) AS c FROM zp GROUP BY 1, 2) GROUP BY 1)
SELECT domain, calls, unparsed, round(top / calls, 6) AS skew, acc, caf1, uar, chance_uar FROM zm JOIN tp USING (domain)""")
def zs_report(spark, sf_dir):
    return zeroshot.zs_report(zs_predictions(spark, sf_dir))


@query("probe_path")
def probe_path(spark, sf_dir):
    """Validation score of every constant for the logistic probe of one domain, and the choice."""
    items = transfer.task_labels(studied(spark, sf_dir).where("domain = 'LARGE'"), "binary")
    _, chosen, path = probe.fit_probe(items.where("split = 'train'"), items.where("split = 'val'"), HANDCRAFTED)
    return spark.createDataFrame([(c, s, c == chosen) for c, s, _ in path], "c double, val_caf1 double, chosen boolean")


@query("probe_boosted")
def probe_boosted(spark, sf_dir):
    """The binary matrix of boosted trees: one fit a domain, scored on every domain's test items."""
    items = transfer.task_labels(studied(spark, sf_dir).where("domain <> 'TINY'"), "binary")
    test, preds = items.where("split = 'test'"), None
    for domain in ("CLEAN", "LARGE", "NOISY"):
        model = probe.fit_boosted(items.where((F.col("domain") == domain) & (F.col("split") == "train")), HANDCRAFTED)
        own = model(test).select("item_id", F.col("y").alias("truth"), "pred", F.lit(domain).alias("train_domain"), F.col("domain").alias("test_domain"))
        preds = own if preds is None else preds.unionByName(own)
    return transfer.transfer_matrix(preds)


def _network(name: str, step: float, epochs: int):
    @query(name)
    def run(spark, sf_dir):
        items = transfer.task_labels(studied(spark, sf_dir).where("domain = 'LARGE'"), "binary")
        model = probe.fit_network(items.where("split = 'train'"), HANDCRAFTED, step=step, epochs=epochs)
        preds = model(items.where("split = 'test'")).select("item_id", F.col("y").alias("truth"), "pred", F.lit(name).alias("train_domain"), F.lit("LARGE").alias("test_domain"))
        return transfer.transfer_matrix(preds)


_network("arm_full", 0.5, 5)
_network("arm_stable", 0.03, 60)


@query("overfit_check")
def overfit_check(spark, sf_dir):
    """Boosted trees memorise 64 items: training accuracy of 1."""
    items = transfer.task_labels(studied(spark, sf_dir).where("domain = 'LARGE' and split = 'train'"), "binary")
    few = materialize(items.orderBy(F.md5(F.col("item_id").cast("string").cast("binary")), "item_id").limit(64), "few")
    out = probe.fit_boosted(few, HANDCRAFTED, trees=20)(few)
    return out.agg(F.count(F.lit(1)).alias("n"), F.avg((F.col("y") == F.col("pred")).cast("double")).alias("train_accuracy"))


STAR = """WITH b AS (SELECT r_name AS domain, l_returnflag AS y, l_quantity, l_extendedprice, l_discount, l_tax, o_custkey AS g, l_orderkey, l_linenumber, CAST('0x' || substr(md5('st:' || o_custkey), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE < 0.7 AS train
 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)
SELECT domain, train, y, count(*) AS n, round(avg(l_quantity), 4) AS quantity, round(avg(l_extendedprice), 2) AS price FROM b GROUP BY 1, 2, 3"""


def star_items(spark, sf_dir):
    """Line items with their customer's region as domain and the customer as group."""
    t = lambda n: table(spark, sf_dir, n)
    geo = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    buyers = t("customer").join(F.broadcast(geo), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "r_name")
    rows = t("lineitem").join(t("orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(buyers, F.col("o_custkey") == F.col("c_custkey"))
    h = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit("st"), "o_custkey").cast("binary")), 1, 8), 16, 10).cast("double") / 4294967296.0
    return rows.select(F.col("r_name").alias("domain"), F.col("l_returnflag").alias("y"), "l_quantity", "l_extendedprice", "l_discount", "l_tax", F.col("o_custkey").alias("group_id"), F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice").alias("item_id"), F.when(h < 0.7, "train").otherwise("test").alias("split"))


@query("star_audit", STAR)
def star_audit(spark, sf_dir):
    return star_items(spark, sf_dir).groupBy("domain", (F.col("split") == "train").alias("train"), "y").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("l_quantity"), 4).alias("quantity"), F.round(F.avg("l_extendedprice"), 2).alias("price"))


STAR_FEATURES = ("l_quantity", "l_extendedprice", "l_discount", "l_tax")


@query("star_matrix", STAR.split(")\nSELECT")[0].replace("SELECT r_name", "SELECT row_number() OVER () AS item_id, r_name", 1).replace("o_custkey AS g,", "o_custkey AS group_id,", 1) + "), trn AS (SELECT * FROM b WHERE train), tst AS (SELECT * FROM b WHERE NOT train)" + sql_probe("sp", "trn", "tst", f=STAR_FEATURES) + sql_scores("sm", "sp") + " SELECT * FROM sm")
def star_matrix(spark, sf_dir):
    """Return flags predicted across regions: a null case that should sit at chance."""
    return transfer.transfer_matrix(transfer.predict(star_items(spark, sf_dir), features=STAR_FEATURES))
