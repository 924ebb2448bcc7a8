"""Transfer matrices on the items, their summaries and tests."""

from __future__ import annotations

from pyspark.sql import functions as F

from crossaudit.functions.storage import materialize
from crossaudit.operators import encode, probe, stats, transfer
from crossaudit.operators.encode import HANDCRAFTED, LINE_STATS
from crossaudit.operators.ranks import running
from crossaudit.plans.registry import query
from crossaudit.plans.workloads import SQL_ITEMS, SQL_SPLIT, split_items
from crossaudit.sources import table

DRAWS = 40

SQL_FEATS = """,
ln AS (SELECT item_id, length(text) AS size, unnest(string_split(text, chr(10))) AS line FROM rawi),
st AS (SELECT item_id, size, nullif(length(line), 0)::DOUBLE AS chars, length(regexp_replace(line, '[^0-9]', '', 'g')) / nullif(length(line), 0)::DOUBLE AS digits,
   length(regexp_replace(line, '[^A-Z]', '', 'g')) / nullif(length(line), 0)::DOUBLE AS upper, length(regexp_replace(line, '[^.,;:!?]', '', 'g')) / nullif(length(line), 0)::DOUBLE AS punct,
   len(list_distinct(list_filter(string_split(line, ' '), lambda w: w <> ''))) / nullif(len(list_filter(string_split(line, ' '), lambda w: w <> '')), 0)::DOUBLE AS fresh FROM ln),
feats AS (SELECT item_id, """ + ", ".join(f"round(coalesce({f}({s}), 0), 6) AS {s}_{n}" for n, f in (("mean", "avg"), ("std", "stddev_pop")) for s in LINE_STATS) + """,
   round(ln(max(size) + 1.0::DOUBLE), 6) AS log_length FROM st GROUP BY item_id)"""

TASK_SQL = {
    "multi": "SELECT *, class AS y FROM base",
    "binary": "SELECT *, CASE WHEN class = 'brief' THEN 'brief' ELSE 'rest' END AS y FROM base",
    "subset": "SELECT *, CASE WHEN class = 'brief' THEN 'brief' ELSE 'rest' END AS y FROM base WHERE class <> 'neutral'",
    "common": "SELECT *, class AS y FROM base WHERE class IN ('brief', 'extended')",
}


def sql_probe(name: str, train: str, test: str, label: str = "y", by: str = "domain", extra: str = "", f: tuple[str, ...] = HANDCRAFTED) -> str:
    """CTEs that fit centroids on the rows of ``train`` and predict those of ``test`` as ``name``."""
    d = " + ".join(f"power(coalesce((t.{x} - m_{x}) / nullif(s_{x}, 0), 0) - c_{x}, 2)" for x in f)
    return f""",
{name}_sc AS (SELECT {by}, {', '.join(f'avg({x}) AS m_{x}, stddev_pop({x}) AS s_{x}' for x in f)} FROM {train} GROUP BY {by}),
{name}_mo AS (SELECT {by} AS model, {label} AS pred, {', '.join(f'any_value(m_{x}) AS m_{x}, any_value(s_{x}) AS s_{x}, coalesce((avg({x}) - any_value(m_{x})) / nullif(any_value(s_{x}), 0), 0) AS c_{x}' for x in f)}
   FROM {train} JOIN {name}_sc USING ({by}) GROUP BY {by}, {label}),
{name} AS (SELECT t.item_id, t.group_id, model AS train_domain, t.domain AS test_domain, t.{label} AS truth, pred{extra} FROM {test} t, {name}_mo
   QUALIFY row_number() OVER (PARTITION BY t.item_id, model ORDER BY round({d}, 6), pred) = 1)"""


def sql_scores(name: str, preds: str, keys: str = "train_domain, test_domain", weight: str = "1") -> str:
    """CTEs of per-class counts ``{name}_pc`` and overall scores ``{name}``."""
    return f""",
{name}_pc AS (SELECT {keys}, class, sum(tp) AS tp, sum(fp) AS fp, sum(fn) AS fn, coalesce(2.0::DOUBLE * sum(tp) / nullif(2 * sum(tp) + sum(fp) + sum(fn), 0), 0) AS f1, sum(tp)::DOUBLE / nullif(sum(tp) + sum(fn), 0) AS recall
  FROM (SELECT {keys}, truth AS class, CASE WHEN truth = pred THEN {weight} ELSE 0 END AS tp, 0 AS fp, CASE WHEN truth <> pred THEN {weight} ELSE 0 END AS fn FROM {preds}
        UNION ALL SELECT {keys}, pred, 0, {weight}, 0 FROM {preds} WHERE truth <> pred) GROUP BY {keys}, class),
{name} AS (SELECT {keys}, CAST(sum(tp + fn) AS BIGINT) AS n, round(sum(tp) / sum(tp + fn), 6) AS acc, round(avg(f1), 6) AS caf1, round(avg(recall), 6) AS uar, round(1.0::DOUBLE / count(recall), 6) AS chance_uar FROM {name}_pc GROUP BY {keys})"""


def sql_task(task: str, where: str = "true") -> str:
    return f"""WITH {SQL_ITEMS}{SQL_SPLIT}{SQL_FEATS},
base AS (SELECT i.item_id, i.domain, i.group_id, i.class, i.split, f.* EXCLUDE (item_id) FROM items i JOIN feats f USING (item_id) WHERE i.domain <> 'TINY' AND {where}),
t_{task} AS ({TASK_SQL[task]}),
tr_{task} AS (SELECT * FROM t_{task} WHERE split = 'train'), te_{task} AS (SELECT * FROM t_{task} WHERE split = 'test')""" + sql_probe("preds", f"tr_{task}", f"te_{task}") + sql_scores("mat", "preds")


def features(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), "text")
    return encode.handcrafted(docs)


def base_items(spark, sf_dir):
    """Split items of the domains that pass the size gate, with the handcrafted vector; computed once."""
    items = split_items(spark, sf_dir).where("domain <> 'TINY'").select("item_id", "domain", "group_id", "class", "split", "digest")
    return materialize(items.join(features(spark, sf_dir), "item_id"), "items")


def task_predictions(spark, sf_dir, task: str, items=None):
    items = base_items(spark, sf_dir) if items is None else items
    return transfer.predict(transfer.task_labels(items, task))


def task_matrix(spark, sf_dir, task: str, items=None):
    return transfer.transfer_matrix(task_predictions(spark, sf_dir, task, items))


@query("enc_handcrafted", f"WITH {SQL_ITEMS}{SQL_FEATS} SELECT * FROM feats")
def enc_handcrafted(spark, sf_dir):
    return features(spark, sf_dir)


def gram_sql(name: str, grams: str) -> str:
    """CTEs that make ``name`` (item_id, lang, d, x), the centred unit vectors of a query's grams (item_id, lang, g)."""
    return f"""
{name}_u AS (SELECT item_id, lang, CAST('0x' || substr(md5(g), 1, 4) AS BIGINT) % 64 AS d, count(*)::DOUBLE AS n FROM ({grams}) GROUP BY ALL),
{name}_z AS (SELECT item_id, lang, k.d, coalesce(u.n, 0) AS n FROM (SELECT DISTINCT item_id, lang FROM {name}_u) CROSS JOIN (SELECT unnest(range(64)) AS d) k LEFT JOIN {name}_u u USING (item_id, lang, d)),
{name}_v AS (SELECT item_id, lang, d, n / sqrt(sum(n * n) OVER (PARTITION BY item_id)) AS x FROM {name}_z),
{name} AS (SELECT item_id, lang, d, x - avg(x) OVER (PARTITION BY lang, d) AS x FROM {name}_v)"""


SQL_WORDS = "SELECT doc_id AS item_id, lang, list_filter(regexp_split_to_array(lower(text), '[^\\p{L}0-9]+'), lambda w: w <> '') AS w FROM documents"
CHAR3 = gram_sql("char3", "SELECT item_id, lang, substr(text, k, 3) AS g FROM (SELECT doc_id AS item_id, lang, text, unnest(range(1, greatest(length(text) - 2, 1) + 1)) AS k FROM documents)")
WORD = gram_sql("wordv", f"SELECT item_id, lang, unnest(w) AS g FROM ({SQL_WORDS})")
WORD2 = gram_sql("word2v", f"SELECT item_id, lang, CASE WHEN len(w) = 1 THEN w[1] ELSE w[k] || ' ' || w[k + 1] END AS g FROM (SELECT item_id, lang, w, unnest(range(1, greatest(len(w) - 1, 1) + 1)) AS k FROM ({SQL_WORDS}) WHERE len(w) > 0)")


def char3(spark, sf_dir, dims: int = 64):
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), "lang", "text")
    return encode.hashed(docs, "char3", dims, center="lang")


@query("enc_char3", f"WITH {CHAR3} SELECT item_id, d, round(x, 6) AS x FROM char3")
def enc_char3(spark, sf_dir):
    return char3(spark, sf_dir).select("item_id", F.posexplode("features").alias("d", "x")).select("item_id", F.col("d").cast("long").alias("d"), (F.round("x", 6) + F.lit(0.0)).alias("x"))


@query("pool_readouts", """
WITH fr AS (SELECT doc_id AS item_id, k AS t, string_split(text, chr(10))[k + 1] AS line FROM (SELECT doc_id, text, unnest(range(len(string_split(text, chr(10))))) AS k FROM documents)),
x AS (SELECT item_id, t, [length(line)::DOUBLE, length(regexp_replace(line, '[^ ]', '', 'g'))::DOUBLE] AS f FROM fr WHERE length(line) > 0)
SELECT item_id, 'mean' AS how, 0 AS d, round(avg(f[1]), 6) AS x FROM x GROUP BY 1 UNION ALL SELECT item_id, 'mean', 1, round(avg(f[2]), 6) FROM x GROUP BY 1
UNION ALL SELECT item_id, 'mean_std', 0, round(avg(f[1]), 6) FROM x GROUP BY 1 UNION ALL SELECT item_id, 'mean_std', 1, round(avg(f[2]), 6) FROM x GROUP BY 1
UNION ALL SELECT item_id, 'mean_std', 2, round(stddev_pop(f[1]), 6) FROM x GROUP BY 1 UNION ALL SELECT item_id, 'mean_std', 3, round(stddev_pop(f[2]), 6) FROM x GROUP BY 1
UNION ALL SELECT item_id, 'first', 0, arg_min(f[1], t) FROM x GROUP BY 1 UNION ALL SELECT item_id, 'first', 1, arg_min(f[2], t) FROM x GROUP BY 1""")
def pool_readouts(spark, sf_dir):
    """Lines as frames with two numbers each; empty lines are masked."""
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), F.posexplode(F.split("text", "\n")).alias("t", "line"))
    n = F.length("line")
    frames = docs.select("item_id", "t", (n > 0).alias("mask"), F.array(n.cast("double"), F.length(F.regexp_replace("line", "[^ ]", "")).cast("double")).alias("features"))
    parts = [encode.pooled(frames, how).select("item_id", F.lit(how).alias("how"), F.posexplode("features").alias("d", "x")) for how in ("mean", "mean_std", "first")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).withColumn("x", F.round("x", 6))


@query("transfer_matrix", sql_task("multi") + " SELECT * FROM mat")
def transfer_matrix(spark, sf_dir):
    return task_matrix(spark, sf_dir, "multi")


def _task_query(name: str, task: str):
    @query(name, sql_task(task) + " SELECT * FROM mat")
    def run(spark, sf_dir):
        return task_matrix(spark, sf_dir, task)


_task_query("matrix_binary", "binary")
_task_query("matrix_subset", "subset")
_task_query("matrix_common", "common")


@query("metrics_per_class", sql_task("multi") + " SELECT train_domain, test_domain, class, CAST(tp AS BIGINT) AS tp, CAST(fp AS BIGINT) AS fp, CAST(fn AS BIGINT) AS fn, round(f1, 6) AS f1, round(recall, 6) AS recall FROM mat_pc")
def metrics_per_class(spark, sf_dir):
    keys = ["train_domain", "test_domain"]
    out = transfer.per_class(transfer.confusion(task_predictions(spark, sf_dir, "multi"), keys), keys)
    return out.withColumns({"f1": F.round("f1", 6), "recall": F.round("recall", 6)})


@query("metrics_overall", sql_task("multi") + """, pooled AS (SELECT 'all' AS train_domain, 'all' AS test_domain, truth, pred FROM preds)""" + sql_scores("po", "pooled") + " SELECT * FROM mat UNION ALL SELECT * FROM po")
def metrics_overall(spark, sf_dir):
    """Scores by cell, and pooled over all cells."""
    preds = task_predictions(spark, sf_dir, "multi")
    pooled = preds.withColumns({"train_domain": F.lit("all"), "test_domain": F.lit("all")})
    return transfer.transfer_matrix(preds).unionByName(transfer.transfer_matrix(pooled))


SQL_NTR = """(SELECT round(1 - avg(caf1) FILTER (train_domain <> test_domain) / nullif(avg(caf1) FILTER (train_domain = test_domain), 0), 6) AS ntr, round(avg(caf1) FILTER (train_domain <> test_domain), 6) AS mean_off,
  round(avg(caf1) FILTER (train_domain = test_domain), 6) AS mean_diag, count(caf1) FILTER (train_domain <> test_domain) AS n_off, count(caf1) FILTER (train_domain = test_domain) AS n_diag FROM {m}
  WHERE train_domain IN (SELECT test_domain FROM {m}) AND test_domain IN (SELECT train_domain FROM {m}))"""


@query("ntr", sql_task("multi") + f", n AS {SQL_NTR.format(m='mat')} SELECT * FROM n")
def ntr(spark, sf_dir):
    return transfer.negative_transfer_ratio(task_matrix(spark, sf_dir, "multi"))


@query("asymmetry", sql_task("multi") + " SELECT a.train_domain AS domain_a, a.test_domain AS domain_b, round(abs(a.caf1 - b.caf1), 6) AS asymmetry FROM mat a JOIN mat b ON a.train_domain = b.test_domain AND a.test_domain = b.train_domain WHERE a.train_domain < a.test_domain")
def asymmetry(spark, sf_dir):
    return transfer.asymmetry(task_matrix(spark, sf_dir, "multi"))


SQL_GAPS = ", gp AS (SELECT a.train_domain, a.test_domain, a.caf1, b.caf1 AS diag, round(b.caf1 - a.caf1, 6) AS gap, a.caf1 > b.caf1 AS reversed FROM mat a JOIN mat b ON a.test_domain = b.test_domain AND b.train_domain = b.test_domain WHERE a.train_domain <> a.test_domain)"


@query("gaps", sql_task("binary") + SQL_GAPS + " SELECT *, round(avg(abs(gap)) OVER (), 6) AS mean_abs_gap FROM gp")
def gaps(spark, sf_dir):
    g = transfer.gaps(task_matrix(spark, sf_dir, "binary"))
    return g.join(F.broadcast(g.agg(F.round(F.avg(F.abs("gap")), 6).alias("mean_abs_gap"))))


@query("reversed_cells", sql_task("binary") + SQL_GAPS + " SELECT train_domain, test_domain, caf1, diag, gap FROM gp WHERE reversed")
def reversed_cells(spark, sf_dir):
    return transfer.gaps(task_matrix(spark, sf_dir, "binary")).where("reversed").drop("reversed")


def _gap_mean(task: str) -> str:
    return sql_task(task).replace("WITH ", "(WITH ", 1) + SQL_GAPS + " SELECT avg(abs(gap)) FROM gp)"


@query("task_gap", f"SELECT round({_gap_mean('binary')}, 6) AS binary_gap, round({_gap_mean('common')}, 6) AS common_gap, round(1 - {_gap_mean('common')} / nullif({_gap_mean('binary')}, 0), 6) AS task_share")
def task_gap(spark, sf_dir):
    """Share of the mean gap that goes away when both sides have the same two classes."""
    items = base_items(spark, sf_dir)
    mean = {t: transfer.gaps(task_matrix(spark, sf_dir, t, items)).agg(F.avg(F.abs("gap")).alias(t)) for t in ("binary", "common")}
    both = mean["binary"].join(F.broadcast(mean["common"]))
    return both.select(F.round("binary", 6).alias("binary_gap"), F.round("common", 6).alias("common_gap"), F.round(1 - F.try_divide(F.col("common"), F.col("binary")), 6).alias("task_share"))


@query("domain_swing", sql_task("multi") + " SELECT round(max(caf1) - min(caf1), 6) AS swing, max_by(test_domain, (caf1, test_domain)) AS best_domain, min_by(test_domain, (caf1, test_domain)) AS worst_domain FROM mat WHERE train_domain = test_domain")
def domain_swing(spark, sf_dir):
    return transfer.domain_swing(task_matrix(spark, sf_dir, "multi"))


def sql_boot(unit: str, prefix: str = "") -> str:
    """Paired bootstrap CTEs over ``preds``; the result is ``{prefix}boot``."""
    p = prefix
    return f""",
{p}dg AS (SELECT test_domain, item_id, pred AS own FROM preds WHERE train_domain = test_domain),
{p}bo AS (SELECT p.train_domain, p.test_domain, CAST(p.{unit} AS VARCHAR) AS unit, truth, pred, own FROM preds p JOIN {p}dg USING (test_domain, item_id) WHERE train_domain <> test_domain),
{p}un AS (SELECT test_domain, unit, row_number() OVER (PARTITION BY test_domain ORDER BY unit) - 1 AS k, count(*) OVER (PARTITION BY test_domain) AS g FROM (SELECT DISTINCT test_domain, CAST({unit} AS VARCHAR) AS unit FROM preds)),
{p}pk AS (SELECT test_domain, b, CAST('0x' || substr(md5('42:' || b || ':' || i), 1, 8) AS BIGINT) % g AS k, count(*) AS w FROM (SELECT test_domain, g, b, unnest(range(g)) AS i FROM (SELECT DISTINCT test_domain, g FROM {p}un), (SELECT unnest(range(1, {DRAWS} + 1)) AS b)) GROUP BY 1, 2, 3),
{p}wt AS (SELECT test_domain, b, unit, w FROM {p}pk JOIN {p}un USING (test_domain, k) UNION ALL SELECT test_domain, 0, unit, 1 FROM {p}un),
{p}rs AS (SELECT train_domain, test_domain, b, 'off' AS which, truth, pred, w FROM {p}bo JOIN {p}wt USING (test_domain, unit) UNION ALL SELECT train_domain, test_domain, b, 'diag', truth, own, w FROM {p}bo JOIN {p}wt USING (test_domain, unit))""" + sql_scores(f"{p}bs", f"{p}rs", "train_domain, test_domain, b, which", "w") + f""",
{p}av AS (SELECT train_domain, test_domain, b, which, avg(f1) AS caf1 FROM {p}bs_pc GROUP BY ALL),
{p}dl AS (SELECT train_domain, test_domain, b, round(max(caf1) FILTER (which = 'off') - max(caf1) FILTER (which = 'diag'), 9) AS d FROM {p}av GROUP BY 1, 2, 3),
{p}boot AS (SELECT train_domain, test_domain, round(max(d) FILTER (b = 0), 6) AS delta, round(quantile_cont(d, 0.025) FILTER (b > 0), 6) AS ci_lo, round(quantile_cont(d, 0.975) FILTER (b > 0), 6) AS ci_hi,
  round((1 + count(*) FILTER (b > 0 AND d >= 0)) / (1 + count(*) FILTER (b > 0)), 6) AS p FROM {p}dl GROUP BY 1, 2)"""


SQL_BH = """, rk AS (SELECT *, row_number() OVER (ORDER BY p, train_domain, test_domain) AS rank, count(*) OVER () AS m FROM boot),
bh AS (SELECT train_domain, test_domain, delta, ci_lo, ci_hi, p, round(least(1.0::DOUBLE, min(p * m / rank) OVER (ORDER BY rank DESC ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)), 6) AS p_adj FROM rk)"""


@query("boot_cluster", sql_task("multi") + sql_boot("group_id") + " SELECT * FROM boot")
def boot_cluster(spark, sf_dir):
    return stats.paired_bootstrap(materialize(task_predictions(spark, sf_dir, "multi"), "preds"), DRAWS)


@query("boot_item", sql_task("multi") + sql_boot("item_id") + " SELECT * FROM boot")
def boot_item(spark, sf_dir):
    return stats.paired_bootstrap(materialize(task_predictions(spark, sf_dir, "multi"), "preds"), DRAWS, unit="item_id")


@query("boot_flips", sql_task("multi") + sql_boot("group_id") + sql_boot("item_id", "i_") + """
SELECT c.train_domain, c.test_domain, c.p AS p_cluster, i.p AS p_item, c.p <= 0.05 AS keep_cluster, i.p <= 0.05 AS keep_item, (c.p <= 0.05) <> (i.p <= 0.05) AS flipped, round(abs(c.delta - i.delta), 6) AS drift FROM boot c JOIN i_boot i USING (train_domain, test_domain)""")
def boot_flips(spark, sf_dir):
    """Cells whose verdict changes between resampling groups and items."""
    preds = materialize(task_predictions(spark, sf_dir, "multi"), "preds")
    c, i = (stats.paired_bootstrap(preds, DRAWS, unit=u).select("train_domain", "test_domain", F.col("p").alias(f"p_{n}"), F.col("delta").alias(f"d_{n}")) for u, n in (("group_id", "cluster"), ("item_id", "item")))
    kc, ki = F.col("p_cluster") <= 0.05, F.col("p_item") <= 0.05
    return c.join(i, ["train_domain", "test_domain"]).select("train_domain", "test_domain", "p_cluster", "p_item", kc.alias("keep_cluster"), ki.alias("keep_item"), (kc != ki).alias("flipped"), F.round(F.abs(F.col("d_cluster") - F.col("d_item")), 6).alias("drift"))


@query("bh_fdr", sql_task("multi") + sql_boot("group_id") + SQL_BH + " SELECT *, p_adj <= 0.05 AS keep FROM bh")
def bh_fdr(spark, sf_dir):
    return stats.bh_adjust(stats.paired_bootstrap(materialize(task_predictions(spark, sf_dir, "multi"), "preds"), DRAWS))


@query("boot_poisson")
def boot_poisson(spark, sf_dir):
    """Ten thousand resamples with Poisson weights."""
    return stats.poisson_bootstrap(materialize(task_predictions(spark, sf_dir, "multi"), "preds"))


@query("ntr_interval", sql_task("multi") + """,
un AS (SELECT test_domain, group_id, row_number() OVER (PARTITION BY test_domain ORDER BY group_id) - 1 AS k, count(*) OVER (PARTITION BY test_domain) AS g FROM (SELECT DISTINCT test_domain, group_id FROM preds)),
pk AS (SELECT test_domain, b, CAST('0x' || substr(md5('42:' || b || ':' || i), 1, 8) AS BIGINT) % g AS k, count(*) AS w FROM (SELECT test_domain, g, b, unnest(range(g)) AS i FROM (SELECT DISTINCT test_domain, g FROM un), (SELECT unnest(range(1, 41)) AS b)) GROUP BY 1, 2, 3),
rs AS (SELECT train_domain, test_domain, b, truth, pred, w FROM preds JOIN un USING (test_domain, group_id) JOIN pk USING (test_domain, k))""" + sql_scores("bs", "rs", "train_domain, test_domain, b", "w") + """,
r AS (SELECT b, round(1 - avg(caf1) FILTER (train_domain <> test_domain) / nullif(avg(caf1) FILTER (train_domain = test_domain), 0), 6) AS ntr FROM bs GROUP BY b)
SELECT count(ntr) AS n, round(quantile_cont(ntr, 0.025), 6) AS ci_lo, round(quantile_cont(ntr, 0.975), 6) AS ci_hi FROM r""")
def ntr_interval(spark, sf_dir):
    """Percentile interval of the ratio, with the same resampled groups in every cell of a column."""
    return stats.ratio_interval(materialize(task_predictions(spark, sf_dir, "multi"), "preds"), DRAWS)


for _name, _of in (("boot_cluster_10k", stats.paired_bootstrap), ("ntr_interval_10k", stats.ratio_interval), ("bh_fdr_10k", lambda preds: stats.bh_adjust(stats.paired_bootstrap(preds)))):

    @query(_name)
    def _resampled(spark, sf_dir, of=_of):
        """Ten thousand resamples; the query without the suffix is the same function with as many as SQL can follow."""
        return of(materialize(task_predictions(spark, sf_dir, "multi"), "preds"))


@query("seed_summary", sql_task("binary") + """,
sd AS (SELECT * REPLACE ('sampled#' || seed AS domain) FROM tr_binary, (SELECT unnest([42, 43, 44]) AS seed) WHERE domain = 'LARGE' AND CAST('0x' || substr(md5(seed || ':' || item_id), 1, 8) AS BIGINT) < 2147483648
  UNION ALL SELECT * REPLACE ('whole#' || seed AS domain) FROM tr_binary, (SELECT unnest([42, 43, 44]) AS seed) WHERE domain = 'LARGE'),
sl AS (SELECT * FROM te_binary WHERE domain = 'LARGE')""" + sql_probe("sq", "sd", "sl") + sql_scores("sc", "sq") + """
SELECT split_part(train_domain, '#', 1) AS model, CAST(count(*) AS BIGINT) AS n_runs, round(avg(caf1), 6) AS mean, round(stddev_samp(caf1), 6) AS std, count(DISTINCT caf1) AS n_distinct, count(DISTINCT caf1) = 1 AS deterministic FROM sc GROUP BY 1""")
def seed_summary(spark, sf_dir):
    """Three seeds of a probe on half of LARGE's train rows, and of one on all, which no seed can change."""
    items = transfer.task_labels(base_items(spark, sf_dir), "binary").where("domain = 'LARGE'")
    train = items.where("split = 'train'").withColumn("seed", F.explode(F.array(*[F.lit(x) for x in (42, 43, 44)])))
    h = F.conv(F.substring(F.md5(F.concat_ws(":", "seed", "item_id").cast("binary")), 1, 8), 16, 10).cast("long")
    both = train.where(h < 2147483648).withColumn("domain", F.concat(F.lit("sampled#"), "seed")).unionByName(train.withColumn("domain", F.concat(F.lit("whole#"), "seed")))
    test = items.where("split = 'test'").select("item_id", F.col("y").alias("truth"), F.lit("LARGE").alias("test_domain"), *HANDCRAFTED)
    scores = transfer.transfer_matrix(transfer.score_all(test, transfer.fit_centroid(both)).withColumnRenamed("model", "train_domain"))
    return stats.seed_summary(scores.select(F.substring_index("train_domain", "#", 1).alias("model"), F.col("caf1").alias("score")), ["model"])


@query("binom_ci", sql_task("multi") + """ SELECT domain, count(*) AS n, count(*) AS k, round(power(0.025::DOUBLE, 1.0::DOUBLE / count(*)), 6) AS lower, 1.0::DOUBLE AS upper FROM base WHERE split = 'test' GROUP BY domain""")
def binom_ci(spark, sf_dir):
    """What a perfect score on a domain's test items would prove."""
    n = base_items(spark, sf_dir).where("split = 'test'").groupBy("domain").agg(F.count(F.lit(1)).alias("n"))
    return stats.binom_ci(n.withColumn("k", F.col("n")))


SQL_BISECT = """, ck AS (SELECT train_domain, test_domain, CAST(sum(CASE WHEN truth = pred THEN 1 ELSE 0 END) AS BIGINT) AS k, count(*) AS n FROM preds GROUP BY 1, 2),
bs AS (SELECT train_domain, test_domain, n, k AS kk, 0.025::DOUBLE AS t, 'lower' AS which, 0.0::DOUBLE AS lo, 1.0::DOUBLE AS hi, 0 AS step FROM ck
  UNION ALL SELECT train_domain, test_domain, n, k + 1, 0.975::DOUBLE, 'upper', 0.0::DOUBLE, 1.0::DOUBLE, 0 FROM ck
  UNION ALL SELECT train_domain, test_domain, n, kk, t, which, CASE WHEN v < t THEN (lo + hi) / 2 ELSE lo END, CASE WHEN v < t THEN hi ELSE (lo + hi) / 2 END, step + 1
  FROM (SELECT *, list_sum(list_transform(range(kk, n + 1), lambda i: exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln((lo + hi) / 2) + (n - i) * ln(1 - (lo + hi) / 2)))) AS v FROM bs WHERE step < 60))
SELECT train_domain, test_domain, k, n, round(CASE WHEN k = 0 THEN 0 ELSE max((lo + hi) / 2) FILTER (which = 'lower') END, 6) AS lower, round(CASE WHEN k = n THEN 1 ELSE max((lo + hi) / 2) FILTER (which = 'upper') END, 6) AS upper
FROM ck JOIN bs USING (train_domain, test_domain, n) WHERE step = 60 GROUP BY train_domain, test_domain, k, n"""


@query("binom_ci_cells", sql_task("multi").replace("WITH ", "WITH RECURSIVE ", 1) + SQL_BISECT)
def binom_ci_cells(spark, sf_dir):
    """Exact bounds of every cell's accuracy."""
    preds = task_predictions(spark, sf_dir, "multi")
    return stats.binom_ci(preds.groupBy("train_domain", "test_domain").agg(F.sum((F.col("truth") == F.col("pred")).cast("int")).alias("k"), F.count(F.lit(1)).alias("n")))


SQL_FISHER = """, fp AS (SELECT count(*) AS m, -2 * sum(ln(p)) AS x FROM boot)
SELECT CAST(m AS INT) AS m, round(x, 6) AS chi2, round(exp(-x / 2) * list_sum(list_transform(range(m), lambda k: power(x / 2, k) / factorial(CAST(k AS INT)))), 6) AS p FROM fp"""


@query("fisher_combined", sql_task("multi") + sql_boot("group_id") + SQL_FISHER)
def fisher_combined(spark, sf_dir):
    """The directed cells' p-values as one; descriptive, for the cells share their test items."""
    ps = stats.paired_bootstrap(materialize(task_predictions(spark, sf_dir, "multi"), "preds"), DRAWS).agg(F.count("p").cast("int").alias("m"), (-2 * F.sum(F.log("p"))).alias("chi2"))
    return ps.select("m", F.round("chi2", 6).alias("chi2"), F.round(stats.fisher_combine(F.col("chi2"), F.col("m")), 6).alias("p"))


@query("size_matched", sql_task("binary") + """,
want AS (SELECT count(*) AS k FROM tr_binary WHERE domain = 'NOISY'),
dr AS (SELECT * FROM (SELECT t.* REPLACE ('LARGE#' || draw AS domain), row_number() OVER (PARTITION BY draw ORDER BY md5('sm:' || draw || ':' || item_id), item_id) AS r FROM tr_binary t, (SELECT unnest([1, 2, 3]) AS draw) WHERE domain = 'LARGE') , want WHERE r <= k),
ny AS (SELECT * FROM te_binary WHERE domain = 'NOISY')""" + sql_probe("sm", "dr", "ny") + sql_scores("sc", "sm") + """
SELECT s.train_domain, s.caf1, m.caf1 AS diag, round(s.caf1 - m.caf1, 6) AS margin, s.caf1 > m.caf1 AS win FROM sc s, mat m WHERE m.train_domain = 'NOISY' AND m.test_domain = 'NOISY'""")
def size_matched(spark, sf_dir):
    """LARGE cut to the train size of NOISY, three draws, scored on NOISY."""
    items = transfer.task_labels(base_items(spark, sf_dir), "binary")
    train = items.where("split = 'train'")
    want = train.where("domain = 'NOISY'").agg(F.count(F.lit(1)).alias("k"))
    draws = train.where("domain = 'LARGE'").withColumn("draw", F.explode(F.array(*[F.lit(i) for i in (1, 2, 3)])))
    draws = running(draws, ["draw"], F.md5(F.concat_ws(":", F.lit("sm"), "draw", "item_id").cast("binary")), "item_id")
    draws = draws.join(F.broadcast(want)).where("before < k").withColumn("domain", F.concat(F.lit("LARGE#"), "draw"))
    models = transfer.fit_centroid(draws)
    noisy = items.where("split = 'test' and domain = 'NOISY'").select("item_id", "domain", F.col("y").alias("truth"), *HANDCRAFTED)
    preds = transfer.score_all(noisy, models).select("item_id", F.col("model").alias("train_domain"), F.col("domain").alias("test_domain"), "truth", "pred")
    scores = transfer.transfer_matrix(preds).select("train_domain", "caf1")
    diag = task_matrix(spark, sf_dir, "binary", base_items(spark, sf_dir)).where("train_domain = 'NOISY' and test_domain = 'NOISY'").select(F.col("caf1").alias("diag"))
    return scores.join(F.broadcast(diag)).select("train_domain", "caf1", "diag", F.round(F.col("caf1") - F.col("diag"), 6).alias("margin"), (F.col("caf1") > F.col("diag")).alias("win"))


HASHED = ("char3", "word", "word2")
SQL_ENCODED = f"""WITH {SQL_ITEMS}{SQL_SPLIT}{SQL_FEATS}, {CHAR3}, {WORD}, {WORD2},
gv AS (SELECT doc_id AS item_id, unnest(range(64)) AS d, unnest(embedding)::DOUBLE AS x FROM documents JOIN embeddings ON vec_id = doc_id % (SELECT count(*) FROM embeddings)),
hc AS (SELECT item_id, unnest(range({len(HANDCRAFTED)})) AS d, unnest([{', '.join(HANDCRAFTED)}]) AS x FROM feats),
fx AS (SELECT 'char3' AS encoder, item_id, d, x FROM char3 UNION ALL SELECT 'word', item_id, d, x FROM wordv UNION ALL SELECT 'word2', item_id, d, x FROM word2v
  UNION ALL SELECT 'given', item_id, d, x FROM gv UNION ALL SELECT 'handcrafted', item_id, d, x FROM hc),
eb AS (SELECT encoder, i.item_id, domain, split, class AS y, d, x FROM items i JOIN fx USING (item_id) WHERE domain <> 'TINY'),
es AS (SELECT encoder, domain, d, avg(x) AS m, round(stddev_pop(x), 12) AS s FROM eb WHERE split = 'train' GROUP BY ALL),
em AS (SELECT encoder, domain, y AS pred, d, avg(x) AS a FROM eb WHERE split = 'train' GROUP BY ALL),
ec AS (SELECT encoder, domain AS train_domain, pred, d, m, s, coalesce((a - m) / nullif(s, 0), 0) AS c FROM em JOIN es USING (encoder, domain, d)),
ed AS (SELECT encoder, e.item_id, e.domain AS test_domain, train_domain, e.y AS truth, pred, round(sum(power(coalesce((e.x - m) / nullif(s, 0), 0) - c, 2)), 6) AS dist FROM eb e JOIN ec USING (encoder, d) WHERE e.split = 'test' GROUP BY ALL),
preds AS (SELECT encoder, item_id, train_domain, test_domain, truth, pred FROM ed QUALIFY row_number() OVER (PARTITION BY encoder, item_id, train_domain ORDER BY dist, pred) = 1)""" + sql_scores("mat", "preds", "encoder, train_domain, test_domain")


def encoded_items(spark, sf_dir):
    """``encoder, item_id, domain, group_id, split, y, features`` of every item under every frozen encoder; computed once."""
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), "lang", "text")
    feats = [encode.hashed(docs, k, 64, center="lang").withColumn("encoder", F.lit(k)) for k in HASHED]
    given = table(spark, sf_dir, "embeddings")
    given = docs.select("item_id", F.pmod("item_id", F.lit(given.count())).alias("vec_id")).join(given, "vec_id").select("item_id", F.transform("embedding", lambda x: x.cast("double")).alias("features"), F.lit("given").alias("encoder"))
    own = features(spark, sf_dir).select("item_id", F.array(*[F.col(f) for f in HANDCRAFTED]).alias("features"), F.lit("handcrafted").alias("encoder"))
    every = own.unionByName(given)
    for f in feats:
        every = every.unionByName(f.select("item_id", "features", "encoder"))
    items = split_items(spark, sf_dir).where("domain <> 'TINY'").select("item_id", "domain", "group_id", F.col("class").alias("y"), "split")
    return materialize(items.join(every, "item_id"), "encoded")


def _tested(items):
    return items.where("split = 'test'").select("encoder", "item_id", "group_id", F.col("domain").alias("test_domain"), F.col("y").alias("truth"), F.col("features").alias("x"))


def centroid_predictions(items):
    models = transfer.fit_centroid_vectors(items.where("split = 'train'"), ("encoder",))
    return transfer.nearest(_tested(items), models, ("encoder",)).withColumnRenamed("model", "train_domain")


def probe_predictions(items):
    probes = materialize(probe.grouped_probes(items), "probes")
    return probe.score_probes(_tested(items), probes).withColumnRenamed("model", "train_domain")


def encoder_measures(matrix):
    """Ratio, largest asymmetry, mean absolute gap, reversed cells and swing of every encoder."""
    keys = ("encoder",)
    ratio = transfer.negative_transfer_ratio(matrix, keys)
    uneven = transfer.asymmetry(matrix, keys).groupBy("encoder").agg(F.max("asymmetry").alias("max_asymmetry"))
    gap = transfer.gaps(matrix, keys).groupBy("encoder").agg(F.round(F.avg(F.abs("gap")), 6).alias("mean_abs_gap"), F.sum(F.col("reversed").cast("int")).alias("reversed_cells"))
    swing = transfer.domain_swing(matrix, keys).select("encoder", "swing")
    return ratio.join(uneven, "encoder").join(gap, "encoder").join(swing, "encoder")


@query("encoder_matrix", SQL_ENCODED + " SELECT * FROM mat")
def encoder_matrix(spark, sf_dir):
    """The multi-class matrix of the centroid probe under five frozen encoders."""
    return transfer.transfer_matrix(centroid_predictions(encoded_items(spark, sf_dir)), ("encoder",))


@query("encoder_summary", SQL_ENCODED + """ SELECT encoder, round(1 - avg(caf1) FILTER (train_domain <> test_domain) / nullif(avg(caf1) FILTER (train_domain = test_domain), 0), 6) AS ntr, round(avg(caf1) FILTER (train_domain <> test_domain), 6) AS mean_off,
 round(avg(caf1) FILTER (train_domain = test_domain), 6) AS mean_diag, count(caf1) FILTER (train_domain <> test_domain) AS n_off, count(caf1) FILTER (train_domain = test_domain) AS n_diag,
 any_value(max_asymmetry) AS max_asymmetry, any_value(mean_abs_gap) AS mean_abs_gap, any_value(reversed_cells) AS reversed_cells, round(max(caf1) FILTER (train_domain = test_domain) - min(caf1) FILTER (train_domain = test_domain), 6) AS swing
FROM mat JOIN (SELECT a.encoder, max(round(abs(a.caf1 - b.caf1), 6)) AS max_asymmetry FROM mat a JOIN mat b ON a.encoder = b.encoder AND a.train_domain = b.test_domain AND a.test_domain = b.train_domain GROUP BY 1) USING (encoder)
JOIN (SELECT a.encoder, round(avg(abs(round(b.caf1 - a.caf1, 6))), 6) AS mean_abs_gap, CAST(count(*) FILTER (a.caf1 > b.caf1) AS BIGINT) AS reversed_cells FROM mat a JOIN mat b ON a.encoder = b.encoder AND a.test_domain = b.test_domain AND b.train_domain = b.test_domain WHERE a.train_domain <> a.test_domain GROUP BY 1) USING (encoder) GROUP BY encoder""")
def encoder_summary(spark, sf_dir):
    return encoder_measures(encoder_matrix(spark, sf_dir))


@query("probe_grid")
def probe_grid(spark, sf_dir):
    """Validation score and size of coefficients of every constant, for every encoder and domain, and the choice."""
    rows = probe.grouped_probes(encoded_items(spark, sf_dir)).select("encoder", F.col("model").alias("domain"), F.col("c").alias("best"), F.explode("path").alias("x"))
    return rows.select("encoder", "domain", "x.c", F.round("x.val_caf1", 6).alias("val_caf1"), F.round("x.size", 6).alias("size"), (F.col("x.c") == F.col("best")).alias("chosen"))


@query("probe_matrix")
def probe_matrix(spark, sf_dir):
    """The main matrix: logistic probes tuned on source validation, every train by test pair, every encoder."""
    return transfer.transfer_matrix(probe_predictions(encoded_items(spark, sf_dir)), ("encoder",))


@query("probe_summary")
def probe_summary(spark, sf_dir):
    return encoder_measures(materialize(probe_matrix(spark, sf_dir), "probe-matrix"))


@query("fdr_family")
def fdr_family(spark, sf_dir):
    """False-discovery control over the family of thirty cells (five encoders, six directed pairs), 10,000 group resamples each."""
    preds = materialize(probe_predictions(encoded_items(spark, sf_dir)), "probe-preds")
    return stats.bh_adjust(stats.paired_bootstrap(preds, keys=("encoder",)), tie=("encoder", "train_domain", "test_domain"))
