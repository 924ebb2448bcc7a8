"""Probes, the train-by-test matrix and its summaries."""

from __future__ import annotations

from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crossaudit.operators.encode import HANDCRAFTED


def fit_centroid(train: DataFrame, features: tuple[str, ...] = HANDCRAFTED, by: str = "domain", label: str = "y") -> DataFrame:
    """One row for each (``by``, class): scaled class means ``c_*`` with the training mean ``m_*`` and deviation ``s_*``.

    Deviations are those of the population; a constant feature scales to 0. Two aggregations of a few rows' width.
    """
    scale = train.groupBy(by).agg(*[F.avg(f).alias(f"m_{f}") for f in features], *[F.stddev_pop(f).alias(f"s_{f}") for f in features])
    means = train.groupBy(by, label).agg(*[F.avg(f).alias(f"a_{f}") for f in features], F.count(F.lit(1)).alias("n_train"))
    z = [F.coalesce(F.try_divide(F.col(f"a_{f}") - F.col(f"m_{f}"), F.col(f"s_{f}")), F.lit(0.0)).alias(f"c_{f}") for f in features]
    return means.join(scale, by).select(F.col(by).alias("model"), F.col(label).alias("pred"), "n_train", *[f"m_{f}" for f in features], *[f"s_{f}" for f in features], *z)


def score_all(test: DataFrame, models: DataFrame, features: tuple[str, ...] = HANDCRAFTED) -> DataFrame:
    """Every test row under every model, in one scan: nearest class mean, ties to the first class by name.

    The models are one row each with all their classes, a few for each domain, and are broadcast; nothing is shuffled.
    """
    keep = [c for c in test.columns if c not in features]
    each = models.groupBy("model").agg(
        F.first(F.array(*[F.col(f"m_{f}") for f in features])).alias("m"), F.first(F.array(*[F.col(f"s_{f}") for f in features])).alias("s"),
        F.collect_list(F.struct("pred", F.array(*[F.col(f"c_{f}") for f in features]).alias("c"))).alias("classes"),
    )
    rows = test.select(*keep, F.array(*[F.col(f).cast("double") for f in features]).alias("x"))
    return nearest(rows, each).select(*keep, "model", "pred")


def nearest(rows: DataFrame, models: DataFrame, on: tuple[str, ...] = ()) -> DataFrame:
    """Rows (``x``, an array) with ``model, pred`` for every model (``model, m, s, classes`` of ``pred, c``) that agrees ``on`` some columns."""
    z = F.zip_with(F.zip_with("x", "m", lambda a, b: a - b), "s", lambda a, b: F.coalesce(F.try_divide(a, b), F.lit(0.0)))
    pairs = (rows.join(F.broadcast(models), list(on)) if on else rows.join(F.broadcast(models))).withColumn("z", z)
    apart = lambda c: F.aggregate(F.zip_with("z", c["c"], lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    best = F.array_min(F.transform("classes", lambda c: F.struct(F.round(apart(c), 6).alias("dist"), c["pred"].alias("pred"))))
    return pairs.withColumn("pred", best["pred"]).drop("x", "z", "m", "s", "classes")


def fit_centroid_vectors(train: DataFrame, keys: tuple[str, ...] = (), by: str = "domain", label: str = "y") -> DataFrame:
    """As `fit_centroid` for ``features`` arrays: one row for each (keys, ``by``) with ``model, m, s, classes``."""
    rows = train.withColumn("v", array_to_vector("features"))
    scale = rows.groupBy(*keys, by).agg(Summarizer.metrics("mean", "variance", "count").summary(F.col("v")).alias("w"))
    n = F.col("w.count").cast("double")
    scale = scale.select(*keys, F.col(by), vector_to_array("w.mean").alias("m"), F.transform(vector_to_array("w.variance"), lambda x: F.round(F.sqrt(F.greatest(x * (n - 1) / n, F.lit(0.0))), 12)).alias("s"))
    means = rows.groupBy(*keys, by, label).agg(Summarizer.mean(F.col("v")).alias("a")).select(*keys, by, F.col(label).alias("pred"), vector_to_array("a").alias("a"))
    z = F.zip_with(F.zip_with("a", "m", lambda a, b: a - b), "s", lambda a, b: F.coalesce(F.try_divide(a, b), F.lit(0.0)))
    both = means.join(scale, [*keys, by]).select(*keys, by, "m", "s", F.struct("pred", z.alias("c")).alias("k"))
    return both.groupBy(*keys, F.col(by).alias("model")).agg(F.first("m").alias("m"), F.first("s").alias("s"), F.collect_list("k").alias("classes"))


def confusion(predictions: DataFrame, keys: list[str]) -> DataFrame:
    return predictions.groupBy(*keys, "truth", "pred").agg(F.count(F.lit(1)).alias("n"))


def per_class(counts: DataFrame, keys: list[str], class_set: str = "union", declared: list[str] | None = None) -> DataFrame:
    """``class, tp, fp, fn, f1, recall`` by keys from confusion counts.

    Classes are those of truth and predictions together, or the ``declared`` ones (F1 of an absent one is then 0).
    """
    sides = counts.select(*keys, F.col("truth").alias("class"), F.when(F.col("truth") == F.col("pred"), F.col("n")).otherwise(0).alias("tp"), F.lit(0).cast("long").alias("fp"), F.when(F.col("truth") != F.col("pred"), F.col("n")).otherwise(0).alias("fn"))
    wrong = counts.where("truth <> pred").select(*keys, F.col("pred").alias("class"), F.lit(0).cast("long").alias("tp"), F.col("n").alias("fp"), F.lit(0).cast("long").alias("fn"))
    out = sides.unionByName(wrong).groupBy(*keys, "class").agg(*[F.sum(c).alias(c) for c in ("tp", "fp", "fn")])
    if class_set == "declared":
        grid = counts.select(*keys).distinct().withColumn("class", F.explode(F.array(*[F.lit(c) for c in declared or []])))
        out = grid.join(out, [*keys, "class"], "left").fillna(0, ["tp", "fp", "fn"])
    f1 = F.coalesce(F.try_divide(2.0 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")), F.lit(0.0))
    return out.select(*keys, "class", "tp", "fp", "fn", f1.alias("f1"), F.try_divide(F.col("tp").cast("double"), F.col("tp") + F.col("fn")).alias("recall"))


def overall(counts: DataFrame, keys: list[str], **options) -> DataFrame:
    """``n, acc, caf1, uar, chance_uar`` by keys; UAR over classes that the truth has, and chance is one over their number."""
    scores = per_class(counts, keys, **options).groupBy(*keys).agg(
        F.sum(F.col("tp") + F.col("fn")).alias("n"), F.sum("tp").alias("hits"), F.avg("f1").alias("caf1"), F.avg("recall").alias("uar"), F.count("recall").alias("present"),
    )
    r = lambda c: F.round(c, 6)
    return scores.select(*keys, "n", r(F.col("hits") / F.col("n")).alias("acc"), r(F.col("caf1")).alias("caf1"), r(F.col("uar")).alias("uar"), r(1 / F.col("present")).alias("chance_uar"))


def transfer_matrix(predictions: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """``train_domain, test_domain, n, acc, caf1, uar, chance_uar`` (and keys) of predictions."""
    cell = [*keys, "train_domain", "test_domain"]
    return overall(confusion(predictions, cell), cell)


def negative_transfer_ratio(matrix: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """``ntr, mean_off, mean_diag, n_off, n_diag``: one minus mean off-diagonal over mean diagonal score.

    Only domains both trained and tested on count; null if the diagonal's mean is 0 or missing.
    """
    same = F.col("train_domain") == F.col("test_domain")
    sources = matrix.select(*keys, F.col("train_domain").alias("d1")).distinct()
    targets = matrix.select(*keys, F.col("test_domain").alias("d2")).distinct()
    both = sources.join(targets, [*keys, *[]] if keys else F.col("d1") == F.col("d2")) if not keys else sources.join(targets, list(keys)).where("d1 = d2")
    both = both.select(*keys, F.col("d1").alias("d"))
    rows = matrix.join(both.withColumnRenamed("d", "train_domain"), [*keys, "train_domain"]).join(both.withColumnRenamed("d", "test_domain"), [*keys, "test_domain"])
    out = rows.groupBy(*keys).agg(
        F.avg(F.when(~same, F.col("caf1"))).alias("mean_off"), F.avg(F.when(same, F.col("caf1"))).alias("mean_diag"),
        F.count(F.when(~same, F.col("caf1"))).alias("n_off"), F.count(F.when(same, F.col("caf1"))).alias("n_diag"),
    )
    return out.select(*keys, F.round(1 - F.try_divide(F.col("mean_off"), F.col("mean_diag")), 6).alias("ntr"), F.round("mean_off", 6).alias("mean_off"), F.round("mean_diag", 6).alias("mean_diag"), "n_off", "n_diag")


def asymmetry(matrix: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """``domain_a, domain_b, asymmetry`` of every unordered pair."""
    a = matrix.select(*keys, F.col("train_domain").alias("domain_a"), F.col("test_domain").alias("domain_b"), F.col("caf1").alias("there"))
    b = matrix.select(*keys, F.col("test_domain").alias("domain_a"), F.col("train_domain").alias("domain_b"), F.col("caf1").alias("back"))
    return a.where("domain_a < domain_b").join(b, [*keys, "domain_a", "domain_b"]).select(*keys, "domain_a", "domain_b", F.round(F.abs(F.col("there") - F.col("back")), 6).alias("asymmetry"))


def gaps(matrix: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """Off-diagonal cells with their gap to the target's own diagonal; ``reversed`` where transfer beats it."""
    diag = matrix.where("train_domain = test_domain").select(*keys, "test_domain", F.col("caf1").alias("diag"))
    out = matrix.where("train_domain <> test_domain").join(F.broadcast(diag), [*keys, "test_domain"])
    return out.select(*keys, "train_domain", "test_domain", "caf1", "diag", F.round(F.col("diag") - F.col("caf1"), 6).alias("gap"), (F.col("caf1") > F.col("diag")).alias("reversed"))


def domain_swing(matrix: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """Largest minus smallest diagonal score."""
    diag = matrix.where("train_domain = test_domain")
    return diag.groupBy(*keys).agg(F.round(F.max("caf1") - F.min("caf1"), 6).alias("swing"), F.max_by("test_domain", F.struct("caf1", "test_domain")).alias("best_domain"), F.min_by("test_domain", F.struct("caf1", "test_domain")).alias("worst_domain"))


def majority_baseline(items: DataFrame, label: str = "class") -> DataFrame:
    """``domain, majority, share, n_classes, caf1``: a majority vote scores (2p/(1+p))/M for the share p of M classes."""
    per = items.groupBy("domain", label).agg(F.count(F.lit(1)).alias("n"))
    out = per.groupBy("domain").agg(F.min(F.struct((-F.col("n")).alias("m"), F.col(label).alias("c"))).alias("top"), F.sum("n").alias("total"), F.count(F.lit(1)).alias("n_classes"))
    p = -F.col("top.m") / F.col("total")
    return out.select("domain", F.col("top.c").alias("majority"), F.round(p, 6).alias("share"), "n_classes", F.round(2 * p / (1 + p) / F.col("n_classes"), 6).alias("caf1"))


def task_labels(items: DataFrame, task: str, positive: str = "brief", drop: str = "neutral", common: tuple[str, ...] = ("brief", "extended")) -> DataFrame:
    """Items with ``y`` under a task: ``multi``; ``binary`` (one class against the rest); ``subset`` (binary without
    the dropped class); ``common`` (only the shared classes)."""
    c = F.col("class")
    one = F.when(c == positive, positive).otherwise("rest")
    if task == "multi":
        return items.withColumn("y", c)
    if task == "binary":
        return items.withColumn("y", one)
    if task == "subset":
        return items.where(c != drop).withColumn("y", one)
    if task == "common":
        return items.where(c.isin(*common)).withColumn("y", c)
    raise ValueError(f"unknown task {task!r}")


def predict(items: DataFrame, label: str = "y", features: tuple[str, ...] = HANDCRAFTED, train: Column | None = None) -> DataFrame:
    """Predictions of every domain's model on every domain's test split."""
    on = train if train is not None else F.col("split") == "train"
    models = fit_centroid(items.where(on), features, label=label)
    test = items.where("split = 'test'").select("item_id", "domain", "group_id", F.col(label).alias("truth"), *features)
    return score_all(test, models, features).select("item_id", "group_id", F.col("model").alias("train_domain"), F.col("domain").alias("test_domain"), "truth", "pred")
