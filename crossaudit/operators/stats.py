"""Resampling tests, false-discovery control, intervals and correlations."""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


#: Resamples that one task draws.
PER_TASK = 500


def resampled_scores(predictions: DataFrame, draws: int, unit: str = "group_id", seed: int = 42, keys: tuple[str, ...] = ()) -> DataFrame:
    """``train_domain, test_domain, b, caf1`` (and keys) of every cell under multinomial resampling of the target's test units; resample 0 is the data.

    Units of a test domain are numbered by id; draw k of resample b takes the unit that an MD5 names, the same for all
    cells of a column. Counts by unit come first; then blocks of resamples are drawn in tasks of their own, so work is
    shared out by resamples, and a task holds the counts of one column and its weights. `poisson_bootstrap` is for more units than that.
    """
    counts = predictions.groupBy(*keys, "train_domain", "test_domain", F.col(unit).cast("string").alias("unit"), "truth", "pred").agg(F.count(F.lit(1)).alias("n"))
    blocks = counts.select("*", F.explode(F.sequence(F.lit(0), F.lit(max(1, -(-draws // PER_TASK)) - 1))).alias("block"))

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        names = np.unique(pdf["unit"].to_numpy().astype(str))
        g, first = len(names), int(key[-1]) * PER_TASK + 1
        numbers = list(range(first, min(draws, first + PER_TASK - 1) + 1))
        weights = np.zeros((len(numbers), g))
        for row, b in enumerate(numbers):
            picks = [int(hashlib.md5(f"{seed}:{b}:{i}".encode()).hexdigest()[:8], 16) % g for i in range(g)]
            weights[row] = np.bincount(picks, minlength=g)
        if key[-1] == 0:
            weights, numbers = np.concatenate([np.ones((1, g)), weights]), [0, *numbers]
        out = []
        for train, part in pdf.groupby("train_domain"):
            classes = sorted(set(part["truth"]) | set(part["pred"]))
            m, place = len(classes), {c: i for i, c in enumerate(classes)}
            table = np.zeros((g, m, m))
            np.add.at(table, (np.searchsorted(names, part["unit"].to_numpy().astype(str)), part["truth"].map(place).to_numpy(), part["pred"].map(place).to_numpy()), part["n"].to_numpy())
            total = np.tensordot(weights, table, 1)
            hits, below = np.einsum("bii->bi", total), total.sum(1) + total.sum(2)
            f1 = np.divide(2 * hits, below, out=np.zeros_like(hits), where=below > 0)
            caf1 = f1.sum(1) / np.maximum(1, (below > 0).sum(1))
            out.append(pd.DataFrame({**dict(zip(keys, key, strict=False)), "train_domain": train, "test_domain": key[-2], "b": numbers, "caf1": caf1}))
        return pd.concat(out)

    schema = ", ".join([*(f"{k} string" for k in keys), "train_domain string, test_domain string, b long, caf1 double"])
    return blocks.groupBy(*keys, "test_domain", "block").applyInPandas(run, schema)


def paired_bootstrap(predictions: DataFrame, draws: int = 10_000, unit: str = "group_id", seed: int = 42, keys: tuple[str, ...] = ()) -> DataFrame:
    """``train_domain, test_domain, delta, ci_lo, ci_hi, p`` (and keys): score of the transferred model minus the target's own.

    One-sided p that transfer is worse: (1 + resamples with a difference of 0 or more) / (resamples + 1). The interval
    is the 2.5th to 97.5th percentile.
    """
    scores = resampled_scores(predictions, draws, unit, seed, keys)
    own = scores.where("train_domain = test_domain").select(*keys, "test_domain", "b", F.col("caf1").alias("own"))
    delta = scores.where("train_domain <> test_domain").join(own, [*keys, "test_domain", "b"]).withColumn("d", F.round(F.col("caf1") - F.col("own"), 9))
    real = F.col("b") > 0
    out = delta.groupBy(*keys, "train_domain", "test_domain").agg(
        F.max(F.when(~real, F.col("d"))).alias("delta"), F.percentile(F.when(real, F.col("d")), 0.025).alias("lo"), F.percentile(F.when(real, F.col("d")), 0.975).alias("hi"),
        ((1 + F.sum((real & (F.col("d") >= 0)).cast("int"))) / (1 + F.sum(real.cast("int")))).alias("p"),
    )
    return out.select(*keys, "train_domain", "test_domain", F.round("delta", 6).alias("delta"), F.round("lo", 6).alias("ci_lo"), F.round("hi", 6).alias("ci_hi"), F.round("p", 6).alias("p"))


def ratio_interval(predictions: DataFrame, draws: int = 10_000, unit: str = "group_id", seed: int = 42) -> DataFrame:
    """``n, ci_lo, ci_hi``: percentile interval of the negative-transfer ratio, with the same resampled units in every cell of a column."""
    cells = resampled_scores(predictions, draws, unit, seed).where("b > 0").withColumn("caf1", F.round("caf1", 6))
    same = F.col("train_domain") == F.col("test_domain")
    ratio = cells.groupBy("b").agg(F.round(1 - F.try_divide(F.avg(F.when(~same, F.col("caf1"))), F.avg(F.when(same, F.col("caf1")))), 6).alias("ntr"))
    return ratio.agg(F.count("ntr").alias("n"), F.round(F.percentile("ntr", 0.025), 6).alias("ci_lo"), F.round(F.percentile("ntr", 0.975), 6).alias("ci_hi"))


def poisson_bootstrap(predictions: DataFrame, draws: int = 10_000, seed: int = 42, parts: int = 16) -> DataFrame:
    """The same test with Poisson weights, for many resamples: per-unit counts go through one matrix product in blocks of resamples.

    Returns ``train_domain, test_domain, delta, ci_lo, ci_hi, p``.
    """
    diag = predictions.where("train_domain = test_domain").select("test_domain", "item_id", F.col("pred").alias("own"))
    off = predictions.where("train_domain <> test_domain").join(diag, ["test_domain", "item_id"])
    units = off.groupBy("train_domain", "test_domain", "group_id", "truth", "pred", "own").agg(F.count(F.lit(1)).alias("n"))
    blocks = units.select("*", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("block"))
    per = -(-draws // parts)

    def score(counts: np.ndarray) -> np.ndarray:
        tp = np.einsum("bii->bi", counts)
        below = counts.sum(1) + counts.sum(2)
        f1 = np.divide(2 * tp, below, out=np.full_like(tp, np.nan), where=below > 0)
        return np.nanmean(f1, axis=1)

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        classes = sorted(set(pdf["truth"]) | set(pdf["pred"]) | set(pdf["own"]))
        place = {c: i for i, c in enumerate(classes)}
        groups, g = np.unique(pdf["group_id"].astype(str).to_numpy(), return_inverse=True)
        m = len(classes)
        off_counts, own_counts = np.zeros((len(groups), m, m)), np.zeros((len(groups), m, m))
        t = pdf["truth"].map(place).to_numpy()
        np.add.at(off_counts, (g, t, pdf["pred"].map(place).to_numpy()), pdf["n"].to_numpy())
        np.add.at(own_counts, (g, t, pdf["own"].map(place).to_numpy()), pdf["n"].to_numpy())
        rng = np.random.default_rng([seed, int(key[2]), *key[1].encode()])
        w = rng.poisson(1.0, (per, len(groups))).astype(float)
        d = score(np.tensordot(w, off_counts, 1)) - score(np.tensordot(w, own_counts, 1))
        real = score(off_counts.sum(0)[None])[0] - score(own_counts.sum(0)[None])[0]
        return pd.DataFrame({"train_domain": key[0], "test_domain": key[1], "real": real, "d": [d[~np.isnan(d)].tolist()]})

    rows = blocks.groupBy("train_domain", "test_domain", "block").applyInPandas(run, "train_domain string, test_domain string, real double, d array<double>")
    flat = rows.select("train_domain", "test_domain", "real", F.explode("d").alias("d"))
    return flat.groupBy("train_domain", "test_domain").agg(
        F.max("real").alias("delta"), F.percentile_approx("d", 0.025, 10_000).alias("ci_lo"), F.percentile_approx("d", 0.975, 10_000).alias("ci_hi"),
        ((1 + F.sum((F.col("d") >= 0).cast("int"))) / (1 + F.count("d"))).alias("p"),
    )


def bh_adjust(tests: DataFrame, p: str = "p", family: tuple[str, ...] = (), q: float = 0.05, tie: tuple[str, ...] = ("train_domain", "test_domain")) -> DataFrame:
    """Tests with ``p_adj`` (step-up) and ``keep`` (``p_adj`` at most ``q``), within each family."""
    order = Window.partitionBy(*family) if family else Window.partitionBy(F.lit(1))
    up = order.orderBy(F.col(p), *tie)
    ranked = tests.withColumn("rank", F.row_number().over(up)).withColumn("m", F.count(F.lit(1)).over(order))
    back = order.orderBy(F.desc("rank")).rowsBetween(Window.unboundedPreceding, 0)
    adjusted = F.least(F.lit(1.0), F.min(F.col(p) * F.col("m") / F.col("rank")).over(back))
    return ranked.withColumn("p_adj", F.round(adjusted, 6)).withColumn("keep", F.col("p_adj") <= q).drop("rank", "m")


def seed_summary(scores: DataFrame, keys: list[str], value: str = "score") -> DataFrame:
    """``n_runs, mean, std, n_distinct, deterministic``; the deviation is the sample's, null for one run."""
    out = scores.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_runs"), F.round(F.avg(value), 6).alias("mean"), F.round(F.stddev_samp(value), 6).alias("std"), F.count_distinct(value).alias("n_distinct"))
    return out.withColumn("deterministic", F.col("n_distinct") == 1)


def _beta_tail(k: int, n: int, p: float) -> float:
    """P(Bin(n, p) >= k)."""
    if p <= 0:
        return float(k <= 0)
    if p >= 1:
        return 1.0
    lg = math.lgamma
    return math.fsum(math.exp(lg(n + 1) - lg(i + 1) - lg(n - i + 1) + i * math.log(p) + (n - i) * math.log1p(-p)) for i in range(k, n + 1))


def exact_bounds(k: int, n: int, alpha: float = 0.05) -> tuple[float, float]:
    """Exact two-sided binomial bounds, by bisection."""

    def solve(tail, target):
        lo, hi = 0.0, 1.0
        for _ in range(60):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if tail(mid) < target else (lo, mid)
        return (lo + hi) / 2

    lower = 0.0 if k == 0 else solve(lambda p: _beta_tail(k, n, p), alpha / 2)
    upper = 1.0 if k == n else solve(lambda p: _beta_tail(k + 1, n, p), 1 - alpha / 2)
    return lower, upper


def binom_ci(counts: DataFrame, k: str = "k", n: str = "n", alpha: float = 0.05) -> DataFrame:
    """Counts with ``lower, upper``."""

    @F.pandas_udf("lower double, upper double")
    def bounds(ks: pd.Series, ns: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([exact_bounds(int(a), int(b), alpha) for a, b in zip(ks, ns, strict=True)], columns=["lower", "upper"])

    out = counts.withColumn("ci", bounds(F.col(k), F.col(n)))
    return out.select(*counts.columns, F.round("ci.lower", 6).alias("lower"), F.round("ci.upper", 6).alias("upper"))


#: 97.5th percentiles of Student's t by degrees of freedom.
T975 = (12.706205, 4.302653, 3.182446, 2.776445, 2.570582, 2.446912, 2.364624, 2.306004, 2.262157, 2.228139, 2.200985, 2.178813, 2.160369, 2.144787, 2.131450, 2.119905, 2.109816, 2.100922, 2.093024, 2.085963, 2.079614, 2.073873, 2.068658, 2.063899, 2.059539, 2.055529, 2.051831, 2.048407, 2.045230, 2.042272)


def t975(df: Column) -> Column:
    """97.5th percentile of t; the normal's beyond thirty degrees, with a first-order correction."""
    return F.when(df <= len(T975), F.element_at(F.array(*[F.lit(x) for x in T975]), F.greatest(df, F.lit(1)).cast("int"))).otherwise(1.959964 + 2.372 / df)


def t_interval(df: DataFrame, keys: list[str], value: str) -> DataFrame:
    """``n, mean, ci_lo, ci_hi`` of values by keys."""
    out = df.groupBy(*keys).agg(F.count(value).alias("n"), F.avg(value).alias("m"), F.stddev_samp(value).alias("s"))
    half = t975(F.col("n") - 1) * F.col("s") / F.sqrt("n")
    return out.select(*keys, "n", F.round("m", 6).alias("mean"), F.round(F.col("m") - half, 6).alias("ci_lo"), F.round(F.col("m") + half, 6).alias("ci_hi"))


def point_biserial(rows: DataFrame, keys: list[str], quality: str = "quality", correct: str = "correct") -> DataFrame:
    """``n, r, t`` of a quality with 0/1 correctness; null where either is constant."""
    x, y = F.col(quality), F.col(correct).cast("double")
    out = rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), F.covar_pop(x, y).alias("c"), F.stddev_pop(x).alias("sx"), F.stddev_pop(y).alias("sy"))
    r = F.try_divide(F.col("c"), F.col("sx") * F.col("sy"))
    out = out.select(*keys, "n", F.round(r, 6).alias("r"))
    return out.select(*keys, "n", "r", F.round(F.try_divide(F.col("r") * F.sqrt(F.col("n") - 2.0), F.sqrt(1 - F.col("r") * F.col("r"))), 6).alias("t"))


def fisher_combine(p: Column, m: Column) -> Column:
    """Tail of chi-squared with 2m degrees of freedom at ``p`` = -2 times the sum of logs: a closed form for even degrees."""
    half = p / 2
    terms = F.transform(F.sequence(F.lit(0), m.cast("int") - 1), lambda k: F.exp(k * F.log(half) - F.log(F.factorial(k).cast("double"))))
    return F.exp(-half) * F.aggregate(terms, F.lit(0.0), lambda s, x: s + x)
