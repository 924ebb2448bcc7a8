"""Label budgets, episodes, unlabelled pools and paired contrasts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crossaudit.operators.ranks import running
from crossaudit.operators.stats import t_interval


def draw_shots(train: DataFrame, draws: list[int], budgets: list[int], prefix: str, label: str = "y") -> DataFrame:
    """``draw, budget, item_id, actual_n``: for each draw and class the first ``budget`` items by a hash.

    Budgets are nested; a short class gives what it has, which ``actual_n`` shows. Ranks are taken in two levels.
    """
    rows = train.select("item_id", label, F.explode(F.array(*[F.lit(d) for d in draws])).alias("draw"))
    ranked = running(rows, ["draw", label], F.md5(F.concat_ws(":", F.lit(prefix), "draw", "item_id").cast("binary")), "item_id").withColumn("r", F.col("before") + 1).where(F.col("r") <= max(budgets))
    out = ranked.withColumn("budget", F.explode(F.array(*[F.lit(b) for b in budgets]))).where("r <= budget")
    return out.select("draw", "budget", "item_id", label, F.least("budget", "total").cast("long").alias("actual_n"))


def build_pool(items: DataFrame, extra: DataFrame, protocol: str = "inductive") -> DataFrame:
    """``item_id, origin`` of the unlabelled pool: train items (inductive) or all (transductive), and an external pool."""
    own = items if protocol == "transductive" else items.where("split = 'train'")
    return own.select("item_id", F.lit("items").alias("origin")).unionByName(extra.select("item_id", F.lit("extra").alias("origin")))


def pool_violations(pool: DataFrame, items: DataFrame) -> DataFrame:
    """Validation and test items that the pool holds."""
    held = items.where("split <> 'train'").select("item_id", "split")
    return pool.where("origin = 'items'").join(held, "item_id").select("item_id", "split")


def paired_contrast(scores: DataFrame, a: str, b: str, pairing: str = "episode") -> DataFrame:
    """``budget, n, mean, ci_lo, ci_hi, significant`` of arm a minus arm b over shared episodes.

    ``episode`` averages an episode's seeds first (conservative); ``run`` pairs every episode and seed.
    """
    keys = ["budget", "episode"] + (["seed"] if pairing == "run" else [])
    arm = lambda x: scores.where(F.col("arm") == x).groupBy(*keys).agg(F.avg("score").alias(x))
    d = arm(a).join(arm(b), keys).withColumn("d", F.col(a) - F.col(b))
    return t_interval(d, ["budget"], "d").withColumn("significant", (F.col("ci_lo") > 0) | (F.col("ci_hi") < 0))


def crossover(contrast: DataFrame) -> DataFrame:
    """``crossover, kind``: the smallest budget whose interval lies above 0 after one that does not; ``trend`` if only a mean does."""
    rows = contrast.agg(F.min(F.when(F.col("ci_lo") > 0, F.col("budget"))).alias("sure"), F.min(F.when(F.col("mean") > 0, F.col("budget"))).alias("maybe"), F.min("budget").alias("first"))
    sure = F.col("sure") > F.col("first")
    return rows.select(F.when(sure, F.col("sure")).when(F.col("maybe") > F.col("first"), F.col("maybe")).alias("crossover"), F.when(sure, "crossover").when(F.col("maybe") > F.col("first"), "trend").otherwise("none").alias("kind"))
