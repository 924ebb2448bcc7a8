"""A training-free control: a pluggable predictor, strict parsing, and its report."""

from __future__ import annotations

import time
from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from crossaudit.operators.ranks import running
from crossaudit.operators.transfer import confusion, overall

UNPARSED = "UNPARSED"


def stratified_subsample(items: DataFrame, n: int, seed: int = 42, label: str = "truth") -> DataFrame:
    """``n`` items of each domain with class shares kept by largest remainders; all of a domain that has no more."""
    per = items.groupBy("domain", label).agg(F.count(F.lit(1)).alias("n_c"))
    total = F.sum("n_c").over(Window.partitionBy("domain"))
    share = per.withColumn("total", total).withColumn("x", F.col("n_c") * F.least(F.lit(n), F.col("total")) / F.col("total")).withColumn("base", F.floor("x"))
    left = F.least(F.lit(n), F.col("total")) - F.sum("base").over(Window.partitionBy("domain"))
    rank = F.row_number().over(Window.partitionBy("domain").orderBy(F.desc(F.round(F.col("x") - F.col("base"), 9)), label))
    quota = share.withColumn("left", left).withColumn("rank", rank).select("domain", label, (F.col("base") + (F.col("rank") <= F.col("left")).cast("int")).alias("quota"))
    ranked = running(items, ["domain", label], F.md5(F.concat_ws(":", F.lit(str(seed)), "item_id").cast("binary")), "item_id").drop("total")
    return ranked.join(F.broadcast(quota), ["domain", label]).where("before < quota").drop("before", "quota")


def rule_answer(n: Column) -> Column:
    """Answer of the built-in rule predictor: a sentence with a label by length, or none."""
    return F.when(n < 700, "this is brief").when(n < 2600, "medium").when(n < 9000, "Extended.").otherwise("brief or extended?")


def parse_answer(answer: Column, labels: list[str]) -> Column:
    """The one legal label that an answer names; with none or several, UNPARSED."""
    found = F.filter(F.array(*[F.lit(x) for x in labels]), lambda x: F.contains(F.lower(answer), x))
    return F.when(F.size(found) == 1, F.element_at(found, 1)).otherwise(UNPARSED)


def zero_shot(items: DataFrame, predict: Callable[[str], str], labels: list[str], parallel: int = 4, per_second: float | None = None, tries: int = 3) -> DataFrame:
    """``item_id, answer, error, pred, seconds``: one call for each item, with bounded parallelism, pauses and growing retries.

    A call that fails every time has no answer and its last error's text.
    """

    def run(batches):
        for pdf in batches:
            out = []
            for i, text in zip(pdf["item_id"], pdf["text"], strict=True):
                began, answer, error = time.time(), None, None
                for k in range(tries):
                    try:
                        answer, error = predict(text), None
                        break
                    except Exception as e:  # any failure of a foreign call is an answer of its own
                        error = f"{type(e).__name__}: {e}"
                        time.sleep(0.1 * 2**k)
                out.append((i, answer, error, time.time() - began))
                if per_second:
                    time.sleep(max(0.0, parallel / per_second - (time.time() - began)))
            yield pd.DataFrame(out, columns=["item_id", "answer", "error", "seconds"])

    calls = items.select("item_id", "text").repartition(parallel).mapInPandas(run, "item_id long, answer string, error string, seconds double")
    return calls.select("item_id", "answer", "error", parse_answer(F.coalesce("answer", F.lit("")), labels).alias("pred"), "seconds")


def zs_report(predictions: DataFrame) -> DataFrame:
    """Scores by domain with the number of unparsed answers and the share of the commonest answer."""
    p = predictions.withColumn("train_domain", F.lit("rule"))
    scores = overall(confusion(p, ["domain"]), ["domain"])
    top = p.groupBy("domain", "pred").agg(F.count(F.lit(1)).alias("c")).groupBy("domain").agg(F.max("c").alias("top"), F.sum(F.when(F.col("pred") == UNPARSED, F.col("c")).otherwise(0)).alias("unparsed"), F.sum("c").alias("calls"))
    return scores.join(top, "domain").select("domain", "calls", "unparsed", F.round(F.col("top") / F.col("calls"), 6).alias("skew"), "acc", "caf1", "uar", "chance_uar")
