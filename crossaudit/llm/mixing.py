"""Mixing sources to target weights by Pareto order sampling (native DataFrame operations only).

Each source has a target in words. Its rows are wanted in proportion to a weight (by default the square root of their size, so a
long document is likelier than a short one, but not as much likelier as it is longer): a row's expected copies are the weight times the source's
level, two at most, the level being such that the expected words are the target. The whole part of the expected copies
is taken for certain. The fraction that is left is the row's inclusion probability p, drawn without replacement by order sampling: a
row's uniform number u becomes the odds u/(1-u), divided by the inclusion odds p/(1-p), and the rows with the smallest
quotients are taken until the words that are left are reached as closely as whole rows allow.

Finding the place where a source's running total meets its need does not sort the source: quotients are mapped to
(0, 1), counted in 256 cells, the crossing cell is split into 256 again, and only the rows of that last cell are ordered. Levels come from
sums by source and weight, and sources themselves are ranked in ranges, so that no task holds them all.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from crossaudit.functions.storage import materialize
from crossaudit.llm.words import count_words, free_names

CELLS = 256
WEIGHTS = (3.0, 1.0, 2.0)
SHARE, MOST = 1.5, 2.0
#: Weights of rows are taken to a thousandth, so that their sums are exact.
UNIT = 1000


def uniform(seed: int, *ids: Column) -> Column:
    """Reproducible number in (0, 1) from 52 bits of an MD5, the same in any engine."""
    digest = F.md5(F.concat_ws(":", F.lit(str(seed)), *[F.coalesce(c.cast("string"), F.lit("")) for c in ids]).cast("binary"))
    return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") + 0.5) / F.lit(float(1 << 52))


def running(rows: DataFrame, order: list[Column], **sums: Column) -> DataFrame:
    """Rows with the sums of all rows before them in a global order; only one row a range meets in one task."""
    ranged = materialize(rows.repartitionByRange(*order).withColumn("range", F.spark_partition_id()), "mix-ranges")
    part = ranged.groupBy("range").agg(*[F.sum(c).alias(f"{n}_all") for n, c in sums.items()])
    first = Window.partitionBy(F.lit(1)).orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    part = part.select("range", *[F.coalesce(F.sum(f"{n}_all").over(first), F.lit(0)).alias(f"{n}_first") for n in sums])
    inside = Window.partitionBy("range").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    out = ranged.join(part, "range")
    return out.select(*rows.columns, *[(F.col(f"{n}_first") + F.coalesce(F.sum(c).over(inside), F.lit(0))).alias(n) for n, c in sums.items()])


def source_targets(sizes: DataFrame, share: float = SHARE, most: float = MOST, weights: tuple[float, ...] = WEIGHTS) -> DataFrame:
    """``source, source_size, target`` from rows of ``source, size``.

    Sources by code point, null last, carry ``weights`` in turn and split ``share`` of all words; a target never
    exceeds ``most`` times its source, and the excess goes to the others by weight. The fixed point is found in
    closed form: sources fill up in the order of capacity per weight, so with that order's running sums the level
    (words per unit of weight) is the largest for which the capped ones before it are full.
    """
    per = sizes.groupBy("source").agg(F.coalesce(F.sum("size"), F.lit(0)).cast("long").alias("source_size"))
    per = running(per, [F.col("source").asc_nulls_last()], turn=F.lit(1))
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.col("turn") % len(weights) + 1).cast("int"))
    per = per.withColumn("w", w).withColumn("cap", F.col("source_size") * F.lit(float(most)))
    per = running(per.withColumn("fill", F.col("cap") / F.col("w")), [F.col("fill"), F.col("source").asc_nulls_last()], caps=F.col("cap"), ws=F.col("w"))
    per = materialize(per, "mix-sources")
    whole = per.agg(F.sum("source_size").alias("all_size"), F.sum("w").alias("all_w"))  # one row
    level = (F.lit(float(share)) * F.col("all_size") - F.col("caps")) / (F.col("all_w") - F.col("ws"))
    final = per.join(F.broadcast(whole)).withColumn("level", level).where("level <= fill").agg(F.min(F.struct("fill", "level"))["level"].alias("final"))
    return per.join(F.broadcast(final)).select("source", "source_size", F.least("cap", F.coalesce(F.col("w") * F.col("final"), F.col("cap"))).alias("target"))


def expected_copies(weight: Column, level: Column, most: float = MOST) -> Column:
    """Copies of a row that its source's level grants; no level grants all rows the most."""
    return F.when(weight > 0, F.least(F.lit(float(most)), F.coalesce(level * weight, F.lit(float(most))))).otherwise(0.0)


def levels(rows: DataFrame, targets: DataFrame, most: float = MOST) -> DataFrame:
    """``source, source_size, target, level, need``: expected words at ``level`` are the target; ``need`` of them are not whole copies.

    Rows (``source, size, weight``) are summed by source and weight. From the largest weight down, weights that the level
    would grant more than the most are capped; the level is that of the first one that is not.
    """
    same = lambda a, b: a["source"].eqNullSafe(b["source"])
    sums = materialize(rows.where("size > 0 and weight > 0").groupBy("source", "weight").agg(F.sum("size").cast("decimal(38,0)").alias("words")), "mix-weights")
    down = Window.partitionBy("source").orderBy(F.desc("weight"))
    above = F.coalesce(F.sum("words").over(down.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).cast("double")
    below = F.sum(F.col("words") * F.col("weight").cast("decimal(20,0)")).over(down.rowsBetween(0, Window.unboundedFollowing)).cast("double")
    found = sums.select("source", "weight", above.alias("above"), below.alias("below")).join(targets, sums["source"].eqNullSafe(targets["source"])).select(sums["source"], "weight", ((F.col("target") - most * F.col("above")) / F.col("below")).alias("level"))
    found = found.where(F.col("level") * F.col("weight") <= most).groupBy("source").agg(F.max(F.struct("weight", "level"))["level"].alias("level"))
    out = targets.join(found, same(targets, found), "left").select(targets["source"], "source_size", "target", "level")
    out = materialize(out, "mix-levels")
    granted = sums.join(out, same(sums, out)).select(sums["source"], (F.floor(expected_copies(F.col("weight"), F.col("level"), most)) * F.col("words")).alias("sure"))
    granted = granted.groupBy("source").agg(F.sum("sure").cast("double").alias("sure"))
    return out.join(granted, same(out, granted), "left").select(out["source"], "source_size", "target", "level", (F.col("target") - F.coalesce("sure", F.lit(0.0))).alias("need"))


def order_key(u: Column, p: Column) -> Column:
    """Place of a row in its source's order, in (0, 1): random odds over inclusion odds, q, as q/(1+q); null if it is not to be drawn."""
    return F.when((p > 0) & (p < 1), u * (1 - p) / (u * (1 - p) + (1 - u) * p))


def _crossing(rows: DataFrame, cell: Column) -> DataFrame:
    """Of each source, the first ``cell`` at whose end the running total of words passes ``need``; total ``below`` it."""
    counted = rows.groupBy("source", cell.alias("cell")).agg(F.sum("size").alias("words"), F.first("need").alias("need"), F.first("below").alias("below"))
    upto = Window.partitionBy("source").orderBy("cell").rowsBetween(Window.unboundedPreceding, 0)
    counted = counted.withColumn("end", F.col("below") + F.sum("words").over(upto)).where("end >= need")
    return counted.groupBy("source").agg(F.min(F.struct("cell", (F.col("end") - F.col("words")).alias("start"))).alias("x")).select("source", "x.cell", F.col("x.start").alias("start"))


def cuts(rows: DataFrame) -> DataFrame:
    """``source, cut``: rows (``source, size, v, need``) with ``v`` up to the cut come as near to ``need`` words as whole rows allow."""

    def inside(df: DataFrame, cell: Column) -> DataFrame:
        x = materialize(_crossing(df, cell), "mix-cell")
        return df.join(x, df["source"].eqNullSafe(x["source"]) & (cell == x["cell"])).select(df["source"], "size", "v", "need", F.col("start").alias("below"))

    first = F.floor(F.col("v") * CELLS)
    second = F.floor(F.col("v") * CELLS * CELLS)
    last = inside(inside(rows.withColumn("below", F.lit(0.0)), first), second)
    upto = Window.partitionBy("source").orderBy("v").rangeBetween(Window.unboundedPreceding, 0)
    last = last.groupBy("source", "v", "need", "below").agg(F.sum("size").alias("size"))
    last = last.withColumn("end", F.col("below") + F.sum("size").over(upto))
    # the row before the last cell is a cut too: everything below the cell, none of it
    miss = F.abs(F.col("end") - F.col("need"))
    best = last.groupBy("source").agg(
        F.min(F.struct(miss.alias("miss"), F.col("v").alias("cut"))).alias("b"),
        F.first(F.col("need") - F.col("below")).alias("none"),
        F.min(second).alias("cell"),
    )
    cut = F.when(F.col("b.miss") <= F.col("none"), F.col("b.cut")).otherwise(F.col("cell") / float(CELLS * CELLS) - F.lit(2.0**-60))
    return best.select("source", cut.alias("cut"))


def mix(documents: DataFrame, seed: int = 7, share: float = SHARE, most: float = MOST, weights: tuple[float, ...] = WEIGHTS, weight: Column | None = None) -> DataFrame:
    """The documents with ``mix_size, mix_source_size, mix_target, mix_copies`` added, in place of any columns of these names.

    ``weight`` makes rows likelier in proportion; null and non-positive ones are never taken. Null text has size 0 and is never taken, null source is a
    source of its own and the last one; rows with one ``doc_id`` share their random number, so repeated rows are taken or
    left together, as are ties; an empty table gives an empty result.
    """
    documents = documents.drop("mix_size", "mix_source_size", "mix_target", "mix_copies")
    size = count_words(F.col("text"))
    own = F.sqrt(size.cast("double")) if weight is None else weight.cast("double")
    parts = {"source": F.col("source"), "size": size, "weight": F.coalesce(F.floor(own * UNIT), F.lit(0)).cast("long"), "u": uniform(seed, F.col("doc_id"))}
    rows = materialize(documents.select(*[c.alias(n) for n, c in parts.items()]), "mix-rows")
    plan = materialize(levels(rows, source_targets(rows, share, most, weights), most), "mix-plan")
    same = rows["source"].eqNullSafe(plan["source"])
    drawn = rows.where("size > 0").join(plan.where("need > 0"), same).select(plan["source"], "size", "need", "u", expected_copies(F.col("weight"), F.col("level"), most).alias("copies"))
    drawn = drawn.select("source", "size", "need", order_key(F.col("u"), F.col("copies") - F.floor("copies")).alias("v"))
    drawn = materialize(drawn, "mix-drawn").where("v is not null")
    found = materialize(cuts(drawn), "mix-cut")
    plan = plan.join(found, plan["source"].eqNullSafe(found["source"]), "left").select(plan["source"], "source_size", "target", "level", "cut")
    s, w, u, ps, pz, pt, pl, pc = free_names(documents, "mix_size", "mix_w", "mix_u", "mix_s", "mix_source_size", "mix_target", "mix_level", "mix_cut")
    plan = plan.select(*[F.col(a).alias(b) for a, b in zip(("source", "source_size", "target", "level", "cut"), (ps, pz, pt, pl, pc), strict=True)])
    out = documents.withColumns({s: size, w: parts["weight"], u: parts["u"]})
    out = out.join(plan, out["source"].eqNullSafe(plan[ps]), "left")
    granted = expected_copies(F.col(w), F.col(pl), most)
    extra = F.coalesce(order_key(F.col(u), granted - F.floor(granted)) <= F.col(pc), F.lit(False))
    taken = F.when(F.col(s) > 0, F.floor(granted) + extra.cast("int")).otherwise(0).cast("int")
    return out.select(*documents.columns, F.col(s).alias("mix_size"), F.col(pz).alias("mix_source_size"), F.col(pt).alias("mix_target"), taken.alias("mix_copies"))


def mixed(documents: DataFrame, **options) -> DataFrame:
    """The mix itself: every document repeated as often as it is taken, with the columns it came with, whatever their names.

    Nulls, repeated rows, ties and empty tables are as in `mix`.
    """
    (name,) = free_names(documents, "mix_copy")
    plain = [f"mixed_{i}" for i in range(len(documents.columns))]
    keep = {"doc_id", "source", "text"}
    own = documents.select(*[F.col(c).alias(c if c in keep else p) for c, p in zip(documents.columns, plain, strict=True)])
    out = mix(own, **options).where("mix_copies > 0").withColumn(name, F.explode(F.sequence(F.lit(1), F.col("mix_copies"))))
    return out.select(*[F.col(c if c in keep else p).alias(c) for c, p in zip(documents.columns, plain, strict=True)])


def query(spark, sf_dir):
    """op9: words taken from every document."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source", "text")
    return mix(docs).select(
        "doc_id", F.col("mix_size").alias("size"), F.col("mix_source_size").alias("source_size"),
        F.col("mix_target").alias("target"), (F.col("mix_copies") * F.col("mix_size")).cast("long").alias("taken"),
    )


#: The same in one piece of SQL. Running totals are exact integers below 2^53, so the engines agree.
ORACLE = r"""
WITH d0 AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
         (CAST('0x' || substr(md5('7:' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 13) AS BIGINT) + 0.5::DOUBLE) / 4503599627370496.0::DOUBLE AS u
  FROM documents),
d AS (SELECT *, CAST(floor(sqrt(size::DOUBLE) * 1000) AS BIGINT) AS wt FROM d0),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (SELECT *, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 3.0::DOUBLE WHEN 1 THEN 1.0::DOUBLE ELSE 2.0::DOUBLE END AS w,
             source_size * 2.0::DOUBLE AS cap FROM s),
l AS (SELECT *, (1.5::DOUBLE * sum(source_size) OVER () - coalesce(sum(cap) OVER (ORDER BY cap / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
             / sum(w) OVER (ORDER BY cap / w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM w),
f AS (SELECT arg_min(level, cap / w) AS level FROM l WHERE level <= cap / w),
t AS (SELECT l.source, source_size, least(cap, coalesce(w * f.level, cap)) AS target FROM l LEFT JOIN f ON true),
g AS (SELECT source, wt, sum(size) AS words FROM d WHERE size > 0 GROUP BY source, wt),
h AS (SELECT g.source, wt, (target - 2.0::DOUBLE * coalesce(sum(words) OVER (PARTITION BY g.source ORDER BY wt DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::DOUBLE)
        / (sum(words * wt) OVER (PARTITION BY g.source ORDER BY wt DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))::DOUBLE AS level
      FROM g JOIN t ON g.source IS NOT DISTINCT FROM t.source),
v AS (SELECT source, arg_max(level, wt) AS level FROM h WHERE level * wt <= 2.0::DOUBLE GROUP BY source),
e AS (SELECT d.doc_id, d.source, d.size, d.u, t.source_size, t.target, CASE WHEN d.size > 0 THEN least(2.0::DOUBLE, coalesce(v.level * d.wt, 2.0::DOUBLE)) ELSE 0 END AS copies
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source LEFT JOIN v ON d.source IS NOT DISTINCT FROM v.source),
p AS (SELECT *, floor(copies) AS whole, copies - floor(copies) AS p, target - sum(floor(copies) * size) OVER (PARTITION BY source) AS need FROM e),
q AS (SELECT *, CASE WHEN p > 0 THEN u * (1 - p) / (u * (1 - p) + (1 - u) * p) END AS v FROM p),
c AS (SELECT *, sum(CASE WHEN v IS NOT NULL THEN size END) OVER (PARTITION BY source ORDER BY v RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto FROM q),
b AS (SELECT source, arg_min(v, abs(upto - need)) AS cut, min(abs(upto - need)) AS miss FROM c WHERE v IS NOT NULL GROUP BY source)
SELECT c.doc_id, c.size, c.source_size, c.target,
       CAST(c.size * (c.whole + CASE WHEN c.need > 0 AND b.miss <= c.need AND c.v <= b.cut THEN 1 ELSE 0 END) AS BIGINT) AS taken
FROM c LEFT JOIN b ON c.source IS NOT DISTINCT FROM b.source
"""
