"""Frozen encoders: one row for each item with its vector, computed once and reused."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, StructField, StructType

#: Per-line statistics of the handcrafted descriptor; its vector is their means, then their deviations, then log length.
LINE_STATS = ("chars", "digits", "upper", "punct", "fresh")
HANDCRAFTED = tuple(f"{s}_mean" for s in LINE_STATS) + tuple(f"{s}_std" for s in LINE_STATS) + ("log_length",)


def handcrafted(docs: DataFrame, text: str = "text") -> DataFrame:
    """``item_id`` and eleven numbers: mean and deviation over lines (the windows) of length and of the ratios of digits,
    capitals, punctuation and distinct words, and the log of the text's length. Empty lines are no windows; a text without any has zeros.
    Each row is computed by itself."""
    whole = F.coalesce(F.col(text), F.lit(""))

    def ratio(line: Column, other: str) -> Column:
        return F.length(F.regexp_replace(line, other, "")) / F.length(line)

    def fresh(line: Column) -> Column:
        words = F.filter(F.split(line, " "), lambda w: w != "")
        return F.size(F.array_distinct(words)) / F.nullif(F.size(words), F.lit(0))

    stats = dict(zip(LINE_STATS, (lambda x: F.length(x).cast("double"), lambda x: ratio(x, "[^0-9]"), lambda x: ratio(x, "[^A-Z]"), lambda x: ratio(x, "[^.,;:!?]"), fresh), strict=True))
    lines = docs.select("item_id", F.length(whole).alias("size"), F.filter(F.split(whole, "\n"), lambda x: x != "").alias("lines"))
    rows = lines.select("item_id", "size", *[F.filter(F.transform("lines", f), lambda v: v.isNotNull()).alias(s) for s, f in stats.items()])
    total = lambda c: F.aggregate(c, F.lit(0.0), lambda s, v: s + v)
    means = rows.select("*", *[F.try_divide(total(F.col(s)), F.size(s)).alias(f"{s}_m") for s in LINE_STATS])
    deviation = lambda s: F.sqrt(F.try_divide(F.aggregate(s, F.lit(0.0), lambda t, v: t + (v - F.col(f"{s}_m")) * (v - F.col(f"{s}_m"))), F.size(s)))
    out = [F.round(F.coalesce(F.col(f"{s}_m"), F.lit(0.0)), 6).alias(f"{s}_mean") for s in LINE_STATS]
    out += [F.round(F.coalesce(deviation(s), F.lit(0.0)), 6).alias(f"{s}_std") for s in LINE_STATS]
    return means.select("item_id", *out, F.round(F.log(F.col("size") + F.lit(1.0)), 6).alias("log_length"))


def _words(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, list[str]]:
    """Text and number of each word in order, and the distinct words: runs of letters and digits, in lower case."""
    parts = pc.split_pattern_regex(pc.utf8_lower(pc.fill_null(texts, "").cast(pa.large_string())), r"[^\p{L}0-9]+")
    coded = pc.list_flatten(parts).dictionary_encode()
    names = coded.dictionary.to_pylist()
    codes = coded.indices.to_numpy().astype(np.int64)
    row = np.repeat(np.arange(len(texts)), np.diff(np.asarray(parts.offsets)))
    real = np.array([w != "" for w in names], bool)[codes] if len(codes) else np.zeros(0, bool)
    return row[real], codes[real], names


def _grams(texts: pa.Array, kind: str) -> tuple[np.ndarray, np.ndarray, list[str]]:
    """Text and number of each gram, and the distinct grams."""
    if kind == "char3":
        rows, keys, short = [], [], {}
        for i, t in enumerate(texts.to_pylist()):
            x = np.frombuffer((t or "").encode("utf-32-le"), "<u4").astype(np.int64)
            if len(x) < 3:
                short[i] = t or ""
            else:
                keys.append(x[:-2] << 42 | x[1:-1] << 21 | x[2:])
                rows.append(np.full(len(x) - 2, i))
        distinct, code = np.unique(np.concatenate([np.zeros(0, np.int64), *keys]), return_inverse=True)
        names = ["".join(map(chr, (k >> 42, k >> 21 & 0x1FFFFF, k & 0x1FFFFF))) for k in distinct.tolist()]
        return np.concatenate([np.zeros(0, np.int64), *rows, list(short)]).astype(np.int64), np.concatenate([code, len(names) + np.arange(len(short))]).astype(np.int64), names + list(short.values())
    row, code, names = _words(texts)
    if kind == "word":
        return row, code, names
    if kind == "word2":
        # the last word of a text alone if it is the only one
        pair = row[1:] == row[:-1]
        lone = np.flatnonzero(np.bincount(row, minlength=len(texts))[row] == 1) if len(row) else np.zeros(0, np.int64)
        both = np.concatenate([code[:-1][pair] * len(names) + code[1:][pair], len(names) ** 2 + code[lone]]) if len(row) else np.zeros(0, np.int64)
        distinct, number = np.unique(both, return_inverse=True)
        spelled = [names[k - len(names) ** 2] if k >= len(names) ** 2 else f"{names[k // len(names)]} {names[k % len(names)]}" for k in distinct.tolist()]
        return np.concatenate([row[:-1][pair], row[lone]]) if len(row) else row, number, spelled
    raise ValueError(f"unknown encoder {kind!r}")


def hashed(docs: DataFrame, kind: str = "char3", dims: int = 64, center: str | None = None) -> DataFrame:
    """``item_id, features``: counts of grams by the first four hex digits of their MD5, of unit length, then centred on the mean of their ``center`` column's value.

    Each text is counted by itself, in Arrow batches; only the means, one row a value, are aggregated. A text without grams has no row.
    """
    keep = [f for f in docs.schema.fields if f.name in ("item_id", center)]

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 500):
                part = b.slice(at, 500)
                row, code, names = _grams(part.column(part.num_columns - 1), kind)
                place = np.array([int(hashlib.md5(g.encode()).hexdigest()[:4], 16) % dims for g in names], np.int64)
                counts = np.bincount(row * dims + place[code], minlength=part.num_rows * dims).reshape(part.num_rows, dims).astype(float) if len(row) else np.zeros((part.num_rows, dims))
                norm = np.sqrt((counts * counts).sum(axis=1))
                live = np.flatnonzero(norm > 0)
                unit = counts[live] / norm[live, None]
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(live) + 1) * dims, pa.int32()), pa.array(unit.ravel()))
                yield pa.RecordBatch.from_arrays([*(part.column(i).take(pa.array(live)) for i in range(part.num_columns - 1)), lists], names=[*(f.name for f in keep), "features"])

    schema = StructType([*keep, StructField("features", ArrayType(DoubleType()))])
    vectors = docs.select(*[f.name for f in keep], "text").mapInArrow(run, schema)
    if not center:
        return vectors
    mean = vectors.groupBy(center).agg(F.array(*[F.avg(F.get("features", F.lit(d))) for d in range(dims)]).alias("mean"))
    return vectors.join(mean, center).select("item_id", F.zip_with("features", "mean", lambda a, b: a - b).alias("features"))


def pooled(frames: DataFrame, how: str, order: str = "t") -> DataFrame:
    """Readouts of ``item_id, t, mask, features`` frames: ``mean`` and ``mean_std`` over unmasked frames, or the ``first`` frame."""
    live = frames.where("mask")
    if how == "first":
        return live.groupBy("item_id").agg(F.min_by("features", order).alias("features"))
    dims = live.select("item_id", F.posexplode("features").alias("d", "x")).groupBy("item_id", "d").agg(F.avg("x").alias("m"), F.stddev_pop("x").alias("s"))
    rows = dims.groupBy("item_id").agg(F.array_sort(F.collect_list(F.struct("d", "m", "s"))).alias("a"))
    mean, std = F.transform("a", lambda e: e["m"]), F.transform("a", lambda e: e["s"])
    return rows.select("item_id", (mean if how == "mean" else F.concat(mean, std)).alias("features"))


def standardize(df: DataFrame, item: str, order: str, value: str, length: int, peak: bool = True) -> DataFrame:
    """``item, series, ok``: an item's values in order, cut or padded to ``length`` and scaled to a peak of 1.

    Null values count as 0; a series of zeros stays as it is; ``ok`` is false for a series without any value.
    """
    rows = df.groupBy(item).agg(F.array_sort(F.collect_list(F.struct(order, F.coalesce(value, F.lit(0.0)).alias("v")))).alias("a"), F.count(value).alias("n"))
    series = F.slice(F.concat(F.transform("a", lambda e: e["v"]), F.array_repeat(F.lit(0.0), length)), 1, length)
    top = F.array_max(F.transform(F.col("s"), lambda x: F.abs(x)))
    out = rows.select(item, series.alias("s"), (F.col("n") > 0).alias("ok"))
    return out.select(item, F.when(F.lit(peak) & (top > 0), F.transform("s", lambda x: x / top)).otherwise(F.col("s")).alias("series"), "ok")


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    """Null for a vector without direction."""
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def columns_to_array(columns: tuple[str, ...] = HANDCRAFTED) -> Column:
    return F.array(*[F.col(c).cast("double") for c in columns])
