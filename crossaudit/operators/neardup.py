"""Near copies by vectors and by similarity hashes; candidates in blocks or bands, never a plan-level cross join."""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from crossaudit.functions.storage import materialize
from crossaudit.operators.encode import _words, cosine

BLOCK = 2048
#: Rows of a block whose products are held at once.
TILE = 512
#: More than a cosine in single precision can be off, at up to a hundred dimensions.
ROUGH = 1e-5


def _blocks(df: DataFrame, rows: int, block: int) -> DataFrame:
    """Rows repeated into the unordered pairs of blocks that they belong to, as ``part_a, part_b, own``."""
    parts = max(1, math.ceil(rows / block))
    own = F.pmod(F.xxhash64("item_id"), F.lit(parts)).cast("int")
    pairs = F.transform(F.sequence(F.lit(0), F.lit(parts - 1)), lambda p: F.struct(F.least(p, F.col("own")).alias("a"), F.greatest(p, F.col("own")).alias("b")))
    return df.withColumn("own", own).withColumn("p", F.explode(pairs)).select("*", F.col("p.a").alias("part_a"), F.col("p.b").alias("part_b")).drop("p")


def _unit(x: np.ndarray) -> np.ndarray:
    n = np.linalg.norm(x, axis=1, keepdims=True)
    return np.divide(x, n, out=np.zeros_like(x), where=n > 0)


def _packed(vectors: DataFrame, block: int) -> DataFrame:
    """One row for each block of up to ``block`` items: ``key``, the ids and unit vectors as bytes, a domain after the other, and where each domain ends."""
    files = max(1, math.ceil(vectors.count() / (8 * block)))

    def run(batches):
        part, k = TaskContext.get().partitionId(), 0
        for b in batches:
            for rows in np.array_split(np.arange(b.num_rows), max(1, math.ceil(b.num_rows / block))):
                if len(rows):
                    own = b.take(pa.array(rows))
                    names, code = np.unique(np.array(own.column(1).to_pylist(), object), return_inverse=True)
                    order = np.argsort(code, kind="stable")
                    x = _unit(np.stack(own.column(2).to_numpy(zero_copy_only=False)).astype(float))[order]
                    ends = np.bincount(code).cumsum().tolist()
                    cols = [part << 32 | k, own.column(0).to_numpy()[order].tobytes(), x.tobytes(), names.tolist(), ends]
                    kinds = [pa.int64(), pa.binary(), pa.binary(), pa.list_(pa.string()), pa.list_(pa.int32())]
                    yield pa.RecordBatch.from_arrays([pa.array([c], t) for c, t in zip(cols, kinds, strict=True)], names=["key", "ids", "x", "names", "ends"])
                    k += 1

    spread = vectors.select(F.col("item_id").cast("long"), "domain", "features").repartition(files, "item_id")
    return materialize(spread.mapInArrow(run, "key long, ids binary, x binary, names array<string>, ends array<int>"), "vector-blocks")


def blocked_cosines(vectors: DataFrame, tau: float, thresholds: tuple[float, ...] = (), block: int = BLOCK, labelled: bool = False) -> DataFrame:
    """Exact: all unordered pairs of items of different ``domain`` with cosine of ``tau`` or more, or their counts.

    Without ``thresholds`` returns ``left_id, right_id, cos``; with them, for each pair of blocks and domains, the
    largest cosine and the number above each threshold, so that no pair is emitted. If ``labelled``, pairs tell whether their
    ends' ``label`` agree, too (a null agrees with nothing). The vectors are shuffled once, into
    written blocks; every task reads the two lists of blocks that it compares, so that nothing is repeated on disk. Products in
    single precision settle what is further than their error from a threshold, and the rest is computed in double
    precision. The work is quadratic and meant for audits of bounded corpora.
    """
    names = [f"n{round(1000 * t)}" for t in thresholds]
    if labelled:  # a block is cut by domain and label, so that all pairs of two cuts agree or none
        told = F.when(F.col("label").isNull(), F.lit("")).otherwise(F.concat(F.lit("="), F.col("label").cast("string")))
        vectors = vectors.select("item_id", F.concat("domain", F.lit("\x1f"), told).alias("domain"), "features")
    own = lambda d: d.rpartition("\x1f")[::2] if labelled else (d, "")

    def sides(row: dict, k: str) -> dict[str, tuple[np.ndarray, np.ndarray, np.ndarray]]:
        ids = np.frombuffer(row[f"ids_{k}"], np.int64)
        x = np.frombuffer(row[f"x_{k}"], float).reshape(len(ids), -1)
        cuts = [0, *row[f"ends_{k}"]]
        return {d: (ids[i:j], x[i:j], x[i:j].astype(np.float32)) for d, i, j in zip(row[f"names_{k}"], cuts, cuts[1:], strict=False)}

    def exact(x: np.ndarray, y: np.ndarray, at: np.ndarray, width: int) -> np.ndarray:
        return np.concatenate([np.zeros(0), *(np.einsum("ij,ij->i", x[p // width], y[p % width]) for p in np.split(at, range(65_536, len(at), 65_536)))])

    def run(batches):
        for b in batches:
            for row in (r for i in range(b.num_rows) for r in b.slice(i, 1).to_pylist()):
                a, other, found = sides(row, "a"), sides(row, "b"), []
                for d, e in ((d, e) for d in a for e in other if own(d)[0] != own(e)[0] and (d < e or row["key_a"] != row["key_b"])):
                    agree = own(d)[1] == own(e)[1] != ""
                    (ids_y, y, y4), most, above = other[e], -2.0, np.zeros(len(names), np.int64)
                    for i in range(0, len(a[d][0]), TILE):
                        ids_x, x, x4 = (c[i : i + TILE] for c in a[d])
                        rough = (x4 @ y4.T).ravel()
                        if not names:
                            at = np.flatnonzero(rough >= tau - ROUGH)
                            cos = exact(x, y, at, len(y))
                            at, cos = at[cos >= tau], cos[cos >= tau]
                            left, right = ids_x[at // len(y)], ids_y[at % len(y)]
                            found.append((np.minimum(left, right), np.maximum(left, right), cos, *[np.full(len(cos), agree)] * labelled))
                            continue
                        if (top := float(rough.max())) > most - ROUGH:
                            most = max(most, exact(x, y, np.flatnonzero(rough >= top - 2 * ROUGH), len(y)).max())
                        high = np.flatnonzero(rough > min(thresholds) - ROUGH)
                        near = rough[high]
                        for k, t in enumerate(thresholds):
                            above[k] += (near > t + ROUGH).sum() + (exact(x, y, high[np.abs(near - t) <= ROUGH], len(y)) > t).sum()
                    if names:
                        found.append((min(d, e), max(d, e), most, *above.tolist()))
                if not found:
                    continue
                if names:
                    cols = [pa.array(c, t) for c, t in zip(zip(*found, strict=True), [pa.string(), pa.string(), pa.float64()] + [pa.int64()] * len(names), strict=True)]
                    yield pa.RecordBatch.from_arrays(cols, names=["domain_a", "domain_b", "max_cos", *names])
                else:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*found, strict=True)], names=["left_id", "right_id", "cos", *["agree"] * labelled])

    blocks = _packed(vectors, block)
    side = lambda k: blocks.select(*[F.col(c).alias(f"{c}_{k}") for c in blocks.columns])
    met = side("a").hint("shuffle_replicate_nl").join(side("b"), F.col("key_a") <= F.col("key_b"))
    schema = "left_id long, right_id long, cos double" + ", agree boolean" * labelled if not names else "domain_a string, domain_b string, max_cos double, " + ", ".join(f"{n} long" for n in names)
    return met.mapInArrow(run, schema)


def cosine_audit(vectors: DataFrame, thresholds: tuple[float, ...] = (0.95, 0.98, 0.99)) -> DataFrame:
    """``domain_a, domain_b, max_cos`` and the number of pairs above each threshold."""
    parts = blocked_cosines(vectors, 1.0, thresholds)
    names = [f"n{round(1000 * t)}" for t in thresholds]
    return parts.groupBy("domain_a", "domain_b").agg(F.round(F.max("max_cos"), 6).alias("max_cos"), *[F.sum(n).alias(n) for n in names])


def pair_summary(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """``n_pairs, n_items, agreement`` of near pairs; labels are ``item_id, label``, a pair without both is no agreement."""
    a = labels.select(F.col("item_id").alias("left_id"), F.col("label").alias("la"))
    b = labels.select(F.col("item_id").alias("right_id"), F.col("label").alias("lb"))
    rows = pairs.join(a, "left_id", "left").join(b, "right_id", "left")
    ends = pairs.select(F.explode(F.array("left_id", "right_id")).alias("item_id")).distinct().agg(F.count(F.lit(1)).alias("n_items"))
    out = rows.agg(F.count(F.lit(1)).alias("n_pairs"), F.round(F.avg(F.coalesce((F.col("la") == F.col("lb")).cast("double"), F.lit(0.0))), 6).alias("agreement"))
    return out.join(F.broadcast(ends)).select("n_pairs", "n_items", "agreement")


def near_summary(vectors: DataFrame, tau: float, block: int = BLOCK) -> DataFrame:
    """`pair_summary` of all pairs that `blocked_cosines` finds, by the vectors' own ``label``; a task emits its counts and its distinct items, no pair."""

    def run(batches):
        items, held, size, n, agreed = np.zeros(0, np.int64), [], 0, 0, 0
        for b in batches:
            ends = np.unique(np.concatenate([b.column(0).to_numpy(), b.column(1).to_numpy()]))
            held.append(ends)
            size += len(ends)
            n += b.num_rows
            agreed += int(b.column(2).to_numpy(zero_copy_only=False).sum())
            if size > max(262_144, len(items)):
                items, held, size = np.unique(np.concatenate([items, *held])), [], 0
        items = np.unique(np.concatenate([items, *held]))
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([None], pa.int64()), pa.array([n], pa.int64()), pa.array([agreed], pa.int64())], names=["item_id", "n", "agreed"])
        for at in range(0, len(items), 65_536):
            part = items[at : at + 65_536]
            zero = pa.array(np.zeros(len(part), np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(part), zero, zero], names=["item_id", "n", "agreed"])

    pairs = blocked_cosines(vectors, tau, block=block, labelled=True).select("left_id", "right_id", "agree")
    parts = pairs.mapInArrow(run, "item_id long, n long, agreed long").groupBy("item_id").agg(F.sum("n").alias("n"), F.sum("agreed").alias("agreed"))
    out = parts.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n_pairs"), F.count("item_id").alias("n_items"), F.sum("agreed").alias("agreed"))
    return out.select("n_pairs", "n_items", F.round(F.try_divide(F.col("agreed").cast("double"), F.col("n_pairs").cast("double")), 6).alias("agreement"))


def near_pairs_lsh(vectors: DataFrame, tau: float, bands: int = 24, bits: int = 12, seed: int = 5) -> DataFrame:
    """Pairs of different domains at ``tau`` or more that share a band of hyperplane signs, verified on the vectors.

    A pair at angle a is found with probability 1 - (1 - (1 - a/pi)^bits)^bands. Each bucket is compared where it lies, on
    vectors of one byte a component: only pairs that can reach ``tau`` by the bound of their rounding leave it, and a pair
    leaves only the first bucket that it shares, so that neither the pairs of a bucket nor copies of one are shuffled.
    """
    first = vectors.select(F.size("features").alias("d")).first()
    dims = first["d"] if first else 1
    planes = np.random.default_rng(seed).normal(size=(dims, bands * bits))
    kind, width = ("<u2", 2) if bits <= 16 else ("<u4", 4)

    def coded(batches):
        for b in batches:
            for at in range(0, b.num_rows, 1000):
                part = b.slice(at, 1000)
                x = np.stack(part.column(2).to_numpy(zero_copy_only=False)).astype(float)
                keys = ((x @ planes >= 0).reshape(len(x), bands, bits) * (1 << np.arange(bits))).sum(axis=2)
                x = _unit(x)
                scale = (np.maximum(np.abs(x).max(axis=1), 1e-30) / 127).astype("<f4")
                small = np.rint(x / scale[:, None]).clip(-127, 127).astype(np.int8)
                off = (np.linalg.norm(x - small * scale[:, None].astype(float), axis=1) + 1e-6).astype("<f4")
                codes = np.concatenate([c.view(np.uint8).reshape(len(x), -1) for c in (scale, off, small, keys.astype(kind))], axis=1)
                code = pa.array([c.tobytes() for c in codes], pa.binary())
                row = pa.array(np.repeat(np.arange(len(x)), bands))
                bucket = pa.array(((np.arange(bands) << bits) + keys).ravel())
                yield pa.RecordBatch.from_arrays([bucket, *(c.take(row) for c in (part.column(0), part.column(1), code))], names=["bucket", "item_id", "domain", "code"])

    def close(bucket: int, ids: np.ndarray, domain: np.ndarray, code: np.ndarray):
        """Pairs of one bucket, a tile after the other."""
        if len(ids) < 2 or (domain == domain[0]).all():
            return
        scale, off = np.ascontiguousarray(code[:, :8]).view("<f4").T
        x = code[:, 8 : 8 + dims].view(np.int8) * scale[:, None]
        keys = np.ascontiguousarray(code[:, 8 + dims :]).view(kind)
        for i in range(0, len(ids), TILE):
            for k in range(i, len(ids), BLOCK):
                a, b = slice(i, i + TILE), slice(k, k + BLOCK)
                reach = x[a] @ x[b].T + (off[a][:, None] + (1 + off[a])[:, None] * off[b][None, :])
                left, right = np.nonzero((reach >= tau - ROUGH) & (domain[a][:, None] != domain[b][None, :]))
                left, right = left + i, right + k
                for c in range(0, len(left), 65_536):
                    p, q = left[c : c + 65_536], right[c : c + 65_536]
                    p, q = p[p < q], q[p < q]
                    new = (keys[p] == keys[q]).argmax(axis=1) == bucket >> bits
                    m, n = ids[p[new]], ids[q[new]]
                    yield np.minimum(m, n)[m != n], np.maximum(m, n)[m != n]

    def run(batches):
        names: dict[str, int] = {}
        before: list[tuple] = []  # the bucket that may go on in the next batch
        out, size = [], 0

        def buckets():
            for b in batches:
                if b.num_rows:
                    bucket, ids = (b.column(c).to_numpy() for c in (0, 1))
                    domain = np.array([names.setdefault(d, len(names)) for d in b.column(2).to_pylist()])
                    code = np.frombuffer(b"".join(b.column(3).to_pylist()), np.uint8).reshape(len(ids), 8 + dims + width * bands)
                    ends = [0, *(np.flatnonzero(np.diff(bucket)) + 1).tolist(), len(ids)]
                    for i, j in zip(ends, ends[1:], strict=False):
                        if before and before[0][0] != bucket[i]:
                            yield before[0][0], *map(np.concatenate, list(zip(*before, strict=True))[1:])
                            before.clear()
                        before.append((int(bucket[i]), ids[i:j], domain[i:j], code[i:j]))
            if before:
                yield before[0][0], *map(np.concatenate, list(zip(*before, strict=True))[1:])

        for own in buckets():
            for pair in close(*own):
                out.append(pair)
                size += len(pair[0])
                if size >= 65_536:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out, strict=True)], names=["left_id", "right_id"])
                    out, size = [], 0
        if size:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out, strict=True)], names=["left_id", "right_id"])

    rows = vectors.select(F.col("item_id").cast("long"), "domain", "features")
    keyed = rows.mapInArrow(coded, "bucket long, item_id long, domain string, code binary").repartition("bucket").sortWithinPartitions("bucket")
    return _exact(materialize(keyed.mapInArrow(run, "left_id long, right_id long"), "lsh-pairs"), rows, tau)


def _exact(pairs: DataFrame, vectors: DataFrame, tau: float, share: int = 32_768) -> DataFrame:
    """``left_id, right_id, cos`` of pairs at ``tau`` or more; the vectors are dealt into shares, and a left vector goes to a share once for all its pairs there."""
    parts = max(1, math.ceil(vectors.count() / share))
    part = F.pmod(F.xxhash64("right_id"), F.lit(parts)).alias("part")
    asked = pairs.select("left_id", "right_id", part).repartition("left_id").groupBy("left_id", "part").agg(F.collect_list("right_id").alias("rights"))
    asked = asked.join(vectors.select(F.col("item_id").alias("left_id"), F.col("features").alias("x")), "left_id")
    own = vectors.select(F.col("item_id").alias("right_id"), F.col("features").alias("y")).select("right_id", "y", part)

    def run(asked: pa.Table, own: pa.Table) -> pa.Table:
        found = []
        if asked.num_rows and own.num_rows:
            ids = own["right_id"].to_numpy()
            order = np.argsort(ids)
            y = _unit(np.stack(own["y"].to_numpy()).astype(float))[order]
            for b in asked.to_batches(max_chunksize=2000):
                x = _unit(np.stack(b["x"].to_numpy(zero_copy_only=False)).astype(float))
                rights = b["rights"]
                row, right = np.repeat(np.arange(b.num_rows), np.diff(np.asarray(rights.offsets))), rights.flatten().to_numpy()
                left = b["left_id"].to_numpy()[row]
                for i in range(0, len(row), 65_536):
                    s = slice(i, i + 65_536)
                    cos = np.einsum("ij,ij->i", x[row[s]], y[np.searchsorted(ids, right[s], sorter=order)])
                    high = cos >= tau
                    found.append((left[s][high], right[s][high], cos[high]))
        cols = [np.concatenate(c) for c in zip(*found, strict=True)] if found else [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        return pa.table(dict(zip(("left_id", "right_id", "cos"), cols, strict=True)))

    return asked.groupBy("part").cogroup(own.groupBy("part")).applyInArrow(run, "left_id long, right_id long, cos double")


def mutual_best(pairs: DataFrame, score: str = "cos") -> DataFrame:
    """Pairs whose ends are each other's best partner; ties go to the smaller id."""
    both = pairs.select("left_id", "right_id", F.col("left_id").alias("me"), F.col("right_id").alias("other"), score).unionByName(
        pairs.select("left_id", "right_id", F.col("right_id").alias("me"), F.col("left_id").alias("other"), score)
    )
    best = both.withColumn("r", F.row_number().over(Window.partitionBy("me").orderBy(F.desc(score), "other"))).where("r = 1")
    return best.groupBy("left_id", "right_id").agg(F.count(F.lit(1)).alias("n"), F.max(score).alias(score)).where("n = 2").select("left_id", "right_id", score)


def best_cosines(vectors: DataFrame, tau: float, block: int = BLOCK, digits: int = 6) -> DataFrame:
    """`mutual_best` of all pairs that `blocked_cosines` finds, on cosines of ``digits`` places, without writing or shuffling the pairs.

    A task keeps for each item only the best partner of those that it has met, so that a task emits a row an item at most.
    """
    schema = "me long, other long, cos double"

    def run(batches):
        kept = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        held, size = [], 0

        def best(parts):
            me, other, cos = (np.concatenate(c) for c in zip(*parts, strict=True))
            order = np.lexsort((other, -cos, me))
            first = order[np.flatnonzero(np.diff(me[order], prepend=me[order[0]] - 1))] if len(order) else order
            return [me[first], other[first], cos[first]]

        for b in batches:
            for at in range(0, b.num_rows, 262_144):
                left, right, cos = (c.to_numpy() for c in b.slice(at, 262_144).columns)
                held += [best([(left, right, cos), (right, left, cos)])]
                size += len(held[-1][0])
                if size > max(262_144, len(kept[0])):
                    kept, held, size = best([kept, *held]), [], 0
        kept = best([kept, *held])
        for at in range(0, len(kept[0]), 65_536):
            yield pa.RecordBatch.from_arrays([pa.array(c[at : at + 65_536]) for c in kept], names=["me", "other", "cos"])

    pairs = blocked_cosines(vectors, tau, block=block).select("left_id", "right_id", F.round("cos", digits).alias("cos"))
    best = pairs.mapInArrow(run, schema).groupBy("me").agg(F.min(F.struct((-F.col("cos")).alias("c"), "other")).alias("b"))
    ends = best.select(F.least("me", "b.other").alias("left_id"), F.greatest("me", "b.other").alias("right_id"), (-F.col("b.c")).alias("cos"))
    return ends.groupBy("left_id", "right_id").agg(F.count(F.lit(1)).alias("n"), F.max("cos").alias("cos")).where("n = 2").select("left_id", "right_id", "cos")


def confirm(pairs: DataFrame, vectors: DataFrame, tau: float) -> DataFrame:
    """Pairs with ``cos2`` under a second encoder, and whether it reaches ``tau``."""
    a = vectors.select(F.col("item_id").alias("left_id"), F.col("features").alias("fa"))
    b = vectors.select(F.col("item_id").alias("right_id"), F.col("features").alias("fb"))
    out = pairs.join(a, "left_id").join(b, "right_id").withColumn("cos2", F.round(cosine(F.col("fa"), F.col("fb")), 6))
    return out.select(*pairs.columns, "cos2", (F.col("cos2") >= tau).alias("confirmed"))


def nearest_train(vectors: DataFrame, block: int = BLOCK) -> DataFrame:
    """``test_id, train_id, cos``: nearest train item of the same domain for every test item; ties to the smaller id."""
    n = vectors.count()
    parts = max(1, math.ceil(n / block))
    own = F.pmod(F.xxhash64("item_id"), F.lit(parts)).cast("int")
    live = vectors.where("split in ('train', 'test')").withColumn("own", own)
    spread = live.where("split = 'train'").withColumn("part", F.col("own")).unionByName(live.where("split = 'test'").withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))))

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        test, train = pdf[pdf["split"] == "test"], pdf[pdf["split"] == "train"].sort_values("item_id")
        if not len(test) or not len(train):
            return pd.DataFrame({"test_id": [], "train_id": [], "cos": []}).astype({"test_id": "int64", "train_id": "int64"})
        cos = np.round(_unit(np.stack(test["features"].to_numpy())) @ _unit(np.stack(train["features"].to_numpy())).T, 9)
        best = cos.argmax(axis=1)
        return pd.DataFrame({"test_id": test["item_id"].to_numpy(), "train_id": train["item_id"].to_numpy()[best], "cos": cos[np.arange(len(test)), best]})

    found = spread.groupBy("domain", "part").applyInPandas(run, "test_id long, train_id long, cos double")
    best = found.groupBy("test_id").agg(F.min(F.struct((-F.col("cos")).alias("c"), "train_id")).alias("b"))
    return best.select("test_id", F.col("b.train_id").alias("train_id"), F.round(-F.col("b.c"), 6).alias("cos"))


def simhash(docs: DataFrame) -> DataFrame:
    """``item_id, hi, lo``: 64 votes over the first 64 bits of the words' MD5s, by occurrences; as two 32-bit numbers.

    Each text is counted by itself, in Arrow batches. A text without words has zeros.
    """

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 500):
                part = b.slice(at, 500)
                row, code, names = _words(part.column(1))
                raw = np.frombuffer(b"".join(hashlib.md5(w.encode()).digest()[:8] for w in names), np.uint8).reshape(len(names), 8)
                votes = np.unpackbits(raw, axis=1).astype(np.int64) * 2 - 1  # the first bit is the highest of the first half
                total = np.zeros((part.num_rows, 64), np.int64)
                if len(row):
                    heads = np.flatnonzero(np.diff(row, prepend=-1))
                    total[row[heads]] = np.add.reduceat(votes[code], heads, axis=0)
                halves = np.packbits(total > 0, axis=1).view(">u4").astype(np.int64)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(halves[:, 0]), pa.array(halves[:, 1])], names=["item_id", "hi", "lo"])

    return docs.select(F.col("item_id").cast("long"), "text").mapInArrow(run, "item_id long, hi long, lo long")


def hamming(a: str = "a", b: str = "b") -> Column:
    return F.bit_count(F.col(f"hi_{a}").bitwiseXOR(F.col(f"hi_{b}"))) + F.bit_count(F.col(f"lo_{a}").bitwiseXOR(F.col(f"lo_{b}")))


def hamming_pairs(hashes: DataFrame) -> DataFrame:
    """``left_id, right_id, hamming`` of pairs that differ in one bit at most: one of two halves agrees."""
    side = lambda k: hashes.select(*[F.col(c).alias(f"{c}_{k}") for c in ("item_id", "hi", "lo")])
    found = [side("a").join(side("b"), F.col(f"{h}_a") == F.col(f"{h}_b")).where("item_id_a < item_id_b") for h in ("hi", "lo")]
    both = found[0].unionByName(found[1]).select(F.col("item_id_a").alias("left_id"), F.col("item_id_b").alias("right_id"), hamming().cast("int").alias("hamming"))
    return both.where("hamming <= 1").distinct()


def min_distance_hist(hashes: DataFrame, block: int = BLOCK) -> DataFrame:
    """``distance, n``: how far each item's nearest other item is, by which the threshold is calibrated. Exact, in blocks."""
    rows = _blocks(hashes, hashes.count(), block)

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        code = (pdf["hi"].to_numpy().astype(np.uint64) << np.uint64(32)) | pdf["lo"].to_numpy().astype(np.uint64)
        a, b = (pdf["own"] == key[0]).to_numpy(), (pdf["own"] == key[1]).to_numpy()
        ids = pdf["item_id"].to_numpy()
        d = np.bitwise_count(code[a][:, None] ^ code[b][None, :]).astype(int)
        d[ids[a][:, None] == ids[b][None, :]] = 65
        out = [(i, x) for i, x in zip(ids[a], d.min(axis=1, initial=65), strict=True)] + [(i, x) for i, x in zip(ids[b], d.min(axis=0, initial=65), strict=True)]
        return pd.DataFrame(out, columns=["item_id", "distance"])

    near = rows.groupBy("part_a", "part_b").applyInPandas(run, "item_id long, distance int").groupBy("item_id").agg(F.min("distance").alias("distance"))
    return near.where("distance <= 64").groupBy("distance").agg(F.count(F.lit(1)).alias("n"))


def shift_match(pairs: DataFrame, series: DataFrame, max_lag: int, threshold: float = 0.8) -> DataFrame:
    """``left_id, right_id, best_lag, xcorr, match``: best correlation over lags of candidate pairs only.

    Pearson over the overlap, which is at least half the length; constant overlaps do not count; ties go to the
    smallest lag in size, then to the negative one.
    """
    a = series.select(F.col("item_id").alias("left_id"), F.col("series").alias("sa"))
    b = series.select(F.col("item_id").alias("right_id"), F.col("series").alias("sb"))
    rows = pairs.select("left_id", "right_id").join(a, "left_id").join(b, "right_id")
    rows = rows.select("left_id", "right_id", "sa", "sb", F.explode(F.sequence(F.lit(-max_lag), F.lit(max_lag))).alias("lag"))
    n = F.least(F.size("sa"), F.size("sb")) - F.abs("lag")
    rows = rows.where(n * 2 >= F.size("sa"))
    left, right = F.slice("sa", F.greatest(F.lit(0), F.col("lag")) + 1, n), F.slice("sb", F.greatest(F.lit(0), -F.col("lag")) + 1, n)
    points = rows.select("left_id", "right_id", "lag", F.explode(F.arrays_zip(left.alias("x"), right.alias("y"))).alias("p"))
    x, y = F.col("p.x"), F.col("p.y")
    r = points.groupBy("left_id", "right_id", "lag").agg(F.round(F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y)), 6).alias("r")).where("r is not null")
    best = r.groupBy("left_id", "right_id").agg(F.min(F.struct((-F.col("r")).alias("m"), F.abs("lag").alias("size"), "lag")).alias("b"))
    return best.select("left_id", "right_id", F.col("b.lag").alias("best_lag"), (-F.col("b.m")).alias("xcorr"), (-F.col("b.m") >= threshold).alias("match"))


def contamination(docs: DataFrame, passages: DataFrame, n: int = 8) -> DataFrame:
    """``item_id, passage_id, shared``: distinct n-grams of words that a document shares with a held-out passage.

    Both sides are reduced to 64-bit hashes before the join; whether to broadcast the passages is left to their size.
    """

    def hashes(df: DataFrame, key: str) -> DataFrame:
        words = F.filter(F.split(F.lower(F.coalesce("text", F.lit(""))), "[^\\p{L}0-9]+"), lambda w: w != "")
        rows = df.select(key, words.alias("ws")).where(F.size("ws") >= n)
        return rows.select(key, F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("ws") - n + 1), lambda i: F.xxhash64(F.array_join(F.slice("ws", i, F.lit(n)), " "))))).alias("h"))

    met = hashes(docs, "item_id").join(hashes(passages, "passage_id"), "h")
    return met.groupBy("item_id", "passage_id").agg(F.count(F.lit(1)).alias("shared"))
