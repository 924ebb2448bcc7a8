"""Near-duplicate vectors by iterative quantisation, multi-index Hamming tables and exact reranking.

Several rotations, each learnt so that the signs of the rotated vectors lose least (and with centred vectors are
balanced), give 64 bits each. Every 16 bits key one table; vectors that share a bucket in any table and whose first
64 bits are near enough become candidates, whose cosine is then computed from the original vectors in double
precision. Equal vectors are one node with a multiplicity, so copies are never paired with each other.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crossaudit.functions.storage import materialize
from crossaudit.llm.runs import whole_runs
from crossaudit.operators.components import connected_components

#: Expected vectors that the rotations are learnt on: the documented bound of the sample. Every vector is indexed.
SAMPLE = 20_000
ROTATIONS = 6
KEY_BITS = 16
#: Most bits of the first code in which candidates differ. At cosine 0.9, 9.2 of 64 are expected, with a deviation of 2.8.
NEAR_BITS = 22
COSINE = 0.9
#: Most vectors of a bucket that one task compares with each other.
BUCKET = 2048


def learn_rotations(sample: np.ndarray, rotations: int = ROTATIONS, steps: int = 30, seed: int = 11) -> tuple[np.ndarray, np.ndarray]:
    """Mean of the unit vectors, and ``rotations`` orthogonal (d, d) matrices.

    From a random start, signs and rotation take turns: the signs of the rotated data, then the rotation that brings
    the data closest to them (orthogonal Procrustes).
    """
    d = sample.shape[1]
    unit = sample / np.linalg.norm(sample, axis=1, keepdims=True) if len(sample) else sample
    mean = unit.mean(axis=0) if len(sample) else np.zeros(d)
    centred, rng, out = unit - mean, np.random.default_rng(seed), []
    for _ in range(rotations):
        r = np.linalg.qr(rng.normal(size=(d, d)))[0]
        for _ in range(steps if len(sample) > d else 0):
            u, _, v = np.linalg.svd(centred.T @ np.where(centred @ r >= 0, 1.0, -1.0))
            r = u @ v
        out.append(r)
    return mean, np.stack(out)


def codes(vectors: np.ndarray, mean: np.ndarray, rotations: np.ndarray) -> np.ndarray:
    """(n, bytes) codes: the signs under each rotation, packed."""
    unit = vectors / np.linalg.norm(vectors, axis=1, keepdims=True)
    bits = np.concatenate([(unit - mean) @ r >= 0 for r in rotations], axis=1)
    return np.packbits(bits, axis=1)


def usable(v: Column) -> Column:
    """Whether a vector has a direction: not null or empty, no null or non-finite component, not all zero."""
    return (
        F.coalesce(F.size(v) > 0, F.lit(False))
        & ~F.coalesce(F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))), F.lit(True))
        & F.coalesce(F.exists(v, lambda x: x != 0), F.lit(False))
    )


def _dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def _pairs(batches):
    """Candidate pairs of every run of equal keys."""
    for rows, starts, lengths in whole_runs(batches, ["key", "part_a", "part_b"]):
        code = rows.column("code").to_numpy().view(np.uint64)
        node = rows.column("node").to_numpy()
        later = rows.column("later").to_numpy(zero_copy_only=False)
        cross = (rows.column("part_a").to_numpy() != rows.column("part_b").to_numpy())[starts]
        left, right = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        small = (lengths > 1) & (lengths <= 32) & ~cross
        own = lengths[small]
        end = np.repeat(starts[small] + own, own)
        at = np.repeat(starts[small], own) + np.arange(own.sum()) - np.repeat(np.cumsum(own) - own, own)
        for s in range(1, int(own.max(initial=1))):
            i = at[at + s < end]
            i = i[np.bitwise_count(code[i] ^ code[i + s]) <= NEAR_BITS]
            left.append(i)
            right.append(i + s)
        for a, n, two in zip(*(x[(lengths > 1) & ~small].tolist() for x in (starts, lengths, cross)), strict=True):
            rows_a = a + np.flatnonzero(~later[a : a + n]) if two else np.arange(a, a + n)
            rows_b = a + np.flatnonzero(later[a : a + n]) if two else rows_a
            for c in range(0, len(rows_a), 256):
                part = rows_a[c : c + 256]
                near = np.bitwise_count(code[part][:, None] ^ code[rows_b][None, :]) <= NEAR_BITS
                i, j = np.nonzero(near if two else near & (part[:, None] < rows_b[None, :]))
                left.append(part[i])
                right.append(rows_b[j])
        x, y = node[np.concatenate(left)], node[np.concatenate(right)]
        yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y))], names=["a", "b"])


def candidates(nodes: DataFrame, sample: int = SAMPLE, rotations: int = ROTATIONS, bucket: int = BUCKET) -> DataFrame:
    """Distinct pairs ``a, b`` of nodes (``node, v``; all ``v`` usable) that meet in a table."""
    n = nodes.count()
    drawn = nodes if n <= sample else nodes.where(F.pmod(F.xxhash64("node"), F.lit(1 << 20)) / float(1 << 20) < sample / n)
    drawn = [np.array(r["v"], float) for r in drawn.select("v").collect()]
    sizes = [len(v) for v in drawn]
    d = max(set(sizes), key=sizes.count) if sizes else 1
    mean, turns = learn_rotations(np.array([v for v in drawn if len(v) == d]).reshape(-1, d), rotations)
    shared = nodes.sparkSession.sparkContext.broadcast((mean, turns))
    tables = max(1, rotations * d // KEY_BITS)

    def run(batches):
        m, r = shared.value
        for b in batches:
            vs = np.zeros((b.num_rows, len(m)))
            for i, v in enumerate(b.column(1).to_pylist()):
                vs[i, : len(v)] = v[: len(m)]
            norm = np.linalg.norm(vs, axis=1)
            vs[norm == 0, 0] = 1.0
            packed = codes(vs, m, r)
            if packed.shape[1] < 8:
                packed = np.pad(packed, ((0, 0), (0, 8 - packed.shape[1])))
            first = np.ascontiguousarray(packed[:, :8]).view(np.int64)[:, 0]
            width = KEY_BITS // 8
            keys = np.zeros((len(vs), tables), np.int64)
            for t in range(tables):
                keys[:, t] = t << KEY_BITS
                for k in range(width):
                    keys[:, t] |= packed[:, (t * width + k) % packed.shape[1]].astype(np.int64) << (8 * k)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(first), pa.FixedSizeListArray.from_arrays(pa.array(keys.ravel()), tables).cast(pa.list_(pa.int64()))], names=["node", "code", "keys"]
            )

    rows = materialize(nodes.select("node", "v").mapInArrow(run, "node long, code long, keys array<long>"), "itq-codes").select("node", "code", F.explode("keys").alias("key"))
    counted = rows.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    counted = counted.select("key", F.when(F.col("n") > bucket, F.ceil(F.col("n") / F.lit(bucket // 2))).otherwise(1).cast("int").alias("parts"))
    spread = rows.join(counted, "key").withColumn("own", F.pmod(F.hash("node"), F.col("parts")))
    pair = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda p: F.struct(F.least(p, F.col("own")).alias("a"), F.greatest(p, F.col("own")).alias("b")))
    spread = spread.select("key", "node", "code", "own", F.explode(pair).alias("p"))
    spread = spread.select("key", F.col("p.a").alias("part_a"), F.col("p.b").alias("part_b"), "node", "code", (F.col("own") != F.col("p.a")).alias("later"))
    where = ["key", "part_a", "part_b"]
    return spread.repartition(*where).sortWithinPartitions(*where).mapInArrow(_pairs, "a long, b long").distinct()


def vector_links(vectors: DataFrame, cosine: float = COSINE, **options) -> DataFrame:
    """``vec_id, n_links, component_id, kept`` of every row of ``vec_id, embedding``.

    Vectors without a direction, and vectors of different lengths, link with nothing. Repeated rows and equal vectors
    under other ids link with each other. Null ids count as partners but name no component unless nothing else does.
    """
    v = F.col("embedding")
    rows = materialize(vectors.select("vec_id", usable(v).alias("ok"), F.xxhash64(v, F.lit(1)).alias("h1"), F.xxhash64(F.lit(2), v).alias("h2"), v.alias("v")), "vec-rows")
    nodes = rows.where("ok and vec_id is not null").groupBy("h1", "h2").agg(F.min("vec_id").alias("node"), F.count(F.lit(1)).alias("copies"), F.any_value("v").alias("v"))
    nodes = materialize(nodes, "vec-nodes")
    pairs = candidates(nodes, **options)
    a = nodes.select(F.col("node").alias("a"), F.col("copies").alias("copies_a"), F.col("v").alias("va"))
    b = nodes.select(F.col("node").alias("b"), F.col("copies").alias("copies_b"), F.col("v").alias("vb"))
    near = F.when(F.size("va") == F.size("vb"), _dot(F.col("va"), F.col("vb")) / F.sqrt(_dot(F.col("va"), F.col("va"))) / F.sqrt(_dot(F.col("vb"), F.col("vb"))))
    links = materialize(pairs.join(a, "a").join(b, "b").where(near >= cosine).select("a", "b", "copies_a", "copies_b"), "vec-links")
    ends = links.select(F.col("a").alias("node"), F.col("copies_b").alias("n")).unionAll(links.select(F.col("b").alias("node"), F.col("copies_a").alias("n")))
    linked = ends.groupBy("node").agg(F.sum("n").alias("others"))
    groups = connected_components(links.select(F.col("a").alias("src"), F.col("b").alias("dst")))
    known = nodes.select("h1", "h2", "node", "copies").join(linked, "node", "left").join(groups, "node", "left")
    known = known.select("h1", "h2", (F.col("copies") - 1 + F.coalesce("others", F.lit(0))).alias("n"), F.coalesce("component", "node").alias("c"))
    ready = rows.select("vec_id", F.when(F.col("ok") & F.col("vec_id").isNotNull(), F.col("h1")).alias("h1"), "h2").join(known, ["h1", "h2"], "left")
    return ready.select(
        "vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), F.coalesce("c", "vec_id").alias("component_id"),
        F.coalesce(F.col("vec_id") == F.coalesce("c", "vec_id"), F.lit(True)).alias("kept"),
    )


def query(spark, sf_dir):
    """op6: links and groups of all vectors."""
    return vector_links(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))
