"""Near-duplicate documents by fingerprints of word shingles, compared bit-sliced.

Fingerprints are stored vertically: a block is one 64-bit word for each bit position, with a fingerprint in each of its lanes. The
distances of a whole block to a probe are counted at once with carry-save counters of one word a binary digit, started so
that a carry out of the last one means "past the radius"; a block whose lanes are all past it is abandoned.

`near_duplicates` links 64-bit fingerprints that differ in three bits or less. They agree in at least two of five blocks
of bits, so distinct fingerprints meet in ten tables, each keyed by two blocks (about 26 bits), and no link is lost.

`near_copies` joins documents whose sets of shingles have a Jaccard similarity of 0.8 or more. Fingerprints only
propose: tables keyed by random bits (as many as make a miss at just that similarity rarer than ``MISS``) bring sets together, the distance on 128
bits must be within four deviations of what the similarity makes expect, and what is left is verified on the sets themselves. Sets of
few shingles, whose fingerprints are coarse, meet under the rarest of their hashes besides, which misses none.

Buckets above a bound are cut into blocks that meet pairwise in tasks of their own, so that no task holds an unbounded
bucket and no link is lost.
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crossaudit.functions.storage import discard, materialize
from crossaudit.llm.places import only_needed
from crossaudit.llm.runs import whole_runs
from crossaudit.llm.words import free_names
from crossaudit.operators.components import connected_components

SEED = 42
SHINGLE = 3
RADIUS = 3
#: First bits and widths of the blocks of a fingerprint.
BLOCKS = ((0, 13), (13, 13), (26, 13), (39, 13), (52, 12))
#: Most fingerprints of a bucket that one task compares with each other.
BUCKET = 4096
#: Shingles of `near_copies`, and its similarity as a fraction of integers, so that the threshold is exact.
NEAR_SHINGLE, NEAR = 5, (4, 5)
#: Share of links at exactly the wanted similarity that the tables may miss; nearer ones are missed far less.
MISS = 0.005
#: Sets of so many shingles or fewer meet under the first of their hashes, too.
FEW = 30
#: 64-bit words of a set's bits that tables draw from, and of those that distances are counted on.
WIDTH, COMPARED = 4, 2
#: Tables in which sets only meet the first of their bucket, to join large groups before pairs are formed.
HUBS = 8
_ALL = np.uint64(0xFFFFFFFFFFFFFFFF)
_LAST = (1 << 63) - 1


def shingle_hashes(text: str | None, words: int = SHINGLE, seed: int = SEED) -> np.ndarray:
    """64-bit hashes of all shingles in order, with repeats; a text of fewer words is one shingle, none without words."""
    import xxhash

    parts = (text or "").encode().lower().split()
    if not parts:
        return np.zeros(0, np.uint64)
    joined = b" ".join(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    k = min(words, len(parts))
    h = xxhash.xxh64_intdigest
    return np.array([h(joined[a:b], seed) for a, b in zip(starts[: len(parts) - k + 1].tolist(), ends[k - 1 :].tolist(), strict=True)], np.uint64)


def _votes(hashes: np.ndarray) -> np.ndarray:
    """Number of hashes that have each bit."""
    total = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 65536):
        part = hashes[i : i + 65536]
        total += np.unpackbits(part.view(np.uint8).reshape(len(part), 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return total


def fingerprint(text: str | None, words: int = SHINGLE, seed: int = SEED) -> int:
    """Bit k is 1 if it is set in over half of the shingles' hashes; 0 for no words."""
    hashes = shingle_hashes(text, words, seed)
    return int.from_bytes(np.packbits(_votes(hashes) * 2 > len(hashes), bitorder="little").tobytes(), "little")


def fingerprints(documents: DataFrame, words: int = SHINGLE, seed: int = SEED) -> DataFrame:
    """``doc_id, fp`` (signed long) of whole texts."""

    def run(batches):
        for b in batches:
            fps = np.array([fingerprint(t, words, seed) for t in b.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps)], names=["doc_id", "fp"])

    return documents.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, fp long")


def planes(fps: np.ndarray) -> np.ndarray:
    """(64 w, blocks) array of (n, w) fingerprints: row k holds bit k of all, 64 to a block; missing ones at the end are 0."""
    fps = fps if fps.ndim == 2 else fps[:, None]
    n, w = -(-len(fps) // 64) * 64, fps.shape[1]
    full = np.zeros((n, w), np.uint64)
    full[: len(fps)] = fps
    bits = np.unpackbits(full.view(np.uint8).reshape(n, 8 * w), axis=1, bitorder="little")
    return np.ascontiguousarray(np.packbits(bits.T, axis=1, bitorder="little")).view(np.uint64)


def count_lanes(sliced: np.ndarray, probes: np.ndarray, block: np.ndarray, over: np.ndarray, radius: int) -> np.ndarray:
    """Masks of the lanes of ``block[i]`` at a distance of ``radius`` or less from ``probes[i]``; lanes set in ``over`` are none."""
    digits = radius.bit_length()
    first = (1 << digits) - 1 - radius
    counters = [np.full(len(block), _ALL if first >> j & 1 else 0, np.uint64) for j in range(digits)]
    out, open_ = np.zeros(len(block), np.uint64), np.arange(len(block))
    probes, over = probes.reshape(len(block), len(sliced) // 64), over.copy()
    for k in range(len(sliced)):
        bit = (probes[:, k // 64] >> np.uint64(k % 64)) & np.uint64(1)
        carry = sliced[k][block] ^ (np.uint64(0) - bit)
        for j in range(digits):
            counters[j], carry = counters[j] ^ carry, counters[j] & carry
        over |= carry
        if k % 8 == 7:
            live = over != _ALL
            if np.count_nonzero(live) * 4 < 3 * len(live):
                open_, block, probes, over = open_[live], block[live], probes[live], over[live]
                counters = [c[live] for c in counters]
                if not len(open_):
                    return out
    out[open_] = ~over
    return out


def within(fps: np.ndarray, probes: np.ndarray, radius: int = RADIUS) -> np.ndarray:
    """(probes, blocks) masks of the stored fingerprints at a distance of ``radius`` or less."""
    sliced = planes(fps)
    return _within(sliced, probes, len(fps), radius)


def _past(n: np.ndarray | int) -> np.ndarray:
    """Masks whose first ``n`` lanes (0 to 64) are clear and whose others are set."""
    n = np.asarray(n)
    return np.where(n >= 64, np.uint64(0), _ALL << np.minimum(n, 63).astype(np.uint64))


def _within(sliced: np.ndarray, probes: np.ndarray, n: int, radius: int) -> np.ndarray:
    blocks = sliced.shape[1]
    pad = _past(np.minimum(64, n - 64 * np.arange(blocks)))
    masks = count_lanes(sliced, np.repeat(probes, blocks, axis=0), np.tile(np.arange(blocks), len(probes)), np.tile(pad, len(probes)), radius)
    return masks.reshape(len(probes), blocks)


def _members(mask: np.ndarray, n: int) -> np.ndarray:
    return np.unpackbits(mask.view(np.uint8), bitorder="little")[:n].astype(bool)


def forest(fps: np.ndarray, other: np.ndarray | None = None, radius: int = RADIUS) -> list[tuple[int, int]]:
    """Edges (as places) that join whatever the links within ``fps`` join; between ``fps`` and ``other`` if given.

    A breadth-first search whose frontier is compared with all stored fingerprints at once.
    """
    stored = fps if other is None else np.concatenate([fps, other])
    n, sliced = len(stored), planes(stored)
    side = np.zeros(n, bool)
    side[len(fps) :] = other is not None
    new, edges = np.ones(n, bool), []
    for start in range(n):
        if not new[start]:
            continue
        new[start] = False
        frontier = [start]
        while frontier:
            part, frontier = frontier[:256], frontier[256:]
            for i, mask in zip(part, _within(sliced, stored[part], n, radius), strict=True):
                near = _members(mask, n) & new
                if other is not None:
                    near &= side != side[i]
                for j in np.flatnonzero(near).tolist():
                    new[j] = False
                    edges.append((i, j))
                    frontier.append(j)
    return edges


def linked_pairs(fps: np.ndarray, starts: np.ndarray, lengths: np.ndarray, first: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Linked places in many buckets at once: each row against the rows of its bucket from ``first`` (a place in it) on.

    ``starts`` and ``lengths`` are the buckets' rows in ``fps``, one bucket behind the other; ``first`` has one entry a row of them.
    """
    each = -(-lengths // 64)
    block0 = np.cumsum(each) - each
    own = np.repeat(np.arange(len(starts)), lengths)
    at = np.arange(len(own)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    rows = starts[own] + at
    full = np.zeros((int(each.sum()) * 64, *fps.shape[1:]), np.uint64)
    full[block0[own] * 64 + at] = fps[rows]
    sliced = planes(full)
    pad = _past(np.minimum(64, np.repeat(lengths, each) - 64 * (np.arange(int(each.sum())) - np.repeat(block0, each))))
    row_of = np.repeat(starts, each) + 64 * (np.arange(int(each.sum())) - np.repeat(block0, each))
    n_cells = np.maximum(0, each[own] - first // 64)
    left, right = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    ends = np.cumsum(n_cells)
    cut = [0]
    while cut[-1] < len(own):
        done = ends[cut[-1] - 1] if cut[-1] else 0
        cut.append(max(cut[-1] + 1, int(np.searchsorted(ends, done + (1 << 18), side="right"))))
    for a, b in zip(cut, cut[1:], strict=False):
        n = n_cells[a:b]
        probe = np.repeat(np.arange(a, b), n)
        step = np.arange(len(probe)) - np.repeat(np.cumsum(n) - n, n)
        block = block0[own[probe]] + first[probe] // 64 + step
        over = pad[block] | np.where(step == 0, ~_past(first[probe] % 64), np.uint64(0))
        masks = count_lanes(sliced, fps[rows[probe]], block, over, radius)
        hit = np.flatnonzero(masks)
        cell, lane = np.nonzero(np.unpackbits(masks[hit].view(np.uint8).reshape(len(hit), 8), axis=1, bitorder="little"))
        left.append(rows[probe[hit[cell]]])
        right.append(row_of[block[hit[cell]]] + lane)
    return np.concatenate(left), np.concatenate(right)


def _table_keys(fp: Column) -> Column:
    """The ten (table, key) pairs of a fingerprint."""
    out = []
    for t, pair in enumerate(combinations(BLOCKS, 2)):
        mask = sum(((1 << w) - 1) << at for at, w in pair)
        out.append(F.struct(F.lit(t).alias("t"), fp.bitwiseAND(F.lit(mask - (1 << 64) if mask >> 63 else mask)).alias("key")))
    return F.array(*out)


def _compare_runs(batches):
    """Rows sorted by ``t, key, part_a, part_b``: edges of every run of equal keys."""
    small = 64
    for rows, starts, lengths in whole_runs(batches, ["t", "key", "part_a", "part_b"]):
        signed = rows.column("fp").to_numpy()
        fps = signed.view(np.uint64)
        later = rows.column("later").to_numpy(zero_copy_only=False)
        cross = (rows.column("part_a").to_numpy() != rows.column("part_b").to_numpy())[starts]
        little = (lengths > 1) & (lengths <= small) & ~cross
        n = lengths[little]
        i, j = linked_pairs(fps, starts[little], n, np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + 1, RADIUS)
        src, dst = [signed[i]], [signed[j]]
        large = (lengths > 1) & ~little
        for a, n, two in zip(starts[large].tolist(), lengths[large].tolist(), cross[large].tolist(), strict=True):
            order = a + np.argsort(later[a : a + n], kind="stable")
            first = int(n - later[a : a + n].sum())
            pairs = forest(fps[order][:first], fps[order][first:]) if two else forest(fps[order])
            if pairs:
                p = order[np.array(pairs)]
                src.append(signed[p[:, 0]])
                dst.append(signed[p[:, 1]])
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(src)), pa.array(np.concatenate(dst))], names=["src", "dst"])


def _dealt(rows: DataFrame, crowded: DataFrame, key: list[str], row: str, keep: list[str]) -> DataFrame:
    """Rows by bucket; those of a ``crowded`` one (``key, parts``) in all pairs of parts that theirs belongs to, ``later`` if it is the second."""
    spread = rows.join(crowded, key, "left").withColumn("own", F.pmod(F.hash(row), F.coalesce("parts", F.lit(1))))
    pair = F.transform(
        F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1),
        lambda p: F.struct(F.least(p, F.col("own")).alias("a"), F.greatest(p, F.col("own")).alias("b")),
    )
    spread = spread.select(*key, *keep, "own", F.explode(pair).alias("p"))
    return spread.select(*key, F.col("p.a").alias("part_a"), F.col("p.b").alias("part_b"), *keep, (F.col("own") != F.col("p.a")).alias("later"))


def links(nodes: DataFrame, bucket: int = BUCKET) -> DataFrame:
    """Edges ``src, dst`` between distinct fingerprints (``fp``) that span what links of 3 bits or less join."""
    rows = nodes.select("fp", F.explode(_table_keys(F.col("fp"))).alias("k")).select("fp", "k.t", "k.key")
    crowded = rows.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > bucket)
    crowded = materialize(crowded.select("t", "key", F.ceil(F.col("n") / F.lit(bucket // 2)).cast("int").alias("parts")), "simhash-crowded")
    where = ["t", "key", "part_a", "part_b"]
    return _dealt(rows, crowded, ["t", "key"], "fp", ["fp"]).repartition(*where).sortWithinPartitions(*where, "fp").mapInArrow(_compare_runs, "src long, dst long").distinct()


def _one_document(rows: DataFrame, node: str) -> DataFrame:
    """Edges ``src, dst`` between the nodes of rows that share a ``doc_id``."""
    rows = rows.where("doc_id is not null").select("doc_id", node)
    several = rows.groupBy("doc_id").agg(F.min(node).alias("src"), F.max(node).alias("m")).where("src <> m")
    return rows.join(several, "doc_id").select("src", F.col(node).alias("dst"))


def _named(rows: DataFrame, nodes: DataFrame, found: DataFrame, node: str) -> DataFrame:
    """``node, component_id``: the smallest id among the rows of a component; ids that are null name none."""
    named = nodes.join(found.withColumnRenamed("node", node), node, "left").select(node, "doc_id", F.coalesce("component", node).alias("component"))
    names = named.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    return named.select(node, "component").join(names, "component").select(node, "component_id")


def near_duplicates(documents: DataFrame, words: int = SHINGLE, seed: int = SEED) -> DataFrame:
    """``doc_id, fingerprint, component_id`` of every row.

    Null and wordless texts have fingerprint 0 and are linked like any other. Rows with the same ``doc_id`` are one
    document for components. Ids that are null take part through their fingerprint but never name a component. An
    empty table gives an empty result; ties cannot arise, and long texts are fingerprinted whole.
    """
    docs = materialize(fingerprints(documents.select("doc_id", "text"), words, seed), "simhash-fp")
    nodes = materialize(docs.groupBy("fp").agg(F.min("doc_id").alias("doc_id")), "simhash-nodes")
    found = connected_components(links(nodes.select("fp")).unionAll(_one_document(docs, "fp")))
    out = docs.join(_named(docs, nodes, found, "fp"), "fp")
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def agreement(near: tuple[int, int]) -> float:
    """Share of bits that two sets of that similarity are expected to agree in."""
    j = near[0] / near[1]
    return 1 - math.acos(2 * j / (1 + j)) / math.pi


def near_radius(near: tuple[int, int]) -> int:
    """Bits in which sets of that similarity may differ: the mean and four deviations."""
    n, p = 64 * COMPARED, 1 - agreement(near)
    return min(n - 1, round(n * p + 4 * math.sqrt(n * p * (1 - p))))


def table_bits(rows: int, near: tuple[int, int], miss: float = MISS) -> np.ndarray:
    """(tables, bits) places of the bits that key each table: about 32 unlike sets to a bucket, and few enough misses."""
    bits = min(40, max(8, math.ceil(math.log2(max(2, rows) / 32))))
    tables = max(HUBS, math.ceil(math.log(miss) / math.log1p(-agreement(near) ** bits)))
    rng = np.random.default_rng(SEED)
    return np.stack([rng.choice(64 * WIDTH, bits, replace=False) for _ in range(tables)])


def _set(text: str | None, words: int) -> tuple[int, np.ndarray]:
    """Hash of the set of shingles, and the set in order."""
    import xxhash

    hashes = np.unique(shingle_hashes(text, words))
    return xxhash.xxh64_intdigest(hashes.tobytes(), SEED), hashes


def _wide_votes(hashes: np.ndarray) -> np.ndarray:
    """Votes on 64 bits of the hashes and of as many remixes as make ``WIDTH`` words."""
    out = [_votes(hashes)]
    for i in range(1, WIDTH):
        x = hashes + np.uint64((0x9E3779B97F4A7C15 * i) & ((1 << 64) - 1))
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        out.append(_votes(x ^ (x >> np.uint64(31))))
    return np.concatenate(out)


def _longs(values) -> pa.Array:
    return pa.array(np.asarray(values, np.uint64).view(np.int64))


def _lists(parts: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0, *map(len, parts)])
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), _longs(np.concatenate([np.zeros(0, np.uint64), *parts])))


def _described(documents: DataFrame, words: int, near: tuple[int, int], tables: np.ndarray) -> DataFrame:
    """``doc_id, sig, n, fp_a, fp_b, keys`` of every row: the first keys are those of the tables."""
    up, down = near
    weights = np.uint64(1) << np.arange(tables.shape[1], dtype=np.uint64)
    table = np.arange(len(tables), dtype=np.uint64) << np.uint64(48)

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                b = batch.slice(at, 500)
                sets = [_set(t, words) for t in b.column(1).to_pylist()]
                size = np.array([len(h) for _, h in sets])
                bits = np.array([_wide_votes(h) for _, h in sets]) * 2 > size[:, None]
                fps = np.packbits(bits, axis=1, bitorder="little").view(np.uint64)
                keys = (bits[:, tables] * weights).sum(axis=2, dtype=np.uint64) | table
                few = [h[: len(h) - -(-len(h) * up // down) + 1] | np.uint64(1 << 63) if len(h) <= FEW else h[:0] for _, h in sets]
                columns = [b.column(0), _longs([s for s, _ in sets]), pa.array(size, pa.int32()), _longs(fps[:, 0]), _longs(fps[:, 1]), _lists([np.concatenate(x) for x in zip(keys, few, strict=True)])]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "sig", "n", "fp_a", "fp_b", "keys"])

    return documents.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, sig long, n int, fp_a long, fp_b long, keys array<long>")


def _whole(documents: DataFrame, words: int) -> DataFrame:
    """``sig, hashes`` of every row."""

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                sets = [_set(t, words) for t in batch.slice(at, 500).column(0).to_pylist()]
                yield pa.RecordBatch.from_arrays([_longs([s for s, _ in sets]), _lists([h for _, h in sets])], names=["sig", "hashes"])

    return documents.select("text").mapInArrow(run, "sig long, hashes array<long>")


def _verified(pairs: DataFrame, sets: DataFrame, documents: DataFrame, words: int, near: tuple[int, int]) -> DataFrame:
    """``src, dst``: the pairs ``sig_a, sig_b`` whose sets are similar enough; only texts that a pair names are read again."""
    up, down = near
    pairs = materialize(pairs.select(F.least("sig_a", "sig_b").alias("sig_a"), F.greatest("sig_a", "sig_b").alias("sig_b")).distinct(), "near-pairs")
    if pairs.isEmpty():
        return pairs.select(F.col("sig_a").alias("src"), F.col("sig_b").alias("dst"))
    ends = materialize(pairs.select(F.explode(F.array("sig_a", "sig_b")).alias("sig")).distinct(), "near-ends")
    place = lambda c: F.coalesce(c.cast("long"), F.lit(_LAST))
    again = only_needed(sets.join(ends, "sig").select(place(F.col("doc_id")).alias("doc")), documents, place(documents["doc_id"]))
    again = _whole(again, words).join(ends, "sig", "left_semi")
    again = materialize(again.groupBy("sig").agg(F.first("hashes").alias("hashes")), "near-whole")
    side = lambda k: again.select(*[F.col(c).alias(f"{c}_{k}") for c in ("sig", "hashes")])
    both = F.size("hashes_a") + F.size("hashes_b")
    shared = F.size(F.array_intersect("hashes_a", "hashes_b"))
    out = pairs.join(side("a"), "sig_a").join(side("b"), "sig_b").where(shared * (up + down) >= both * up)
    out = materialize(out.select(F.col("sig_a").alias("src"), F.col("sig_b").alias("dst")), "near-links")
    discard(pairs, ends, again)
    return out


def _near_runs(near: tuple[int, int]):
    """Rows sorted by ``key, part_a, part_b, component``: pairs of different components under a key that pass the filters."""
    up, down, radius = *near, near_radius(near)

    def run(batches):
        for rows, starts, lengths in whole_runs(batches, ["key", "part_a", "part_b"]):
            sig, component, n = (rows.column(c).to_numpy() for c in ("sig", "component", "n"))
            fps = np.stack([rows.column(c).to_numpy().view(np.uint64) for c in ("fp_a", "fp_b")], axis=1)
            later = rows.column("later").to_numpy(zero_copy_only=False)
            cross = rows.column("part_a").to_numpy() != rows.column("part_b").to_numpy()
            # where the component of each row ends inside its bucket
            begin = np.zeros(len(sig), bool)
            begin[starts] = True
            begin[1:] |= component[1:] != component[:-1]
            heads = np.flatnonzero(begin)
            ends = np.repeat(np.append(heads[1:], len(sig)), np.diff(np.append(heads, len(sig))))
            i, j = linked_pairs(fps, starts, lengths, ends - np.repeat(starts, lengths), radius)
            ok = (np.minimum(n[i], n[j]) * down >= np.maximum(n[i], n[j]) * up) & (~cross[i] | (later[i] != later[j]))
            yield pa.RecordBatch.from_arrays([pa.array(sig[i[ok]]), pa.array(sig[j[ok]])], names=["sig_a", "sig_b"])

    return run


def near_copies(documents: DataFrame, words: int = NEAR_SHINGLE, near: tuple[int, int] = NEAR, bucket: int = BUCKET, miss: float = MISS) -> DataFrame:
    """``doc_id, component_id`` of every row: the smallest id among the documents that links of ``near`` or more join.

    A text of fewer words than a shingle is one shingle; null and wordless texts are equal to each other. Rows with the
    same ``doc_id`` are one document. Ids that are null take part through their texts but never name a component. An
    empty table gives an empty result. A link is missed with a chance of ``miss`` at just the wanted similarity.
    """
    docs = documents.select("doc_id", "text")
    rows = materialize(_described(docs, words, near, table_bits(docs.count(), near, miss)), "near-rows")
    sets = rows.groupBy("sig").agg(F.min("doc_id").alias("doc_id"), F.first(F.struct("n", "fp_a", "fp_b", "keys")).alias("x"))
    sets = materialize(sets.select("sig", "doc_id", "x.*"), "near-sets")
    ends = sets.select("sig", "doc_id")
    # in a few tables all sets meet the first one of their bucket
    some = sets.select("sig", "n", "fp_a", "fp_b", F.explode(F.slice("keys", 1, HUBS)).alias("key"))
    hubs = some.groupBy("key").agg(F.min(F.struct("sig", "n", "fp_a", "fp_b")).alias("hub"), F.max("sig").alias("last")).where("hub.sig <> last").select("key", "hub")
    apart = F.bit_count(F.col("fp_a").bitwiseXOR(F.col("hub.fp_a"))) + F.bit_count(F.col("fp_b").bitwiseXOR(F.col("hub.fp_b")))
    like = F.least("n", "hub.n") * near[1] >= F.greatest("n", "hub.n") * near[0]
    met = some.join(hubs, "key").where((F.col("sig") != F.col("hub.sig")) & (apart <= near_radius(near)) & like)
    edges = _verified(met.select(F.col("sig").alias("sig_a"), F.col("hub.sig").alias("sig_b")), ends, docs, words, near).unionAll(_one_document(rows, "sig"))
    found = connected_components(edges)
    # in all tables, sets that are still apart are compared
    split = sets.join(found.withColumnRenamed("node", "sig"), "sig", "left").select("sig", F.coalesce("component", "sig").alias("component"), "n", "fp_a", "fp_b", F.explode("keys").alias("key"))
    crowded = split.groupBy("key").agg(F.count(F.lit(1)).alias("k"), F.min("component").alias("lo"), F.max("component").alias("hi")).where(F.col("k") > bucket)
    crowded = materialize(crowded.select("key", F.when(F.col("lo") == F.col("hi"), 0).otherwise(F.ceil(F.col("k") / F.lit(max(1, bucket // 2)))).cast("int").alias("parts")), "near-crowded")
    where = ["key", "part_a", "part_b"]
    mixed = split.join(crowded.where("parts = 0").select("key"), "key", "left_anti")
    dealt = _dealt(mixed, crowded, ["key"], "sig", ["sig", "component", "n", "fp_a", "fp_b"])
    more = dealt.repartition(*where).sortWithinPartitions(*where, "component").mapInArrow(_near_runs(near), "sig_a long, sig_b long")
    more = _verified(more, ends, docs, words, near)
    if not more.isEmpty():
        found = connected_components(edges.unionAll(more))
    return rows.select("doc_id", "sig").join(_named(rows, ends, found, "sig"), "sig").select("doc_id", "component_id")


def representatives(documents: DataFrame, words: int = NEAR_SHINGLE, near: tuple[int, int] = NEAR, bucket: int = BUCKET) -> DataFrame:
    """The documents that stay when one of each group of `near_copies` does: those of the smallest id.

    Columns stay as they are, whatever their names. Documents without an id stay, and of rows that share an id all or none.
    """
    (name,) = free_names(documents, "leave_id")
    leave = near_copies(documents.select("doc_id", "text"), words, near, bucket).where("component_id < doc_id").select(F.col("doc_id").alias(name)).distinct()
    return documents.join(leave, documents["doc_id"] == F.col(name), "left_anti")


def query(spark, sf_dir):
    """op2: fingerprint and near-duplicate group of every document."""
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
