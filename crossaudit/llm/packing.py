"""Best-fit packing of token sequences by minimum bin slack.

Sequences hold 1024 tokens. Only the number of pieces of each length matters to which combinations fill a sequence,
so the search runs on the histogram of lengths, of at most 1024 rows whatever the input: for the longest length that
is left, a subset-sum dynamic program over bitsets of reachable fills (one bit a token) finds the fullest feasible
combination, which is then removed as often as the counts allow. Pieces find their places by their rank within their length,
computed in two levels of salted groups, and a join with the plan, whose size has a fixed bound.
"""

from __future__ import annotations

import re
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from crossaudit.functions.storage import materialize
from crossaudit.llm.kept import Memo, held

CAPACITY = 1024
END = 2
SALTS = 256
#: Bytes, about, that the kept words of a worker may take.
_KEPT_BYTES = 110_000_000
_TEXTS = 500
#: Marks that end words and are tokens of their own.
_MARKS = frozenset(".,;:!?")

_BETWEEN = re.compile(r"(?<=\S)\n(?=\S)")
#: White space other than lone spaces and line breaks between words.
_ODD = r"[ \n][ \n]|^[ \n]|[ \n]$|[\t\v\f\r\x1c-\x1f\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}]"


def tokenizer(path: str):
    """The tokenizer of a file, as it stands: its added tokens are found in texts."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


class Encoder:
    """Token ids of whole texts as little-endian unsigned 32-bit bytes, with the ids of words kept.

    The pre-tokenizer of byte-level BPE always starts a new pre-token before a space that follows a non-space, and
    treats a single line break between non-spaces as one of its own. So a text whose white space is lone spaces and
    line breaks is the concatenation of its words' ids, and new words are encoded together, a line each. Texts with
    other spacing are encoded whole, but for such line breaks; texts that hold one of the vocabulary's added tokens are encoded whole
    as they are. A word that ends in one punctuation mark is its letters and the mark.

    A word is kept with what stands before it: nothing for a space, a line break, or a vertical tab for a text's start.
    """

    def __init__(self, path: str):
        self.t = tokenizer(path)
        self.added = [x.content for x in self.t.get_added_tokens_decoder().values()]
        self.newline = self.raw("\n")
        self.kept = Memo(_KEPT_BYTES)

    def ids(self, text: str) -> np.ndarray:
        return np.array(self.t.encode_batch_fast([text], add_special_tokens=False)[0].ids, "<u4")

    def raw(self, text: str) -> bytes:
        return self.ids(text).tobytes()

    def together(self, lead: str, words: list[str]) -> list[bytes]:
        """Ids of words, each behind ``lead``."""
        out, cut = [], np.frombuffer(self.newline, "<u4")[0]
        for i in range(0, len(words), 20_000):
            part = words[i : i + 20_000]
            ids = self.ids(f"{lead}{f'\n{lead}'.join(part)}\n")
            ends = np.flatnonzero(ids == cut).tolist()
            data = ids.tobytes()
            out += [data[4 * a : 4 * b] for a, b in zip([0, *[e + 1 for e in ends[:-1]]], ends, strict=True)]
        return out

    def learn(self, words: list[str]) -> None:
        kept = self.kept
        marked = [w for w in words if w[-1:] in _MARKS and w[:-1].isalpha()]
        stems = [w[:-1] for w in marked]
        plain = set(words)
        plain.difference_update(marked)
        plain.update(w for w in stems if w not in kept)
        after_break = [w for w in plain if w[:1] in ("\n", "\v")]
        after_space = list(plain.difference(after_break))
        kept.add_all(after_space, self.together(" ", after_space))
        found = self.together("", [w[1:] for w in after_break])
        kept.add_all(after_break, [self.newline + ids if w[0] == "\n" else ids for w, ids in zip(after_break, found, strict=True)])
        marks = {m: self.raw(m) for m in _MARKS}
        kept.add_all(marked, [kept[x] + marks[w[-1]] for x, w in zip(stems, marked, strict=True)])

    def texts(self, texts: pa.Array) -> list[bytes]:
        """Ids of each text; null is empty."""
        texts = pc.fill_null(texts, "").cast(pa.large_string())
        odd = pc.or_(pc.match_substring_regex(texts, _ODD), pc.equal(texts, "")).to_numpy(zero_copy_only=False)
        whole = np.zeros(len(texts), bool)
        for x in self.added:
            whole |= pc.match_substring(texts, x).to_numpy(zero_copy_only=False)
        odd = odd | whole
        out: list[bytes] = [b""] * len(texts)
        for i in np.flatnonzero(odd).tolist():
            if t := texts[i].as_py():
                out[i] = self.raw(t) if whole[i] else self.newline.join(map(self.raw, _BETWEEN.split(t)))
        even = np.flatnonzero(~odd)
        if not len(even):
            return out
        plain = texts.take(pa.array(even))
        words = pc.split_pattern(pc.binary_join_element_wise(*(pa.scalar(x, pa.large_string()) if isinstance(x, str) else x for x in ("\v", pc.replace_substring(plain, "\n", " \n"), ""))), " ")
        coded = pc.list_flatten(words).dictionary_encode()
        # no word has a space, so that all can be decoded at once
        names = pc.binary_join(pa.ListArray.from_arrays([0, len(coded.dictionary)], coded.dictionary), pa.scalar(" ", pa.large_string()))[0].as_py().split(" ")
        ids = list(map(self.kept.get, names))
        if new := [w for w, x in zip(names, ids, strict=True) if x is None]:
            self.learn(new)
            ids = [self.kept[w] if x is None else x for w, x in zip(names, ids, strict=True)]
            self.kept.trim(names)  # frequent words are among those of any batch
        flat = pa.array(ids, pa.large_binary()).take(coded.indices)
        ends = np.frombuffer(flat.buffers()[1], np.int64)[: len(flat) + 1]
        data = flat.buffers()[2].to_pybytes()
        at = ends[np.asarray(words.offsets)].tolist()
        for i, a, b in zip(even.tolist(), at, at[1:], strict=False):
            out[i] = data[a:b]
        return out


def encoder(path: str) -> Encoder:
    """The worker's encoder of a vocabulary file; what other operators keep there is dropped."""
    return held(f"encoder {path}", lambda: Encoder(path))


def vocabulary_path() -> str:
    """Default vocabulary file: the public byte-level BPE of about 50,000 tokens."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def pieces(documents: DataFrame, capacity: int = CAPACITY, end: int = END, path: str | None = None, with_ids: bool = False) -> DataFrame:
    """Token pieces of whole documents: ``doc_id, piece, start, length, ids_crc32`` (and ``ids`` on request).

    Null or empty text is the end token alone. A document of up to ``capacity`` tokens is one piece; a longer one is
    cut into full pieces after a first one that takes the remainder. Repeated rows give repeated pieces, null ids stay null,
    and an empty table has no piece.
    """
    vocabulary = path or vocabulary_path()
    stop = end.to_bytes(4, "little")

    def run(batches):
        enc = encoder(vocabulary)
        for b in batches:
            out = []
            for i in range(0, b.num_rows, _TEXTS):
                part = b.slice(i, _TEXTS)
                encoded = enc.texts(part.column(1))
                for doc, ids in zip(part.column(0).to_pylist(), encoded, strict=True):
                    ids += stop
                    n = len(ids) // 4
                    at, k = 0, 0
                    size = n % capacity or capacity
                    while at < n:
                        own = ids[4 * at : 4 * (at + size)]
                        out.append((doc, k, at, size, zlib.crc32(own), own))
                        at, k, size = at + size, k + 1, capacity
            cols = list(zip(*out, strict=True)) or [()] * 6
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()] + [pa.binary()] * with_ids
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=False)], names=[x.split()[0] for x in PIECES.split(", ")] + ["ids"] * with_ids)

    return documents.select(F.col("doc_id").cast("long"), F.col("text")).mapInArrow(run, PIECES + ", ids binary" * with_ids)


def _fullest(counts: dict[int, int], lengths: list[int], room: int) -> list[tuple[int, int]]:
    """Lengths and how often, that fill ``room`` most: bits of ``reach`` are the fills that the lengths so far allow."""
    whole = (1 << (room + 1)) - 1
    steps, reach = [], 1
    for n in lengths:
        if n > room or not counts[n]:
            continue
        before, left, part = reach, min(counts[n], room // n), 1
        while left:
            take = min(part, left)
            reach |= (reach << (take * n)) & whole
            left, part = left - take, part * 2
        steps.append((n, before))
        if reach >> room & 1:
            break
    fill, chosen = reach.bit_length() - 1, []
    for n, before in reversed(steps):
        k = 0
        while not before >> fill & 1:
            fill, k = fill - n, k + 1
        if k:
            chosen.append((n, k))
    return chosen


def minimum_slack(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, list[tuple[int, int]]]]:
    """Sequences of the same make-up: ``(how many, [(length, how often in each)])``, together using every piece once."""
    counts = {n: c for n, c in counts.items() if c > 0}
    out = []
    while counts:
        lengths = sorted(counts, reverse=True)
        longest = lengths[0]
        counts[longest] -= 1
        found = dict(_fullest(counts, lengths, capacity - longest))
        counts[longest] += 1
        found[longest] = found.get(longest, 0) + 1
        times = min(counts[n] // k for n, k in found.items())
        for n, k in found.items():
            counts[n] -= times * k
            if not counts[n]:
                del counts[n]
        out.append((times, sorted(found.items(), reverse=True)))
    return out


def pack(items: DataFrame, keys: list[str], capacity: int = CAPACITY) -> DataFrame:
    """``items`` with ``sequence_id`` and ``offset`` added; their ``length`` is 1 to ``capacity``.

    ``keys`` order the items of one length; items equal in them (repeated rows, ties) may change places, and each has its own.
    Any number of items, also all of one length, spreads over salted groups. An empty table gives an empty result.
    """
    spark = items.sparkSession
    items = materialize(items, "pack-items")
    counted = items.groupBy("length").agg(F.count(F.lit(1)).alias("n"))  # at most `capacity` rows
    plan, sequence = [], 0
    ranks: dict[int, int] = {}
    for times, make in minimum_slack({r["length"]: r["n"] for r in counted.collect()}, capacity):
        offset = 0
        for n, k in make:
            first = ranks.get(n, 0)
            plan.append((n, first, first + times * k, k, sequence, offset))
            ranks[n] = first + times * k
            offset += n * k
        sequence += times
    plan = spark.createDataFrame(plan, "p_length long, p_from long, p_to long, p_each long, p_sequence long, p_offset long")
    spread = F.xxhash64(*keys)
    salted = items.withColumns({"salt_a": F.pmod(spread, F.lit(SALTS)), "salt_b": F.pmod(F.shiftright(spread, 32), F.lit(SALTS))})
    fine = salted.groupBy("length", "salt_a", "salt_b").agg(F.count(F.lit(1)).alias("n"))
    coarse = salted.groupBy("length", "salt_a").agg(F.count(F.lit(1)).alias("n"))

    def base(counts: DataFrame, name: str, inside: list[str], by: str) -> DataFrame:
        before = Window.partitionBy(*inside).orderBy(by).rowsBetween(Window.unboundedPreceding, -1)
        return counts.select(*inside, by, F.coalesce(F.sum("n").over(before), F.lit(0)).alias(name))

    bases = base(fine, "base_b", ["length", "salt_a"], "salt_b").join(base(coarse, "base_a", ["length"], "salt_a"), ["length", "salt_a"])
    bases = materialize(bases, "pack-base")
    place = Window.partitionBy("length", "salt_a", "salt_b").orderBy(*keys)
    ranked = salted.join(bases, ["length", "salt_a", "salt_b"])
    ranked = ranked.withColumn("rank", F.col("base_a") + F.col("base_b") + F.row_number().over(place) - 1)
    there = (F.col("length") == F.col("p_length")) & (F.col("rank") >= F.col("p_from")) & (F.col("rank") < F.col("p_to"))
    k = F.col("rank") - F.col("p_from")
    return ranked.join(F.broadcast(plan), there).select(
        *items.columns,
        (F.col("p_sequence") + F.floor(k / F.col("p_each"))).cast("long").alias("sequence_id"),
        (F.col("p_offset") + F.pmod(k, F.col("p_each")) * F.col("p_length")).cast("long").alias("offset"),
    )


def query(spark, sf_dir):
    """op1: every document of the corpus packed into sequences of 1024 tokens."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return pack(pieces(docs), ["doc_id", "piece", "ids_crc32"])
