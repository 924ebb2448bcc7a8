"""Near-duplicate lines by an exact set-similarity join (native DataFrame operations only).

A line is the set of its words. A word is a 64-bit key: the rank of its hash's bucket by how often words of the bucket
occur (1,048,576 buckets, counted over all documents), then the rest of the hash; so the order of keys is the order of
rarity, ties by hash. Lines with equal sets meet by a hash of the set. Of two similar sets, the rarest word that both
have stands in the probe prefix of the longer and in the still shorter index prefix of the other, so distinct sets meet
under the words of their prefixes. Pairs that meet pass a length filter, a positional filter and a 128-bit parity sketch (whose
differing bits are at most the sets' symmetric difference). Whole sets are never shuffled for the search: the lines of the
surviving pairs are read from the documents again to be verified. A line is removed if any earlier line, by ``doc_id``
and place, matches it.

Words shared by many prefixes of lines of a like length are not paired in full at once: under them each line first meets
the earliest lines, which settles groups of near copies, and only lines that nothing has removed yet meet all earlier ones
of a like length. A word that lines of very different lengths share is no such word: its lines are paired where they lie.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from crossaudit.functions.storage import discard, materialize
from crossaudit.llm.places import only_needed
from crossaudit.llm.words import free_names

#: Similarity as a fraction of integers, so that thresholds are exact.
NEAR = (4, 5)
#: Buckets of words that are ranked by their number of occurrences; the table of ranks (8 MB) is the same size for all inputs.
BUCKET_BITS = 20
#: Most lines of a like length under a word that are paired in full at once.
GROUP = 64
#: Bands of lengths that are counted apart under a word, in turns; a power of two.
BANDS = 8
#: Sets of more words have the second half of the sketch, too.
WIDE = 64
_LAST = (1 << 63) - 1


def spaced(text: Column) -> Column:
    """Text whose white space inside lines is single spaces; null is empty."""
    text = F.coalesce(text, F.lit(""))
    odd = [F.contains(text, F.lit(x)) for x in ("\t", "\r", "\x0b", "\x0c", "  ")]
    return F.when(reduce(Column.__or__, odd), F.regexp_replace(text, "[\\t\\x0b\\x0c\\r ]+", " ")).otherwise(text)


def _doc(documents: DataFrame) -> Column:
    return F.coalesce(documents["doc_id"].cast("long"), F.lit(_LAST))


def lines(documents: DataFrame) -> DataFrame:
    """``doc, pos, line`` of every line, its words a space apart; null ids come last."""
    return documents.select(_doc(documents).alias("doc"), F.posexplode(F.split(spaced(documents["text"]), "\n")).alias("pos", "line"))


def _slot(word_hash: Column) -> Column:
    return word_hash.bitwiseAND(F.lit((1 << BUCKET_BITS) - 1))


def _ranks(documents: DataFrame) -> DataFrame:
    """One row: for each bucket of words its rank by occurrences, shifted to the key's top bits."""
    n = 1 << BUCKET_BITS
    words = lines(documents).select(F.explode(F.split("line", " ")).alias("w"))
    seen = words.select(_slot(F.xxhash64("w")).alias("b")).groupBy("b").agg(F.count(F.lit(1)).alias("n"))
    every = documents.sparkSession.range(n).select(F.col("id").alias("b")).join(seen, "b", "left")
    # as many rows as there are buckets, whatever the input
    rank = F.row_number().over(Window.orderBy(F.coalesce("n", F.lit(0)), "b")) - 1 - n // 2
    table = every.select("b", F.call_function("shiftleft", rank.cast("long"), F.lit(64 - BUCKET_BITS)).alias("top"))
    table = table.agg(F.sort_array(F.collect_list(F.struct("b", "top"))).alias("x")).select(F.col("x.top").alias("ranks"))
    return materialize(table, "line-ranks")


def _keyed(rows: DataFrame, ranks: DataFrame) -> DataFrame:
    """Adds ``keys``, the line's distinct words from rare to frequent, and ``sig``, a hash of them; a line without a word has the empty word.

    The ranks must be named once, in a projection that Catalyst can merge with theirs (its other inputs are plain columns), and
    no filter may follow: else they are copied into every row.
    """

    def key(h: Column) -> Column:
        top = F.coalesce(F.get(F.col("ranks"), _slot(h).cast("int")), F.lit(0).cast("long"))
        return top.bitwiseOR(F.call_function("shiftrightunsigned", h, F.lit(BUCKET_BITS)))

    # nothing is shared inside a lambda: a word is hashed once only if its hash is what the second one gets
    hashes = F.transform(F.split(F.trim("line"), " "), lambda w: F.xxhash64(w))
    keys = F.sort_array(F.array_distinct(F.transform(hashes, key)))
    return rows.withColumn("ranks", ranks.scalar()).withColumn("keys", keys).drop("ranks").withColumn("sig", F.xxhash64("keys"))


def _keep(n: Column, near: tuple[int, int]) -> Column:
    """Words of a set of ``n`` that a match must share at least: the similarity times n, rounded up."""
    return F.floor((n * near[0] + near[1] - 1) / near[1])


def _overlap(both: Column, near: tuple[int, int]) -> Column:
    """Words that two sets of together ``both`` words must share at least."""
    up, down = near
    return F.floor((both * up + up + down - 1) / (up + down))


_META = ("sig", "n", "i", "bits", "half")


def _plausible(a: dict[str, Column], b: dict[str, Column], near: tuple[int, int]) -> Column:
    """Length, positional and sketch filters at the rarest word that both have; no pair of the wanted similarity fails them there."""
    up, down = near
    both = a["n"] + b["n"]
    overlap = _overlap(both, near)
    whole, half = a["bits"].bitwiseXOR(b["bits"]), a["half"].bitwiseXOR(b["half"])
    differ = F.when(F.least(a["n"], b["n"]) > WIDE, F.bit_count(half) + F.bit_count(half.bitwiseXOR(whole))).otherwise(F.bit_count(whole))
    return (
        (F.least(a["n"], b["n"]) * down >= F.greatest(a["n"], b["n"]) * up)
        & (F.least(a["n"] - a["i"], b["n"] - b["i"]) >= overlap)
        & (a["i"] + b["i"] <= both - 2 * overlap)
        & (differ <= both - 2 * overlap)
    )


def _band(near: tuple[int, int]) -> Column:
    """Band of the length ``n``: lengths within the wanted ratio lie in one band or in neighbouring ones."""
    return F.floor(F.log("n") / F.log(F.lit(near[1] / near[0]))).cast("int")


def _crowds(rows: DataFrame, near: tuple[int, int], group: int) -> DataFrame:
    """Adds what the other rows under a ``word`` are to each: whether any may be ``longer`` or ``shorter`` and of a like length, whether
    the longer ones are a ``crowd`` of more than ``group``, and whether the row or one that it may be longer than has a crowd (``crowded``).

    Rows are counted by bands of lengths, eight in turns, so a count may hold other lengths, too, but is the same for all rows of a band.
    The window has no order: rows are sorted by the word alone, which Spark does by radix, without comparing rows.
    """
    under, one = Window.partitionBy("word"), F.lit(1).cast("long")
    odd = lambda s: s.bitwiseAND(F.lit(1)) * 32
    pair = lambda s: F.call_function("shiftright", s, F.lit(1))
    # two counts of 32 bits share a column
    tallies = [f"tally_{k}" for k in range(BANDS // 2)]
    mine = F.col("slot")
    rows = rows.withColumn("slot", _band(near).bitwiseAND(F.lit(BANDS - 1)))
    rows = rows.withColumns({c: F.sum(F.when(pair(mine) == k, F.call_function("shiftleft", one, odd(mine))).otherwise(F.lit(0).cast("long"))).over(under) for k, c in enumerate(tallies)})

    def tally(step: int) -> Column:
        slot = (mine + (step % BANDS)).bitwiseAND(F.lit(BANDS - 1))
        return F.call_function("shiftrightunsigned", F.get(F.array(*tallies), pair(slot)), odd(slot)).bitwiseAND(F.lit((1 << 32) - 1))

    rows = rows.withColumns({"upward": tally(0) + tally(1), "downward": tally(0) + tally(-1)})
    most = group + 1
    return rows.withColumns({"longer": F.col("upward") > 1, "shorter": F.col("downward") > 1, "crowd": F.col("upward") > most, "crowded": (F.col("upward") > most) | (F.col("downward") > most)})


def _verified(pairs: DataFrame, sets: DataFrame, documents: DataFrame, ranks: DataFrame, near: tuple[int, int]) -> DataFrame | None:
    """``sig`` of the later line of every pair whose sets are similar enough; the lines are read from the documents again."""
    pairs = materialize(pairs.select(F.least("sig_a", "sig_b").alias("sig_a"), F.greatest("sig_a", "sig_b").alias("sig_b")).distinct(), "line-pairs")
    if pairs.isEmpty():
        return None
    ends = pairs.select(F.explode(F.array("sig_a", "sig_b")).alias("sig")).distinct()
    need = materialize(sets.select("sig", "doc", "pos").join(ends, "sig"), "line-need")
    some = only_needed(need.select("doc"), documents, _doc(documents))
    again = only_needed(need.select("doc", "pos"), lines(some), F.col("doc"), F.col("pos"))
    again = _keyed(again, ranks).select("sig", "doc", "pos", "keys").join(need.select("sig", F.col("doc").alias("d"), F.col("pos").alias("p")), "sig")
    again = again.where("doc = d and pos = p").groupBy("sig").agg(F.first(F.struct("doc", "pos", "keys")).alias("x")).select("sig", "x.*")  # one of rows that share an id
    side = lambda k: again.select(*[F.col(c).alias(f"{c}_{k}") for c in ("sig", "doc", "pos", "keys")])
    whole = pairs.join(side("a"), "sig_a").join(side("b"), "sig_b")
    shared = F.size(F.array_intersect("keys_a", "keys_b"))
    similar = shared * near[1] >= (F.size("keys_a") + F.size("keys_b") - shared) * near[0]
    # of two lines at the same place (rows that share an id), neither is later
    later = F.when(F.struct("doc_a", "pos_a") < F.struct("doc_b", "pos_b"), F.col("sig_b")).when(F.struct("doc_b", "pos_b") < F.struct("doc_a", "pos_a"), F.col("sig_a"))
    out = materialize(whole.where(similar).select(later.alias("sig")).where("sig is not null").distinct(), "line-gone")
    discard(pairs, need)
    return out


def repeated_sets(documents: DataFrame, near: tuple[int, int] = NEAR, group: int = GROUP) -> tuple[DataFrame, DataFrame, DataFrame]:
    """All lines with the ``sig`` of their set, the sets with their first place, and the ``sig`` of those that an earlier, different set matches."""
    up, down = near
    ranks = _ranks(documents)
    size, one = F.size("keys"), F.lit(1).cast("long")
    place = lambda w: w.bitwiseAND(F.lit(63)).cast("int")
    upper = lambda w: F.call_function("shiftright", w, F.lit(6)).bitwiseAND(F.lit(1))
    bits = F.aggregate("keys", F.lit(0).cast("long"), lambda s, w: s.bitwiseXOR(F.call_function("shiftleft", one, place(w))))
    half = F.when(size > WIDE, F.aggregate("keys", F.lit(0).cast("long"), lambda s, w: s.bitwiseXOR(F.call_function("shiftleft", upper(w), place(w))))).otherwise(F.lit(0).cast("long"))
    prefix = F.slice("keys", F.lit(1), (size - _keep(size, near) + 1).cast("int"))
    found = _keyed(lines(documents), ranks).select("doc", "pos", "sig", F.when(F.trim("line") == "", 0).otherwise(size).alias("n"), bits.alias("bits"), half.alias("half"), prefix.alias("prefix"))
    written = materialize(found, "line-found")
    found = written.where("n > 0")
    # equal sets have equal prefixes: the first row's will do
    whole = materialize(found.groupBy("sig").agg(F.min(F.struct("doc", "pos", "n", "bits", "half", "prefix")).alias("x")).select("sig", "x.*"), "line-sets")
    sets = whole.select("sig", "doc", "pos")
    places = materialize(found.select("doc", "pos", "sig"), "line-places")
    # all that is needed of the lines is in the two tables
    discard(written)
    rows = whole.select("sig", "n", "bits", "half", F.posexplode("prefix").alias("i", "word"))
    # columns that can't be null get no null filters below the exchange, so that all three readers share it
    kinds = {"word": "long", "sig": "long", "n": "int", "i": "int", "bits": "long", "half": "long"}
    rows = rows.select(*[F.coalesce(F.col(c), F.lit(0).cast(t)).alias(c) for c, t in kinds.items()])
    # dealt here, so that the bands are not shuffled with the rows
    counted = _crowds(rows.repartition("word"), near, group)

    own = {c: F.col(c) for c in _META}
    ends = [{c: F.col(f"{c}_{k}") for c in _META} for k in "ab"]
    longer = (F.col("n_a") > F.col("n_b")) | ((F.col("n_a") == F.col("n_b")) & (F.col("sig_a") > F.col("sig_b")))
    side = lambda df, k: df.select("word", *[F.col(c).alias(f"{c}_{k}") for c in _META])
    # filtered behind the window, which counts these rows, too
    index = counted.where(F.col("longer") & ~F.col("crowd")).where(F.col("i") <= F.col("n") - F.floor((F.col("n") * 2 * up + up + down - 1) / (up + down)))
    pairs = side(counted.where("shorter"), "a").join(side(index, "b"), "word").where(longer & _plausible(*ends, near))
    # pairs of lines with few like ones and the rows of the others are written by one job, so that the prefixes are shuffled once
    none = lambda *names: [F.lit(None).cast(kinds[c]).alias(c) for c in names]
    pairs = pairs.select(*none("word"), F.col("sig_a").alias("sig"), F.col("sig_b").alias("other"), *none("n", "i", "bits", "half"), F.lit(0).alias("busy"))
    busy = counted.where("crowded").select("word", "sig", F.lit(None).cast("long").alias("other"), "n", "i", "bits", "half", F.lit(1).alias("busy"))
    met = materialize(pairs.unionAll(busy), "line-met", "busy")
    many = materialize(met.where("busy = 1").select("word", *_META).join(sets, "sig"), "line-many")
    by_age = Window.partitionBy("word").orderBy("doc", "pos", "sig")
    first = F.struct(*_META)
    olds = [F.first(first).over(by_age), *[F.lag(first, k).over(by_age) for k in (1, 2, 3)]]
    told_old = lambda o: o.isNotNull() & (o["sig"] != F.col("sig")) & _plausible(own, {c: o[c] for c in _META}, near)
    # filtered in the row: only what can match is a row of its own
    olds = many.select(*_META, F.array(*olds).alias("met")).select("sig", F.filter("met", lambda o: F.coalesce(told_old(o), F.lit(False))).alias("met"))
    olds = olds.select(F.col("sig").alias("sig_a"), F.explode(F.col("met.sig")).alias("sig_b"))
    none_gone = sets.where("false").select("sig")
    gone = _verified(met.where("busy = 0").select(F.col("sig").alias("sig_a"), F.col("other").alias("sig_b")).unionAll(olds), sets, documents, ranks, near)
    gone = none_gone if gone is None else gone

    band = _band(near)
    asks = many.join(gone, "sig", "left_anti").select("word", F.explode(F.array(band - 1, band, band + 1)).alias("band"), F.col("doc").alias("doc_a"), F.col("pos").alias("pos_a"), *[F.col(c).alias(f"{c}_a") for c in _META])
    told = many.select("word", band.alias("band"), F.col("doc").alias("doc_b"), F.col("pos").alias("pos_b"), *[F.col(c).alias(f"{c}_b") for c in _META])
    older = (F.col("doc_b") < F.col("doc_a")) | ((F.col("doc_b") == F.col("doc_a")) & (F.col("pos_b") <= F.col("pos_a")))
    rest = asks.join(told, ["word", "band"]).where(older & (F.col("sig_a") != F.col("sig_b")) & _plausible(*ends, near)).select("sig_a", "sig_b")
    more = _verified(rest, sets, documents, ranks, near)
    discard(met, many)
    return places, sets, gone if more is None else gone.unionAll(more).distinct()


def removed_lines(documents: DataFrame, near: tuple[int, int] = NEAR, group: int = GROUP) -> DataFrame:
    """``doc, places``: for each document with lines to remove, their places in order.

    Null text has no lines; of rows that share a ``doc_id`` places are joined; an empty table gives an empty result; of
    equal lines the first by ``doc_id`` and place stays, so ties cannot arise but between rows that share an id.
    """
    every, sets, gone = repeated_sets(documents, near, group)
    # every copy of a matched set goes; of an unmatched one, all but the first
    first = sets.select("sig", F.col("doc").alias("d"), F.col("pos").alias("p")).join(gone.withColumn("later", F.lit(True)), "sig", "left")
    out = every.join(first, "sig").where(F.coalesce("later", F.lit(False)) | (F.struct("doc", "pos") != F.struct("d", "p")))
    return out.groupBy("doc").agg(F.array_sort(F.collect_set("pos")).alias("places"))


def remove_lines(documents: DataFrame, near: tuple[int, int] = NEAR) -> DataFrame:
    """The documents without their later matching lines; other columns stay, ``n_chars`` (if there) is counted anew.

    Lines without a word stay where they are, unless nothing else is left: a document whose every line with a word
    is removed goes. Documents that had no word stay. Null text stays null. Rows that share a ``doc_id`` lose the lines
    at the same places. Columns of any name may come along. An empty table stays empty.
    """
    doc, places = free_names(documents, "gone_doc", "gone_places")
    gone = removed_lines(documents.select("doc_id", "text"), near).select(F.col("doc").alias(doc), F.col("places").alias(places))
    out = documents.join(gone, _doc(documents) == F.col(doc), "left")
    parts = F.split(F.col("text"), "\n")
    kept = F.filter(F.transform(parts, lambda x, i: F.struct(x.alias("x"), i.alias("i"))), lambda s: ~F.array_contains(places, s["i"]))
    text = F.when(F.col(places).isNull(), F.col("text")).otherwise(F.array_join(F.transform(kept, lambda s: s["x"]), "\n"))
    out = out.withColumn("text", text).where(F.col(places).isNull() | F.coalesce(F.col("text").rlike(r"[^\x20\x09-\x0D]"), F.lit(True)))
    if "n_chars" in documents.columns:
        out = out.withColumn("n_chars", F.length("text").cast("long"))
    return out.select(*documents.columns)


def query(spark, sf_dir):
    """op4: of every document, its lines, how many are removed and at which places."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    gone = removed_lines(docs)
    n = F.size(F.split(F.coalesce("text", F.lit("")), "\n")).cast("long")
    out = docs.select("doc_id", n.alias("n_lines")).join(gone, F.coalesce(F.col("doc_id"), F.lit(_LAST)) == F.col("doc"), "left")
    return out.select(
        "doc_id", "n_lines", F.coalesce(F.size("places"), F.lit(0)).cast("long").alias("n_removed"),
        F.coalesce(F.array_join(F.col("places").cast("array<string>"), ","), F.lit("")).alias("removed_places"),
    )


#: All pairs of distinct sets that share a word, verified; for small tables.
ORACLE = r"""
WITH l AS (
  SELECT doc_id, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) - 1 AS pos, unnest(string_split(coalesce(text, ''), chr(10))) AS line FROM documents),
w AS (SELECT doc_id, pos, list_sort(list_distinct(regexp_extract_all(line, '[^\x20\x09-\x0D]+'))) AS words FROM l),
s AS (SELECT words, min({'d': doc_id, 'p': pos}) AS first, row_number() OVER () AS id, len(words) AS n FROM w WHERE len(words) > 0 GROUP BY words),
t AS (SELECT id, n, unnest(words) AS word FROM s),
f AS (SELECT word, count(*) AS c FROM t GROUP BY word),
o AS (SELECT id, n, word, row_number() OVER (PARTITION BY id ORDER BY c, word) AS k FROM t JOIN f USING (word)),
x AS (SELECT id, n, word FROM o WHERE k <= n - CAST(ceil(n * 0.8) AS BIGINT) + 1),
c AS (SELECT DISTINCT a.id AS a, b.id AS b FROM x a JOIN x b USING (word) WHERE a.id <> b.id AND a.n * 5 >= b.n * 4 AND b.n * 5 >= a.n * 4),
g AS (SELECT DISTINCT c.a AS id FROM c JOIN s a ON a.id = c.a JOIN s b ON b.id = c.b
      WHERE b.first < a.first AND len(list_intersect(a.words, b.words)) * 5 >= (a.n + b.n - len(list_intersect(a.words, b.words))) * 4),
r AS (SELECT w.doc_id, w.pos FROM w JOIN s USING (words) LEFT JOIN g USING (id) WHERE g.id IS NOT NULL OR s.first <> {'d': w.doc_id, 'p': w.pos})
SELECT d.doc_id, CAST(len(string_split(coalesce(text, ''), chr(10))) AS BIGINT) AS n_lines, CAST(coalesce(count(r.pos), 0) AS BIGINT) AS n_removed,
       coalesce(string_agg(CAST(r.pos AS VARCHAR), ',' ORDER BY r.pos), '') AS removed_places
FROM documents d LEFT JOIN r USING (doc_id) GROUP BY d.doc_id, text
"""
