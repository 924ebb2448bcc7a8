import random

import pytest

import corpus_pipeline
from crossaudit.llm import licenses, linededup, packing

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def brute_removed(rows):
    lines = [(d, k, frozenset(x.split())) for d, t in rows for k, x in enumerate((t or "").split("\n"))]
    lines = sorted([x for x in lines if x[2]], key=lambda x: x[:2])
    out = set()
    for i, (d, k, a) in enumerate(lines):
        if any(len(a & b) * 5 >= len(a | b) * 4 for e, j, b in lines[:i] if (e, j) < (d, k)):
            out.add((d, k))
    return out


@pytest.mark.parametrize("group", [64, 2])
def test_lines_against_all_pairs(spark, group):
    rng = random.Random(1)
    words = [f"w{i}" for i in range(60)]
    base = [rng.sample(words, rng.randint(1, 14)) for _ in range(25)]
    rows = []
    for d in range(60):
        lines = []
        for _ in range(rng.randint(0, 4)):
            x = list(rng.choice(base))
            for _ in range(rng.randint(0, 2)):
                x[rng.randrange(len(x))] = rng.choice(words)
            lines.append(" ".join(x))
        rows.append((d, "\n".join(lines)))
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r["doc"], p) for r in linededup.removed_lines(frame, group=group).collect() for p in r["places"]}
    assert got == brute_removed(rows)


def test_ranks_are_not_copied_into_rows(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    keyed = linededup._keyed(linededup.lines(docs), linededup._ranks(docs)).select("sig", linededup.F.trim("line").alias("t"), linededup.F.size("keys").alias("n"))
    assert " AS ranks#" not in keyed._jdf.queryExecution().optimizedPlan().toString()


def test_lines_odd_rows(spark):
    rows = [(1, "a b c d e\nsame line here now yes", "en", "s", 9), (2, "same line here now yes", "en", "s", 9), (3, None, None, None, None), (4, "", "en", "s", 0), (4, "", "en", "s", 0), (None, "a b c d e\nnew words stand here", "en", "s", 1)]
    docs = spark.createDataFrame(rows, SCHEMA)
    out = linededup.remove_lines(docs)
    got = [(r["doc_id"], r["text"]) for r in out.collect()]
    assert out.columns == docs.columns
    assert sorted(got, key=repr) == sorted([(1, rows[0][1]), (3, None), (4, ""), (4, ""), (None, "new words stand here")], key=repr)
    assert linededup.remove_lines(docs.limit(0)).count() == 0
    clash = docs.withColumns({c: linededup.F.lit("own") for c in ("places", "gone_doc", "gone_places", "doc")})
    again = linededup.remove_lines(clash)
    assert again.columns == clash.columns and again.count() == len(got) and {r["places"] for r in again.collect()} == {"own"}


def test_licences_inherit_from_the_nearest_directory(spark):
    rows = [
        ("LICENSE", "Released under the MIT License."), ("a/b/LICENSE.txt", "Licensed under the Apache License, Version 2.0."), ("a/x.txt", "plain words"), ("a/b/c/y.txt", "plain words"),
        ("a/b/c/z.txt", "first line of the text\nAll rights reserved.\nmore"), ("q/note.txt", None), ("q/empty.txt", ""), (None, "plain"), ("a/b/c/y.txt", "plain words"),
    ]
    files = spark.createDataFrame(rows, "path string, text string")
    got = {(r["path"], r["licence_found"], r["origin"], r["from_dir"]) for r in licenses.scan(files).collect()}
    assert got == {
        ("LICENSE", "MIT", "own", None), ("a/b/LICENSE.txt", "Apache-2.0", "own", None), ("a/x.txt", "MIT", "inherited", ""), ("a/b/c/y.txt", "Apache-2.0", "inherited", "a/b"),
        ("a/b/c/z.txt", "proprietary", "own", None), ("q/note.txt", "MIT", "inherited", ""), ("q/empty.txt", "MIT", "inherited", ""), (None, None, "none", None),
    }
    assert licenses.scan(files.limit(0)).count() == 0


def test_whole_licence_files_and_wrapped_headers(spark):
    grant = """Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:"""
    header = """/* Redistribution and use in source and binary
 * forms, with or without modification, are
 * permitted provided that the following conditions are met: */

int main() { return 0; }"""
    rows = [("m/LEGAL", grant), ("m/x.c", "int x;"), ("b/main.c", header), ("b/y.c", "int y;"), ("z/long.txt", "plain words here " * 70_000)] + [(f"f/{i}", f"some text number {i} of many words") for i in range(40)]
    files = spark.createDataFrame([(p, t, "own", 1) for p, t in rows], "path string, text string, licence string, places int")
    out = licenses.scan(files)
    assert out.columns == [*files.columns, "licence_found", "similarity", "origin", "from_dir"]
    got = {r["path"]: (r["licence_found"], r["origin"]) for r in out.collect()}
    assert got["m/LEGAL"] == ("MIT", "own") and got["m/x.c"] == ("MIT", "inherited") and got["b/main.c"] == ("BSD-3-Clause", "own")
    assert got["b/y.c"] == ("BSD-3-Clause", "inherited")  # most of main.c's few words are the header's
    assert got["z/long.txt"] == got["f/3"] == (None, "none")


def test_pipeline_stages(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    columns = docs.columns
    seen = docs
    for name, stage in corpus_pipeline.STAGES:
        before, seen = seen, corpus_pipeline.materialize(stage(spark, seen, tiny), f"test-{name}")
        if name != "pack":
            assert seen.columns == columns
        if name == "language":
            assert seen.count() >= 0.95 * before.count()
        if name == "line_dedup":
            rows = [(r["doc_id"], r["text"]) for r in before.collect()]
            gone = brute_removed(rows)
            want = {}
            for d, t in rows:
                kept = [x for k, x in enumerate((t or "").split("\n")) if (d, k) not in gone]
                if any(x.split() for x in kept) or not any(e == d for e, _ in gone):
                    want[d] = "\n".join(kept)
            assert {r["doc_id"]: r["text"] for r in seen.collect()} == want
    ids = packing.encoder(packing.vocabulary_path())
    total = sum(len(ids.raw(r["text"] or "")) // 4 + 1 for r in before.collect())
    assert seen.agg({"length": "sum"}).first()[0] == total
    assert corpus_pipeline.ORACLE_SQL is None and len(corpus_pipeline.STAGES) == 5


def test_frequencies_count_paths_once(spark):
    rows = [("a", "one two two"), ("a", "Two three"), ("a", "one two two"), (None, "one four"), (None, "four"), ("b", "one"), ("c", None), ("d", "")]
    rows += [(f"e/{k}", "two") for k in range(50)]
    files = spark.createDataFrame(rows, "path string, text string")
    want = {}
    for path, text in rows:
        for word in (text or "").lower().split():
            want.setdefault(word, set()).add(path)
    got = {r["word"]: r["df"] for r in licenses.frequencies(files).collect()}
    assert got == {word: len(paths) for word, paths in want.items()}
    assert licenses.frequencies(files.limit(0)).count() == 0


def test_all_readers_of_the_prefixes_share_one_exchange(spark, tiny, monkeypatch):
    plans = {}

    def kept(df, name, *by):
        plans[name] = df._jdf.queryExecution().optimizedPlan().toString()
        return materialize(df, name, *by)

    from crossaudit.functions.storage import materialize

    monkeypatch.setattr(linededup, "materialize", kept)
    linededup.removed_lines(spark.read.parquet(f"{tiny}/documents.parquet").limit(60)).count()
    # each of the three reads through the window over words, so that no filter of its own lies below the exchange
    assert sum(line.lstrip(" :+-|").startswith("Window") for line in plans["line-met"].splitlines()) == 3


def test_written_tables_leave_no_shuffle_files(spark):
    from crossaudit.functions.storage import materialize

    disk = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    shuffled = lambda: {x for x in disk.getAllBlocks().mkString(" ").split() if x.startswith("shuffle_")}
    before = shuffled()
    rows = spark.range(4000).selectExpr("id", "id % 7 AS k").repartition(3, "k")
    out = materialize(rows.groupBy("k").count(), "sevens")
    assert shuffled() <= before
    assert out.count() == 7 and spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") == "false"


def test_prefixes_are_deleted_when_nothing_reads_them(spark, tiny, monkeypatch):
    gone = []
    real = linededup.discard
    monkeypatch.setattr(linededup, "discard", lambda *tables: gone.extend(t._written_at for t in tables) or real(*tables))
    linededup.removed_lines(spark.read.parquet(f"{tiny}/documents.parquet").limit(60)).count()
    assert any("/line-found-" in path for path in gone)


def test_lines_that_share_a_word_but_not_a_length_are_not_crowded(spark, monkeypatch):
    """A frequent word under which no length has many lines is settled where its lines lie: none of them is joined again."""
    from crossaudit.functions.storage import materialize

    crowded = []

    def kept(df, name, *by):
        out = materialize(df, name, *by)
        if name == "line-met":
            crowded.append(out.where("busy = 1").count())
        return out

    monkeypatch.setattr(linededup, "materialize", kept)
    for sizes, like in (([4, 6, 8, 11, 15, 20], False), ([9] * 6, True)):
        # the shared word is the rarest of its lines, as all others stand alone in eight lines more
        own = [[f"w{k}x{i}" for i in range(n - 1)] for k, n in enumerate(sizes)]
        rows = [(k, " ".join(["shared", *words])) for k, words in enumerate(own)]
        rows += [(100 + k, "\n".join(w for words in own for w in words)) for k in range(8)]
        frame = spark.createDataFrame(rows, "doc_id long, text string")
        got = {(r["doc"], p) for r in linededup.removed_lines(frame, group=4).collect() for p in r["places"]}
        assert got == brute_removed(rows)
        assert (crowded.pop() > 0) == like


@pytest.mark.parametrize("group", [1, 3, 5])
def test_crowded_and_uncrowded_lines_meet(spark, group):
    """Near copies of many lengths under common words: whichever side of a pair is crowded, it is found."""
    rng = random.Random(group)
    words = [f"w{i}" for i in range(40)]
    base = rng.sample(words, 30)
    rows = [(d, " ".join(rng.sample(base[: rng.randint(6, 30)], k=1) + base[: rng.randint(4, 30)] + rng.sample(words, rng.randint(0, 3)))) for d in range(120)]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r["doc"], p) for r in linededup.removed_lines(frame, group=group).collect() for p in r["places"]}
    assert got == brute_removed(rows)


def test_prefixes_are_sorted_by_word_alone(spark, tiny, monkeypatch):
    """One sort key of 64 bits is sorted by radix; lengths and hashes behind it made Spark compare rows, most of that step's time."""
    from crossaudit.functions.storage import materialize

    plans = {}

    def kept(df, name, *by):
        plans[name] = df._jdf.queryExecution().executedPlan().toString()
        return materialize(df, name, *by)

    monkeypatch.setattr(linededup, "materialize", kept)
    linededup.removed_lines(spark.read.parquet(f"{tiny}/documents.parquet").limit(60)).count()
    sorts = [line.split("Sort [", 1)[1].split("]", 1)[0] for line in plans["line-met"].splitlines() if "Sort [" in line]
    assert sorts and all(keys.startswith("word") and "," not in keys for keys in sorts)


@pytest.mark.parametrize("group", [1, 4, 64])
def test_pairs_of_a_crowd_are_left_whole_to_the_crowded(spark, group):
    """A line is paired at once, or it and all that it may be paired with are crowded; lengths that share a counter change nothing."""
    rng = random.Random(group)
    data = [(w, k, rng.choice([1, 2, 4, 5, 6, 7, 8, 9, 10, 25, 31, 60, 150, 151, 4000])) for w in range(6) for k in range(2 ** (w + 2))]
    frame = spark.createDataFrame(data, "word long, sig long, n int")
    rows = linededup._crowds(frame, linededup.NEAR, group).collect()
    assert len(rows) == len(data)
    for b in rows:
        after = [a for a in rows if a["word"] == b["word"] and a["sig"] != b["sig"] and b["n"] <= a["n"] and a["n"] * 4 <= b["n"] * 5]
        assert b["crowd"] or len(after) <= group
        assert all(b["longer"] and a["shorter"] for a in after)
        assert not b["crowd"] or (b["crowded"] and all(a["crowded"] for a in after))
