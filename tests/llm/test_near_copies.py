import random

import pytest

import corpus_pipeline
from crossaudit.llm import simhash

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def shingle_set(text):
    words = (text or "").lower().split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def brute_components(rows):
    parent = {d: d for d, _ in rows}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    sets = [(d, shingle_set(t)) for d, t in rows]
    for i, (d, a) in enumerate(sets):
        for e, b in sets[:i]:
            if a == b or 5 * len(a & b) >= 4 * len(a | b):
                x, y = root(d), root(e)
                parent[max(x, y)] = min(x, y)
    return {d: root(d) for d in parent}


def near_rows(rng):
    """Groups of copies with a few words replaced or cut off, chains of small steps, a passage that many share, short texts."""
    vocabulary = [f"w{i}" for i in range(500)]
    passage = rng.choices(vocabulary, k=12)
    texts = []
    for g in range(12):
        base = rng.choices(vocabulary, k=rng.randint(30, 150)) + (passage if g % 2 else [])
        for _ in range(8):
            x = list(base)
            for _ in range(rng.randint(0, max(1, len(x) // 40))):
                x[rng.randrange(len(x))] = rng.choice(vocabulary)
            texts.append(x[: len(x) - rng.randint(0, len(x) // 6)])
    chain = rng.choices(vocabulary, k=160)
    texts += [chain[k : k + 100] for k in range(0, 60, 6)]
    texts += [["one", "two"], ["one", "two"], ["ONE", "two"], [], [], ["x"]]
    rng.shuffle(texts)
    return [(i, " ".join(x)) for i, x in enumerate(texts)]


@pytest.mark.parametrize("bucket", [4096, 4])
def test_near_texts_against_all_pairs(spark, bucket):
    rows = near_rows(random.Random(bucket))
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_copies(spark.createDataFrame(rows, "doc_id long, text string"), bucket=bucket).collect()}
    want = brute_components(rows)
    assert got == want and 10 < len(set(want.values())) < len(rows) - 10


def test_pipeline_stage_drops_copies_at_four_fifths(spark):
    rng = random.Random(6)
    rows = []
    for g in range(20):
        base = [f"g{g}w{rng.randrange(10**6)}" for _ in range(104)]
        rows.append((10 * g, " ".join(base)))
        for k, changed in enumerate((1, 2, 3), 1):  # each changed word takes five of 100 shingles
            x = list(base)
            for at in rng.sample(range(5, 95, 10), changed):
                x[at] = "other"
            rows.append((10 * g + k, " ".join(x)))
    docs = spark.createDataFrame([(d, t, "en", "s", len(t)) for d, t in rows], SCHEMA)
    kept = {r["doc_id"] for r in corpus_pipeline.drop_near_copies(spark, docs, "").collect()}
    want = brute_components(rows)
    assert kept == set(want.values())
    assert all(10 * g in kept and 10 * g + 1 not in kept for g in range(20))


def test_near_texts_odd_rows(spark):
    text = "a b c d e f g h"
    rows = [(1, text), (1, "other words"), (2, None), (3, ""), (None, text), (4, text), (5, "other words"), (None, "alone")]
    docs = spark.createDataFrame([(d, t, "en", "s", 1) for d, t in rows], SCHEMA)
    out = simhash.representatives(docs)
    assert out.columns == docs.columns
    assert sorted((r["doc_id"] for r in out.collect()), key=repr) == [1, 1, 2, None, None]
    assert simhash.representatives(docs.limit(0)).count() == 0
