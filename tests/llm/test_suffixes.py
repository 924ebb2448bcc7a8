import hashlib
import random

import numpy as np
import pytest

from crossaudit.llm import suffixes


def brute(rows):
    first = {}
    for d, t in rows:
        b = (t or "").encode()
        for i in range(len(b) - 49):
            w = b[i : i + 50]
            first[w] = min(first.get(w, d), d)
    out = []
    for d, t in rows:
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for i in range(len(b) - 49):
            if first[b[i : i + 50]] < d:
                gone[i : i + 50] = True
        kept = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        spans = sum(1 for i in range(len(b)) if gone[i] and (i == 0 or not gone[i - 1]))
        out.append((d, len(b), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def texts():
    rng = random.Random(3)
    base = ["".join(rng.choice("abcdé ") for _ in range(rng.randint(0, 400))) for _ in range(40)]
    rows = []
    for i in range(160):
        parts = [rng.choice(base)[rng.randint(0, 80) : rng.randint(100, 400)] for _ in range(rng.randint(0, 3))]
        rows.append((i, "".join(parts) + "".join(rng.choice("xyz") for _ in range(rng.randint(0, 30)))))
    rows += [(500, "ab" * 200), (501, "ab" * 100), (502, None), (503, ""), (504, "x" * 49), (505, "x" * 50), (506, "x" * 51), (507, "x" * 500)]
    rows += [(7, rows[7][1]), (600, rows[3][1]), (601, rows[3][1])]
    return rows


@pytest.mark.parametrize("size", [6_000_000, 3_000])
def test_against_every_window(spark, size):
    rows = texts()
    got = suffixes.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), group_bytes=size).collect()
    assert sorted(tuple(r) for r in got) == brute(rows)


@pytest.mark.parametrize("hot", [64, 1])
def test_cells_and_hot_anchors(spark, hot):
    rows = texts() + [(1000 + i, "z" * i + "the very same passage stands in a great many of the documents here, word for word.") for i in range(40)]
    got = suffixes.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), group_bytes=1500, cell=4, hot=hot).collect()
    assert sorted(tuple(r) for r in got) == brute(rows)


def test_distinct_rows():
    rng = np.random.default_rng(6)
    matrix = rng.integers(0, 2, (500, 9)).astype(np.uint8)
    chosen, number = suffixes.distinct_rows(matrix)
    assert (matrix[chosen][number] == matrix).all() and len(chosen) == len(np.unique(matrix, axis=0))


def test_given_table(spark, tiny):
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()]
    assert sorted(tuple(r) for r in suffixes.query(spark, tiny).collect()) == brute(rows)


def test_blind_trie_ranks():
    rng = random.Random(4)
    for _ in range(300):
        tails = [bytes(rng.choice(b"ab") for _ in range(6)) for _ in range(rng.randint(1, 20))]
        distinct = sorted(set(tails))
        assert suffixes.blind_trie(tails) == [distinct.index(t) for t in tails]


def test_sorted_windows():
    rng = np.random.default_rng(5)
    data = np.concatenate([rng.integers(97, 99, 300), np.tile(rng.integers(97, 99, 60), 6)]).astype(np.uint8)
    at = np.arange(len(data) - 49)
    order, new = suffixes.sort_windows(data, at)
    raw = data.tobytes()
    ordered = [raw[i : i + 50] for i in at[order]]
    assert ordered == sorted(ordered)
    assert new.tolist() == [i == 0 or ordered[i] != ordered[i - 1] for i in range(len(ordered))]


def test_odd_rows(spark):
    frame = spark.createDataFrame([(None, "y" * 60), (1, "y" * 60), (None, None)], "doc_id long, text string")
    got = {(r["doc_id"], r["n_bytes"]): r["n_removed"] for r in suffixes.remove_repeats(frame).collect()}
    assert got == {(None, 60): 60, (1, 60): 0, (None, 0): 0}
    assert suffixes.remove_repeats(frame.limit(0)).count() == 0
    assert suffixes.remove_repeats(frame, with_text=True).columns[-1] == "kept"


def test_runs_do_not_depend_on_row_order(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(suffixes, "_CHUNK", 512)
    rows = [(d, t or "") for d, t in texts()]
    shuffled = random.Random(6).sample(rows, len(rows))
    a, b = (suffixes.Group(pa.table({"doc": [d for d, _ in r], "text": [t for _, t in r]}), 7) for r in (rows, shuffled))
    assert (a.first == b.first).all() and (a.count == b.count).all() and (a.code == b.code).all()
