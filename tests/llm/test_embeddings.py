import numpy as np
import pytest

from crossaudit.llm import embeddings


def brute(rows, cosine=0.9):
    ids = [i for i, _ in rows]
    ok = [v is not None and len(v) > 0 and all(x is not None and np.isfinite(x) for x in v) and any(v) for _, v in rows]
    d = max(len(v) for (_, v), k in zip(rows, ok, strict=True) if k)
    m = np.array([np.array(v, float) / np.linalg.norm(v) if k else np.zeros(d) for (_, v), k in zip(rows, ok, strict=True)])
    near = m @ m.T >= cosine
    np.fill_diagonal(near, False)
    return dict(zip(ids, near.sum(1).tolist(), strict=True)), near


def planted(n=600, d=64, seed=1):
    rng = np.random.default_rng(seed)
    base = rng.normal(size=(n, d))
    rows = [(i, v.astype(np.float32).tolist()) for i, v in enumerate(base)]
    for k in range(200):
        v = base[k] / np.linalg.norm(base[k])
        e = rng.normal(size=d)
        e -= (e @ v) * v
        e /= np.linalg.norm(e)
        c = rng.uniform(0.88, 0.999)
        rows.append((n + k, (c * v + np.sqrt(1 - c * c) * e).astype(np.float32).tolist()))
    return rows


@pytest.mark.parametrize("bucket", [2048, 2])
def test_recall_and_precision(spark, bucket):
    rows = planted() + [(2000 + i, [1.0] * 64) for i in range(50)]
    got = {r["vec_id"]: r for r in embeddings.vector_links(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), bucket=bucket).collect()}
    want, _ = brute(rows)
    assert all(got[i]["n_links"] <= want[i] for i in want)
    assert sum(r["n_links"] for r in got.values()) >= 0.93 * sum(want.values())
    assert {got[2000 + i]["component_id"] for i in range(50)} == {2000} and got[2001]["n_links"] == 49


def test_given_table(spark, small):
    rows = [(r["vec_id"], r["embedding"]) for r in spark.read.parquet(f"{small}/embeddings.parquet").collect()]
    want, _ = brute(rows)
    got = {r["vec_id"]: r["n_links"] for r in embeddings.query(spark, small).collect()}
    assert sum(got.values()) >= 0.9 * sum(want.values()) and all(got[i] <= want[i] for i in want)


def test_odd_vectors(spark):
    rows = [(1, None), (2, []), (3, [0.0, 0.0]), (4, [1.0, None]), (5, [float("nan"), 1.0]), (6, [float("inf"), 1.0]), (7, [1.0, 0.0]), (8, [1.0, 0.0]), (8, [1.0, 0.0]), (9, [1.0, 0.0, 0.0]), (None, [1.0, 0.0])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = embeddings.vector_links(frame).collect()
    assert len(got) == len(rows)
    by = {r["vec_id"]: r for r in got}
    assert all(by[k]["n_links"] == 0 and by[k]["component_id"] == k for k in (1, 2, 3, 4, 5, 6, 9))
    assert by[8]["component_id"] == 7 and by[7]["n_links"] == 2
    assert embeddings.vector_links(frame.limit(0)).count() == 0
