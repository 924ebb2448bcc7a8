import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from crossaudit.operators import adapt, dedup, encode, neardup, ontology, probe, ranks, stats, transfer, zeroshot
from crossaudit.operators.components import connected_components

MATRIX = "train_domain string, test_domain string, caf1 double"


def published(spark):
    """Printed binary cells of one encoder for two domains."""
    return spark.createDataFrame([("NOISY", "NOISY", 0.422), ("LARGE", "LARGE", 0.730), ("NOISY", "LARGE", 0.561), ("LARGE", "NOISY", 0.695)], MATRIX)


def test_published_gap_and_asymmetry(spark):
    g = transfer.gaps(published(spark)).agg(F.avg(F.abs("gap"))).first()[0]
    assert g == pytest.approx(0.221, abs=6e-4)
    assert transfer.asymmetry(published(spark)).first()["asymmetry"] == pytest.approx(0.134, abs=1e-6)
    assert [r["train_domain"] for r in transfer.gaps(published(spark)).where("reversed").collect()] == ["LARGE"]


def test_ratio_of_a_constant_matrix_is_zero(spark):
    rows = [(a, b, 0.5) for a, b in itertools.product("xyz", repeat=2)]
    got = transfer.negative_transfer_ratio(spark.createDataFrame(rows, MATRIX)).first()
    assert (got["ntr"], got["n_off"], got["n_diag"]) == (0.0, 6, 3)
    one = transfer.negative_transfer_ratio(spark.createDataFrame(rows[:2], MATRIX)).first()
    assert one["n_off"] == 0 and one["ntr"] is None


def test_published_deviation_and_bounds(spark):
    runs = spark.createDataFrame([(0.7025,), (0.2727,), (0.3849,)], "score double").withColumn("k", F.lit(1))
    assert stats.seed_summary(runs, ["k"]).first()["std"] == pytest.approx(0.223, abs=6e-4)
    for (k, n), low in {(30, 30): 0.884, (90, 90): 0.960, (87, 90): 0.906, (29, 30): 0.828, (81, 90): 0.819, (27, 30): 0.735}.items():
        assert stats.exact_bounds(k, n)[0] == pytest.approx(low, abs=6e-4)


def test_false_discovery_control(spark):
    ps = [0.001, 0.008, 0.039, 0.041, 0.042, 0.06, 0.074, 0.205, 0.212, 0.216]
    rows = stats.bh_adjust(spark.createDataFrame([(p, f"d{i}", "t") for i, p in enumerate(ps)], "p double, train_domain string, test_domain string")).orderBy("p").collect()
    want = [min(min(1.0, p * len(ps) / (j + 1)) for j, p in list(enumerate(ps))[i:]) for i in range(len(ps))]
    assert [r["p_adj"] for r in rows] == pytest.approx(want, abs=1e-6)
    assert [r["keep"] for r in rows] == [w <= 0.05 for w in want]


def test_scores_against_hand_count(spark):
    rows = [("a", "a")] * 3 + [("a", "b")] + [("b", "b")] * 2 + [("b", "c")]
    df = spark.createDataFrame([(*r, "x", "y") for r in rows], "truth string, pred string, train_domain string, test_domain string")
    got = transfer.transfer_matrix(df).first()
    f1 = [6 / 7, 4 / 6, 0.0]
    assert got["caf1"] == pytest.approx(np.mean(f1), abs=1e-6) and got["uar"] == pytest.approx((3 / 4 + 2 / 3) / 2, abs=1e-6)
    declared = transfer.overall(transfer.confusion(df, ["test_domain"]), ["test_domain"], class_set="declared", declared=["a", "b"]).first()
    assert declared["caf1"] == pytest.approx(np.mean(f1[:2]), abs=1e-6)


def test_item_and_cluster_resampling_agree_on_single_items(spark):
    rows = [(i, f"g{i:02d}", s, "T", "a" if i % 2 else "b", "a" if (i + (s == "S") * (i % 3 == 0)) % 2 else "b") for i in range(24) for s in ("S", "T")]
    preds = spark.createDataFrame(rows, "item_id long, group_id string, train_domain string, test_domain string, truth string, pred string").withColumn("item_id", F.format_string("g%02d", "item_id"))
    a, b = (stats.paired_bootstrap(preds, 20, unit=u).first() for u in ("group_id", "item_id"))
    assert a == b and a["delta"] < 0


def test_components_against_union_find(spark):
    rng = np.random.default_rng(1)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 60, (45, 2))] + [(100 + i, 101 + i) for i in range(40)]
    parent = {x: x for e in edges for x in e}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        x, y = root(a), root(b)
        parent[max(x, y)] = min(x, y)
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame([*edges, (None, 3)], "src long, dst long")).collect()}
    assert got == {x: root(x) for e in edges if e[0] != e[1] for x in e}
    assert connected_components(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_key_modes(spark):
    rows = [(1, "A", "x", "n1"), (2, "B", "x", "n2"), (3, "B", "y", "n2"), (4, "A", "z", "n4")]
    items = spark.createDataFrame(rows, "item_id long, domain string, digest string, name string")
    left = {m: sorted(r["item_id"] for r in dedup.exact_dedup(items, m)[0].collect()) for m in ("hash", "name", "both", "either")}
    assert left == {"hash": [1, 3, 4], "name": [1, 2, 4], "both": [1, 2, 3, 4], "either": [1, 4]}


def test_conflicts_inside_one_domain_do_not_count(spark):
    rows = [("k1", "A", "x"), ("k1", "A", "y"), ("k2", "A", "x"), ("k2", "B", "y"), ("k3", "A", "x"), ("k3", "B", "x")]
    got = ontology.label_conflicts(spark.createDataFrame(rows, "k string, domain string, raw_label string"), [F.col("k")], F.col("raw_label")).collect()
    assert [r["key_0"] for r in got] == ["k2"]


def test_banded_pairs_against_exact(spark):
    rng = np.random.default_rng(2)
    base = rng.normal(size=(60, 32))
    rows = [(i, "AB"[i % 2], v.tolist()) for i, v in enumerate(base)] + [(100 + i, "BA"[i % 2], (v + 0.05 * rng.normal(size=32)).tolist()) for i, v in enumerate(base)]
    v = spark.createDataFrame(rows, "item_id long, domain string, features array<double>")
    exact = {(r["left_id"], r["right_id"]) for r in neardup.blocked_cosines(v, 0.95, block=40).collect()}
    banded = {(r["left_id"], r["right_id"]) for r in neardup.near_pairs_lsh(v, 0.95).collect()}
    assert len(exact) == 60 and banded <= exact and len(banded) >= 57


def test_banded_pairs_are_those_that_share_a_band_and_are_compared_in_their_bucket(spark, monkeypatch):
    rng = np.random.default_rng(8)
    base = rng.normal(size=(40, 16))
    x = np.concatenate([base, base + 0.25 * rng.normal(size=(40, 16)), base[:1] + 0.1 * rng.normal(size=(60, 16)), np.zeros((2, 16))])
    domain = ["ABC"[k] for k in rng.integers(0, 3, len(x))]
    v = spark.createDataFrame([(3 * i, domain[i], x[i].tolist()) for i in range(len(x))], "item_id long, domain string, features array<double>").repartition(3)
    unit = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
    cos = unit @ unit.T
    signs = (x @ np.random.default_rng(5).normal(size=(16, 4 * 6)) >= 0).reshape(len(x), 4, 6)
    meet = (signs[:, None] == signs[None]).all(axis=3).any(axis=2)
    near = [(i, j) for i in range(len(x)) for j in range(i + 1, len(x)) if domain[i] != domain[j] and cos[i, j] >= 0.93]
    want = {(3 * i, 3 * j): cos[i, j] for i, j in near if meet[i, j]}
    assert 500 < len(want) < len(near)
    for tile, block in ((512, 2048), (7, 11)):
        monkeypatch.setattr(neardup, "TILE", tile)
        monkeypatch.setattr(neardup, "BLOCK", block)
        rows = neardup.near_pairs_lsh(v, 0.93, 4, 6).collect()
        assert len(rows) == len(want) and {(r["left_id"], r["right_id"]): r["cos"] for r in rows} == pytest.approx(want)
    kept = []
    real = neardup.materialize
    monkeypatch.setattr(neardup, "materialize", lambda df, name, *by: kept.append(df._jdf.queryExecution().optimizedPlan().toString()) or real(df, name, *by))
    plan = neardup.near_pairs_lsh(v, 0.93, 4, 6)._jdf.queryExecution().optimizedPlan().toString()
    # no join makes the pairs of a bucket, no distinct removes a pair's copies, no vector follows each pair
    assert len(kept) == 1 and "Join" not in kept[0] and plan.count("Join") == 1 and plan.count("Aggregate") == 1
    assert neardup.near_pairs_lsh(v.where("false"), 0.93).count() == 0


def test_blocked_pairs_and_counts_against_all_pairs(spark):
    rng = np.random.default_rng(6)
    base = rng.normal(size=(90, 16))
    x = np.concatenate([base, base[:60] + 0.08 * rng.normal(size=(60, 16)), base[:5], np.zeros((1, 16))])
    domain = [("A", "B", "C")[k] for k in rng.integers(0, 3, len(x))]
    v = spark.createDataFrame([(7 * i, domain[i], x[i].tolist()) for i in range(len(x))], "item_id long, domain string, features array<double>")
    unit = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
    cos = unit @ unit.T
    apart = [(i, j) for i in range(len(x)) for j in range(i + 1, len(x)) if domain[i] != domain[j]]
    for block in (10, 1000):
        got = {(r["left_id"], r["right_id"]): r["cos"] for r in neardup.blocked_cosines(v, 0.9, block=block).collect()}
        assert got == pytest.approx({(7 * i, 7 * j): cos[i, j] for i, j in apart if cos[i, j] >= 0.9})
    whole = {(r["domain_a"], r["domain_b"]): (r["max_cos"], r["n500"], r["n950"]) for r in neardup.cosine_audit(v, (0.5, 0.95)).collect()}
    for d, e in (("A", "B"), ("A", "C"), ("B", "C")):
        own = [cos[i, j] for i, j in apart if {domain[i], domain[j]} == {d, e}]
        assert whole[d, e] == (pytest.approx(max(own), abs=1e-6), sum(c > 0.5 for c in own), sum(c > 0.95 for c in own))
    assert neardup.blocked_cosines(v.where("false"), 0.9).count() == 0


def test_blocked_pairs_shuffle_no_vector_per_pair_of_blocks(spark):
    v = spark.range(300).selectExpr("id AS item_id", "if(id % 2 = 0, 'A', 'B') AS domain", "array(cos(id), sin(id)) AS features")
    for thresholds in ((), (0.95,)):
        plan = neardup.blocked_cosines(v, 0.9, thresholds, block=10)._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan and "Generate" not in plan


def near_copies(spark):
    """Ten groups of forty near copies over three domains, some pairs equal and so tied, and some labels missing."""
    rng = np.random.default_rng(9)
    base = np.repeat(rng.normal(size=(10, 12)), 40, axis=0)
    x = base + 0.02 * rng.normal(size=base.shape) * (np.arange(400) % 4 > 0)[:, None]
    rows = [(3 * i - 50, "ABC"[i % 3], [None, "x", "y"][i % 7 % 3], x[i].tolist()) for i in range(400)]
    return spark.createDataFrame(rows, "item_id long, domain string, label string, features array<double>")


def test_best_partners_and_summaries_equal_those_of_all_pairs(spark):
    v = near_copies(spark)
    pairs = neardup.blocked_cosines(v.drop("label"), 0.9)
    whole = sorted(map(tuple, neardup.mutual_best(pairs.withColumn("cos", F.round("cos", 6))).collect()))
    summary = tuple(neardup.pair_summary(pairs, v.select("item_id", "label")).first())
    assert len(whole) > 10 and summary[0] > 4000 and 0 < summary[2] < 1
    for block in (50, 1000):
        assert sorted(map(tuple, neardup.best_cosines(v.drop("label"), 0.9, block=block).collect())) == whole
        assert tuple(neardup.near_summary(v, 0.9, block=block).first()) == summary
    assert neardup.best_cosines(v.drop("label").where("false"), 0.9).count() == 0
    assert tuple(neardup.near_summary(v.where("false"), 0.9).first()) == (0, 0, None)


def test_queries_of_best_partners_and_summaries_write_and_shuffle_no_pairs(spark, monkeypatch):
    from crossaudit.plans import leaks

    v = near_copies(spark)
    monkeypatch.setattr(leaks, "vectors", lambda *_: v.withColumnRenamed("label", "class"))
    monkeypatch.setattr(leaks, "materialize", lambda df, name: pytest.fail(f"{name} is written"))
    for q in (leaks.mutual_best_pairs, leaks.near_pair_summary):
        plan = q(spark, None)._jdf.queryExecution().executedPlan().toString()
        # what is first shuffled has gone through a task's own reduction of the pairs
        first = plan[: plan.rindex("CartesianProduct")]
        assert first.count("MapInArrow") == 2 * plan.count("CartesianProduct") and "Window" not in plan


def test_paired_contrast_and_crossover(spark):
    rows = [(a, b, e, s, 0.5 + (0.1 if a == "B" and b >= 10 else 0.0) - (0.05 if a == "B" and b < 10 else 0) + 0.001 * e) for a in "AB" for b in (1, 10) for e in range(5) for s in (42, 43)]
    scores = spark.createDataFrame(rows, "arm string, budget int, episode int, seed int, score double")
    got = {r["budget"]: r for r in adapt.paired_contrast(scores, "B", "A").collect()}
    assert got[1]["mean"] == pytest.approx(-0.05) and got[10]["mean"] == pytest.approx(0.1) and got[10]["n"] == 5
    assert adapt.paired_contrast(scores, "B", "A", "run").where("budget = 1").first()["n"] == 10
    assert adapt.crossover(adapt.paired_contrast(scores, "B", "A")).first()["crossover"] == 10


def test_fisher_tail_against_integration(spark):
    x = -2 * sum(math.log(p) for p in (0.04, 0.2, 0.5))
    grid = np.linspace(x, x + 200, 400_001)
    density = grid**2 * np.exp(-grid / 2) / 16  # chi-squared with six degrees of freedom
    tail = float(((density[1:] + density[:-1]) / 2 * np.diff(grid)).sum())
    got = spark.range(1).select(stats.fisher_combine(F.lit(x), F.lit(3)).alias("p")).first()["p"]
    assert got == pytest.approx(tail, rel=1e-6)


def probe_rows(spark, shift=1.5):
    rng = np.random.default_rng(4)
    rows = []
    for i in range(400):
        y = "abc"[i % 3]
        x = rng.normal(size=4) + shift * np.eye(4)[i % 3]
        rows.append(("e", i, "AB"[i % 2], f"g{i // 4}", ("train", "train", "val", "test")[i // 2 % 4], y, x.tolist()))
    return spark.createDataFrame(rows, "encoder string, item_id long, domain string, group_id string, split string, y string, features array<double>")


def test_logistic_solver_reaches_the_minimum():
    rng = np.random.default_rng(5)
    for classes in (2, 3):
        x, y = rng.normal(size=(90, 3)), rng.integers(0, classes, 90)
        weight = (len(y) / (classes * np.bincount(y)))[y]

        def loss(w, c=0.5, x=x, y=y, weight=weight, classes=classes):
            z = x @ w[:, :-1].T + w[:, -1]
            z = z - z.max(axis=1, keepdims=True)
            own = (w[1:] if classes == 2 else w)[:, :-1]
            return 0.5 * (own**2).sum() - c * (weight * (z[np.arange(len(y)), y] - np.log(np.exp(z).sum(axis=1)))).sum()

        w = probe.solve_logistic(x, y, weight, classes, 0.5)
        best = loss(w)
        for _ in range(200):
            step = rng.normal(size=w.shape) * 1e-3
            if classes == 2:
                step[0] = 0
            assert loss(w + step) >= best - 1e-9


def test_grid_reaches_the_probes_and_they_learn(spark):
    rows = probe_rows(spark)
    got = probe.grouped_probes(rows).collect()
    assert {r["model"] for r in got} == {"A", "B"}
    for r in got:
        sizes = [round(p["size"], 9) for p in r["path"]]
        probe.assert_grid_effect([(p["c"], p["val_caf1"], [p["size"]]) for p in r["path"]])
        assert sizes == sorted(sizes) and r["val_caf1"] == max(p["val_caf1"] for p in r["path"])
    test = rows.where("split = 'test'").select("encoder", "item_id", F.col("y").alias("truth"), F.col("features").alias("x"))
    preds = probe.score_probes(test, probe.grouped_probes(rows)).collect()
    assert len(preds) == 2 * test.count() and np.mean([r["truth"] == r["pred"] for r in preds]) > 0.7
    one = probe.grouped_probes(rows.where("y = 'a'")).collect()
    assert all([c["pred"] for c in r["classes"]] == ["a"] for r in one)


def test_two_level_sums_equal_one_order(spark):
    import hashlib

    rows = [(k, i, i % 5) for k in "xy" for i in range(300)]
    frame = spark.createDataFrame(rows, "k string, i long, v long")
    got = {(r["k"], r["i"]): (r["before"], r["total"]) for r in ranks.running(frame, ["k"], F.md5(F.col("i").cast("string").cast("binary")), "i", F.col("v"), digits=1).collect()}
    for k in "xy":
        order, before = sorted(range(300), key=lambda i: (hashlib.md5(str(i).encode()).hexdigest(), i)), 0
        for i in order:
            assert got[k, i] == (before, sum(j % 5 for j in range(300)))
            before += i % 5


def test_row_local_grams_and_fingerprints(spark):
    import hashlib
    import random

    import regex

    rng = random.Random(6)
    texts = ["".join(rng.choice("ab\u00e9 \n.\U0001f600X") for _ in range(rng.randint(0, 60))) for _ in range(60)] + [None, "", "one", "a b"]
    docs = spark.createDataFrame(list(enumerate(texts)), "item_id long, text string")
    words = [[w for w in regex.split(r"[^\p{L}0-9]+", (t or "").lower()) if w] for t in texts]
    kinds = {
        "char3": [[t[i : i + 3] for i in range(len(t) - 2)] or [t] for t in (x or "" for x in texts)],
        "word": words,
        "word2": [[" ".join(w[i : i + 2]) for i in range(max(1, len(w) - 1))] if w else [] for w in words],
    }
    for kind, grams in kinds.items():
        got = {r["item_id"]: r["features"] for r in encode.hashed(docs, kind, 16).collect()}
        assert set(got) == {i for i, g in enumerate(grams) if g}
        for i, g in enumerate(grams):
            if g:
                n = np.bincount([int(hashlib.md5(x.encode()).hexdigest()[:4], 16) % 16 for x in g], minlength=16)
                assert got[i] == pytest.approx((n / np.linalg.norm(n)).tolist())
    prints = {r["item_id"]: (r["hi"] << 32) | r["lo"] for r in neardup.simhash(docs).collect()}
    for i, own in enumerate(words):
        codes = [int(hashlib.md5(w.encode()).hexdigest()[:16], 16) for w in own]
        assert prints[i] == sum(1 << k for k in range(64) if sum(1 if c >> k & 1 else -1 for c in codes) > 0)


def test_calls_that_fail_keep_their_error(spark):
    def predict(text):
        if text == "bad":
            raise ValueError("no answer")
        return "it is brief"

    items = spark.createDataFrame([(1, "fine"), (2, "bad")], "item_id long, text string")
    got = {r["item_id"]: r for r in zeroshot.zero_shot(items, predict, ["brief", "medium"], parallel=1, tries=2).collect()}
    assert got[1]["pred"] == "brief" and got[1]["error"] is None
    assert got[2]["pred"] == zeroshot.UNPARSED and got[2]["error"] == "ValueError: no answer"


def test_entry_imports():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
