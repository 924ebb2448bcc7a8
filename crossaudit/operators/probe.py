"""Probes fitted by Spark ML: regularised logistic regression with a tuned constant, and boosted trees."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.ml.classification import GBTClassifier, LogisticRegression, MultilayerPerceptronClassifier, OneVsRest
from pyspark.ml.feature import StandardScaler
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crossaudit.operators.transfer import overall

GRID = (0.01, 0.1, 1.0, 10.0)


def balanced(train: DataFrame, label: str = "y") -> DataFrame:
    """Rows with ``weight`` = N / (M N_c) and ``label``, the class's number by name."""
    per = train.groupBy(label).agg(F.count(F.lit(1)).alias("n_c"))
    rows = {r[label]: r["n_c"] for r in per.orderBy(label).collect()}  # one row a class
    total = sum(rows.values())
    table = train.sparkSession.createDataFrame([(c, float(i), total / (len(rows) * n)) for i, (c, n) in enumerate(sorted(rows.items()))], f"{label} string, label double, weight double")
    return train.join(F.broadcast(table), label)


def fit_probe(train: DataFrame, val: DataFrame, features: tuple[str, ...], grid: tuple[float, ...] = GRID, label: str = "y"):
    """``(model function, chosen C, path)``: the constant with the best class-averaged F1 on validation, ties to the smallest.

    The usual C scales the loss's sum and Spark averages it by weight, so the penalty is 1 / (C times the weights' sum);
    features are scaled beforehand, with deviations of the sample. Two classes take the binomial family. A single
    training class gives a constant predictor.
    """
    vector = array_to_vector(F.array(*[F.col(f).cast("double") for f in features]))
    rows = balanced(train, label).withColumn("raw", vector).cache()
    classes = [r[label] for r in rows.select(label).distinct().orderBy(label).collect()]
    names = F.array(*[F.lit(c) for c in classes])
    if len(classes) < 2:
        return (lambda df: df.withColumn("pred", F.lit(classes[0] if classes else None))), None, []
    scaler = StandardScaler(inputCol="raw", outputCol="features", withMean=True).fit(rows)
    scaled, weights = scaler.transform(rows), rows.agg(F.sum("weight")).first()[0]
    models, path = {}, []
    for c in grid:
        lr = LogisticRegression(weightCol="weight", regParam=1 / (c * weights), elasticNetParam=0.0, maxIter=5000, standardization=False, family="binomial" if len(classes) == 2 else "multinomial")
        models[c] = lr.fit(scaled)

        def apply(df, m=models[c]):
            out = m.transform(scaler.transform(df.withColumn("raw", vector)))
            return out.withColumn("pred", F.element_at(names, (F.col("prediction") + 1).cast("int"))).drop("raw", "features", "rawPrediction", "probability", "prediction")

        counts = apply(val).groupBy(F.col(label).alias("truth"), "pred").agg(F.count(F.lit(1)).alias("n")).withColumn("k", F.lit(1))
        score = overall(counts, ["k"]).first()
        path.append((c, score["caf1"] if score else None, [round(float(x), 9) for x in models[c].coefficientMatrix.toArray().ravel()], apply))
    rows.unpersist()
    best = min(path, key=lambda p: (-(p[1] if p[1] is not None else -1), p[0]))
    return best[3], best[0], [(c, s, w) for c, s, w, _ in path]


def assert_grid_effect(path: list) -> None:
    """The grid's values must reach the estimator: coefficients differ between them."""
    if len({tuple(w) for _, _, w in path}) != len(path):
        raise AssertionError("some grid values gave the same model")


def fit_boosted(train: DataFrame, features: tuple[str, ...], label: str = "y", trees: int = 10):
    """Boosted trees with balanced weights, one class against the rest; returns a function that adds ``pred``."""
    vector = array_to_vector(F.array(*[F.col(f).cast("double") for f in features]))
    rows = balanced(train, label).withColumn("features", vector)
    classes = [r[label] for r in rows.select(label).distinct().orderBy(label).collect()]
    tree = GBTClassifier(maxIter=trees, maxDepth=3, seed=42, weightCol="weight")
    model = (tree if len(classes) == 2 else OneVsRest(classifier=tree, weightCol="weight")).fit(rows)
    names = F.array(*[F.lit(c) for c in classes])
    return lambda df: model.transform(df.withColumn("features", vector)).withColumn("pred", F.element_at(names, (F.col("prediction") + 1).cast("int")))


def fit_network(train: DataFrame, features: tuple[str, ...], label: str = "y", hidden: tuple[int, ...] = (16,), step: float = 0.3, epochs: int = 5, seed: int = 42):
    """A small network as a stand-in for fine-tuning arms: a high step and few epochs for the full one, a low step for the
    stabilised one. It claims no equivalence with fine-tuned encoders. Returns a function that adds ``pred``."""
    vector = array_to_vector(F.array(*[F.col(f).cast("double") for f in features]))
    rows = balanced(train, label).withColumn("raw", vector)
    classes = [r[label] for r in rows.select(label).distinct().orderBy(label).collect()]
    scaler = StandardScaler(inputCol="raw", outputCol="features", withMean=True).fit(rows)
    net = MultilayerPerceptronClassifier(layers=[len(features), *hidden, max(2, len(classes))], maxIter=epochs, stepSize=step, solver="gd" if step >= 0.1 else "l-bfgs", seed=seed)
    model = net.fit(scaler.transform(rows))
    names = F.array(*[F.lit(c) for c in classes])
    return lambda df: model.transform(scaler.transform(df.withColumn("raw", vector))).withColumn("pred", F.element_at(names, (F.col("prediction") + 1).cast("int")))


#: Rows of a domain and split, about, that a grouped probe is fitted on; a hash of the id draws them.
GROUPED = 20_000


def solve_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, classes: int, c: float, steps: int = 100) -> np.ndarray:
    """(classes, d + 1) coefficients that minimise half their squares plus ``c`` times the weighted log loss; intercepts (last) are not shrunk.

    Newton steps, halved until the objective falls. Two classes are binomial (one set of coefficients), more are multinomial.
    """
    n, d = x.shape
    x = np.column_stack([x, np.ones(n)])
    k = 1 if classes == 2 else classes
    shrink = np.append(np.ones(d), 1e-9)
    beta, target = np.zeros((k, d + 1)), np.eye(classes)[y][:, classes - k :]

    def both(b: np.ndarray) -> tuple[float, np.ndarray]:
        z = x @ b.T
        z = np.column_stack([np.zeros(n), z]) if k == 1 else z
        z = z - z.max(axis=1, keepdims=True)
        q = np.exp(z)
        q /= q.sum(axis=1, keepdims=True)
        return 0.5 * float((b * b * shrink).sum()) - c * float(weight @ np.log(np.maximum(q[np.arange(n), y], 1e-300))), q[:, classes - k :]

    value, q = both(beta)
    for _ in range(steps):
        grad = (c * (weight[:, None] * (q - target)).T @ x + beta * shrink).ravel()
        hess = np.zeros((k * (d + 1), k * (d + 1)))
        for i in range(k):
            for j in range(k):
                w = c * weight * (q[:, i] * ((i == j) - q[:, j]))
                hess[i * (d + 1) : (i + 1) * (d + 1), j * (d + 1) : (j + 1) * (d + 1)] = (x * w[:, None]).T @ x + (np.diag(shrink) if i == j else 0)
        step = np.linalg.solve(hess + 1e-9 * np.eye(len(hess)), grad).reshape(k, d + 1)
        size = 1.0
        while size > 1e-6:
            new, fresh = both(beta - size * step)
            if new <= value:
                break
            size /= 2
        done = value - new < 1e-10 * max(1.0, abs(value)) or size <= 1e-6
        if new <= value:
            beta, value, q = beta - size * step, new, fresh
        if done:
            break
    return np.vstack([np.zeros(d + 1), beta]) if k == 1 else beta


def class_f1(truth: np.ndarray, pred: np.ndarray) -> float:
    """Mean F1 over the classes of truth and predictions."""
    out = [2 * np.sum((truth == c) & (pred == c)) / (np.sum(truth == c) + np.sum(pred == c)) for c in np.unique(np.concatenate([truth, pred]))]
    return float(np.mean(out)) if out else float("nan")


PROBES = "encoder string, model string, c double, val_caf1 double, m array<double>, s array<double>, classes array<struct<pred:string,w:array<double>>>, path array<struct<c:double,val_caf1:double,size:double>>"


def grouped_probes(rows: DataFrame, grid: tuple[float, ...] = GRID, sample: int = GROUPED) -> DataFrame:
    """A tuned logistic probe for every encoder and domain, all fitted in one stage: ``encoder, model, c, val_caf1, m, s, classes, path``.

    ``rows`` has ``encoder, domain, split, item_id, y, features``. The constant is chosen on the domain's own validation split by class-averaged F1, ties to the
    smallest; ``path`` keeps every constant's score and size of coefficients. Features are scaled by the training rows, weights balance classes.
    A domain of one class predicts it.
    """
    live = rows.where("split in ('train', 'val')")
    size = live.groupBy("encoder", "domain", "split").agg(F.count(F.lit(1)).alias("rows_"))
    place = F.pmod(F.xxhash64("item_id"), F.lit(1 << 20)) / float(1 << 20)
    drawn = live.join(F.broadcast(size), ["encoder", "domain", "split"]).where(place * F.col("rows_") < sample).select("encoder", "domain", "split", "y", "features")

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        train, val = pdf[pdf["split"] == "train"], pdf[pdf["split"] == "val"]
        classes = sorted(train["y"].unique())
        if not classes:
            return pd.DataFrame(columns=["encoder", "model", "c", "val_caf1", "m", "s", "classes", "path"])
        x = np.stack(train["features"].to_numpy()).astype(float)
        m, s = x.mean(axis=0), x.std(axis=0)
        scale = lambda v: np.divide(v - m, s, out=np.zeros_like(v), where=s > 1e-12)
        y = np.searchsorted(classes, train["y"].to_numpy())
        weight = (len(y) / (len(classes) * np.bincount(y)))[y]
        held = scale(np.stack(val["features"].to_numpy()).astype(float)) if len(val) else np.zeros((0, x.shape[1]))
        best, path = None, []
        for c in grid:
            w = solve_logistic(scale(x), y, weight, len(classes), c) if len(classes) > 1 else np.zeros((1, x.shape[1] + 1))
            pred = np.array(classes, object)[(held @ w[:, :-1].T + w[:, -1]).argmax(axis=1)]
            score = class_f1(val["y"].to_numpy(), pred) if len(val) else float("nan")
            path.append({"c": c, "val_caf1": score, "size": float(np.abs(w[:, :-1]).sum())})
            if best is None or score > best[0]:
                best = (score, c, w)
        rows = [{"pred": p, "w": v.tolist()} for p, v in zip(classes, best[2], strict=True)]
        return pd.DataFrame([[key[0], key[1], best[1], best[0], m.tolist(), np.where(s > 1e-12, s, 0.0).tolist(), rows, path]], columns=["encoder", "model", "c", "val_caf1", "m", "s", "classes", "path"])

    return drawn.groupBy("encoder", "domain").applyInPandas(run, PROBES)


def score_probes(rows: DataFrame, probes: DataFrame) -> DataFrame:
    """Rows (``encoder, x`` and others) with ``model, pred`` under every probe of their encoder; the probes, a few rows, are broadcast."""
    z = F.zip_with(F.zip_with("x", "m", lambda a, b: a - b), "s", lambda a, b: F.coalesce(F.try_divide(a, b), F.lit(0.0)))
    pairs = rows.join(F.broadcast(probes.select("encoder", "model", "m", "s", "classes")), "encoder").withColumn("z", F.concat(z, F.array(F.lit(1.0))))
    value = lambda c: F.aggregate(F.zip_with("z", c["w"], lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    best = F.array_min(F.transform("classes", lambda c: F.struct((-F.round(value(c), 9)).alias("v"), c["pred"].alias("pred"))))
    return pairs.withColumn("pred", best["pred"]).drop("x", "z", "m", "s", "classes")
