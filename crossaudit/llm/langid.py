"""Language identification by words first, character n-grams where words fail.

Training counts words by language; a word kept by the model scores with its smoothed log frequency in each language.
A word it does not know backs off to the longest character n-grams of which at least one is known (from four letters
down to one) and scores with their mean. A text's language has the largest sum.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crossaudit.llm.kept import content_id, held
from crossaudit.llm.words import fold_doc_id, free_names

UNKNOWN = "und"
LONGEST = 4
#: Expected training rows of each language: the documented bound of the sample that the model is fitted on.
SAMPLE = 4000
#: A word or n-gram is kept from one part in so many of its language's, so a language keeps at most so many.
PARTS = 30_000
#: Most languages of a model; more is an error. With ``SAMPLE`` and ``PARTS`` this bounds what is collected and broadcast.
LANGUAGES = 8192
#: Bytes, about, that the kept words of a worker may take.
_KEPT_BYTES = 60_000_000
_TEXTS = 2000
_NOT_LETTERS = r"[^\p{L}\p{M}]+"


@dataclass
class Model:
    """Log frequencies by language: ``tables[0]`` of words, ``tables[n]`` of n-grams; ``floor`` for what a level lacks."""

    languages: list[str]
    prior: np.ndarray
    tables: list[dict[str, np.ndarray]]
    floors: list[np.ndarray]


def _words(text):
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), _NOT_LETTERS), lambda w: w.rlike("\\p{L}"))


def fit(rows: DataFrame, sample: int = SAMPLE, parts: int = PARTS, longest: int = LONGEST) -> Model:
    """Model of ``text, lang`` rows; rows without language are ignored.

    From each language about ``sample`` rows are drawn by a hash of the text, or all if there are fewer: equal texts together.
    Null and empty texts teach nothing but their language's share; no rows give a model that knows no language.
    """
    rows = rows.where("lang is not null")
    share = {r["lang"]: sample / r["n"] for r in rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    if len(share) > LANGUAGES:
        raise ValueError(f"{len(share)} languages; a model has {LANGUAGES} at most")
    if not share:
        return Model([], np.zeros(0), [{} for _ in range(longest + 1)], [np.zeros(0)] * (longest + 1))
    part = rows.sparkSession.createDataFrame(sorted(share.items()), "lang string, share double")
    drawn = rows.join(F.broadcast(part), "lang").where((F.pmod(F.xxhash64("text"), F.lit(1 << 20)) / float(1 << 20)) < F.col("share"))
    counts = drawn.select("lang", F.explode(_words(F.col("text"))).alias("w")).groupBy("lang", "w").agg(F.count(F.lit(1)).alias("n"))
    total = counts.groupBy("lang").agg(F.sum("n").alias("total"))
    kept = counts.join(F.broadcast(total), "lang").where((F.col("n") >= 2) & (F.col("n") * parts >= F.col("total"))).select("lang", "w", "n", "total").collect()
    languages = sorted(share)
    at = {x: i for i, x in enumerate(languages)}
    docs = np.array([sample / share[x] for x in languages])
    raw: list[dict[str, np.ndarray]] = [{} for _ in range(longest + 1)]
    totals = np.zeros((longest + 1, len(languages)))
    for r in kept:
        k, w, n = at[r["lang"]], r["w"], r["n"]
        totals[0, k] = r["total"]
        raw[0].setdefault(w, np.zeros(len(languages)))[k] += n
        padded = f"<{w}>"
        for size in range(1, longest + 1):
            for i in range(len(padded) - size + 1):
                raw[size].setdefault(padded[i : i + size], np.zeros(len(languages)))[k] += n
                totals[size, k] += n
    tables, floors = [], []
    for table, total in zip(raw, totals, strict=True):
        size = len(table) + 1
        tables.append({w: np.log((n + 0.5) / (total + 0.5 * size)).astype(np.float32) for w, n in table.items()})
        floors.append(np.log(0.5 / (total + 0.5 * size)).astype(np.float32))
    return Model(languages, np.log(docs / docs.sum()).astype(np.float32), tables, floors)


class Scorer:
    """Scores words by the model and keeps them, up to a bound."""

    def __init__(self, model: Model):
        self.model = model
        self.clear()

    def clear(self) -> None:
        self.row: dict[str, int] = {}
        self.rows = np.zeros((1024, len(self.model.languages)), np.float32)

    def score(self, word: str) -> np.ndarray:
        m = self.model
        if (known := m.tables[0].get(word)) is not None:
            return known
        padded = f"<{word}>"
        for size in range(min(len(m.tables) - 1, len(padded)), 0, -1):
            table = m.tables[size]
            found = [table.get(padded[i : i + size]) for i in range(len(padded) - size + 1)]
            if any(x is not None for x in found):
                return sum(m.floors[size] if x is None else x for x in found) / len(found)
        return np.zeros(len(m.languages), np.float32)

    def index(self, words: list[str]) -> np.ndarray:
        """Rows of ``self.rows`` for the words."""
        if len(self.row) * (4 * self.rows.shape[1] + 150) > _KEPT_BYTES:
            self.clear()
        out = np.empty(len(words), np.int64)
        for i, w in enumerate(words):
            k = self.row.get(w)
            if k is None:
                k = self.row[w] = len(self.row)
                if k >= len(self.rows):
                    self.rows = np.concatenate([self.rows, np.zeros_like(self.rows)])
                self.rows[k] = self.score(w)
            out[i] = k
        return out

    def texts(self, texts: pa.Array) -> tuple[list[str], np.ndarray]:
        """Language and its posterior probability of each text."""
        m, n = self.model, len(texts)
        lower = pc.utf8_lower(pc.fill_null(texts, "").cast(pa.large_string()))
        words = pc.split_pattern_regex(lower, _NOT_LETTERS)
        coded = pc.list_flatten(words).dictionary_encode()
        names = coded.dictionary.to_pylist()
        index = self.index(names)
        ends = np.asarray(words.offsets)
        doc = np.repeat(np.arange(n), np.diff(ends))
        codes = coded.indices.to_numpy()
        real = np.array([any(map(str.isalpha, w)) for w in names], bool)[codes] if len(codes) else np.zeros(0, bool)
        held = np.bincount(doc[real], minlength=n) > 0
        sums = np.zeros((n, len(m.languages)))
        values = self.rows[index]
        for k in range(len(m.languages)):
            sums[:, k] = np.bincount(doc[real], weights=values[codes[real], k], minlength=n)
        if not m.languages:
            return [UNKNOWN] * n, np.zeros(n)
        sums += m.prior
        best = sums.argmax(axis=1)
        odds = np.exp(sums - sums.max(axis=1, keepdims=True))
        top = 1 / odds.sum(axis=1)
        return [m.languages[b] if h else UNKNOWN for b, h in zip(best, held, strict=True)], np.where(held, top, 0.0)


def predict(df: DataFrame, model: Model, text: str = "text", out: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """``df`` with language and probability added as the columns ``out``, in place of any of these names.

    Null text and text without a letter is ``und`` with score 0, as is everything under an empty model. Ties go to the first
    language by name; equal texts get equal answers; an empty table gives an empty result.
    """
    shared = df.sparkSession.sparkContext.broadcast(model)
    kept = [f for f in df.schema.fields if f.name not in out]
    schema = type(df.schema)(list(kept)).add(out[0], "string").add(out[1], "double")
    names = [f.name for f in kept]
    key = f"language {content_id(model)}"

    def run(batches):
        scorer = held(key, lambda: Scorer(shared.value))
        for b in batches:
            for i in range(0, b.num_rows, _TEXTS):
                p = b.slice(i, _TEXTS)
                langs, score = scorer.texts(p.column(p.schema.get_field_index(text)))
                yield pa.RecordBatch.from_arrays([*(p.column(p.schema.get_field_index(n)) for n in names), pa.array(langs, pa.string()), pa.array(score, pa.float64())], names=[*names, *out])

    return df.mapInArrow(run, schema)


def identify(df: DataFrame, training: DataFrame, **options) -> DataFrame:
    """``df`` with its predicted language, by a model of ``training`` (``text, lang``)."""
    return predict(df, fit(training.select("text", "lang"), **options))


def accepted(df: DataFrame, training: DataFrame, least: float = 0.5) -> DataFrame:
    """Rows whose language is clear: not ``und``, and of a probability of ``least`` or more. Columns stay as they are, whatever their names."""
    lang, score = free_names(df, "accepted_lang", "accepted_score")
    marked = predict(df, fit(training.select("text", "lang")), out=(lang, score))
    return marked.where((F.col(lang) != UNKNOWN) & (F.col(score) >= least)).select(*df.columns)


def query(spark, sf_dir):
    """op7: language of every document, by a model of the documents outside the held-out fold."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    held_out = fold_doc_id(F.col("doc_id"), 4) == 2
    return identify(docs.select("doc_id", held_out.alias("held_out"), "text"), docs.where(~held_out)).drop("text")
