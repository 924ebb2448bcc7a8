"""Toxicity by noisy-channel deobfuscation: restore disguised words first, then score the restored text.

A token becomes a lattice of what its characters may stand for: digits and signs for letters, a doubled letter for one and a longer repetition
for one or two, a sign between letters for nothing or a word's end, a sign that hides for any letter, signs at the ends for nothing. Where
a token is a single character among such, or a piece of three characters or less that is no known word, the spaces beside it may be noise, and the
tokens that such spaces join are one lattice in which each of them stands for a word's end or for nothing. Viterbi decoding
finds the path that is likeliest under a character trigram model times the channel, over all states and lengths. The trigrams are counted over
all documents. The presence of words, as they stand and restored, feeds a logistic model whose words are chosen by their likelihood
ratio with the label.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crossaudit.functions.storage import materialize
from crossaudit.llm.kept import Memo, content_id, held
from crossaudit.llm.words import fold_doc_id

#: Expected labelled rows that the logistic model is fitted on: the documented bound of its sample.
SAMPLE = 20_000
#: Words that the logistic model may use.
FEATURES = 256
#: A character trigram is kept from one part in so many, which bounds the model that is broadcast.
PARTS = 1_000_000
#: Share of all words from which a word of so many letters is known, and a space beside it no noise.
KNOWN = {1: 1e-3, 2: 2e-5, 3: 2e-5}
#: Hidden letters in a row; a longer run of such signs is a separator.
HIDDEN = 8
_KEPT_BYTES, _TEXTS = 150_000_000, 2000

#: Letters that a digit or sign is commonly written for.
STANDS_FOR = {
    "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "gb", "7": "t", "8": "b", "9": "gq",
    "@": "a", "$": "s", "!": "il", "|": "il", "+": "t", "(": "c", "\u20ac": "e", "\u00a3": "l",
}
#: Signs set between letters; ``*`` and ``#`` may also hide a letter.
BETWEEN = "._-*#~'/\\,:^="
HIDES = "*#"
#: Logs of what the channel does: a letter by a sign, by a hidden sign or a digit as itself, a sign as nothing or as a word's end, a
#: repetition meant twice, a doubled letter meant once, a space as noise.
_SUBST, _OPEN, _DROP, _SPLIT, _SECOND, _ONCE, _GLUE = (math.log(x) for x in (0.2, 0.02, 0.3, 0.1, 0.15, 0.02, 0.1))

_RUN = re.compile(r"(.)\1*", re.S)
_PLAIN = re.compile(r"[^\W\d_]+\Z")
#: Signs that are stripped from the ends of a token at once.
_SIGNS = ".,;:?\"'`)[]{}<>~-_/\\&%=^"
_LETTERS = re.compile(r"[^\W\d_]+")
#: Where a word may end inside a lattice: at white space or a sign that may be one.
_BREAKS = re.compile("[" + re.escape("".join(c for c in BETWEEN if c not in HIDES)) + "*#\\s]+")
_DOUBLED = re.compile(r"([^\W\d_])\1")


@dataclass
class CharacterModel:
    """Interpolated trigrams over words written as ``^word$``."""

    counts: dict[str, float]
    known: frozenset[str] = frozenset()
    letters: list[str] = field(default_factory=list)
    memo: dict[str, float] = field(default_factory=dict)
    table: np.ndarray | None = None

    def __post_init__(self):
        self.total = sum(n for g, n in self.counts.items() if len(g) == 1) or 1.0
        self.letters = sorted(g for g in self.counts if len(g) == 1 and g.isalpha())
        self.place = {c: i for i, c in enumerate(self.letters)}

    def dense(self) -> np.ndarray:
        """Log probabilities of every letter after every two letters."""
        if self.table is None:
            x = self.letters
            self.table = np.array([[[self.log(a, b, c) for c in x] for b in x] for a in x]).reshape(len(x), len(x), len(x))
        return self.table

    def log(self, a: str, b: str, c: str) -> float:
        """Log probability of ``c`` after ``ab``."""
        key = a + b + c
        got = self.memo.get(key)
        if got is None:
            if len(self.memo) > 500_000:
                self.memo.clear()
            n = self.counts.get
            one = (n(c, 0.0) + 0.1) / (self.total + 10)
            two = (n(b + c, 0.0) + 20 * one) / (n(b, 0.0) + 20)
            got = self.memo[key] = math.log((n(key, 0.0) + 10 * two) / (n(a + b, 0.0) + 10))
        return got


def core_of(token: str) -> str:
    """A lower-case token without the signs around it that stand for no letter."""
    token = token.strip(_SIGNS)
    a, b = 0, len(token)
    while a < b and not (token[a].isalnum() or token[a] in STANDS_FOR or token[a] in HIDES):
        a += 1
    while a < b and not (token[b - 1].isalnum() or token[b - 1] in STANDS_FOR or token[b - 1] in HIDES):
        b -= 1
    return token[a:b]


def disguised(token: str) -> bool:
    """Whether the lattice of a lower-case token has more than one path; a token without a letter is taken as it is."""
    core = core_of(token)
    if _PLAIN.match(core):
        return bool(_DOUBLED.search(core))
    return any(c.isalpha() for c in core) and any(c in STANDS_FOR or c in BETWEEN for c in core)


def lattice(core: str, letters: list[str]) -> list[list[tuple[str, float]]]:
    """What each run of a character may stand for, with the channel's log probability; a space is a word's end."""
    steps = []
    for run in _RUN.finditer(core):
        c, n = run.group(1), len(run.group())
        edge = run.start() == 0 or run.end() == len(core)
        if c.isalpha():
            steps.append([(c, 0.0)] if n == 1 else [(c + c, 0.0), (c, _ONCE)] if n == 2 else [(c, 0.0), (c + c, _SECOND)])
        elif c in HIDES and n <= HIDDEN:
            steps += [[("", 0.0 if edge else _DROP), *((x, _OPEN) for x in letters)]] * n
        elif c in STANDS_FOR:
            options = [(x * k, _SUBST + (_SECOND if k == 2 else 0.0)) for x in STANDS_FOR[c] for k in ((1, 2) if n > 1 else (1,))]
            steps.append([*options, (c * min(n, 2), _OPEN) if c.isdigit() else ("", 0.0 if edge else _DROP)])
        elif c in BETWEEN:
            steps.append([("", _DROP), (" ", _SPLIT)])
        else:
            steps.append([(c, _OPEN)])
    return steps


def path_score(steps: list[str], model: CharacterModel) -> float:
    """Log probability of what a path's steps spell, as words."""
    a = b = "^"
    total = 0.0
    for x in "".join(steps):
        if x == " ":
            if b != "^":
                total += model.log(a, b, "$")
            a = b = "^"
        else:
            total += model.log(a, b, x)
            a, b = b, x
    return total + (model.log(a, b, "$") if b != "^" else 0.0)


def _step(scores: dict, options: list[tuple[str, float]], model: CharacterModel) -> tuple[dict, dict]:
    """Best score of each state after one more step, and the state and option that it came from."""
    grown, came = {}, {}
    for state, score in scores.items():
        for x, cost in options:
            (a, b), s = state, score + cost
            for c in x:
                if c == " ":
                    s += model.log(a, b, "$") if b != "^" else 0.0
                    a = b = "^"
                else:
                    s += model.log(a, b, c)
                    a, b = b, c
            if (a, b) not in grown or s >= grown[a, b]:
                grown[a, b], came[a, b] = s, (state, x)
    return grown, came


def _hidden_step(scores: dict, options: list[tuple[str, float]], model: CharacterModel) -> tuple[dict, dict]:
    """`_step` for a hidden sign (nothing or any letter) from many states: those of two letters all at once."""
    at, letters = model.place, model.letters
    grid = np.full((len(letters), len(letters)), -np.inf)
    rest = {}
    for (a, b), s in scores.items():
        if a in at and b in at:
            grid[at[a], at[b]] = s
        else:
            rest[a, b] = s
    grown, came = _step(rest, options, model)
    reached = grid[:, :, None] + model.dense()
    source, best, stay = reached.argmax(axis=0), reached.max(axis=0) + options[1][1], grid + options[0][1]
    value = np.maximum(best, stay)
    for i, j in zip(*(x.tolist() for x in np.nonzero(value > -np.inf)), strict=True):
        state, s = (letters[i], letters[j]), float(value[i, j])
        if state not in grown or s >= grown[state]:
            grown[state] = s
            came[state] = (state, "") if stay[i, j] > best[i, j] else ((letters[source[i, j]], letters[i]), letters[j])
    return grown, came


def viterbi(steps: list[list[tuple[str, float]]], model: CharacterModel) -> str:
    """What the likeliest path spells; a state is the last two letters of the word so far. Ties go to the later option."""
    scores, back = {("^", "^"): 0.0}, []
    for options in steps:
        hidden = len(options) > len(model.letters) > 0 and len(scores) > 20
        scores, came = (_hidden_step if hidden else _step)(scores, options, model)
        back.append(came)
    state = max(scores, key=lambda k: scores[k] + (model.log(*k, "$") if k[1] != "^" else 0.0))
    out = []
    for came in reversed(back):
        state, x = came[state]
        out.append(x)
    return "".join(reversed(out))


def _lattice_of(cores: list[str], letters: list[str]) -> list[list[tuple[str, float]]]:
    """Lattice of one core or several whose spaces may be noise."""
    steps: list[list[tuple[str, float]]] = []
    for core in cores:
        steps += [[("", _GLUE), (" ", 0.0)]] * bool(steps) + (lattice(core, letters) if disguised(core) or len(core) == 1 else [[(c, 0.0)] for c in core])
    return steps


def restore(text: str, model: CharacterModel) -> str:
    """Likeliest plain words behind one lower-case token, or several whose spaces may be noise."""
    cores = [c for c in map(core_of, text.split()) if c]
    if len(cores) == 1 and not disguised(text):
        return cores[0]
    return " ".join(viterbi(_lattice_of(cores, model.letters), model).split())


def prefix_tree(words) -> dict:
    """Words as nested dictionaries by character; the key ``""`` marks a word's end."""
    root: dict = {}
    for w in words:
        node = root
        for c in w:
            node = node.setdefault(c, {})
        node[""] = {}
    return root


def spells(steps: list[list[tuple[str, float]]], root: dict, letters: int) -> bool:
    """Whether some path of a lattice spells a word of the prefix tree between two word ends; a step of more than ``letters`` options is any letter or nothing."""
    live = {id(root): root}
    for options in steps:
        grown = {}
        if len(options) > letters > 0:
            grown = live | {id(kid): kid for n in live.values() for c, kid in n.items() if c}
        else:
            for x, _ in options:
                if x == " ":
                    if any("" in n for n in live.values()):
                        return True
                    grown[id(root)] = root
                else:
                    for node in live.values():
                        for c in x:
                            node = node.get(c)
                            if node is None:
                                break
                        else:
                            grown[id(node)] = node
        live = grown
    return any("" in n for n in live.values())


def piece_kind(token: str, known: frozenset[str]) -> int:
    """1 if spaces beside the token may be noise, 2 if only beside another single character, else 0."""
    core = core_of(token)
    if not core or len(core) > 3 or not any(c.isalnum() for c in core):
        return 0
    if core in known or core.isdigit():
        return 2 if len(core) == 1 else 0
    return 1


@dataclass
class Toxicity:
    """Character model, and the logistic model's words and weights."""

    characters: CharacterModel
    words: dict[str, int]
    weights: np.ndarray
    bias: float


def _squeezed(word: str) -> str:
    return _RUN.sub(r"\1", word) if _DOUBLED.search(word) else word


class Restorer:
    """Features of whole texts, with what tokens and runs of tokens stand for kept up to a bound."""

    def __init__(self, characters: CharacterModel, words: dict[str, int]):
        self.characters, self.words = characters, words
        squeezed = sorted({_squeezed(w) for w in words})
        self.near = re.compile("|".join(map(re.escape, squeezed))) if squeezed else None
        self.all = "\n".join(squeezed)
        self.tree = prefix_tree(words)
        self.kept = Memo(_KEPT_BYTES)

    def found(self, text: str) -> tuple[int, ...]:
        """Features among the restored words.

        A lattice never drops a letter: letters alone can only restore to what they spell but for repetition, and a word with a stretch of letters
        that no feature has is none. Of the rest only those are decoded whose lattice has a path that spells a feature.
        """
        plain = text.replace(" ", "")
        if self.near is None:
            return ()
        if _PLAIN.match(plain):
            if not self.near.search(_squeezed(plain)):
                return ()
        elif not any(_squeezed(x) in self.all for x in _LETTERS.findall(text)) and all(_LETTERS.search(x) for x in _BREAKS.split(text) if x):
            return ()
        cores = [c for c in map(core_of, text.split()) if c]
        if len(cores) == 1 and not disguised(text):
            return (self.words[cores[0]],) if cores[0] in self.words else ()
        steps = _lattice_of(cores, self.characters.letters)
        if not spells(steps, self.tree, len(self.characters.letters)):
            return ()
        return tuple({self.words[w] for w in viterbi(steps, self.characters).split() if w in self.words})

    def token(self, token: str) -> tuple[tuple[int, ...], int, int]:
        """Features of a token, its `piece_kind` and the length of its core."""
        got = self.kept.get(token)
        if got is None:
            core = core_of(token)
            if len(core) > 3 and core.isalpha() and not _DOUBLED.search(core):
                got = ((self.words[core],) if core in self.words else (), 0, len(core))
            else:
                got = (self.found(token), piece_kind(token, self.characters.known), len(core))
            self.kept.add(token, got, 50)
        return got

    def run(self, text: str) -> tuple[int, ...]:
        got = self.kept.get(" " + text)
        if got is None:
            got = self.found(text)
            self.kept.add(" " + text, got, 100)
        return got

    def texts(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Distinct (text, feature) pairs as two arrays, in order."""
        self.kept.trim()
        lower = pc.utf8_lower(pc.fill_null(texts, "").cast(pa.large_string()))
        words = pc.split_pattern_regex(lower, r"\s+")
        coded = pc.list_flatten(words).dictionary_encode()
        names = coded.dictionary.to_pylist()
        told = [self.token(w) for w in names]
        codes = coded.indices.to_numpy()
        doc = np.repeat(np.arange(len(texts)), np.diff(np.asarray(words.offsets)))
        pairs = [(-1, -1)]
        some = np.fromiter((bool(t[0]) for t in told), bool, len(told))
        for k in np.flatnonzero(some[codes]).tolist():
            pairs += [(doc[k], f) for f in told[codes[k]][0]]
        for a, b in joined_runs(np.fromiter((t[1] for t in told), np.int8, len(told))[codes], np.fromiter((t[2] for t in told), np.int64, len(told))[codes], doc):
            pairs += [(doc[a], f) for f in self.run(" ".join(names[c] for c in codes[a:b]))]
        both = np.unique(np.array(pairs, np.int64), axis=0)[1:]
        return both[:, 0], both[:, 1]


def joined_runs(kind: np.ndarray, length: np.ndarray, doc: np.ndarray) -> list[tuple[int, int]]:
    """Stretches of tokens (from, to) that spaces which may be noise join; ``kind`` is that of `piece_kind`, an empty token has no length."""
    if len(kind) < 2:
        return []
    beside = np.zeros(len(kind), bool)
    pair = (doc[1:] == doc[:-1]) & (length[1:] == 1) & (length[:-1] == 1)
    beside[1:] |= pair
    beside[:-1] |= pair
    noisy = (kind == 1) | ((kind == 2) & beside)
    open_ = (doc[1:] == doc[:-1]) & (noisy[1:] | noisy[:-1]) & (length[1:] > 0) & (length[:-1] > 0)
    edge = np.flatnonzero(np.diff(np.concatenate([[False], open_, [False]]).astype(np.int8)))
    return [(a, b + 1) for a, b in zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True)]


def _logistic(rows: np.ndarray, cols: np.ndarray, y: np.ndarray, k: int, ridge: float = 1.0) -> tuple[np.ndarray, float]:
    """Ridge logistic regression on a presence matrix, by Newton steps; the bias is not shrunk."""
    x = np.zeros((len(y), k + 1))
    x[rows, cols] = 1.0
    x[:, k] = 1.0
    w, shrink = np.zeros(k + 1), np.append(np.full(k, ridge), 1e-6)
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(shrink), x.T @ (y - p) - shrink * w)
        w += step
        if np.abs(step).max() < 1e-6:
            break
    return w[:k], float(w[k])


def character_model(documents: DataFrame, parts: int = PARTS) -> CharacterModel:
    """Character trigrams and short known words of all documents (``text``), counted by Spark; the kept ones have a bounded number."""
    tokens = F.filter(F.split(F.lower("text"), r"[^\p{L}\p{M}]+"), lambda w: w != "")
    words = documents.select(F.explode(tokens).alias("w")).groupBy("w").agg(F.count(F.lit(1)).cast("double").alias("n"))
    padded = F.concat(F.lit("^^"), "w", F.lit("$"))
    grams = F.flatten(F.transform(F.sequence(F.lit(1), F.lit(3)), lambda k: F.transform(F.sequence(F.lit(1), F.length("p") - k + 1), lambda i: F.substring("p", i, k))))
    short = F.when(F.length("w") <= max(KNOWN), F.array(F.concat(F.lit("="), "w"))).otherwise(F.array().cast("array<string>"))
    grams = words.select("n", "w", padded.alias("p")).select("n", F.explode(F.concat(grams, short)).alias("g")).groupBy("g").agg(F.sum("n").alias("n"))
    grams = materialize(grams, "toxic-grams")
    total = grams.agg(F.sum("n")).first()[0] or 0.0
    counts = {r["g"]: r["n"] for r in grams.where(F.col("n") * parts >= total).collect()}
    every = counts.get("$", 0.0)
    known = frozenset(g[1:] for g, n in counts.items() if g[0] == "=" and len(g) > 1 and n >= KNOWN[len(g) - 1] * every)
    return CharacterModel({g: n for g, n in counts.items() if g[0] != "="}, known)


def fit(documents: DataFrame, labels: DataFrame, sample: int = SAMPLE, features: int = FEATURES, parts: int = PARTS) -> Toxicity:
    """Model of ``documents`` (``doc_id, text``) and their ``labels`` (``doc_id, toxic``); null labels and ids are ignored.

    Characters are counted over all documents. About ``sample`` labelled rows are drawn for the logistic model by a hash of the id, or all if there
    are fewer; their ids are what is broadcast. Of several labels of an id the largest counts. Without labels of both kinds every text
    gets the prior's score.
    """
    characters = character_model(documents, parts)
    marked = labels.where("toxic is not null and doc_id is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    marked = materialize(marked, "toxic-labels")
    n = marked.count()
    if n > sample:
        marked = marked.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) / float(1 << 20) < sample / n)
    rows = documents.select("doc_id", "text").join(F.broadcast(marked), "doc_id").select("doc_id", "toxic", F.coalesce("text", F.lit("")).alias("text"))
    rows = materialize(rows, "toxic-sample")
    size = {r["toxic"]: r["n"] for r in rows.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    bad, good = float(size.get(1, 0)), float(size.get(0, 0))
    tokens = F.filter(F.split(F.lower("text"), r"[^\p{L}\p{M}]+"), lambda w: w != "")
    seen = rows.select("toxic", F.explode(F.array_distinct(tokens)).alias("w")).groupBy("w").agg(F.sum((F.col("toxic") == 1).cast("double")).alias("a"), F.sum((F.col("toxic") == 0).cast("double")).alias("b"))
    prior = math.log((bad + 0.5) / (good + 0.5))
    if not bad or not good:
        return Toxicity(characters, {}, np.zeros(0), prior)

    def part(x, of):
        return F.when(x > 0, x * F.log(x / of)).otherwise(0.0)

    a, b, share = F.col("a"), F.col("b"), bad / (bad + good)
    c, d = F.lit(bad) - a, F.lit(good) - b
    ratio = part(a, (a + b) * share) + part(b, (a + b) * (1 - share)) + part(c, (c + d) * share) + part(d, (c + d) * (1 - share))
    best = seen.where("a + b >= 3").withColumn("g2", 2 * ratio).where("g2 >= 15").orderBy(F.desc("g2"), "w").limit(features)
    words = {r["w"]: i for i, r in enumerate(best.select("w").collect())}
    if not words:
        return Toxicity(characters, {}, np.zeros(0), prior)
    found = _features(rows.select("doc_id", "toxic", "text"), characters, words).collect()
    k = np.array([len(r["found"]) for r in found])
    weights, bias = _logistic(np.repeat(np.arange(len(found)), k), np.array([f for r in found for f in r["found"]], np.int64), np.array([r["toxic"] for r in found], float), len(words))
    return Toxicity(characters, words, weights, bias)


def _features(rows: DataFrame, characters: CharacterModel, words: dict[str, int]) -> DataFrame:
    shared = rows.sparkSession.sparkContext.broadcast((characters, words))

    def run(batches):
        restorer = Restorer(*shared.value)
        for b in batches:
            for i in range(0, b.num_rows, _TEXTS):
                p = b.slice(i, _TEXTS)
                doc, feature = restorer.texts(p.column(2))
                ends = np.searchsorted(doc, np.arange(p.num_rows + 1))
                yield pa.RecordBatch.from_arrays([p.column(0), p.column(1), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(feature, pa.int32()))], names=["doc_id", "toxic", "found"])

    return rows.select("doc_id", F.col("toxic").cast("int"), "text").mapInArrow(run, "doc_id long, toxic int, found array<int>")


def score(df: DataFrame, model: Toxicity, text: str = "text") -> DataFrame:
    """``df`` with ``score`` (0 to 1) and ``predicted`` (1 from 0.5 on) added in place of any columns of these names.

    Null and empty texts get the score of a text without any of the model's words; equal texts get equal scores; an empty table gives
    an empty result.
    """
    shared = df.sparkSession.sparkContext.broadcast(model)
    kept = [f for f in df.schema.fields if f.name not in ("score", "predicted")]
    schema = type(df.schema)(list(kept)).add("score", "double").add("predicted", "integer")
    names = [f.name for f in kept]
    key = f"toxicity {content_id(model.characters.counts, sorted(model.characters.known), model.words)}"

    def run(batches):
        m = shared.value
        restorer = held(key, lambda: Restorer(m.characters, m.words))
        for b in batches:
            for i in range(0, b.num_rows, _TEXTS):
                p = b.slice(i, _TEXTS)
                doc, feature = restorer.texts(p.column(p.schema.get_field_index(text)))
                z = m.bias + np.bincount(doc, weights=m.weights[feature], minlength=p.num_rows) if len(m.words) else np.full(p.num_rows, m.bias)
                s = 1 / (1 + np.exp(-np.clip(z, -500, 500)))
                yield pa.RecordBatch.from_arrays([*(p.column(p.schema.get_field_index(n)) for n in names), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], names=[*names, "score", "predicted"])

    return df.mapInArrow(run, schema)


def restore_texts(df: DataFrame, characters: CharacterModel, text: str = "text", out: str = "restored") -> DataFrame:
    """``df`` with the restored text added as ``out`` (in place of a column of this name): lower case, words a space apart; null is empty."""
    shared = df.sparkSession.sparkContext.broadcast(characters)
    kept = [f for f in df.schema.fields if f.name != out]
    names = [f.name for f in kept]

    def restored(t: str | None) -> str:
        model = shared.value
        tokens = (t or "").lower().split()
        kind = np.array([piece_kind(w, model.known) for w in tokens], np.int8)
        runs = joined_runs(kind, np.array([len(core_of(w)) for w in tokens], np.int64), np.zeros(len(tokens), np.int64))
        parts, at = [], 0
        for a, b in [*runs, (len(tokens), len(tokens))]:
            parts += [restore(w, model) for w in tokens[at:a] if core_of(w)]
            parts += [restore(" ".join(tokens[a:b]), model)] * (a < b)
            at = b
        return " ".join(parts)

    def run(batches):
        for b in batches:
            texts = pa.array([restored(t) for t in b.column(b.schema.get_field_index(text)).to_pylist()], pa.string())
            yield pa.RecordBatch.from_arrays([*(b.column(b.schema.get_field_index(n)) for n in names), texts], names=[*names, out])

    return df.mapInArrow(run, type(df.schema)(list(kept)).add(out, "string"))


def query(spark, sf_dir):
    """op3: toxicity of every document, by a model of the labelled rows outside the held-out fold."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(fold_doc_id(F.col("doc_id"), 5) != 0)
    rows = docs.select("doc_id", (fold_doc_id(F.col("doc_id"), 5) == 0).alias("held_out"), "text")
    return score(rows, fit(docs, labels)).drop("text")
