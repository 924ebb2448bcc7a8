import hashlib
import random
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest

from crossaudit.llm import langid, mixing, ogg, packing, simhash, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def odd_documents(spark):
    """Nulls everywhere, empty and long texts, repeated rows."""
    rows = [
        (1, "alpha beta gamma", "en", "a", 16), (1, "alpha beta gamma", "en", "a", 16), (2, None, "en", "b", None), (3, "", None, None, 0),
        (None, "x y z", "de", "a", 5), (4, "word " * 5000, "en", None, 25000), (5, " \t\n ", "de", "b", 4), (6, "ein zwei drei", "de", "b", 3),
    ]
    return spark.createDataFrame(rows, SCHEMA)


def test_pieces_equal_whole_text_encoding(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    t = packing.tokenizer(packing.vocabulary_path())
    got = defaultdict(list)
    for r in packing.query(spark, tiny).collect():
        got[r["doc_id"]].append(r)
    filled = defaultdict(list)
    for d in docs.collect():
        ids = t.encode(d["text"] or "", add_special_tokens=False).ids + [2]
        parts = sorted(got[d["doc_id"]], key=lambda r: r["piece"])
        assert sum(p["length"] for p in parts) == len(ids)
        assert len(parts) == -(-len(ids) // 1024)
        for p in parts:
            own = np.array(ids[p["start"] : p["start"] + p["length"]], "<u4").tobytes()
            assert zlib.crc32(own) == p["ids_crc32"]
            filled[p["sequence_id"]].append((p["offset"], p["length"]))
    for parts in filled.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 1024
    total = sum(length for parts in filled.values() for _, length in parts)
    assert len(filled) <= 1.02 * -(-total // 1024) + 1


@pytest.mark.parametrize("alphabet", [" \n\t  abcdé.,'s!?0129  ßX\x1c\x85\v", "ab \né.'s1"])
def test_encoder_on_random_spacing(alphabet):
    e, rng = packing.encoder(packing.vocabulary_path()), random.Random(1)
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 25))) for _ in range(2000)]
    for s, v in zip(texts, e.texts(pa.array(texts)), strict=True):
        assert v == e.raw(s)


def test_minimum_slack_uses_each_item_once():
    rng = random.Random(2)
    counts = {n: rng.randint(0, 9) for n in range(1, 1025)}
    plan = packing.minimum_slack(counts)
    used = defaultdict(int)
    for times, make in plan:
        assert sum(n * k for n, k in make) <= 1024
        for n, k in make:
            used[n] += times * k
    assert dict(used) == {n: c for n, c in counts.items() if c}
    exact = packing.minimum_slack({700: 1, 600: 1, 424: 1, 324: 1})
    assert sum(t for t, _ in exact) == 2


def test_packing_odd_rows(spark):
    docs = odd_documents(spark)
    got = packing.pack(packing.pieces(docs), ["doc_id", "piece", "ids_crc32"]).collect()
    assert sum(r["length"] == 1 for r in got) == 2
    assert packing.pack(packing.pieces(docs.limit(0)), ["doc_id", "piece"]).count() == 0


def brute_components(fps):
    parent = {d: d for d in fps}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(fps)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            if (fps[a] ^ fps[b]).bit_count() <= 3:
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    return {d: root(d) for d in fps}


def slow_fingerprint(text):
    import xxhash

    words = (text or "").encode().lower().split()
    shingles = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    h = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << k for k in range(64) if 2 * sum(x >> k & 1 for x in h) > len(h))


def test_simhash_against_all_pairs(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    fps = {r["doc_id"]: slow_fingerprint(r["text"]) for r in docs.collect()}
    got = {r["doc_id"]: r for r in simhash.near_duplicates(docs).collect()}
    assert {d: int(r["fingerprint"], 16) for d, r in got.items()} == fps
    assert {d: r["component_id"] for d, r in got.items()} == brute_components(fps)


def test_simhash_crowded_buckets(spark):
    rng = random.Random(3)
    base = [rng.getrandbits(64) for _ in range(4)]
    fps = {b ^ sum(1 << k for k in rng.sample(range(64), rng.randint(0, 6))) for b in base for _ in range(60)}
    signed = sorted(f - (1 << 64) if f >> 63 else f for f in fps)
    frame = spark.createDataFrame([(f,) for f in signed], "fp long")
    want = brute_components({f: f & ((1 << 64) - 1) for f in signed})
    for bucket in (4096, 8):
        got = {r["node"]: r["component"] for r in simhash.connected_components(simhash.links(frame, bucket)).collect()}
        assert {f: got.get(f, f) for f in want} == want


@pytest.mark.parametrize("radius", [0, 1, 2, 3, 12, 37])
def test_carry_save_counters(radius):
    rng = np.random.default_rng(1)
    for width in (1, 2):
        a = rng.integers(0, 2**63, (150, width), dtype=np.int64).view(np.uint64)
        b = a.copy()
        for i in range(len(b)):
            for k in rng.choice(64 * width, i % 50, replace=False):
                b[i, k // 64] ^= np.uint64(1) << np.uint64(k % 64)
        got = np.array([simhash._members(m, len(a)) for m in simhash.within(a, b, radius)])
        assert (got == (np.bitwise_count(a[None, :] ^ b[:, None]).sum(axis=2) <= radius)).all()


def test_blocks_past_the_radius_are_abandoned(monkeypatch):
    rng = np.random.default_rng(2)
    a = rng.integers(0, 2**63, 6400, dtype=np.int64).view(np.uint64)
    sliced, read = simhash.planes(a), []

    class Spy(np.ndarray):
        def __getitem__(self, key):
            if isinstance(key, int):
                read.append(key)
                return np.asarray(self)[key]
            return super().__getitem__(key)

    masks = simhash.count_lanes(sliced.view(Spy), np.repeat(~a[:1], 100), np.arange(100), np.zeros(100, np.uint64), 3)
    assert not masks.any() and max(read) < 40  # no lane is near, and not all planes were read


def test_pairs_in_many_buckets_at_once():
    rng = np.random.default_rng(3)
    lengths = np.array([1, 2, 64, 65, 3, 200, 1])
    fps = rng.integers(0, 4, (lengths.sum(), 2)).astype(np.uint64)
    starts = np.cumsum(lengths) - lengths
    at = np.arange(len(fps)) - np.repeat(starts, lengths)
    i, j = simhash.linked_pairs(fps, starts, lengths, at + 1, 1)
    bucket = np.repeat(np.arange(len(lengths)), lengths)
    near = np.bitwise_count(fps[:, None] ^ fps[None, :]).sum(axis=2) <= 1
    want = np.argwhere(np.triu(near & (bucket[:, None] == bucket[None, :]), 1))
    assert sorted(zip(i.tolist(), j.tolist(), strict=True)) == sorted(map(tuple, want.tolist()))


def test_null_ids_bridge_fingerprints(spark):
    rng = random.Random(8)
    words = [f"w{rng.randrange(10**6)}" for _ in range(3000)]
    texts = [" ".join(words), " ".join(words[:-6]), " ".join(words[:-12])]
    rows = [(5, texts[0]), (None, texts[1]), (3, texts[2])]
    fps = {i: slow_fingerprint(t) for i, (_, t) in enumerate(rows)}
    want = brute_components(fps)
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert len(set(want.values())) == 1 and set(got.values()) == {3}


def test_simhash_odd_rows(spark):
    got = simhash.near_duplicates(odd_documents(spark)).collect()
    assert len(got) == 8
    zero = [r for r in got if r["fingerprint"] == "0" * 16]
    assert len(zero) == 3 and {r["component_id"] for r in zero} == {2}
    assert simhash.near_duplicates(odd_documents(spark).limit(0)).count() == 0


def test_ogg_round_trip_and_checks():
    rng = random.Random(4)
    for n in (0, 1, 191, 192, 193, 960, 961, 5000, 70_000):
        payload = ogg.pad(rng.randbytes(n))
        for segments in (255, 7):
            data = ogg.mux(payload, segments)
            streams = ogg.demux(data)
            assert ogg.payload_of(streams) == payload and len(streams) == 2
        bad = bytearray(data)
        bad[rng.randrange(len(bad))] ^= 1
        with pytest.raises(ogg.OggError):
            ogg.demux(bytes(bad))

    def slow(data):
        c = 0
        for x in data:
            c ^= x << 24
            for _ in range(8):
                c = (c << 1 ^ 0x04C11DB7) & 0xFFFFFFFF if c >> 31 else c << 1
        return c

    sample = rng.randbytes(99)
    assert ogg.page_checksum(sample) == slow(sample)


def test_ogg_query(spark, tiny):
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()}
    for r in ogg.query(spark, tiny).collect():
        raw = (docs[r["doc_id"]] or "").encode()
        payload = raw + b" " * (-len(raw) % 192 or 192 * (not raw))
        assert (r["n_bytes"], r["payload_bytes"]) == (len(raw), len(payload))
        assert r["payload_sha256"] == hashlib.sha256(payload).hexdigest()
        assert r["tail_crc32"] == zlib.crc32(payload[-16:])


def test_language_held_out_accuracy(spark, small):
    truth = {r["doc_id"]: r["lang"] for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    rows = [r for r in langid.query(spark, small).collect() if r["held_out"]]
    assert np.mean([r["lang_pred"] == truth[r["doc_id"]] for r in rows]) > 0.97
    assert all(0 <= r["score"] <= 1 for r in rows)


def test_language_against_word_by_word(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    model = langid.fit(docs.select("text", "lang"), parts=2000)
    texts = [r["text"] for r in docs.limit(60).collect()] + [None, "", "\u0301\u0301 12", "a\u0301", "x" * 1_000_000, "zzqx qxzz " * 3]
    langs, scores = langid.Scorer(model).texts(pa.array(texts))
    for text, lang, score in zip(texts, langs, scores, strict=True):
        words = [w for w in __import__("regex").split(r"[^\p{L}\p{M}]+", (text or "").lower()) if any(map(str.isalpha, w))]
        total = model.prior.astype(float)
        for w in words:
            known = model.tables[0].get(w)
            if known is None:
                padded = f"<{w}>"
                for size in (4, 3, 2, 1):
                    grams = [padded[i : i + size] for i in range(len(padded) - size + 1)]
                    if any(g in model.tables[size] for g in grams):
                        known = np.mean([model.tables[size].get(g, model.floors[size]) for g in grams], axis=0)
                        break
                else:
                    known = np.zeros(len(model.languages))
            total = total + known
        odds = np.exp(total - total.max())
        assert (lang, score) == (("und", 0) if not words else (model.languages[int(total.argmax())], pytest.approx(odds.max() / odds.sum(), abs=1e-3)))


def test_added_tokens_are_found_as_the_file_says():
    e = packing.encoder(packing.vocabulary_path())
    for x in e.added:
        for text in (f"a{x}b", f"one two {x} three", f"{x}", f"line\n{x}\nline  two"):
            plain = e.t.encode(text, add_special_tokens=False).ids
            assert e.texts(pa.array([text]))[0] == np.array(plain, "<u4").tobytes() and e.t.token_to_id(x) in plain


def test_workers_keep_one_thing_at_a_time():
    from crossaudit.llm import kept

    a = kept.held("a", dict)
    assert kept.held("a", dict) is a and kept.held("b", list) == [] and kept.held("a", dict) is not a
    memo = kept.Memo(1000)
    for i in range(10):
        memo.add(str(i), i, 50)
    memo.trim()
    assert not memo and kept.content_id({"x": 1}) != kept.content_id({"x": 2})


def test_a_full_memo_keeps_recent_words_within_half_its_limit():
    from crossaudit.llm import kept

    memo = kept.Memo(10_000)
    for i in range(60):
        memo.add(f"w{i}", b"x" * 40, 40)
    memo.trim(["w5", "w59", "new", "w5"])
    assert dict(memo) == {"w5": b"x" * 40, "w59": b"x" * 40} and memo.used < 500
    for i in range(60):
        memo.add(f"w{i}", b"x" * 40, 40)
    memo.trim(f"w{i}" for i in range(60))
    assert 20 < len(memo) < 30 and memo.used < 6000


def test_words_are_learned_in_bulk(monkeypatch):
    """A batch's new words are kept together, not by a call a word, under the same reckoning."""
    from crossaudit.llm.kept import Memo

    one, all_at_once = Memo(1000), Memo(1000)
    for w in ("a", "bcd", "é"):
        one.add(w, w.encode(), len(w.encode()))
    all_at_once.add_all(["a", "bcd", "é"], [b"a", b"bcd", "é".encode()])
    assert one == all_at_once and one.used == all_at_once.used
    monkeypatch.setattr(Memo, "add", lambda *_: pytest.fail("a call a word"))
    enc = packing.Encoder(packing.vocabulary_path())
    texts = ["Alpha beta. gamma\nbeta. .\n. Alpha", "beta", "x? ?x\nx?", "naïve \U0001f600, ÿ! beta"]
    assert enc.texts(pa.array(texts)) == [enc.raw(t) for t in texts]


def test_language_backs_off(spark):
    train = spark.createDataFrame([("the cat sat on the mat and the hat", "en"), ("der hund und die katze und das haus", "de")] * 5, "text string, lang string")
    asked = spark.createDataFrame([(1, "thethat"), (2, "undhaus"), (3, None), (4, "123 !"), (5, "")], "doc_id long, text string")
    got = {r["doc_id"]: r for r in langid.identify(asked, train).collect()}
    assert (got[1]["lang_pred"], got[2]["lang_pred"]) == ("en", "de")
    assert all(got[k]["lang_pred"] == "und" and got[k]["score"] == 0 for k in (3, 4, 5))
    empty = langid.identify(asked, train.limit(0)).collect()
    assert {r["lang_pred"] for r in empty} == {"und"}
    assert langid.accepted(odd_documents(spark), train).columns == odd_documents(spark).columns


def test_toxicity_held_out(spark, small):
    truth = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{small}/labels.parquet").collect()}
    rows = [r for r in toxicity.query(spark, small).collect() if r["held_out"] and r["doc_id"] in truth]
    assert np.mean([r["predicted"] == truth[r["doc_id"]] for r in rows]) > 0.95


def small_characters(extra=()):
    words = {"idiot": 30, "loser": 30, "trash": 30, "the": 900, "moron": 30, "hello": 20, "stupid": 20, "scum": 20, "you": 300, "are": 300, "a": 400, "off": 50, **dict(extra)}
    counts = defaultdict(float)
    for w, n in words.items():
        p = f"^^{w}$"
        for k in (1, 2, 3):
            for i in range(len(p) - k + 1):
                counts[p[i : i + k]] += n
    return toxicity.CharacterModel(dict(counts), frozenset(w for w in words if len(w) <= 3))


def test_deobfuscation():
    model = small_characters()
    seen = {
        "1d10t": "idiot", "l0s3r": "loser", "tr@$h": "trash", "looooser": "loser", "i.d.i.o.t": "idiot", "id*ot": "idiot", "moron***": "moron", "the": "the", "heeello!!": "hello",
        "s-t-u-p-1-d": "stupid", "scuuuum": "scum", "stuupid": "stupid", "!d!ot": "idiot", "idi*t": "idiot", "st**id": "stupid", "off": "off", "idiot/loser": "idiot loser",
        "you are a i d i o t": "you are a idiot", "i d i o t l o s e r": "idiot loser", "idi ot": "idiot", "1 d 1 0 t": "idiot",
    }
    for text, meant in seen.items():
        assert toxicity.restore(text, model) == meant, text
    assert toxicity.restore("l0s3r" * 9, model) == "loser" * 9 and toxicity.disguised("l0s3r" * 9)


def best_path(text, model):
    """All paths, one by one."""
    import itertools

    cores = [c for c in map(toxicity.core_of, text.split()) if c]
    steps = []
    for core in cores:
        steps += [[("", toxicity._GLUE), (" ", 0.0)]] * bool(steps) + (toxicity.lattice(core, model.letters) if toxicity.disguised(core) or len(core) == 1 else [[(c, 0.0)] for c in core])
    paths = list(itertools.product(*steps))
    scores = [sum(c for _, c in p) + toxicity.path_score([x for x, _ in p], model) for p in paths]
    top = max(scores)
    return {" ".join("".join(x for x, _ in p).split()) for p, s in zip(paths, scores, strict=True) if s >= top - 1e-9}


def test_viterbi_against_all_paths():
    model, rng = small_characters(), random.Random(11)
    asked = ["".join(rng.choice("idotl013s$.! a") for _ in range(rng.randint(2, 8))) for _ in range(250)] + ["id*t", "l0*er", "**t", "i***", "*o**"]
    for text in asked:
        if any(map(toxicity.core_of, text.split())):
            cores = [c for c in map(toxicity.core_of, text.split()) if c]
            if len(cores) > 1 or toxicity.disguised(text):
                assert toxicity.restore(text, model) in best_path(text, model), text


def test_spelled_words_against_all_paths():
    import itertools

    model, rng = small_characters(), random.Random(13)
    words = ["idiot", "loser", "off", "too"]
    tree, hits = toxicity.prefix_tree(words), 0
    pool = [*"idotlsers013$.! f", "off", "l0s", "too", " i d", "er"]
    for text in ["".join(rng.choice(pool) for _ in range(rng.randint(2, 7))) for _ in range(300)] + ["id*ot", "o*f", "t**", "**o", "x.off", "off/x", "xoff", "", "loser"]:
        steps = toxicity._lattice_of([c for c in map(toxicity.core_of, text.split()) if c], model.letters)
        spelled = any(w in words for path in itertools.product(*([x for x, _ in s] for s in steps)) for w in "".join(path).split(" "))
        assert toxicity.spells(steps, tree, len(model.letters)) == spelled, text
        hits += spelled
    assert hits > 10


def test_features_against_token_by_token():
    model, rng = small_characters(), random.Random(12)
    words = {"idiot": 0, "loser": 1, "off": 2}
    pool = ["the", "you", "idiot", "1d10t", "i", "d", "o", "t", "a", "los", "er", "idi", "ot", "12", "-", "looser", "xyzzy", "o f f", "(the", "\n"]
    texts = [" ".join(rng.choice(pool) for _ in range(rng.randint(0, 14))) for _ in range(300)] + [None, ""]
    doc, feature = toxicity.Restorer(model, words).texts(pa.array(texts))
    got = defaultdict(set)
    for d, f in zip(doc.tolist(), feature.tolist(), strict=True):
        got[d].add(f)
    for i, text in enumerate(texts):
        tokens = (text or "").split()
        kinds = [toxicity.piece_kind(t, model.known) for t in tokens]
        alone = [len(toxicity.core_of(t)) == 1 for t in tokens]
        noisy = [k == 1 or (k == 2 and ((j > 0 and alone[j - 1]) or (j + 1 < len(tokens) and alone[j + 1]))) for j, k in enumerate(kinds)]
        runs, now = [], tokens[:1]
        for j in range(1, len(tokens)):
            if (noisy[j] or noisy[j - 1]) and toxicity.core_of(tokens[j]) and toxicity.core_of(tokens[j - 1]):
                now.append(tokens[j])
            else:
                runs, now = [*runs, now], [tokens[j]]
        spelled = [toxicity.restore(t, model) for t in tokens if toxicity.core_of(t)] + [toxicity.restore(" ".join(r), model) for r in [*runs, now] if len(r) > 1]
        assert got[i] == {words[w] for s in spelled for w in s.split() if w in words}, text


def test_toxicity_on_disguises_and_odd_rows(spark):
    rng = random.Random(5)
    filler = ["".join(rng.choice(["th", "er", "on", "an", "re", "st"]) for _ in range(rng.randint(1, 4))) for _ in range(300)]
    rows = [(i, " ".join(rng.choices(filler, k=40) + (["idiot", "loser"] if i % 4 == 0 else []))) for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i in range(400)] + [(None, 1), (7, None)], "doc_id long, toxic int")
    model = toxicity.fit(docs, labels)
    asked = spark.createDataFrame([(1, "ther on 1d10t and l0s3r"), (2, "you i d i o t and l o s e r"), (3, "ther on an"), (4, None), (5, "")], "doc_id long, text string")
    got = {r["doc_id"]: r for r in toxicity.score(asked.withColumn("words", toxicity.F.lit("own")), model).collect()}
    assert {k: r["predicted"] for k, r in got.items()} == {1: 1, 2: 1, 3: 0, 4: 0, 5: 0} and got[1]["words"] == "own"
    for k, texts in {1: ["idiot", "loser"], 3: []}.items():  # the score is the logistic function of the weights of the words found
        z = model.bias + sum(model.weights[model.words[w]] for w in texts if w in model.words)
        z += sum(model.weights[model.words[w]] for w in ("ther", "on", "an") if w in model.words and not (k == 1 and w == "an"))
        assert got[k]["score"] == pytest.approx(1 / (1 + np.exp(-z)))
    assert got[4]["score"] == got[5]["score"] == pytest.approx(1 / (1 + np.exp(-model.bias)))
    blank = toxicity.fit(docs, labels.limit(0))
    assert toxicity.score(asked, blank).count() == 5 and toxicity.score(asked.limit(0), model).count() == 0
    spelled = {r["doc_id"]: r["restored"] for r in toxicity.restore_texts(asked, model.characters).collect()}
    assert spelled[1] == "ther on idiot and loser" and spelled[4] == ""


def test_very_long_texts():
    model = small_characters()
    r = toxicity.Restorer(model, {"idiot": 0})
    long = "1d" * 50_000 + " x " * 5 + "a" + "*" * 20_000 + "b " + "i d i o t"
    doc, feature = r.texts(pa.array([long, "the " * 250_000 + "1d10t"]))
    assert 1 in doc.tolist() and set(feature.tolist()) == {0}


def test_mixing_targets_and_copies(spark, small):
    rows = mixing.query(spark, small).collect()
    assert all(r["taken"] <= 2 * r["size"] and (r["size"] == 0 or r["taken"] % r["size"] == 0) for r in rows)
    source = {r["doc_id"]: r["source"] for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    taken, target, largest = defaultdict(int), {}, defaultdict(int)
    for r in rows:
        s = source[r["doc_id"]]
        taken[s] += r["taken"]
        target[s] = r["target"]
        largest[s] = max(largest[s], r["size"])
    assert abs(sum(target.values()) - 1.5 * sum(r["size"] for r in rows)) < 1e-3
    assert all(abs(taken[s] - target[s]) <= largest[s] / 2 + 1 for s in target)


def test_inclusion_follows_the_probability(spark):
    rng = random.Random(9)
    rows = [(i, "w " * n, "s") for i, n in enumerate(rng.choice([4, 25, 100]) for _ in range(6000))]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    out = mixing.mix(docs, share=0.8).collect()
    by = defaultdict(list)
    for r in out:
        by[r["mix_size"]].append(r["mix_copies"])
    target = out[0]["mix_target"]
    level = target / sum(np.sqrt(n) * n * len(c) for n, c in by.items())
    for n, c in by.items():  # expected copies are in proportion to the root of the size
        assert np.mean(c) == pytest.approx(level * np.sqrt(n), abs=0.04) and max(c) - min(c) <= 1
    assert abs(sum(r["mix_copies"] * r["mix_size"] for r in out) - target) <= 50
    even = mixing.mix(docs, share=0.8, weight=mixing.F.lit(1.0)).collect()
    taken = defaultdict(list)
    for r in even:
        taken[r["mix_size"]].append(r["mix_copies"])
    assert all(np.mean(c) == pytest.approx(0.8, abs=0.04) for c in taken.values())


def test_mixing_odd_rows(spark):
    docs = odd_documents(spark)
    out = mixing.mix(docs).collect()
    assert len(out) == 8 and all(0 <= r["mix_copies"] <= 2 for r in out)
    clash = docs.withColumns({c: mixing.F.lit("own") for c in ("mix_copy", "mix_w", "mix_size_", "u", "weight", "v", "level")})
    got = mixing.mixed(clash)
    assert got.columns == clash.columns and {r["mix_copy"] for r in got.collect()} == {"own"}
    assert mixing.mix(docs.limit(0)).count() == 0
    weighted = mixing.mix(docs, weight=mixing.F.col("n_chars").cast("double")).count()
    assert weighted == 8
