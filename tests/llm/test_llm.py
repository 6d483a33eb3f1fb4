"""Small fixtures with nulls, empties, ties and repeats; brute force beside each operator."""

import os
import time
import zlib
from array import array

import duckdb
import numpy as np
import pytest

from outlyer.llm import decontam, langid, linededup, media, neardup, packing, pii, sharding, token_histogram, toxicity
from outlyer.llm.sql import ORACLES
from outlyer.llm.tokens import WordEncoder, default_vocabulary

WORDS = "alpha beta gamma delta omega kappa sigma theta lambda iota".split()
PASSAGE = " ".join(WORDS[i % 10] + str(i) for i in range(60))


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(0, f"{PASSAGE}\nshort line", "en"), (1, f"intro\n{PASSAGE}\nend", "en"), (2, None, None), (3, "", "en"), (4, PASSAGE, "en"), (4, PASSAGE, "en"), (5, PASSAGE + " extra", None), (None, "no id here", "en"), (6, "a@b.co tel +49 170 1234567 card 4111 1111 1111 1111 ip 10.0.0.255 acc DE89 3704 0044 0532 0130 00", "de")]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string")


def _empty(docs):
    return docs.where("false")


def test_packing(docs):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(default_vocabulary())
    rows = packing.pack_documents(docs, limit=64).collect()
    assert sum(r["length"] for r in rows) == sum(len(t.encode(d["text"] or "", add_special_tokens=False).ids) + 1 for d in docs.collect())
    by: dict = {}
    for r in sorted(rows, key=lambda r: (r["sequence_id"], r["offset"])):
        assert by.get(r["sequence_id"], 0) == r["offset"]
        by[r["sequence_id"]] = r["offset"] + r["length"]
        assert by[r["sequence_id"]] <= 64
    ids = array("I", [*t.encode(PASSAGE + " extra", add_special_tokens=False).ids, 0])
    assert next(r["ids_crc32"] for r in rows if r["doc_id"] == 5 and r["piece"] == 0) == zlib.crc32(ids[:64].tobytes())
    assert packing.pack_documents(_empty(docs)).count() == 0


def test_encoder_equals_tokenizer():
    from tokenizers import Tokenizer

    t, e = Tokenizer.from_file(default_vocabulary()), WordEncoder(default_vocabulary())
    for s in ["", "Don't STOP", "é́ ΣΑΣ", "a\x1cb", "x" * 300, "<|endoftext|> hi", "١٢ 字字 ß."]:
        assert e.encode([s])[0] == array("I", t.encode(s, add_special_tokens=False).ids).tobytes()


class _Counted:
    """A tokenizer that counts the texts it is given."""

    def __init__(self, inner):
        self.inner, self.texts = inner, 0

    def encode_batch_fast(self, texts, **options):
        self.texts += len(texts)
        return self.inner.encode_batch_fast(texts, **options)


def test_encoder_hands_over_new_words_together():
    """An encoding of its own for each new word was most of the time of op2_packing."""
    from tokenizers import Tokenizer

    t, e = Tokenizer.from_file(default_vocabulary()), WordEncoder(default_vocabulary())
    e.letters = _Counted(e.letters)
    rng = np.random.default_rng(7)
    words = ["".join(rng.choice(list("abcdeéñß"), rng.integers(3, 12))) for _ in range(5000)]
    texts = [" ".join(words[i : i + 50]) + "." for i in range(0, 5000, 50)]
    assert e.encode(texts) == [array("I", t.encode(s, add_special_tokens=False).ids).tobytes() for s in texts]
    assert e.letters.texts <= 10


@pytest.mark.parametrize(("limit", "longest"), [(500_000, 48), (0, 3)])
def test_encoder_equals_tokenizer_on_mixed_characters(limit, longest):
    from tokenizers import Tokenizer

    t, e = Tokenizer.from_file(default_vocabulary()), WordEncoder(default_vocabulary(), limit, longest)
    rng = np.random.default_rng(11)
    parts = [*"aAbZ  \t\n09.,'<>/@\x00\x1c\x7f\u0301×÷ßÿÀÞéÉµªº½ıŁςЖ字م١\xa0\u2028\u3000\x85😀\xad", "<|endoftext|>", "</w>", "'ll", "naïve", " THE ", "x1y22."]
    texts = ["".join(rng.choice(parts, rng.integers(0, 30))) for _ in range(3000)]
    got = [x for i in range(0, 3000, 70) for x in e.encode(texts[i : i + 70])]
    assert got == [array("I", x.ids).tobytes() for x in t.encode_batch_fast(texts, add_special_tokens=False)]


def test_best_fit_is_tight():
    sizes = np.random.default_rng(1).integers(1, 100, 500)
    bins, offsets = packing.best_fit(sizes, 100)
    assert bins.max() + 1 <= 1.05 * sizes.sum() / 100 + 1
    assert (offsets + sizes <= 100).all()


def test_sharding(docs, spark):
    rows = sharding.shard_by_bytes(docs, shards=2).collect()
    assert len(rows) == docs.count() and len({r["shard"] for r in rows if r["doc_id"] == 4}) == 1
    for s in {r["shard"] for r in rows}:
        assert sorted(r["slot"] for r in rows if r["shard"] == s) == list(range(sum(r["shard"] == s for r in rows)))
    label = sharding.differencing(np.arange(1, 200), 4)
    sums = np.bincount(label, weights=np.arange(1, 200))
    assert sums.max() - sums.min() <= 2
    assert sharding.shard_by_bytes(_empty(docs)).count() == 0


def test_near_duplicates(docs):
    got = {(r["doc_id"], r["n_shingles"]): r for r in neardup.near_duplicates(docs, 3, 85).collect()}
    assert got[(4, 58)]["component_id"] == 0 and got[(5, 59)]["component_id"] == 0 and not got[(5, 59)]["kept"]
    assert got[(2, 0)]["kept"] and got[(3, 0)]["component_id"] == 3
    assert neardup.near_duplicates(_empty(docs)).count() == 0
    assert neardup.least_matches(120, 0.85, 1e-7) < 0.85 * 120


def test_personal_data(docs):
    r = {x["doc_id"]: x for x in pii.digest(pii.find_spans(docs)).collect()}
    assert (r[6]["n_email"], r[6]["n_ip"], r[6]["n_card"], r[6]["n_phone"]) == (1, 1, 1, 1) and "iban:" in r[6]["spans"]
    assert r[2]["spans"] == ""
    assert "[email]" in {x["doc_id"]: x["text"] for x in pii.masked(docs).collect()}[6]


def test_line_dedup(docs):
    r = {x["doc_id"]: x for x in linededup.dedup_lines(docs.where("doc_id < 4 or doc_id = 5")).collect()}
    assert r[0]["n_removed"] == 0 and r[1]["text"] == "intro\nend" and r[1]["n_removed"] == 1 and r[2]["text"] is None and r[5]["n_removed"] == 0
    assert linededup.dedup_lines(_empty(docs)).count() == 0


def test_decontamination(docs, spark):
    item = PASSAGE[30:200]
    bench = spark.createDataFrame([(1, item), (2, "never seen anywhere in these texts at all"), (3, None), (4, "")], "item_id long, text string")
    edited = docs.unionByName(spark.createDataFrame([(9, "x " + item[:60] + "zz" + item[62:], "en")], docs.schema))
    got = {(r["doc_id"], r["item_id"]): r["distance"] for r in decontam.matches(edited, bench).collect()}
    assert got[(4, 1)] == 0 and 0 < got[(9, 1)] <= 2 and not any(i != 1 for _, i in got)
    assert decontam.decontaminate(edited, bench).where("doc_id in (0, 1, 4, 5, 9)").count() == 0


def test_edit_distance_equals_table():
    rng = np.random.default_rng(4)
    for _ in range(60):
        p, t = ("".join(rng.choice(list("ab"), n)) for n in (rng.integers(1, 8), rng.integers(1, 14)))
        row = [0] * (len(t) + 1)
        for i, a in enumerate(p, 1):
            new = [i]
            for j, b in enumerate(t, 1):
                new.append(min(row[j - 1] + (a != b), row[j] + 1, new[-1] + 1))
            row = new
        hit = decontam.best_match(p, t, 99)
        assert hit is not None and hit[0] == min(row[1:])


def test_language(docs):
    m = langid.CharModels.fit({"en": ["the cat and the dog went there"] * 5, "de": ["der hund und die katze gingen dort"] * 5}).calibrate({"en": ["the cat"], "de": ["der hund"]})
    r = {x["doc_id"]: x for x in langid.predict(docs.withColumn("score", docs.doc_id), m).collect()}
    assert r[2]["lang_pred"] == "und" and r[2]["score"] == 0 and r[3]["rejected"]
    rates, _ = m.rates(["the dog", "die katze"], {})
    assert m.langs[rates[0].argmin()] == "en" and m.langs[rates[1].argmin()] == "de"
    assert {x["lang_pred"] for x in langid.predict(docs, None).collect()} == {"und"}


def test_toxicity(docs):
    texts = ["you are a zorgle"] * 20 + ["a kind day"] * 40
    g = toxicity.induce(texts, [1] * 20 + [0] * 40)
    near, far, plain = g.score(["you zorgle", 'he said that "zorgle" is not zorgle', ""])
    assert near > 0.7 > plain and near >= far
    assert toxicity.scores(docs, g).count() == docs.count()


def test_token_histogram(docs):
    n = sorted(r["n_tokens"] for r in token_histogram.document_lengths(docs).collect())
    h = token_histogram.length_histogram(token_histogram.document_lengths(docs))
    assert token_histogram.truncated_total(h, 10).first()["kept_tokens"] == sum(min(x, 10) for x in n)
    assert token_histogram.length_quantile(h, 0.5).first()["quantile"] == n[(len(n) + 1) // 2 - 1]


def test_image_copies(spark):
    rng = np.random.default_rng(6)
    v = rng.normal(size=(6, 64))
    images = [media.render(x) for x in v]
    edits = [images[0], images[0][6:, 5:], (images[1] * 0.8 + 20).astype(np.uint8), np.rot90(images[2]).copy()]
    rows = [(i, x.shape[1], x.shape[0], bytearray(x.tobytes())) for i, x in enumerate([*images, *edits])] + [(99, None, None, None)]
    got = {r["media_id"]: r["group_id"] for r in media.edited_copies(spark.createDataFrame(rows, "media_id long, width int, height int, pixels binary")).collect()}
    assert [got[i] for i in range(10)] == [0, 1, 2, 3, 4, 5, 0, 0, 1, 2] and got[99] == 99


def test_crops_of_large_images_agree():
    """A half and a quarter of a large image whose strongest corners lie outside the crop; one true transform behind many false partners."""
    rng = np.random.default_rng(8)
    image = media.blur(np.kron(rng.uniform(100, 150, (50, 50)), np.ones((8, 8))))
    image[:200, :200] = (image[:200, :200] - 125) * 4 + 125
    image = image.clip(0, 255).astype(np.uint8)
    whole = media.describe(image)
    assert len(whole) > 32
    for crop in (image[:, 200:], image[200:, 200:]):
        assert media.consensus(whole, media.describe(crop), enough=12) >= 12
    a = _corners(rng, 30)
    b = a.copy()
    b["x"][:20], b["y"][:20] = rng.uniform(0, 200, 20), rng.uniform(0, 200, 20)
    assert media.consensus(a, b) >= 10 and media.consensus(a, b, enough=8) >= 8
    assert not np.array_equal(media.render(np.ones(100) * np.arange(100)), media.render(np.ones(64) * np.arange(64)))


def _corners(rng, n):
    out = np.zeros(n, media.FIELDS)
    out["x"], out["y"], out["scale"] = rng.uniform(0, 200, n), rng.uniform(0, 200, n), 1
    out["bits"] = rng.integers(0, 2**32, (n, media.WORDS), dtype=np.uint64).astype(np.uint32)
    return out


def _turned(image, degrees):
    a, (h, w) = np.deg2rad(degrees), image.shape
    y, x = np.mgrid[:h, :w] - np.array([(h - 1) / 2, (w - 1) / 2])[:, None, None]
    return media.sample(image, np.cos(a) * x - np.sin(a) * y + (w - 1) / 2, np.sin(a) * x + np.cos(a) * y + (h - 1) / 2)


def test_image_copies_against_consensus_over_all_pairs(spark):
    """Groups are those of the consensus over all pairs of images, with a recall of at least 0.9 for every kind of edit."""
    rng = np.random.default_rng(13)
    kinds = {
        "noise": lambda i: i + rng.normal(0, 5, i.shape), "crop": lambda i: i[8:, 6:], "0.7": lambda i: media.resize(i, 0.7), "0.85": lambda i: media.resize(i, 0.85), "1.2": lambda i: media.resize(i, 1.2)[6:, 8:],
        "1.4": lambda i: media.resize(i, 1.4), "right angle": lambda i: np.rot90(i), "turn": lambda i: _turned(i, 20),
    }
    images, whole, kind_of = [], [media.render(x) for x in rng.normal(size=(20 * len(kinds), 64))], {}
    for n, image in enumerate(whole):
        name = list(kinds)[n % len(kinds)]
        kind_of[len(images) + 1] = name
        images += [image, np.ascontiguousarray(kinds[name](image.astype(float)).clip(0, 255).round().astype(np.uint8))]
    described = [media.describe(x) for x in images]
    for i in range(0, 40, 2):
        assert all(media.consensus(described[i], described[j]) < 12 for j in range(i + 2, 80))
    rows = [(i, x.shape[1], x.shape[0], bytearray(x.tobytes())) for i, x in enumerate(images)]
    got = {r["media_id"]: r["group_id"] for r in media.edited_copies(spark.createDataFrame(rows, "media_id long, width int, height int, pixels binary")).collect()}
    assert all(g in (i, i - i % 2) for i, g in got.items())
    for name in kinds:
        linked = [got[i] == i - 1 for i, k in kind_of.items() if k == name and media.consensus(described[i - 1], described[i]) >= 12]
        assert len(linked) >= 18 and np.mean(linked) >= 0.9, name


@pytest.mark.parametrize("crowd", [4, 40])
def test_every_bucket_member_meets_what_is_still_apart(spark, monkeypatch, crowd):
    """Images that share one key and nothing else with a crowd: the two copies among them are found, small bucket or large."""
    rng = np.random.default_rng(9)
    made = [media.stored(_corners(rng, 14)) for _ in range(crowd)]
    made.append(made[-1].copy())
    made[-1]["x"] += 5
    rows = [(i, len(m), bytearray(m.tobytes()), [7, 100 + i], bytearray(str(i).encode())) for i, m in enumerate(made)]
    monkeypatch.setattr(media, "features", lambda m: m)
    got = {r["media_id"]: r["group_id"] for r in media.edited_copies(spark.createDataFrame(rows, "media_id long, n_corners int, corners binary, keys array<long>, same binary")).collect()}
    assert got == {i: min(i, crowd - 1) for i in range(crowd + 1)}


def test_every_near_pair_of_corners_has_its_key():
    """No share of the keys is left out: an image has about as many as near pairs of corners on a level."""
    level = media.blur(np.random.default_rng(4).uniform(0, 255, (60, 60)))
    ys, xs = (g.ravel() for g in np.mgrid[10:50:7, 10:50:7])
    keys = media._pair_keys(level, xs, ys, np.zeros(len(xs)))
    assert len(keys) >= 0.99 * len(media._near_pairs(xs.astype(float), ys.astype(float))[0])


def test_images_without_a_common_key_meet_by_every(spark, monkeypatch):
    """Copies that share no key are linked by their corners alone where that is asked for, across blocks and within one."""
    rng = np.random.default_rng(10)
    made = [media.stored(_corners(rng, 14)) for _ in range(6)]
    made += [made[4].copy(), made[1].copy()]
    made[6]["x"] += 5
    made[7]["y"] += 5
    rows = [(i, len(m), bytearray(m.tobytes()), [100 + i], bytearray(str(i).encode())) for i, m in enumerate(made)]
    monkeypatch.setattr(media, "features", lambda m: m)
    df = spark.createDataFrame(rows, "media_id long, n_corners int, corners binary, keys array<long>, same binary")
    assert {r["media_id"]: r["group_id"] for r in media.edited_copies(df, every=True).collect()} == {i: i for i in range(6)} | {6: 4, 7: 1}
    reps = df.selectExpr("same", "media_id as rep")
    apart = media.links_apart(reps, df, spark.createDataFrame([(1, 1), (7, 1)], "id long, component long"), 12, block_bytes=1200)
    assert [tuple(r) for r in apart.collect()] == [(4, 6)]


def test_image_copies_leave_no_shuffle_files(spark, monkeypatch):
    """What the steps deal out is off the disk when they have ended, and images that need several turns of verification are still linked."""
    rng = np.random.default_rng(12)
    made = [media.stored(_corners(rng, 14)) for _ in range(30)]
    made += [m.copy() for m in made[:4]]
    for m in made[30:]:
        m["x"] += 5
    rows = [(i, len(m), bytearray(m.tobytes()), [7 << 40, (100 + i) << 40], bytearray(str(i).encode())) for i, m in enumerate(made)]
    monkeypatch.setattr(media, "features", lambda m: m)
    df = spark.createDataFrame(rows, "media_id long, n_corners int, corners binary, keys array<long>, same binary")
    files = lambda: {x for x in str(spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString(" ")).split() if "shuffle_" in x}
    before = files()
    out = media.edited_copies(df)
    for _ in range(50):
        if not (left := files() - before):
            break
        time.sleep(0.1)
    assert not left
    assert {r["media_id"]: r["group_id"] for r in out.collect()} == {i: i % 30 if i >= 30 else i for i in range(34)}


def test_heads_of_shared_keys(spark):
    """A head is found if and only if two rows have it, in one batch or in two; keys of either sign."""
    rows = [([-5, 3 << 50, 9 << 45],), ([-5, 1 << 60],), ([],), ([3 << 50, -(1 << 62)],)]
    for parts in (1, 4):
        got = sorted(r["head"] for r in media.shared_heads(spark.createDataFrame(rows, "keys array<long>").repartition(parts)).collect())
        assert got == sorted((k % 2**64) >> (64 - media.HEAD) for k in (-5, 3 << 50))


def test_pairs_at_once_equal_consensus():
    """The comparison of many images at once finds the pairs of the consensus, in both directions."""
    rng = np.random.default_rng(11)
    made = [media.stored(media.describe(media.render(v))) for v in rng.normal(size=(24, 64))]
    rows, block = made[:8], made[8:]
    open_, turned = rng.random((8, 16)) < 0.8, rng.random((8, 16)) < 0.5
    want = {(r, s) for r in range(8) for s in range(16) if open_[r, s] and (media.consensus(block[s], rows[r]) if turned[r, s] else media.consensus(rows[r], block[s])) >= 6}
    assert want and set(media.agreeing_of_all(rows, block, open_, turned, 6)) == want


def test_samples_collapse_copies(spark):
    """Languages and labels whose rows are copies of few texts keep every one of those texts."""
    letters = "abcdefghij"
    name = lambda i: "".join(letters[int(c)] for c in str(i))
    rows = [("one text of one language", "xx")] * 4000 + [(f"wort {name(i % 20)} und mehr", "yy") for i in range(4000)] + [(f"word {name(i)} and more", "en") for i in range(4000)] + [("123 456", "zz"), ("zz text", "zz")]
    got = langid.training_texts(spark.createDataFrame(rows, "text string, lang string"), 50)
    assert {k: len(set(v)) for k, v in got.items()} == {"xx": 1, "yy": 20, "en": 50, "zz": 1}
    assert all(len(v) == len(set(v)) for v in got.values())
    rows = [(f"you are a zorgle {name(i % 4)}", 1) for i in range(4000)] + [(f"a kind day {name(i)}", 0) for i in range(4000)]
    grammar = toxicity.fit(spark.createDataFrame(rows, "text string, toxic int"), per_class=40)
    assert grammar.base == pytest.approx(4 / 124) and "zorgle" in str(grammar.insults) + str(grammar.prefixes) and grammar.score(["you zorgle"])[0] > grammar.score(["a kind day"])[0]


def test_rejection_levels_come_from_rows_outside_the_sample(spark):
    """Clean rows that the sample does not hold pass, also where the sample is a small part or the whole of a language; noise does not."""
    rng = np.random.default_rng(12)
    stems = ["".join(rng.choice(list("abdegilmnorst"), 7)) for _ in range(3000)]
    texts = [" ".join(stems[k] for k in rng.integers(0, 3000, 20)) for _ in range(1500)]
    rows = [(t, "big") for t in texts] + [(" ".join(stems[k] for k in range(i, i + 20)), "small") for i in range(0, 300, 20)] + [("only text", "single")]
    df = spark.createDataFrame(rows, "text string, lang string")
    m = langid.fit(df, per_lang=15)
    level = dict(zip(m.langs, m.reject, strict=True))
    sample = langid.training_texts(df, 15)
    held = [t for t in texts if t not in set(sample["big"])]
    rates = m.rates(held, {})[0][:, m.langs.index("big")]
    assert level["big"] == pytest.approx(1.25 * np.sort(rates)[int(np.ceil(0.999 * len(rates))) - 1]) and (rates <= level["big"]).all()
    assert np.isinf(level["single"]) and level["small"] > 1.25 * m.rates(sample["small"], {})[0][:, m.langs.index("small")].max()
    assert m.rates(["qzxj wqvk xxzq"], {})[0][0, m.langs.index("big")] > level["big"]


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(spark, name):
    from outlyer.llm.queries import queries

    d = "/root/testdata/sf0.001"
    c = duckdb.connect()
    for f in os.listdir(d):
        c.sql(f"create view {f[:-8]} as select * from '{d}/{f}'")
    df = queries()[name](spark, d)
    cols = sorted(df.columns)
    r = c.sql(ORACLES[name])
    assert sorted(tuple(x[k] for k in cols) for x in df.collect()) == sorted(tuple(dict(zip(r.columns, x))[k] for k in cols) for x in r.fetchall())
