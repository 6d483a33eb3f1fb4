"""Operators against plain Python over all rows or pairs, and the cases the docstrings name: empty, null, long, tied, repeated, clashing."""

import re
import time
import zlib
from array import array
from collections import Counter

import numpy as np
import pytest

from outlyer.llm import decontam, langid, linededup, media, neardup, packing, pii, sharding, token_histogram, toxicity
from outlyer.llm.common import guarded, table
from outlyer.llm.queries import op1_toxicity, op6_language
from outlyer.llm.tokens import default_vocabulary
from outlyer.operators.isolation import auc

SMALL = "/root/testdata/sf0.001"


def shingles(text, width):
    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if c.isascii() else c for c in text or ""))
    return {tuple(words[i : i + width]) for i in range(max(1, len(words) - width + 1))} if words else set()


def grouped(ids, sets, pct):
    """Smallest id reachable over pairs of sets that are similar enough."""
    of = {i: i for i in ids}

    def root(i):
        while of[i] != i:
            i = of[i]
        return i

    for a, x in zip(ids, sets, strict=True):
        for b, y in zip(ids, sets, strict=True):
            if a < b and x and y and 100 * len(x & y) >= pct * len(x | y):
                of[max(root(a), root(b))] = min(root(a), root(b))
    return {i: root(i) for i in ids}


def levenshtein_inside(item, text):
    """Smallest edit distance of the item to any part of the text."""
    row = np.zeros(len(text) + 1, int)
    for i, a in enumerate(item, 1):
        step = np.minimum(row[:-1] + (np.array(list(text)) != a), row[1:] + 1)
        new = np.empty_like(row)
        new[0] = i
        # insertions: new[j] = min over k <= j of step[k] + (j - k)
        places = np.arange(1, len(text) + 1)
        new[1:] = np.minimum(np.minimum.accumulate(step - places), i) + places
        row = new
    return int(row.min())


@pytest.mark.parametrize(("width", "pct"), [(3, 85), (5, 80)])
def test_near_duplicates_equal_all_pairs(spark, width, pct):
    docs = table(spark, SMALL, "documents")
    rows = docs.select("doc_id", "text").collect()
    ids, sets = [r["doc_id"] for r in rows], [shingles(r["text"], width) for r in rows]
    want = grouped(ids, sets, pct)
    got = {r["doc_id"]: r for r in neardup.near_duplicates(docs, width, pct).collect()}
    assert {i: r["component_id"] for i, r in got.items()} == want
    assert all(got[i]["n_shingles"] == len(s) and got[i]["kept"] == (want[i] == i) for i, s in zip(ids, sets, strict=True))


def test_two_texts_of_one_id_both_link_in_crowded_buckets(spark):
    """A bucket of more than ``small`` texts: each text of a repeated id meets what it is like."""
    base = [f"w{i}" for i in range(200)]
    vary = lambda k: " ".join([*base[: 190 - k], *(f"x{k}-{i}" for i in range(10 + k))])
    other = [f"v{i}" for i in range(100)]
    rows = [(i, vary(i)) for i in range(1, 30)] + [(50, vary(31)), (50, " ".join(other)), (51, " ".join([*other[:99], "z"]))]
    got = {(r["doc_id"], r["n_shingles"]): r["component_id"] for r in neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), small=3).collect()}
    sets = [shingles(t, 5) for _, t in rows]
    want = grouped(list(range(len(rows))), sets, 80)
    assert {got[rows[i][0], len(sets[i])] == got[rows[j][0], len(sets[j])] or want[i] != want[j] for i in range(len(rows)) for j in range(len(rows))} == {True}
    assert got[51, len(sets[-1])] == 50


def test_decontamination_equals_whole_text_distance(spark):
    rng = np.random.default_rng(3)
    word = lambda: "".join(rng.choice(list("abcdefgh"), 5))
    items = [(i, " ".join(word() for _ in range(int(rng.integers(3, 14))))) for i in range(12)]
    rows = []
    for d in range(60):
        body = list(items[d % 12][1])
        for _ in range(int(rng.integers(0, 9))):
            at = int(rng.integers(len(body)))
            body[at : at + int(rng.integers(0, 2))] = list(rng.choice(list("xyz"), int(rng.integers(0, 2))))
        rows.append((d, " ".join([word(), "".join(body), word()])))
    got = {(r["doc_id"], r["item_id"]): r["distance"] for r in decontam.matches(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()}
    want = {}
    for d, text in rows:
        for i, item in items:
            found = levenshtein_inside(decontam.normalise(item), decontam.normalise(text))
            if found <= decontam.budget(len(item), 0.08, 24):
                want[d, i] = found
    assert got == want and len({i for _, i in want}) > 5 and max(want.values()) > 1


def test_token_report_equals_plain_counts(spark):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(default_vocabulary())
    docs = table(spark, SMALL, "documents").limit(80).unionByName(spark.createDataFrame([(9001, None, None, None, None), (9002, "", "en", "s", 0)], table(spark, SMALL, "documents").schema))
    n = {r["doc_id"]: len(t.encode(r["text"] or "", add_special_tokens=False).ids) for r in docs.collect()}
    all_n = np.array(list(n.values()))
    for r in token_histogram.document_report(token_histogram.document_lengths(docs)).collect():
        own = n[r["doc_id"]]
        assert (r["n_tokens"], r["docs_at_least"], r["docs_fitting"], r["truncated_total"]) == (own, (all_n >= own).sum(), (all_n <= own).sum(), np.minimum(all_n, own).sum())


def test_packing_keeps_every_id_and_wastes_little(spark):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(default_vocabulary())
    docs = table(spark, SMALL, "documents")
    ids = {r["doc_id"]: [*t.encode(r["text"] or "", add_special_tokens=False).ids, 0] for r in docs.collect()}
    rows = packing.pack_documents(docs, 512).collect()
    by: dict = {}
    seen = {i: 0 for i in ids}
    for r in sorted(rows, key=lambda r: (r["doc_id"], r["piece"])):
        part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert r["start"] == seen[r["doc_id"]] and len(part) == r["length"] and zlib.crc32(array("I", part).tobytes()) == r["ids_crc32"]
        seen[r["doc_id"]] += r["length"]
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert seen == {i: len(x) for i, x in ids.items()}
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 512
    assert len(by) <= 1.02 * sum(map(len, ids.values())) / 512 + 2


def test_tree_packing_is_near_plain_best_fit(spark):
    """Many blocks against one: uniform lengths, the hard case; ties and repeated ids among them."""
    sizes = np.random.default_rng(5).integers(1, 2049, 20_000)
    rows = spark.createDataFrame([(int(i % 500), 0, 0, int(n), 0) for i, n in enumerate(sizes)], packing.PIECES).cache()
    rows.count()
    got = packing.pack(rows, per_block=1000, carry=62).select("sequence_id").distinct().count()
    assert got <= 1.02 * (packing.best_fit(sizes, 2048)[0].max() + 1)


def test_sharding_keeps_groups_whole_and_even(spark):
    rng = np.random.default_rng(2)
    rows = [(i, "same text " * 5) for i in range(400)] + [(1000 + i, "x" * int(rng.integers(1, 400))) for i in range(3000)] + [(9000, None), (9001, ""), (1000, "repeated id")]
    got = sharding.shard_by_bytes(spark.createDataFrame(rows, "doc_id long, text string"), shards=4, per_block=500).collect()
    assert len(got) == len(rows)
    of: dict = {}
    for r in got:
        of.setdefault((r["size"], r["text_crc32"]), set()).add(r["shard"])
    assert all(len(s) == 1 for s in of.values())
    total = Counter()
    for r in got:
        total[r["shard"]] += r["size"]
    assert max(total.values()) - min(total.values()) <= 400
    for s in range(4):
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(sum(r["shard"] == s for r in got)))
    hot = sharding.shard_by_bytes(spark.createDataFrame([(i, "y" * 50) for i in range(300)] + [(300 + i, "z" * (i % 40)) for i in range(300)], "doc_id long, text string"), shards=4, per_block=50).collect()
    assert len({r["shard"] for r in hot if r["size"] == 51}) == 1
    rest = Counter()
    for r in hot:
        rest[r["shard"]] += r["size"]
    assert np.ptp(sorted(rest.values())[:3]) <= 45


def test_block_partials_are_combined_by_differencing():
    sizes = np.random.default_rng(1).integers(1, 10_000, 4000)
    parts = [sizes[k::8] for k in range(8)]
    partials = []
    for p in parts:
        label = sharding.differencing(p, 16)
        partials.append((np.bincount(label, weights=p, minlength=16).astype(np.int64), None))
    sums, labels = sharding.combine(partials)
    assert np.ptp(sums) <= max(np.ptp(s) for s, _ in partials) and sums.sum() == sizes.sum()
    assert np.array_equal(np.bincount(labels.ravel(), weights=np.concatenate([s for s, _ in partials]), minlength=16), sums)


def test_held_out_accuracy(spark):
    d = "/root/testdata/sf0.01"
    langs = {r["doc_id"]: r["lang"] for r in table(spark, d, "documents").select("doc_id", "lang").collect()}
    got = [r for r in op6_language(spark, d).collect() if r["held_out"] and langs[r["doc_id"]] is not None and r["lang_pred"] != "und"]
    assert np.mean([langs[r["doc_id"]] == r["lang_pred"] for r in got]) >= 0.98
    toxic = {r["doc_id"]: r["toxic"] for r in table(spark, d, "labels").collect()}
    rows = [r for r in op1_toxicity(spark, d).collect() if r["held_out"] and r["doc_id"] in toxic]
    assert auc(np.array([r["score"] for r in rows]), np.array([toxic[r["doc_id"]] for r in rows])) >= 0.85


def test_clauses_not_words():
    g = toxicity.Grammar({"zorgle": 1.0}, {})
    assert g.weigh("you are a zorgle") > g.weigh("the zorgle") < g.weigh("a zorgle, you")
    assert g.weigh("not a zorgle") < g.weigh("the zorgle") > g.weigh('he said "zorgle"') and g.weigh("zorgle, he said") < g.weigh("zorgle")
    assert g.weigh("i will kill you") >= toxicity.MATCH > g.weigh("the kills") and g.weigh("they are going to strangle him") >= toxicity.MATCH
    assert {"killed", "kills", "killing", "tötet", "mataré"} <= set(toxicity.threat_forms())
    assert g.clauses("One zorgle. None here! You zorgle") == [g.weigh("one zorgle"), g.weigh(" you zorgle")]


def test_very_long_texts_take_linear_time(spark):
    g = toxicity.Grammar({"zorgle": 1.0}, {"zorg": 0.5})
    took = []
    for n in (50_000, 200_000):
        began = time.perf_counter()
        assert len(g.clauses("abc zorgle " * n)) == 1
        took.append(time.perf_counter() - began)
    assert took[1] < 12 * took[0] + 0.5
    many = "a@b.co 10.0.0.1 " * 4000
    long = spark.createDataFrame([(1, many), (2, "word " * 300_000), (3, "x" * 400_000)], "doc_id long, text string")
    r = {x["doc_id"]: x for x in pii.digest(pii.find_spans(long)).collect()}
    assert (r[1]["n_email"], r[1]["n_ip"], r[2]["n_email"]) == (4000, 4000, 0)
    at = re.findall(r"email:(\d+):", r[1]["spans"])
    assert [int(x) for x in at] == list(range(0, 16 * 4000, 16))
    assert {x["doc_id"]: x["n_shingles"] for x in neardup.near_duplicates(long).collect()} == {1: 2, 2: 1, 3: 1}
    assert sum(x["length"] for x in packing.pack_documents(long).collect()) > 300_000
    assert linededup.dedup_lines(long).where("n_removed = 0").count() == 3


def test_context_words_decide_weak_kinds(spark):
    rows = [(1, "call me: +49 170 1234567"), (2, "row +49 170 1234567"), (3, "host 10.0.0.1"), (4, "v 10.0.0.1"), (5, "me@b.co")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r["doc_id"]: r["n_sure"] for r in pii.digest(pii.find_spans(docs)).collect()} == {1: 1, 2: 0, 3: 1, 4: 0, 5: 1}
    assert {r["doc_id"]: r["text"] for r in pii.masked(docs).collect()} == {1: "call me: [phone]", 2: rows[1][1], 3: "host [ip]", 4: rows[3][1], 5: "[email]"}


def test_line_dedup_keeps_rows_of_one_id_apart(spark):
    copy = " ".join(f"w{i}" for i in range(60))
    rows = [(1, copy), (2, "C keep me\nD keep me"), (2, copy + "\nE tail"), (2, copy + "\nE tail"), (None, copy)]
    got = sorted((r["doc_id"] or 0, r["text"], r["n_removed"]) for r in linededup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == [(0, copy, 0), (1, copy, 0), (2, "C keep me\nD keep me", 0), (2, "E tail", 1), (2, "E tail", 1)]


def test_empty_tables(spark):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, toxic int")
    images = spark.createDataFrame([], "media_id long, width int, height int, pixels binary")
    assert toxicity.scores(docs, toxicity.fit(docs)).count() == 0 and pii.digest(pii.find_spans(docs)).count() == 0
    assert langid.fit(docs) is None and langid.predict(docs, None).count() == 0
    items = docs.selectExpr("doc_id as item_id", "text")
    some = spark.createDataFrame([(1, "a text"), (None, "b")], "doc_id long, text string")
    assert decontam.matches(docs, items).count() == 0 and decontam.decontaminate(some, items).count() == 2
    report = token_histogram.document_report(token_histogram.document_lengths(docs))
    assert report.count() == 0 and token_histogram.length_quantile(token_histogram.length_histogram(token_histogram.document_lengths(docs)), 0.5).first()[0] is None
    assert media.edited_copies(images).count() == 0


def test_clashing_columns_are_put_back(spark):
    df = spark.createDataFrame([(1, "t", 0.5, True, 7, 8, "k")], "doc_id long, text string, score double, rejected boolean, gone int, `a.b` int, h string")
    own, back = guarded(df, "doc_id", "text")
    assert not {"score", "rejected", "gone", "h"} & set(own.columns)
    assert back(own.withColumn("score", own.doc_id)).collect() == df.collect()
    more = df.drop("a.b")
    assert neardup.near_duplicates(more).count() == packing.pack_documents(more).count() == sharding.shard_by_bytes(more).count() == linededup.dedup_lines(more).count() == 1
    assert linededup.dedup_lines(more).first()["gone"] == 7
