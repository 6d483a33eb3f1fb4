"""The stages of the pipeline against plain Python over a small corpus with every case planted."""

import re

import numpy as np
import pytest
from test_brute import grouped, levenshtein_inside, shingles

import corpus_pipeline
from outlyer.llm import decontam
from outlyer.llm.common import cut

RNG = np.random.default_rng(21)
STEMS = {"en": ["".join(RNG.choice(list("abdeghiklmnoprst"), 6)) for _ in range(400)], "fr": ["".join(RNG.choice(list("àcéèijouqvxyzê"), 6)) for _ in range(400)]}


def prose(lang, n):
    return " ".join(STEMS[lang][i] for i in RNG.integers(0, 400, n))


@pytest.fixture(scope="module")
def corpus(spark, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("corpus"))
    passage, item = prose("en", 60), prose("en", 25)
    rows = [(i, prose(lang, 80), lang) for i, lang in enumerate(["en", "fr"] * 25)]
    rows += [(100, f"{passage}\nfirst of them {prose('en', 30)}", "en"), (101, f"other head {prose('en', 30)}\n{passage}\ntail {prose('en', 20)}", "en"), (102, passage, "en")]
    words = rows[4][1].split()
    rows += [(110, " ".join([*words[:-1], "changed"]), "en"), (111, rows[4][1], "en"), (112, " ".join(words[:40]), "en")]
    rows += [(120, f"{prose('en', 20)} {item[:40]}zz{item[41:]} {prose('en', 20)}", "en"), (121, f"{prose('en', 9)} {item[: len(item) // 2]}", "en")]
    rows += [(130, None, None), (131, "", "en"), (132, "12 34 56", None), (None, prose("en", 60), "en"), (4, prose("fr", 40), "fr")]
    docs = spark.createDataFrame([(i, t, lang, "s", 0 if t is None else len(t), 0.25, 3) for i, t, lang in rows], "doc_id long, text string, lang string, source string, n_chars long, score double, gone int")
    docs.write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame([(1, item), (2, "never to be found in any of these documents")], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    return d, item


def plain_lines(rows):
    """Windows of whole lines with at least 50 words, shortest from and to each line: later copies go."""
    seen, gone = {}, {}
    for i, text in sorted({(i, t) for i, t in rows if t is not None and i is not None}):
        lines = [(k, x.strip()) for k, x in enumerate(text.split("\n")) if x.strip()]
        counts = [len(re.split(r"\s+", x)) for _, x in lines]
        spans = set()
        for s in range(len(lines)):
            for e in range(s, len(lines)):
                if sum(counts[s : e + 1]) >= 50:
                    spans.add((s, e))
                    break
        for e in range(len(lines)):
            for s in range(e, -1, -1):
                if sum(counts[s : e + 1]) >= 50:
                    spans.add((s, e))
                    break
        for s, e in sorted(spans):
            key = tuple(x for _, x in lines[s : e + 1])
            if seen.setdefault(key, (i, text, s)) != (i, text, s):
                gone.setdefault((i, text), set()).update(lines[k][0] for k in range(s, e + 1))
    return gone


def test_stages_equal_plain_python(spark, corpus):
    d, item = corpus
    docs = spark.read.parquet(f"{d}/documents.parquet")
    columns = docs.columns
    take = lambda df: [(r["doc_id"], r["text"]) for r in df.collect()]
    kept = cut(corpus_pipeline.language(spark, docs, d))
    assert kept.columns == columns and kept.where("score = 0.25 and gone = 3").count() == kept.count()
    ids = {i for i, _ in take(kept)}
    assert {i for i, _ in take(docs)} - ids == {130, 131, 132}

    before = take(kept)
    lines = cut(corpus_pipeline.lines(spark, kept, d))
    gone = plain_lines(before)
    want = []
    for i, t in before:
        left = "\n".join(x for k, x in enumerate(t.split("\n")) if k not in gone.get((i, t), ()))
        if left.strip() or (i, t) not in gone:
            want.append((i, left))
    key = lambda x: (x[0] is None, x)
    assert lines.columns == columns and sorted(take(lines), key=key) == sorted(want, key=key) and not {102, 111} & {i for i, _ in want}
    assert all(r["n_chars"] == len(r["text"]) for r in lines.collect())

    before = take(lines)
    rest = cut(corpus_pipeline.near_duplicates(spark, lines, d))
    rows = [(i, t) for i, t in before if i is not None]
    groups = grouped(list(range(len(rows))), [shingles(t, 5) for _, t in rows], 80)
    lost = {rows[k][0] for k, g in groups.items() if rows[g][0] < rows[k][0]} - {4}
    assert sorted(take(rest), key=key) == sorted(((i, t) for i, t in before if i not in lost), key=key) and lost == {110}

    before = take(rest)
    clean = cut(corpus_pipeline.decontaminated(spark, rest, d))
    items = [decontam.normalise(x) for x in (item, "never to be found in any of these documents")]
    hit = {i for i, t in before if any(levenshtein_inside(x, decontam.normalise(t)) <= decontam.budget(len(x), 0.08, 24) for x in items)}
    assert sorted(take(clean), key=key) == sorted(((i, t) for i, t in before if i not in hit), key=key) and hit == {120}

    packed = corpus_pipeline.packed(spark, clean, d).collect()
    assert {r["doc_id"] for r in packed} == {i for i, _ in take(clean)} and all(r["offset"] + r["length"] <= 2048 for r in packed)


def test_run_on_an_empty_corpus(spark, tmp_path):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_no_labels_reject_nothing(spark):
    docs = spark.createDataFrame([(1, "some text", None), (2, None, None)], "doc_id long, text string, lang string")
    assert corpus_pipeline.language(spark, docs, "").count() == 2
