"""Language identification by interpolated Kneser-Ney character models, one per language.

A word is its letters between two boundary marks; contexts do not cross words, so a text's cross-entropy is
the sum of its words' divided by its characters. N-gram codes are 64-bit hashes in sorted arrays, one array
an order with one row of log-probabilities and back-off weights per language, looked up by binary search.
The language with the lowest length-normalised cross-entropy wins. Calibration: a temperature turns
cross-entropy gaps into a posterior, and a text whose own cross-entropy lies above the rejection level of its
language is rejected. The level comes from the rates of all labelled rows the model was not fitted on.

The model is fitted on at most ``per_lang`` whole, different labelled texts a language (smallest hash of the text
first; copies count once), so its size is bounded whatever the corpus. Every text is scored whole.

Edge cases: null, empty or letterless text is ``und`` with score 0, and rejected; rows with null lang are not
learned from; with no labelled rows everything is ``und``; lang, source and ids never enter a prediction.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, smallest_hashes

ORDER, START, END = 5, 1, 2
_WORD = re.compile(r"[^\W\d_]+")
_MIX = np.uint64(0x9E3779B97F4A7C15)


def _codes(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all words, each between a start and an end mark; and, for each place, how far it is into its word."""
    joined = np.frombuffer(("\x01" + "\x02\x01".join(words) + "\x02").encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    starts = np.flatnonzero(joined == START)
    place = np.arange(len(joined)) - np.repeat(starts, np.diff(np.append(starts, len(joined))))
    return joined, place


def _hashes(codes: np.ndarray, place: np.ndarray) -> list[np.ndarray]:
    """hash[n-1][i]: the n-gram that ends at i (0 where it would start before its word)."""
    out = []
    for n in range(1, ORDER + 1):
        h = np.full(len(codes), n, np.uint64)
        for back in range(n - 1, -1, -1):
            shifted = np.concatenate([np.zeros(back, np.uint64), codes[: len(codes) - back]]) if back else codes
            h = (h ^ shifted) * _MIX
            h ^= h >> np.uint64(31)
        h[place < n - 1] = 0
        out.append(h)
    return out


class CharModels:
    """Sorted hash arrays of n-grams with probabilities for each language."""

    def __init__(self, langs: list[str], grams, probs, weights, reject=None, temperature: float = 1.0):
        self.langs, self.grams, self.probs, self.weights = langs, grams, probs, weights
        self.reject, self.temperature = reject, temperature

    @classmethod
    def fit(cls, texts: dict[str, list[str]], discount: float = 0.75) -> CharModels:
        """Interpolated Kneser-Ney: the highest order counts occurrences, lower orders count distinct left contexts.

        No context crosses a word, so each different word is read once and counts as often as it occurs.
        """
        langs = sorted(texts)
        raw = {}
        for lang in langs:
            words = Counter(w for t in texts[lang] for w in _WORD.findall(t.lower())) or Counter(["a"])
            codes, place = _codes(list(words))
            times = np.repeat(np.fromiter(words.values(), np.float64, len(words)), np.diff(np.append(np.flatnonzero(place == 0), len(place))))
            raw[lang] = (place, _hashes(codes, place), times)
        grams, probs, weights = [], [], []
        alphabet = max(2, len(np.unique(np.concatenate([raw[x][1][0] for x in langs]))))
        for n in range(1, ORDER + 1):
            union = np.unique(np.concatenate([h[1][n - 1][h[0] >= n - 1] for h in raw.values()]))
            union = union[union != 0]
            grams.append(union)
            probs.append(np.zeros((len(union), len(langs)), np.float64))
            weights.append(np.ones((len(union), len(langs)), np.float64))
        for li, lang in enumerate(langs):
            place, h, times = raw[lang]
            for n in range(1, ORDER + 1):
                ok = place >= max(n - 1, 1)  # the start mark itself is never predicted
                gram, often = h[n - 1][ok], times[ok]
                if n < ORDER:  # continuation counts, but what follows the start has no left context and counts by itself
                    at_start = place[ok] == n - 1
                    longer = gram[~at_start][np.unique(h[n][ok][~at_start], return_index=True)[1]]  # a longer n-gram has one ending
                    gram, often = np.concatenate([longer, gram[at_start]]), np.concatenate([np.ones(len(longer)), often[at_start]])
                count = np.bincount(np.searchsorted(grams[n - 1], gram), weights=often, minlength=len(grams[n - 1]))
                if n == 1:
                    total = count.sum()
                    kinds = (count > 0).sum()
                    probs[0][:, li] = np.maximum(count - discount, 0) / total + discount * kinds / total / alphabet
                    self_unknown = discount * kinds / total / alphabet
                    probs[0][count == 0, li] = self_unknown
                    continue
                # context of each n-gram, and its shorter n-gram, from one place where it occurs
                where = np.flatnonzero(place >= n - 1)
                rows = np.searchsorted(grams[n - 1], h[n - 1][where])
                context = np.full(len(grams[n - 1]), -1, np.int64)
                shorter = np.full(len(grams[n - 1]), -1, np.int64)
                context[rows] = np.searchsorted(grams[n - 2], h[n - 2][where - 1])
                shorter[rows] = np.searchsorted(grams[n - 2], h[n - 2][where])
                seen = np.flatnonzero((count > 0) & (context >= 0))
                total = np.bincount(context[seen], weights=count[seen], minlength=len(grams[n - 2]))
                kinds = np.bincount(context[seen], minlength=len(grams[n - 2]))
                has = total > 0
                weights[n - 2][has, li] = discount * kinds[has] / total[has]
                probs[n - 1][seen, li] = np.maximum(count[seen] - discount, 0) / total[context[seen]] + weights[n - 2][context[seen], li] * probs[n - 2][shorter[seen], li]
        floor = 1e-7
        return cls(langs, grams, [np.log2(p, where=p > 0, out=np.full_like(p, np.nan)).astype(np.float32) for p in probs], [np.log2(np.maximum(w, floor)).astype(np.float32) for w in weights])

    def word_bits(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Per word: total bits under each language, and the number of predicted marks (letters and the end)."""
        codes, place = _codes(words)
        h = _hashes(codes, place)
        found = []
        for n in range(ORDER):
            at = np.searchsorted(self.grams[n], h[n])
            at[at == len(self.grams[n])] = 0
            found.append(np.where(self.grams[n][at] == h[n], at, -1))
        k = len(self.langs)
        value = np.full((len(codes), k), np.log2(1e-6))
        ok = found[0] >= 0
        value[ok] = self.probs[0][found[0][ok]]
        for n in range(1, ORDER):
            valid = np.flatnonzero(place >= n)
            ctx = found[n - 1][valid - 1]
            back = np.where(ctx[:, None] >= 0, self.weights[n - 1][ctx], 0.0)
            own = np.where(found[n][valid][:, None] >= 0, self.probs[n][found[n][valid]], np.nan)
            value[valid] = np.where(np.isnan(own), back + value[valid], own)
        value[place == 0] = 0
        starts = np.flatnonzero(place == 0)
        return -np.add.reduceat(value, starts, axis=0), np.diff(np.append(starts, len(codes))) - 1

    def rates(self, texts: list[str], cache: dict) -> tuple[np.ndarray, np.ndarray]:
        """Cross-entropy per character under each language, and the characters counted, for each text."""
        split = [_WORD.findall(t.lower()) for t in texts]
        new = list({w for ws in split for w in ws if w not in cache})
        for at in range(0, len(new), 20_000):
            part = new[at : at + 20_000]
            bits, n = self.word_bits(part)
            for word, row in zip(part, np.concatenate([bits, n[:, None]], 1).tolist(), strict=True):
                cache[word] = row
        out = np.zeros((len(texts), len(self.langs) + 1))
        for i, ws in enumerate(split):
            if ws:
                out[i] = np.array([cache[w] for w in ws]).sum(axis=0) if len(ws) < 4000 else sum(np.array([cache[w] for w in ws[a : a + 4000]]).sum(axis=0) for a in range(0, len(ws), 4000))
        return out[:, :-1] / np.maximum(out[:, -1:], 1), out[:, -1]

    def calibrate(self, texts: dict[str, list[str]], quantile: float = 0.999, slack: float = 1.25) -> CharModels:
        """Rejection level of each language, a quantile of its own texts' rates with some slack, and the posterior's temperature."""
        cache: dict = {}
        self.reject = np.full(len(self.langs), np.inf)
        gaps = []
        for i, lang in enumerate(self.langs):
            rates, n = self.rates(texts[lang], cache)
            rates = rates[n > 0]
            if len(rates):
                self.reject[i] = slack * np.quantile(rates[:, i], quantile)
                if len(self.langs) > 1:
                    gaps.append(np.median(np.delete(rates, i, 1).min(axis=1) - rates[:, i]))
        self.temperature = max(0.05, float(np.median(gaps)) / 4) if gaps else 1.0
        return self


def training_texts(labelled: DataFrame, per_lang: int) -> dict[str, list[str]]:
    """At most ``per_lang`` different texts with letters a language, smallest hash first."""
    rows = labelled.where("lang is not null and text is not null").where(F.col("text").rlike(r"\p{L}")).select(F.col("lang").alias("label"), "text", F.xxhash64("text").alias("h"))
    out: dict[str, list[str]] = {}
    for r in rows.join(F.broadcast(smallest_hashes(rows.select("label", "h"), per_lang)), ["label", "h"]).dropDuplicates(["label", "text"]).orderBy("label", "h", "text").toLocalIterator():
        out.setdefault(r["label"], []).append(r["text"])
    return out


def fit(labelled: DataFrame, per_lang: int = 400, levels: bool = True) -> CharModels | None:
    """Without ``levels`` the rejection levels stay those of the sample; for callers that do not use ``rejected``."""
    texts = training_texts(labelled, per_lang)
    if not texts:
        return None
    model = CharModels.fit(texts).calibrate(texts)
    if levels:
        model.reject = rejection_levels(predict(labelled.where("lang is not null and text is not null").select("lang", "text"), model, known_texts(texts)), model, texts)
    return model


def screen(docs: DataFrame, labelled: Column, per_lang: int = 400) -> DataFrame | None:
    """:func:`predict` with a model and levels of the rows where ``labelled`` holds; every text is scored once, into a table in the shared folder. None without a labelled text.

    ``labelled`` reads columns of ``docs`` that :func:`predict` keeps.
    """
    texts = training_texts(docs.where(labelled).select("text", "lang"), per_lang)
    if not texts:
        return None
    model = CharModels.fit(texts).calibrate(texts)
    scored = cut(predict(docs, model, known_texts(texts)), "languages")
    levels = rejection_levels(scored.where(labelled), model, texts)
    level = F.create_map(*[F.lit(v) for pair in zip(model.langs, levels.tolist(), strict=True) for v in pair])[F.col("lang_pred")]  # an entry a language of the model
    return scored.withColumn("rejected", F.coalesce(F.col("bits_per_char") > level, F.lit(True))).drop("own_rate")


def known_texts(texts: dict[str, list[str]]) -> set[tuple[str, bytes]]:
    """Language and digest of every text a model was fitted on."""
    return {(lang, _digest(t)) for lang, ts in texts.items() for t in ts}


def _digest(text: str) -> bytes:
    return hashlib.md5(text.encode("utf-8", "surrogatepass")).digest()


def rejection_levels(scored: DataFrame, model: CharModels, texts: dict[str, list[str]], quantile: float = 0.999, slack: float = 1.25) -> np.ndarray:
    """Level of each language: ``slack`` times a quantile of ``own_rate`` over all labelled rows, which has none for texts the model was fitted on.

    A language with fewer than 1,000 such rows adds the rates of its sample under models of the other half of it,
    fitted as the whole; one with a single text rejects nothing.
    """
    rated = scored.where("own_rate is not null").groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.percentile_approx("own_rate", quantile, 100_000).alias("level"))
    found = {r["lang"]: r for r in rated.collect()}
    out = np.full(len(model.langs), np.inf)
    for i, lang in enumerate(model.langs):
        n, level = (found[lang]["n"], found[lang]["level"]) if lang in found else (0, 0.0)
        if n < 1000 and len(texts[lang]) > 1:
            halves = [texts[lang][::2], texts[lang][1::2]]
            crossed = [CharModels.fit({lang: fitted}).rates(other, {})[0][:, 0] for fitted, other in (halves, halves[::-1])]
            level = max(level, float(np.quantile(np.concatenate(crossed), quantile)))
        if level > 0:
            out[i] = slack * level
    return out


def _rated(m: CharModels, texts: list[str], cache: dict, chars: int = 1_000_000, words: int = 100_000) -> tuple[np.ndarray, np.ndarray]:
    """Rates of many texts, about ``chars`` characters at a time; the word table starts anew beyond ``words``."""
    rates, counts, at = [], [], 0
    while at < len(texts):
        to, held = at, 0
        while to < len(texts) and (to == at or held + len(texts[to]) <= chars):
            held += len(texts[to])
            to += 1
        r, n = m.rates(texts[at:to], cache)
        rates.append(r)
        counts.append(n)
        if len(cache) > words:
            cache.clear()
        at = to
    return (np.concatenate(rates), np.concatenate(counts)) if rates else (np.zeros((0, len(m.langs))), np.zeros(0))


def predict(docs: DataFrame, model: CharModels | None, known: set[tuple[str, bytes]] | None = None) -> DataFrame:
    """All columns of ``docs`` but any clashing ones, plus lang_pred, score (0 to 1), bits_per_char and rejected.

    With ``known`` also own_rate, the rate under the row's own ``lang``; null where the model has no such language, the text has no letter, or ``known`` holds both.
    """
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast((model, known))  # bounded: per_lang texts a language
    added = ["lang_pred string", "score double", "bits_per_char double", "rejected boolean"] + ["own_rate double"] * (known is not None)
    names = [a.split()[0] for a in added]
    keep = [c for c in docs.columns if c not in names]
    schema = T.StructType([*docs.select(*keep).schema.fields, *T._parse_datatype_string(", ".join(added)).fields])

    def score(batches):
        import pyarrow as pa

        (m, fitted), cache = shared.value, {}
        place = {lang: i for i, lang in enumerate(m.langs)} if m is not None else {}
        for batch in batches:
            texts = [t or "" for t in batch.column(batch.schema.get_field_index("text")).to_pylist()]
            own_langs = batch.column(batch.schema.get_field_index("lang")).to_pylist() if fitted is not None else []
            found, scores = ["und"] * len(texts), [0.0] * len(texts)
            bits: list[float | None] = [None] * len(texts)
            own: list[float | None] = [None] * len(texts)
            bad = [True] * len(texts)
            if m is not None:
                rates, n = _rated(m, texts, cache)
                best = rates.argmin(axis=1)
                posterior = np.exp2(-(rates - rates.min(axis=1, keepdims=True)) / m.temperature)
                sure = 1 / posterior.sum(axis=1)
                for i in np.flatnonzero(n > 0).tolist():
                    b = int(best[i])
                    found[i], scores[i], bits[i] = m.langs[b], float(sure[i]), float(rates[i, b])
                    bad[i] = bool(rates[i, b] > m.reject[b])
                    if own_langs and own_langs[i] in place and (own_langs[i], _digest(texts[i])) not in fitted:
                        own[i] = float(rates[i, place[own_langs[i]]])
            more = [pa.array(found, pa.string()), pa.array(scores, pa.float64()), pa.array(bits, pa.float64()), pa.array(bad, pa.bool_()), pa.array(own, pa.float64())]
            yield pa.record_batch([*batch.columns, *more[: len(names)]], [*batch.schema.names, *names])

    return docs.select(*keep).mapInArrow(score, schema)
