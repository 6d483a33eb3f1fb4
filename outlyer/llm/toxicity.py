"""Toxicity by a weighted finite-state pattern grammar.

Words map to classes (insult, threat, target, intent, negation, report, quote, other). Small weighted transducers
over these classes are composed by a lazy product. Two such products read each clause, one from its start and one
from its end, so what stands before and what stands after a word both count:

* insult: an insult passes with its weight, one soon after another with a little more;
* threat: a threatening verb weighs next to nothing alone, more after a word of intent and more before a target,
  so that only a verb aimed at somebody reaches the level of a match;
* target: a target shortly before or after an insult raises it;
* negation: what it reaches is lowered;
* reported speech: a reporting verb before or after, and quotation marks around, lower what they cover.

A clause whose weights add up to ``MATCH`` is matched. A document's matched clauses, not its isolated words, feed a
logistic calibration.

Function words and threat verbs are parameters; insults are induced from labelled training texts: whole words and
word beginnings that toxic texts hold and others do not, chosen greedily so that few entries cover many toxic
texts. The fit sees at most ``per_class`` toxic and three times as many other texts.

Edge cases: null or empty text has no clause and gets the calibrated base score; without labels of both kinds
every score is the base rate; repeated rows score alike; other columns are ignored; the time of a text is linear
in its length, whatever marks it lacks.
"""

from __future__ import annotations

import bisect
import math
import re
from collections import Counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import smallest_hashes

_TOKEN = re.compile(r"[^\W\d_]+|[\"“”«»]")
_WORD = re.compile(r"[^\W\d_]+")
_MARK = re.compile(r"[.!?;:\n]")
OTHER, INSULT, THREAT, TARGET, INTENT, NEGATION, REPORT, QUOTE = range(8)
MATCH = 0.15

# fixed values: closed-class words of the grammar, four languages
TARGETS = "you your yourself he she they him her them this that these those du dich dir ihr euch sie er tu toi te vous il elle ils usted tú ti él ella ellos".split()
INTENTS = "will ll gonna going shall must should want werde werden soll muss vais va allons voy vamos quiero".split()
NEGATIONS = "not no never nobody neither without nicht kein keine nie ohne pas ne jamais sans ni nunca sin".split()
REPORTS = "said says say called calls wrote quoted claimed according sagte sagt nannte laut dit appelle selon dijo dice llama según".split()
# threat verbs as stem and endings; a bar parts the endings, an empty one is the stem itself
THREATS = [
    ("kill hurt attack beat shoot", "|s|ed|ing|en"), ("murder", "|s|ed|ing|er"), ("destroy", "|s|ed|ing"), ("stab", "|s|bed|bing"), ("shot strangl", "|e|es|ed|ing"), ("chok smash", "|e|es|ed|ing"),
    ("töt", "e|en|et|est|ete"), ("schlag schläg erschieß", "e|en|t|st"), ("getöt verprüg", "et|el|eln|elt"),
    ("tuer", "|ai|as|a|ons"), ("frapp étrangl", "e|es|er|erai|era|é"), ("mat golpe dispar", "ar|aré|ará|aremos|ado|o"),
]


def threat_forms() -> list[str]:
    return sorted({stem + ending for stems, endings in THREATS for stem in stems.split() for ending in endings.split("|") if len(stem + ending) > 3})


class Transducer:
    """States are numbers from 0; arcs[state].get(class) is (next state, weight), else the state's default arc."""

    def __init__(self, arcs: list[dict[int, tuple[int, float]]], default: list[tuple[int, float]]):
        self.arcs, self.default = arcs, default

    def step(self, state: int, symbol: int) -> tuple[int, float]:
        return self.arcs[state].get(symbol, self.default[state])


def _window(trigger: int, reach: int, factors: dict[int, float]) -> Transducer:
    """Multiplies the weight of some classes within ``reach`` words after a trigger."""
    arcs, default = [{trigger: (1, 1.0)}], [(0, 1.0)]
    for k in range(1, reach + 1):
        after = k + 1 if k < reach else 0
        arcs.append({s: (after, f) for s, f in factors.items()} | {trigger: (1, factors.get(trigger, 1.0))})
        default.append((after, 1.0))
    return Transducer(arcs, default)


def _quoted(factor: float) -> Transducer:
    """An open quotation lowers until it closes."""
    lowered = {INSULT: (1, factor), THREAT: (1, factor), QUOTE: (0, 1.0)}
    return Transducer([{QUOTE: (1, 1.0)}, lowered], [(0, 1.0), (1, 1.0)])


def _onward() -> list[Transducer]:
    """What is read from a clause's start."""
    lowered = {INSULT: 0.5, THREAT: 0.5}
    return [_window(INSULT, 3, {INSULT: 1.1}), _window(INTENT, 4, {THREAT: 4.0}), _window(TARGET, 4, {INSULT: 1.25}), _window(NEGATION, 3, lowered), _window(REPORT, 6, {INSULT: 0.6, THREAT: 0.6}), _quoted(0.6)]


def _backward() -> list[Transducer]:
    """What is read from a clause's end: targets and reporting verbs that follow."""
    return [_window(TARGET, 4, {INSULT: 1.25, THREAT: 4.0}), _window(REPORT, 4, {INSULT: 0.6, THREAT: 0.6})]


class Composition:
    """Lazy product of transducers: weights multiply; product states are made when first reached."""

    def __init__(self, parts: list[Transducer]):
        self.parts, self.states, self.table = parts, [tuple(0 for _ in parts)], {}
        self.number = {self.states[0]: 0}

    def step(self, state: int, symbol: int) -> tuple[int, float]:
        hit = self.table.get((state, symbol))
        if hit is None:
            moved = [p.step(s, symbol) for p, s in zip(self.parts, self.states[state], strict=True)]
            to = tuple(m[0] for m in moved)
            if to not in self.number:
                self.number[to] = len(self.states)
                self.states.append(to)
            hit = self.table[state, symbol] = (self.number[to], math.prod(m[1] for m in moved))
        return hit

    def factors(self, symbols: list[int]) -> list[float]:
        state, out = 0, []
        for symbol in symbols:
            state, factor = self.step(state, symbol)
            out.append(factor)
        return out


def one_of(words: list[str]) -> str:
    """A pattern of one alternative for each first letter, and so on down, so that a scan never tries all words in turn."""
    if not words:
        return "(?!)"
    heads: dict[str, list[str]] = {}
    for w in words:
        heads.setdefault(w[:1], []).append(w[1:])
    ends = heads.pop("", None) is not None
    parts = [re.escape(c) + (one_of(rest) if rest != [""] else "") for c, rest in sorted(heads.items())]
    if not parts:
        return ""
    return "(?:" + "|".join(parts) + ")" + "?" * ends


class Grammar:
    def __init__(self, insults: dict[str, float], prefixes: dict[str, float]):
        self.insults, self.prefixes = insults, prefixes
        self.coef: list[float] = [0.0]
        self.base = 0.5
        self._compile()

    def _compile(self) -> None:
        threats = threat_forms()
        self.classes = {w: c for c, ws in ((TARGET, TARGETS), (INTENT, INTENTS), (NEGATION, NEGATIONS), (REPORT, REPORTS), (THREAT, threats)) for w in ws}
        self.onward, self.backward = Composition(_onward()), Composition(_backward())
        whole, starts = sorted({*self.insults, *threats}), sorted(self.prefixes)
        self.any = re.compile(rf"\b(?:{one_of(whole)}\b|{one_of(starts)})")
        self.lengths = sorted({len(p) for p in self.prefixes}, reverse=True)

    def __getstate__(self):
        return {k: self.__dict__[k] for k in ("insults", "prefixes", "coef", "base")}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self._compile()

    def classify(self, word: str) -> tuple[int, float]:
        if word in self.insults:
            return INSULT, self.insults[word]
        for n in self.lengths:
            if word[:n] in self.prefixes:
                return INSULT, self.prefixes[word[:n]]
        symbol = self.classes.get(word, OTHER)
        return symbol, 0.05 if symbol == THREAT else 0.0

    def weigh(self, clause: str) -> float:
        """Weight of one clause: each insult and threat times what the transducers on either side make of it."""
        read = [self.classify(t) if t[0].isalpha() else (QUOTE, 0.0) for t in _TOKEN.findall(clause)]
        symbols = [s for s, _ in read]
        before, after = self.onward.factors(symbols), self.backward.factors(symbols[::-1])[::-1]
        return sum(w * f * g for (_, w), f, g in zip(read, before, after, strict=True))

    def clauses(self, text: str) -> list[float]:
        """Weights of the clauses that match."""
        text = text.lower()
        hits = [m.start() for m in self.any.finditer(text)]
        if not hits:
            return []
        ends = [m.start() for m in _MARK.finditer(text)] + [len(text)]
        out = []
        for k in sorted({bisect.bisect_left(ends, h) for h in hits}):
            weight = self.weigh(text[ends[k - 1] + 1 if k else 0 : ends[k]])
            if weight >= MATCH:
                out.append(weight)
        return out

    def features(self, text: str) -> tuple[float, float]:
        found = self.clauses(text)
        return (max(found), math.log1p(sum(found))) if found else (0.0, 0.0)

    def score(self, texts: list[str]) -> np.ndarray:
        x = np.array([(1.0, *self.features(t)) for t in texts]).reshape(-1, 3)
        if len(self.coef) == 1:
            return np.full(len(texts), self.base)
        return 1 / (1 + np.exp(-np.clip(x @ np.array(self.coef), -30, 30)))


def _entries(text: str) -> set[str]:
    words = set(_WORD.findall(text.lower()))
    return {"=" + w for w in words} | {w[:n] for w in words for n in range(4, min(9, len(w) + 1))}


def induce(texts: list[str], labels: list[int], most: int = 400, price: float = 4.0) -> Grammar:
    """Greedy cover of toxic texts by words and word beginnings, each other text that holds one costs ``price``."""
    toxic = [_entries(t) for t, y in zip(texts, labels, strict=True) if y]
    n_t, n_o = len(toxic), len(texts) - len(toxic)
    in_t: Counter = Counter(e for s in toxic for e in s)
    least = max(3, n_t // 300)
    wanted = {e for e, c in in_t.items() if c >= least}
    in_o: Counter = Counter()
    for t, y in zip(texts, labels, strict=True):
        if not y:
            in_o.update(_entries(t) & wanted)
    good = {e for e in wanted if math.log((in_t[e] + 0.5) / (n_t + 1)) - math.log((in_o[e] + 0.5) / (n_o + 1)) > 2.0}
    left = [s & good for s in toxic]
    insults, prefixes = {}, {}
    gain = Counter(e for s in left for e in s)
    while gain and len(insults) + len(prefixes) < most:
        best = max(gain, key=lambda e: (gain[e] - price * in_o[e] * n_t / max(1, n_o), e[0] == "=", -len(e), e))
        if gain[best] < least or gain[best] - price * in_o[best] * n_t / max(1, n_o) <= 0:
            break
        weight = min(3.0, math.log((in_t[best] + 0.5) / (n_t + 1)) - math.log((in_o[best] + 0.5) / (n_o + 1))) / 3
        (insults if best[0] == "=" else prefixes)[best.lstrip("=")] = weight
        for s in left:
            if best in s:
                gain.subtract(s)
                s.clear()
    # words missed because their texts were covered by others are insults as well
    for e in good:
        if e[0] == "=" and in_t[e] >= least and in_o[e] == 0 and in_t[e] >= 0.02 * n_t and len(insults) < most:
            insults.setdefault(e[1:], 1.0)
    g = Grammar(insults, prefixes)
    y = np.array(labels, float)
    g.base = float(y.mean()) if len(y) else 0.5
    if 0 < y.sum() < len(y):
        x = np.array([(1.0, *g.features(t)) for t in texts])
        w = np.zeros(3)
        for _ in range(30):  # ridge-stabilised Newton steps
            p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
            w += np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + 0.05 * np.eye(3), x.T @ (y - p) - 0.05 * w)
        g.coef = w.tolist()
    return g


def fit(labelled: DataFrame, per_class: int = 800, texts: DataFrame | None = None) -> Grammar:
    """labelled: text, toxic. At most ``per_class`` toxic and three times as many other texts, smallest hash first; equal texts of a label are one.

    With ``texts`` (h, text; h is the text's xxhash64) ``labelled`` holds h in place of text, so that no text takes part in a join of its rows.
    """
    if texts is None:
        texts = labelled.where("text is not null").select(F.xxhash64("text").alias("h"), "text")
        labelled = labelled.where("text is not null").select(F.xxhash64("text").alias("h"), "toxic")
    keyed = labelled.where("toxic is not null and h is not null").select((F.col("toxic").cast("int") == 1).cast("int").alias("label"), "h")
    picked = smallest_hashes(keyed, {0: 3 * per_class, 1: per_class})
    got = texts.join(F.broadcast(picked), "h").select("label", "text").distinct().collect()  # 4 per_class texts at most
    rows = sorted((r["label"], r["text"]) for r in got)
    return induce([t for _, t in rows], [y for y, _ in rows])


def scores(docs: DataFrame, grammar: Grammar, threshold: float = 0.7) -> DataFrame:
    """doc_id, score, predicted, n_clauses."""
    import pyarrow as pa

    shared = docs.sparkSession.sparkContext.broadcast(grammar)

    def run(batches):
        g = shared.value
        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            s = g.score(texts)
            yield pa.record_batch([batch.column(0), pa.array(s), pa.array((s >= threshold).astype("int32"))], ["doc_id", "score", "predicted"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double, predicted int")
