"""Open-set classification: boosted trees on sparse presence features, novelty by the largest raw score."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..core.scratch import scratch
from ..functions.rng import u01

NOVEL = "__novel__"


def tokens(text: str = "text"):
    """Distinct lower-case letter runs of a text."""
    return F.array_distinct(F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"[^\p{L}]+"), lambda w: F.length(w) > 0))


def vocabulary(df: DataFrame, token_col: str, size: int) -> DataFrame:
    """The ``size`` most frequent tokens with their ids from 1, ties by token. Counts are pre-aggregated; a top-k, not a global sort."""
    counts = df.select(F.explode(token_col).alias("token")).groupBy("token").agg(F.count(F.lit(1)).alias("docs"))
    top = counts.orderBy(F.desc("docs"), "token").limit(size)
    return top.withColumn("feat", F.row_number().over(Window.orderBy(F.desc("docs"), "token")))


def presence_features(df: DataFrame, token_col: str, vocab: DataFrame) -> DataFrame:
    """doc rows with ``feats``: sorted ids of the vocabulary's tokens they hold.

    The vocabulary has a fixed size, so it goes into every row as one literal array and a row finds its ids by itself: no explode, no shuffle.
    """
    words = [r["token"] for r in vocab.orderBy("feat").collect()]  # a fixed number of tokens
    if not words:
        return df.withColumn("feats", F.array().cast("array<int>"))
    place = F.create_map(*[F.lit(v) for i, w in enumerate(words) for v in (w, i + 1)])
    held = F.array_intersect(token_col, F.array(*[F.lit(w) for w in words]))
    return df.withColumn("feats", F.coalesce(F.array_sort(F.transform(held, lambda w: F.element_at(place, w))), F.array().cast("array<int>")))


class SoftmaxBooster:
    """Second-order softmax boosting with trees over binary presence features; fitted on a bounded training sample."""

    def __init__(self, rounds: int = 30, depth: int = 3, rate: float = 0.3, lam: float = 1.0):
        self.rounds, self.depth, self.rate, self.lam = rounds, depth, rate, lam
        self.trees: list[list[list]] = []
        self.labels: list[str] = []

    def _tree(self, x: np.ndarray, g: np.ndarray, h: np.ndarray) -> list:
        nodes: list = []

        def grow(rows: np.ndarray, depth: int) -> int:
            at = len(nodes)
            gs, hs = g[rows].sum(), h[rows].sum()
            nodes.append([-1, -1, -1, -self.rate * gs / (hs + self.lam)])
            if depth == self.depth or len(rows) < 2:
                return at
            gl, hl = g[rows] @ x[rows], h[rows] @ x[rows]
            gain = gl**2 / (hl + self.lam) + (gs - gl) ** 2 / (hs - hl + self.lam) - gs**2 / (hs + self.lam)
            f = int(gain.argmax())
            if gain[f] <= 1e-9:
                return at
            has = x[rows, f] > 0
            nodes[at][0] = f
            nodes[at][1], nodes[at][2] = grow(rows[has], depth + 1), grow(rows[~has], depth + 1)
            return at

        grow(np.arange(len(g)), 0)
        return nodes

    @staticmethod
    def _apply(nodes: list, x: np.ndarray) -> np.ndarray:
        out = np.zeros(len(x))

        def walk(at: int, rows: np.ndarray) -> None:
            f, yes, no, value = nodes[at]
            if f < 0:
                out[rows] = value
            elif len(rows):
                has = x[rows, f] > 0
                walk(yes, rows[has])
                walk(no, rows[~has])

        walk(0, np.arange(len(x)))
        return out

    def fit(self, x: np.ndarray, labels: list[str]) -> SoftmaxBooster:
        self.labels = sorted(set(labels))
        y = np.array([[a == b for b in self.labels] for a in labels], float)
        z = np.zeros_like(y)
        for _ in range(self.rounds):
            p = softmax(z)
            g, h = p - y, p * (1 - p)
            self.trees.append([self._tree(x, g[:, c], h[:, c]) for c in range(len(self.labels))])
            z += np.column_stack([self._apply(t, x) for t in self.trees[-1]])
        return self

    def raw_scores(self, x: np.ndarray) -> np.ndarray:
        z = np.zeros((len(x), len(self.labels)))
        for row in self.trees:
            z += np.column_stack([self._apply(t, x) for t in row])
        return z

    def transform(self, df: DataFrame, size: int) -> DataFrame:
        """doc_id and z, one raw score a class; map-only with the trees broadcast."""
        shared = df.sparkSession.sparkContext.broadcast(self)

        def run(frames):
            for pdf in frames:
                yield pd.DataFrame({"doc_id": pdf["doc_id"], "z": list(shared.value.raw_scores(dense(pdf["feats"], size)))})

        return df.select("doc_id", "feats").mapInPandas(run, "doc_id long, z array<double>")


def dense(feats, size: int) -> np.ndarray:
    x = np.zeros((len(feats), size))
    for i, row in enumerate(feats):
        x[i, np.asarray(row, int) - 1] = 1
    return x


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def fit_booster(df: DataFrame, label: str, size: int, most: int = 4000, **how) -> SoftmaxBooster:
    """Fit on at most ``most`` labelled rows, smallest draw first (a documented bound)."""
    rows = df.where(F.col(label).isNotNull()).orderBy(u01("boost", "doc_id"), "doc_id").limit(most).select("feats", label).collect()
    return SoftmaxBooster(**how).fit(dense([r["feats"] for r in rows], size), [r[label] for r in rows])


def threshold_of(scores: DataFrame, fpr: float, col: str = "score") -> DataFrame:
    """One row ``tau``: the order statistic with a share of at most ``fpr`` strictly below it.

    The exact order statistic by aggregation: an approximate percentile brackets it, one pass counts what lies under the
    bracket, and only the values inside it are counted one by one, so no share of the table is sorted in one task.
    """
    low, high = max(0.0, fpr - 0.001), min(1.0, fpr + 0.001)
    scores = scores.where(F.col(col).isNotNull() & ~F.isnan(col))
    around = scores.agg(F.count(F.lit(1)).alias("n"), F.percentile_approx(col, [low, high], 10_000).alias("p"), F.min(col).alias("lo")).first()
    if not around["n"]:
        return scores.sparkSession.createDataFrame([(None,)], "tau double")
    rank = min(int(fpr * around["n"]), around["n"] - 1)
    lo, hi = (around["lo"] if low == 0 else around["p"][0]), around["p"][1]
    while True:
        inside = scores.where(F.col(col).between(lo, hi)).groupBy(F.col(col).alias("v")).agg(F.count(F.lit(1)).alias("c"))
        under = scores.where(F.col(col) < lo).count()
        upto = inside.withColumn("upto", F.sum("c").over(Window.orderBy("v")) + under)  # the values of a narrow bracket
        found = upto.where(F.col("upto") > rank).agg(F.min("v").alias("tau"))
        if under <= rank and found.first()["tau"] is not None:
            return found
        lo, hi = around["lo"], float("inf")  # the approximation missed


def relabel_errors(df: DataFrame, truth: str, predicted: str) -> DataFrame:
    """The other reading of an evaluation: known rows that the plain classifier gets wrong count as novel."""
    return df.withColumn("class", F.when(F.col(truth) == F.col(predicted), F.col(truth)).otherwise(F.lit(NOVEL)))


def ratio_predict(ratios: DataFrame, least: float) -> DataFrame:
    """The nearest-neighbour baseline's decision: novel where the ratio lies under ``least``."""
    return ratios.withColumn("novel", (F.col("ratio") < least).cast("int"))


def folds_scored(df: DataFrame, label: str, size: int, folds: int = 10, most: int = 4000, **how) -> DataFrame:
    """doc_id, label, fold, z, names: every row scored by the booster that has not seen its fold, and the class names of z.

    ``df`` has doc_id, the label, feats and fold. Boosters are fitted in parallel, one task a fold, on at most ``most``
    labelled rows drawn once; rows are then scored by one map with the boosters broadcast.
    """
    spark = df.sparkSession
    rows = df.where(F.col(label).isNotNull()).orderBy(u01("boost", "doc_id"), "doc_id").limit(most).select("feats", label, "fold").collect()
    held = spark.sparkContext.broadcast(([list(r["feats"]) for r in rows], [r[label] for r in rows], np.array([r["fold"] for r in rows])))

    def fit(frames):
        import pickle

        feats, labels, fold = held.value
        for pdf in frames:
            for f in pdf["fold"]:
                use = np.flatnonzero(fold != f)
                made = SoftmaxBooster(**how).fit(dense([feats[i] for i in use], size), [labels[i] for i in use]) if len(use) else None
                yield pd.DataFrame({"fold": [f], "model": [pickle.dumps(made)]})

    import pickle

    jobs = spark.createDataFrame([(f,) for f in range(folds)], "fold int").repartition(folds)
    models = {r["fold"]: pickle.loads(r["model"]) for r in jobs.mapInPandas(fit, "fold int, model binary").collect()}
    shared = spark.sparkContext.broadcast(models)

    def score(frames):
        for pdf in frames:
            for f, part in pdf.groupby("fold"):
                m = shared.value[f]
                if m is not None:
                    yield pd.DataFrame({"doc_id": part["doc_id"], label: part[label], "fold": part["fold"], "z": list(m.raw_scores(dense(part["feats"], size))), "names": [m.labels] * len(part)})

    kind = dict(df.dtypes)[label]
    return df.select("doc_id", label, "fold", "feats").mapInPandas(score, f"doc_id long, {label} {kind}, fold int, z array<double>, names array<string>")


def fold_recalls(scored: DataFrame, label: str, fpr: float = 0.005) -> DataFrame:
    """Micro and macro recall, closed and open, over all folds. A fold's threshold is the ``fpr`` order statistic of the other folds' known rows."""
    top = F.array_max("z")
    best = F.get("names", F.array_position("z", top).cast("int") - 1)
    known = scored.withColumn("top", top).withColumn("closed", best)
    taus = None
    for f in sorted(r["fold"] for r in scored.select("fold").distinct().collect()):  # a stated number of folds
        t = threshold_of(known.where((F.col("fold") != f) & (F.col(label) != NOVEL)), fpr, "top").withColumn("fold", F.lit(f))
        taus = t if taus is None else taus.unionByName(t)
    if taus is None:
        return scored.sparkSession.createDataFrame([], "setting string, micro double, macro double")
    both = known.join(F.broadcast(taus), "fold").withColumn("open", F.when(F.col("top") < F.col("tau"), F.lit(NOVEL)).otherwise(F.col("closed")))
    from .measures import micro_macro_recall

    closed = micro_macro_recall(both.where(F.col(label) != NOVEL), label, "closed").withColumn("setting", F.lit("closed"))
    return closed.unionByName(micro_macro_recall(both, label, "open").withColumn("setting", F.lit("open"))).select("setting", "micro", "macro")


def library_booster(df: DataFrame, label: str, size: int, rounds: int = 10, depth: int = 3, of: DataFrame | None = None) -> DataFrame:
    """The same classifier from the machine-learning library: one boosted-tree model a class against the rest, trained on all rows of ``df``; doc_id and z of the rows of ``of`` (else of ``df``).

    Rows of equal features and label are one row with their number as weight, and equal features are scored once.
    """
    from pyspark.ml.classification import GBTClassifier, OneVsRest
    from pyspark.ml.functions import array_to_vector, vector_to_array

    spark, rows = df.sparkSession, df if of is None else of
    ones = F.transform(F.sequence(F.lit(1), F.lit(size)), lambda i: F.array_contains("feats", i).cast("double"))
    path = scratch(spark, "booster-rows")
    counted = df.where(F.col(label).isNotNull()).groupBy("feats", label).agg(F.count(F.lit(1)).cast("double").alias("weight"))
    counted.write.parquet(path)
    counted = spark.read.schema(counted.schema).parquet(path)
    names = sorted(r[label] for r in counted.select(label).distinct().collect())
    place = F.create_map(*[F.lit(v) for i, n in enumerate(names) for v in (n, float(i))])
    held = counted.select(array_to_vector(ones).alias("features"), F.element_at(place, F.col(label)).alias("label"), "weight")
    model = OneVsRest(classifier=GBTClassifier(maxIter=rounds, maxDepth=depth), weightCol="weight", parallelism=4).fit(held)
    different = rows.select("feats").distinct().withColumn("features", array_to_vector(ones))
    scored = model.transform(different).select("feats", vector_to_array("rawPrediction").alias("z"))
    return rows.select("doc_id", "feats").join(scored, "feats").select("doc_id", "z")


def open_predict(df: DataFrame, labels: list[str], tau: float, score: str = "raw") -> DataFrame:
    """predicted: arg-max class, or novel where the largest raw score (or softmax value) is under tau."""
    z = F.col("z")
    top = F.array_max(z)
    value = top if score == "raw" else 1 / F.aggregate(F.transform(z, lambda v: F.exp(v - top)), F.lit(0.0), lambda a, v: a + v)
    names = F.array(*[F.lit(x) for x in labels])
    best = F.element_at(names, F.array_position(z, top).cast("int"))
    return df.withColumn("top", value).withColumn("predicted", F.when(value < tau, F.lit(NOVEL)).otherwise(best))


def stratified_folds(df: DataFrame, label: str, folds: int = 10) -> DataFrame:
    """fold 0..folds-1, even within each class. Rows are counted in hash slices first, so a hot class is no single window."""
    sliced = df.withColumn("_s", F.pmod(F.xxhash64("doc_id"), F.lit(256)))
    w = Window.partitionBy(label, "_s").orderBy(u01("fold", "doc_id"), "doc_id")
    counts = sliced.groupBy(label, "_s").agg(F.count(F.lit(1)).alias("_n"))
    base = counts.withColumn("_b", F.coalesce(F.sum("_n").over(Window.partitionBy(label).orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select(label, "_s", "_b")
    return sliced.withColumn("_r", F.row_number().over(w)).join(base, [label, "_s"]).withColumn("fold", F.pmod(F.col("_b") + F.col("_r") - 1, F.lit(folds)).cast("int")).drop("_s", "_r", "_b")


def group_rare(df: DataFrame, label: str, least: int = 10) -> DataFrame:
    """Classes with fewer than ``least`` rows become novel."""
    n = df.groupBy(label).agg(F.count(F.lit(1)).alias("_n"))
    return df.join(n, label).withColumn("class", F.when(F.col("_n") < least, F.lit(NOVEL)).otherwise(F.col(label))).drop("_n")


def keep_top_classes(df: DataFrame, label: str, k: int) -> DataFrame:
    """The k largest classes stay known (ties by name), the rest is novel."""
    top = df.groupBy(label).agg(F.count(F.lit(1)).alias("_n")).orderBy(F.desc("_n"), label).limit(k).select(F.col(label).alias("_t"))
    return df.join(F.broadcast(top), F.col(label) == F.col("_t"), "left").withColumn("class", F.coalesce("_t", F.lit(NOVEL))).drop("_t")


def leave_one_class_out(df: DataFrame, label: str, most: int = 10_000) -> DataFrame:
    """One copy of the rows for each class left out: left_out, is_novel. More than ``most`` classes are refused: rows times classes would leave any bound."""
    classes = df.select(F.col(label).alias("left_out")).distinct()
    n = classes.count()
    if n > most:
        raise ValueError(f"{n} classes to leave out, at most {most}; keep the largest ones first")
    return df.crossJoin(F.broadcast(classes)).withColumn("is_novel", (F.col(label) == F.col("left_out")).cast("int"))


def nn_ratio(test: np.ndarray, train: np.ndarray, labels: np.ndarray) -> np.ndarray:
    """Distance to the nearest sample of another class over the distance to the nearest sample (Hamming on presence); inf at distance 0."""
    d = test.sum(1)[:, None] + train.sum(1)[None] - 2 * test @ train.T
    near = d.argmin(axis=1)
    first = d[np.arange(len(d)), near]
    second = np.where(labels[None] != labels[near][:, None], d, np.inf).min(axis=1)
    return np.divide(second, first, out=np.full(len(d), np.inf), where=first > 0)


def nn_ratios(test: DataFrame, train: DataFrame, label: str, size: int, block: int = 2048) -> DataFrame:
    """doc_id, ratio of :func:`nn_ratio` for each row of ``test`` against all rows of ``train``.

    Equal feature rows are one; blocks of queries meet blocks of training rows and only the least distance of each query and class leaves them.
    """
    queries, known = test.select(F.col("feats").alias("qf")).distinct(), train.select(F.col(label).alias("label"), F.col("feats").alias("tf")).distinct()
    nq, nt = (max(1, -(-df.count() // block)) for df in (queries, known))
    all_of = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    part = lambda feats, n: F.pmod(F.xxhash64(feats), F.lit(n)).cast("int")
    q = queries.select("qf", part("qf", nq).alias("i"), all_of(nt).alias("j"))
    t = known.select("label", "tf", all_of(nq).alias("ti"), part("tf", nt).alias("tj"))

    def least(mine: pd.DataFrame, theirs: pd.DataFrame) -> pd.DataFrame:
        if not len(mine) or not len(theirs):
            return pd.DataFrame({"feats": [], "label": [], "d": []})
        x, out = dense(mine["qf"], size), []
        for name, rows in theirs.groupby("label"):
            y = dense(rows["tf"], size)
            d = (x.sum(1)[:, None] + y.sum(1)[None] - 2 * x @ y.T).min(axis=1)
            out.append(pd.DataFrame({"feats": mine["qf"], "label": name, "d": d}))
        return pd.concat(out)

    mins = q.groupBy("i", "j").cogroup(t.groupBy("ti", "tj")).applyInPandas(least, "feats array<int>, label string, d double").groupBy("feats", "label").agg(F.min("d").alias("d"))
    near = mins.groupBy("feats").agg(F.sort_array(F.collect_list("d")).alias("d"))
    first, second = F.get("d", F.lit(0)), F.coalesce(F.get("d", F.lit(1)), F.lit(float("inf")))
    return test.select("doc_id", "feats").join(near, "feats", "left").select("doc_id", F.when(first > 0, F.try_divide(second, first)).otherwise(F.lit(float("inf"))).alias("ratio"))
