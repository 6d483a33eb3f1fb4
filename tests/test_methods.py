"""Hand-computed values, brute force and invariants of the methods."""

import itertools
import math

import numpy as np
import pytest

from outlyer.functions.rng import u01_py
from outlyer.operators import isolation, linkage, measures, openset
from outlyer.operators.families import FAMILIES, sample_models
from outlyer.sources import planted
from outlyer.streaming import online

P, Q = np.array([[1, 0.5, 0]], np.float32), np.array([[0.5, 0.5, 1]], np.float32)


@pytest.mark.parametrize(("kind", "value"), [("ruzicka", 0.6), ("tanimoto", 0.625), ("jaccard", 1 / 3)])
def test_distances_by_hand(kind, value):
    assert isolation.distance(P, Q, kind)[0, 0] == pytest.approx(value, abs=1e-6)
    assert isolation.distance(P, np.zeros((1, 3), np.float32), kind)[0, 0] == 1


def test_constants():
    assert u01_py("x", 0) == u01_py("x", 0) and 0 <= u01_py("x", 1) < 1
    assert isolation.c_iso(256) == pytest.approx(10.2448, abs=1e-3) and isolation.c_iso(2) == 1 and isolation.c_iso(1) == 0
    assert [measures.expected_collision(0.6, b) for b in (2, 4, 8)] == pytest.approx([0.7, 0.55, 0.475])
    assert measures.models_per_window(2**30, 4, 800, 800) == 419 and measures.models_per_window(2**30, 4, 800, 40) * 39**2 == 167_310
    assert [round(measures.critical_difference(*a), 3) for a in ((6, 450), (6, 70), (6, 190), (5, 330))] == [0.355, 0.901, 0.547, 0.336]
    assert online.expected_depth(2048, 32) == (4, 7)


def test_two_lines_merge_when_the_union_is_cheaper():
    t = np.linspace(0, 1, 10)
    u, v = np.column_stack([t, t]), np.column_stack([t + 2, t + 2])
    ok, family = linkage.merge_decision(u, v, [FAMILIES["line"]], 0.01)
    assert ok and family.name == "line"
    assert not linkage.merge_decision(u, np.column_stack([t, 1 - t]), [FAMILIES["line"]], 0.01)[0]


def test_assignment_equals_brute_force():
    rng = np.random.default_rng(3)
    for n, m in ((2, 2), (3, 5), (5, 5)):
        c = rng.random((n, m))
        best = min(sum(c[i, p[i]] for i in range(n)) for p in itertools.permutations(range(m), n))
        assert c[np.arange(n), linkage.assignment(c)].sum() == pytest.approx(best)


@pytest.mark.parametrize("name", list(FAMILIES))
def test_families_fit_their_own_sample(name):
    f = FAMILIES[name]
    x = np.random.default_rng(1).random((f.s, f.r))
    theta = f.fit(x)
    assert theta is None or f.residual(x, theta).max() < (0.5 if name == "fundamental" else 1e-4)  # forced to rank two


def test_preference_space_beats_ambient_on_stars():
    x, truth = planted.shapes("star5", 1)
    models = [(FAMILIES["line"], t) for t in sample_models(x, FAMILIES["line"], 4 * len(x), 1)]
    e = isolation.preference(x, models, 0.03)
    cell = isolation.Forest("cell", 256, seed=1).fit(e, 30).score(e)
    assert ((cell > 0) & (cell <= 1)).all()
    assert isolation.auc(cell, truth == 0) > 0.7


def test_criterion_linkage_recovers_circles():
    x, truth = planted.shapes("circle3", 2, outliers=0.0)
    near = np.argsort(isolation.distance(x, x, "l2"), axis=1)[:, :12]
    models = [(FAMILIES["circle"], t) for t in sample_models(x, FAMILIES["circle"], 300, 1, near)]
    label, _ = linkage.criterion_linkage(x, models, [FAMILIES["circle"]], 0.05)
    assert linkage.misclassification_error(label, truth) < 0.35


@pytest.mark.parametrize("method", list(online.KERNELS))
def test_online_scorers_flag_far_points(method):
    rng = np.random.default_rng(5)
    x = rng.random((900, 3))
    odd = np.zeros(900, bool)
    odd[300::40] = True
    x[odd] += 4 if method != "half_space" else 0.9
    k = online.KERNELS[method](3, 1, **({"omega": 512, "eta": 16, "trees": 16} if method == "adaptive" else {"trees": 8} if method in ("half_space", "cut_forest") else {"omega": 256, "trees": 16, "psi": 128} if method == "window_axis" else {"bins": 20} if method == "projections" else {}))
    score = np.array([k.step(r) for r in x])
    assert isolation.auc(score[260:], odd[260:]) > 0.75


def test_adaptive_forest_keeps_its_bounds():
    f = online.AdaptiveHistogramForest(omega=256, eta=16, trees=4)
    scores = [f.step(r) for r in np.random.default_rng(1).random((600, 2))]
    assert all(0 < s <= 1 for s in scores) and len(f.window) == 256
    assert all(r.h == 256 for r in f.roots)
    with pytest.raises(ValueError):
        online.AdaptiveHistogramForest(omega=16, eta=16)


@pytest.mark.parametrize("forget", ["buffer", "sampled"])
def test_adaptive_scorer_takes_rows_together(forget):
    """Many rows in one call, in parts, get the scores of single steps; boxes and points are plain numbers."""
    x = np.random.default_rng(5).exponential(10, (1500, 3))
    one, many = (online.AdaptiveHistogramForest(omega=256, eta=16, trees=4, forget=forget) for _ in range(2))
    want = [one.step(row) for row in x]
    assert np.array_equal(np.concatenate([many.run(x[:700], at_once=64), many.run(x[700:])]), want) and one.size() == many.size()
    assert all(type(v) is float for root in many.roots for v in root.lo + root.hi)


def test_library_booster_weighs_equal_rows_and_scores_others(spark):
    """Equal rows train as one with a weight, as in the library's plain fit on all rows; other rows can be scored, each once."""
    from pyspark.ml.classification import GBTClassifier, OneVsRest
    from pyspark.ml.linalg import Vectors

    kinds = [([1], "a", 9), ([1], "b", 2), ([2], "b", 7), ([1, 2], "a", 1), ([], "b", 3)]
    rows = [(f, y) for f, y, n in kinds for _ in range(n)]
    df = spark.createDataFrame([(i, y, f) for i, (f, y) in enumerate(rows)], "doc_id long, lang string, feats array<int>")
    rest = spark.createDataFrame([(100, [2]), (101, [1, 2]), (102, [2])], "doc_id long, feats array<int>")
    got = {r["doc_id"]: r["z"] for r in openset.library_booster(df, "lang", 2, rounds=2, depth=2, of=rest).collect()}
    plain = spark.createDataFrame([(Vectors.dense([float(i in f) for i in (1, 2)]), float("ab".index(y))) for f, y in rows], ["features", "label"])
    model = OneVsRest(classifier=GBTClassifier(maxIter=2, maxDepth=2)).fit(plain)
    want = [r["rawPrediction"].toArray() for r in model.transform(spark.createDataFrame([(Vectors.dense([0.0, 1.0]),), (Vectors.dense([1.0, 1.0]),)], ["features"])).collect()]
    assert set(got) == {100, 101, 102} and np.allclose([got[100], got[101], got[102]], [want[0], want[1], want[0]])


def test_booster_and_ratio():
    rng = np.random.default_rng(2)
    y = rng.integers(3, size=120)
    x = (rng.random((120, 9)) < 0.1).astype(float)
    x[np.arange(120), y] = 1
    b = openset.SoftmaxBooster(rounds=10).fit(x, [str(v) for v in y])
    assert (b.raw_scores(x).argmax(axis=1) == y).mean() > 0.95
    assert (openset.nn_ratio(x[:5], x, y) == math.inf).all()


def test_auc_edge_cases():
    assert math.isnan(isolation.auc(np.ones(3), np.zeros(3)))
    assert isolation.auc(np.array([1, 1, 1, 1]), np.array([0, 1, 0, 1])) == 0.5


def test_segmented_replay_equals_plain_in_first_run(spark):
    from outlyer.streaming.online import replay

    df = spark.range(600).selectExpr("id as t", "cast(id % 7 as double) as a", "cast(id % 11 as double) as b")
    how = {"trees": 2, "omega": 64, "eta": 8}
    plain = {r["t"]: r["score"] for r in replay(df, ["a", "b"], ["t"], **how).collect()}
    cut = {r["t"]: r["score"] for r in replay(df, ["a", "b"], ["t"], segment=256, warm=128, **how).collect()}
    assert cut.keys() == plain.keys()
    assert all(cut[t] == plain[t] for t in range(256))


def test_fixed_half_spaces_miss_a_dense_ball(spark):
    from outlyer import catalog

    got = {r["method"]: r["auc"] for r in catalog.queries()["half_space_clustered"](spark, "/root/testdata/sf0.001").collect()}
    assert got["adaptive"] > 0.9 > 0.7 > got["half_space"]


def test_nn_ratios_take_all_training_rows(spark):
    rng = np.random.default_rng(5)
    rows = [(i, "abc"[int(rng.integers(3))] if i % 7 else None, sorted({int(v) for v in rng.integers(1, 25, 6)})) for i in range(1500)]
    df = spark.createDataFrame(rows, "doc_id long, lang string, feats array<int>")
    train = [r for r in rows if r[1] and r[0] % 20]
    assert len(train) > 1000
    x = openset.dense([r[2] for r in rows if r[0] % 20 == 0], 24)
    want = openset.nn_ratio(x, openset.dense([r[2] for r in train], 24), np.array([r[1] for r in train], object))
    got = {r["doc_id"]: r["ratio"] for r in openset.nn_ratios(df.where("doc_id % 20 = 0"), df.where("lang is not null and doc_id % 20 <> 0"), "lang", 24, block=300).collect()}
    assert [got[20 * k] for k in range(75)] == pytest.approx(want.tolist())


def test_nn_ratio_query_equals_brute_force_over_all_training_rows(spark):
    from outlyer import catalog
    from outlyer.plans import methods

    d = "/root/testdata/sf0.01"
    got = {r["doc_id"]: r["ratio"] for r in catalog.queries()["nn_ratio"](spark, d).collect()}
    rows = methods._presence(spark, d)[2].select("doc_id", "lang", "feats").collect()
    train = [r for r in rows if r["lang"] is not None and u01_py("split", r["doc_id"]) < 0.67]
    test = [r for r in rows if r["doc_id"] % 20 == 0]
    want = openset.nn_ratio(openset.dense([r["feats"] for r in test], 154), openset.dense([r["feats"] for r in train], 154), np.array([r["lang"] for r in train], object))
    assert sorted(got) == sorted(r["doc_id"] for r in test)
    assert [got[r["doc_id"]] for r in test] == pytest.approx(want.tolist())
