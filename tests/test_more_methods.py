"""Variants, baselines, tables of structures, decision rules and dataflow against plain numpy."""

import numpy as np
import pytest

from outlyer.core.estimators import StructureScorer, assemble, scale
from outlyer.core.scratch import drained
from outlyer.operators import isolation, linkage, openset
from outlyer.operators.families import FAMILIES, Family, polynomial, sample_models, subspace
from outlyer.sources import planted
from outlyer.streaming import online


@pytest.fixture(scope="module")
def star():
    x, truth = planted.shapes("star5", 1)
    models = [(FAMILIES["line"], t) for t in sample_models(x, FAMILIES["line"], 3 * len(x), 1)]
    return x, truth, models


def two_lines(noise=0.005):
    rng = np.random.default_rng(4)
    t = rng.random(40)
    x = np.vstack([np.column_stack([t, 0.2 + 0 * t]), np.column_stack([0.5 + 0 * t, t])]) + rng.normal(0, noise, (80, 2))
    return x, np.repeat([1, 2], 40)


def test_sparse_preferences_equal_dense(star):
    x, _, models = star
    for kind in ("binary", "gauss", "gauss05"):
        dense = isolation.preference(x, models, 0.03, kind)
        assert np.allclose(isolation.sparse_preference(x, models, 0.03, kind).dense(), dense) and np.allclose(isolation.Sparse.of(dense).dense(), dense)
    s = isolation.sparse_preference(x, models, 0.03)
    w = np.random.default_rng(1).normal(size=s.m)
    assert np.allclose(s.dot(w, np.arange(len(s))), s.dense() @ w, atol=1e-4) and len(s[5:9]) == 4
    assert len(isolation.sparse_preference(x[:3], [], 0.03)) == 3


def test_a_threshold_for_each_family(star):
    x, _, models = star
    mixed = models[:10] + [(FAMILIES["circle"], t) for t in sample_models(x, FAMILIES["circle"], 10, 2)]
    p = isolation.preference(x, mixed, {"line": 0.02, "circle": 0.05}, "binary")
    assert np.array_equal(p[:, :10], isolation.preference(x, mixed[:10], 0.02, "binary")) and np.array_equal(p[:, 10:], isolation.preference(x, mixed[10:], 0.05, "binary"))


def test_cells_on_a_table_equal_cells_on_points(star):
    x, _, models = star
    p = isolation.preference(x, models, 0.03)
    table = isolation.distance(p, p, "tanimoto")
    each = np.arange(len(x))[:, None]
    a = isolation.Forest("table", 128, 4, seed=3, table=table).fit(each, 10).score(each)
    assert a == pytest.approx(isolation.Forest("cell", 128, 4, seed=3).fit(p, 10).score(p), abs=0.02)


@pytest.mark.parametrize("b", [2, 4, 8, 16])
def test_auc_is_flat_in_the_number_of_branches(star, b):
    x, truth, models = star
    s = isolation.sparse_preference(x, models, 0.03)
    table = isolation.distance(s.dense(), s.dense(), "tanimoto")
    each = np.arange(len(x))[:, None]
    assert isolation.auc(isolation.Forest("table", 256, b, table=table).fit(each, 60).score(each), truth == 0) > 0.85
    assert isolation.auc(isolation.Forest("hash", 256, b).fit(s, 60).score(s), truth == 0) > 0.75
    assert isolation.Forest("hash", 256, b, c_base="binary").c(100) == isolation.c_iso(100) and isolation.Forest("hash", 256, 8).c(100) == pytest.approx(isolation.c_iso(100) / 3)


def test_unfolded_and_exact_hashes(star):
    x, truth, models = star
    s = isolation.sparse_preference(x, models, 0.03)
    for how in ({"b": None}, {"exact": True}, {"min_split": 20}):
        f = isolation.Forest("hash", 256, **how).fit(s, 40)
        assert isolation.auc(f.score(s), truth == 0) > 0.65 and f.counters()["trees"] == 40
    # two rows share a branch of an exact unfolded hash as often as they are similar
    p, q = np.array([[1, 0.5]], np.float32), np.array([[1, 0.0]], np.float32)
    both = isolation.Sparse.of(np.vstack([p, q]))
    f = isolation.Forest("hash", 2, None, exact=True)
    same = np.mean([np.ptp(f._hashed((t, 1), both, np.arange(2))) == 0 for t in range(3000)])
    assert same == pytest.approx(1 / 1.5, abs=0.03)
    with pytest.raises(ValueError):
        isolation.Forest("cell", 8, None)


def test_other_distances_and_layouts():
    rng = np.random.default_rng(0)
    x = rng.random((30, 4))
    assert isolation.distance(x, x[:5], "l1") == pytest.approx(np.abs(x[:, None] - x[None, :5]).sum(2))
    assert np.diag(isolation.distance(x, x, "cosine")) == pytest.approx(np.zeros(30), abs=1e-9)
    assert isolation.distance(x, x, lambda p, q: np.abs(p[:, None, 0] - q[None, :, 0])).shape == (30, 30)
    for kind in ("jaccard", "tanimoto", "ruzicka"):
        d = isolation.distance((x > 0.5).astype(np.float32), (x > 0.5).astype(np.float32), kind)
        assert np.allclose(d, isolation.distance((x > 0.5).astype(np.float32), (x > 0.5).astype(np.float32), "jaccard"))
    d = isolation.distance(x[:, :2], x[:, :2], "l2")
    flat = isolation.classical_scaling(d)
    assert isolation.distance(flat, flat, "l2") == pytest.approx(d, abs=1e-5)
    k = isolation.ordered_residual_similarity(np.abs(rng.normal(size=(12, 40))), 10)
    assert np.allclose(k, k.T) and (np.diag(k) >= k.max(axis=1) - 1e-9).all()


@pytest.mark.parametrize("family", [polynomial(3), subspace(2, 5), subspace(2, 5, affine=False), Family.from_callable("mean", 2, 1, lambda x: x.mean(axis=0), lambda x, t: np.linalg.norm(x - t, axis=1), d=0, K=2)])
def test_general_families(family):
    rng = np.random.default_rng(3)
    if family.name.startswith("poly"):
        t = rng.random(30)
        x = np.column_stack([t, 1 - t + 2 * t**3])
    elif family.name == "mean":
        x = np.tile([0.3, 0.4], (5, 1))
    else:
        x = rng.random((30, 2)) @ rng.random((2, 5)) + (1.0 if "affine" in family.name else 0.0)
    theta = family.fit(x)
    assert family.residual(x, theta).max() < 1e-6


@pytest.mark.parametrize("method", ["criterion", "centroid", "nested", "energy", "multi_energy", "progressive", "factorisation"])
def test_clusterings_part_two_lines(method):
    x, truth = two_lines()
    line = FAMILIES["line"]
    near = np.argsort(isolation.distance(x, x, "l2"), axis=1)[:, :12]
    models = [(line, t) for t in sample_models(x, line, 200, 2, near)]
    models = linkage.significant(x, models, 0.03) or models
    p = isolation.preference(x, models, 0.03, "gauss05")
    c = {
        "criterion": lambda: linkage.criterion_linkage(x, models, [line], 0.03)[0], "centroid": lambda: linkage.centroid_linkage(p), "nested": lambda: linkage.nested_linkage(x, [models], 0.03), "energy": lambda: linkage.energy_labelling(x, models, 0.03),
        "multi_energy": lambda: linkage.multi_model_energy(x, models, 0.03), "progressive": lambda: linkage.progressive_models(x, models, 0.03), "factorisation": lambda: linkage.preference_factorisation(p, 2),
    }[method]()
    assert linkage.misclassification_error(c, truth) <= 0.15


def test_criterion_options_and_counters():
    x, truth = two_lines()
    line, count = FAMILIES["line"], {}
    models = [(line, t) for t in sample_models(x, line, 150, 2)]
    label, names = linkage.criterion_linkage(x, models, [line], 0.03, orthogonal=True, counters=count)
    assert count["merges"] == len(x) - len(np.unique(label)) and count["models"] == 150 and count["edges"] == len(x) * (len(x) - 1) // 2
    table = linkage.cluster_table(x, label, names, [line], 0.03)
    assert sum(r[3] for r in table) == len(x) and {r[1] for r in table if not r[5]} == {"line"}
    ratio = np.array([0.2, 0.9, 3.0])
    assert linkage.capped(ratio, line).tolist() == pytest.approx([0.04, 0.81, 1.0]) and linkage.capped(ratio, line, "outside").tolist() == pytest.approx([0.04, 0.81, 1.0])


def test_refinement_never_costs_more():
    rng = np.random.default_rng(6)
    w = 2 * np.pi * rng.random(60)
    x = np.column_stack([np.cos(w), np.sin(w)]) * 0.3 + 0.5 + rng.normal(0, 0.01, (60, 2))
    x[:4] += 0.4
    f = FAMILIES["circle"]
    theta = f.fit(x)
    assert linkage.info_cost(x, f, linkage.refined(x, f, theta, 0.02), 0.02) < linkage.info_cost(x, f, theta, 0.02)


def test_tables_of_structures_equal_numpy(spark):
    x, truth = two_lines()
    df = spark.createDataFrame([("a", int(t), float(p[0]), float(p[1]), i, p.tolist()) for i, (p, t) in enumerate(zip(x, truth, strict=True))], "kind string, truth int, x0 double, x1 double, pid long, x array<double>")
    line, sigma = FAMILIES["line"], 0.03 / np.sqrt(-np.log(0.05))
    got = {r["truth"]: r["cost"] for r in linkage.line_costs(df, ["truth"], 0.03).collect()}
    assert got == pytest.approx({t: linkage.info_cost(x[truth == t], line, line.fit(x[truth == t]), sigma) for t in (1, 2)}, rel=1e-6)
    out = linkage.linkage_by(df, "kind", [line], 0.03)
    rows = sorted((r["pid"], r["cluster"]) for r in out.collect())
    assert linkage.misclassification_error(np.array([c for _, c in rows]), truth) <= 0.15
    table = linkage.contingency(out.join(df.select("pid", "truth"), "pid"), "cluster", "truth")
    assert linkage.matched_error(table, "cluster", "truth") == pytest.approx(linkage.misclassification_error(np.array([c for _, c in rows]), truth))


@pytest.mark.parametrize("fpr", [0.0, 0.005, 0.3, 1.0])
def test_threshold_is_the_exact_order_statistic(spark, fpr):
    v = np.random.default_rng(2).normal(size=4000).round(2)
    want = np.sort(v)[min(int(fpr * len(v)), len(v) - 1)]
    got = openset.threshold_of(spark.createDataFrame([(float(a),) for a in v], "score double"), fpr).first()["tau"]
    assert got == want


def test_presence_features_and_folds(spark):
    rows = [(i, ["a", "b", "z"][: i % 4], "xy"[i % 2]) for i in range(40)] + [(99, None, "x")]
    df = spark.createDataFrame(rows, "doc_id long, tokens array<string>, lang string")
    vocab = spark.createDataFrame([("b", 1), ("a", 2)], "token string, feat int")
    got = {r["doc_id"]: r["feats"] for r in openset.presence_features(df, "tokens", vocab).collect()}
    assert got[1] == [2] and got[2] == [1, 2] and got[0] == [] and not got[99]
    x = openset.presence_features(df.where("doc_id < 40"), "tokens", vocab)
    folded = openset.stratified_folds(x.select("doc_id", "lang", "feats"), "lang", 4)
    z = openset.folds_scored(folded, "lang", 2, folds=4, rounds=2)
    assert z.count() == 40 and z.where("size(z) = 2").count() == 40 and {r["setting"] for r in openset.fold_recalls(z, "lang").collect()} == {"closed", "open"}


def test_first_window_of_half_spaces_is_neutral_and_forgetting_needs_no_buffer():
    rng = np.random.default_rng(1)
    h = online.HalfSpaceTrees(2, window=50, trees=4)
    assert {h.step(x) for x in rng.random((50, 2))} == {0.5} and h.step(rng.random(2)) != 0.5
    f = online.AdaptiveHistogramForest(omega=256, eta=16, trees=4, forget="sampled")
    scores = [f.step(x) for x in rng.random((900, 2))]
    assert all(0 < s <= 1 for s in scores) and not f.window and f.size() < 4 * 64
    assert f.step(np.array([5.0, 5.0])) > np.median(scores)


def test_scores_do_not_depend_on_micro_batches(spark, tmp_path):
    df = spark.range(400).selectExpr("id as t", "'k' || (id % 2) as key", "cast(id % 17 as double) as a")
    for i in range(4):
        df.where(f"t div 100 = {i}").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    how = {"trees": 2, "omega": 64, "eta": 8}
    stream = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    got = {r["t"]: r["score"] for r in drained(online.score_stream(stream, ["a"], "t", "key", **how), "chunks").collect()}
    want = {r["t"]: r["score"] for r in online.replay(df, ["a"], ["t"], key="key", **how).collect()}
    assert got == pytest.approx(want)


def test_rate_source_and_progress(spark):
    q = spark.readStream.format("rate").option("rowsPerSecond", 50).load().writeStream.format("noop").trigger(processingTime="1 second").start()
    for _ in range(60):
        if q.lastProgress and q.lastProgress["numInputRows"] > 0:
            break
        q.awaitTermination(1)
    assert q.lastProgress["numInputRows"] > 0
    q.stop()


def test_repeated_batches_overwrite(spark, tmp_path):
    from pyspark.sql import functions as F

    src = spark.range(100).withColumn("g", F.col("id") % 3)
    src.write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(src.schema).parquet(str(tmp_path / "in")).groupBy("g").count()
    assert {r["g"]: r["count"] for r in drained(stream, "c", "complete").collect()} == {0: 34, 1: 33, 2: 33} == {r["g"]: r["count"] for r in drained(stream, "u", "update").select("g", "count").collect()}


def test_estimator_round_trip_and_features(spark, tmp_path):
    x, _ = two_lines()
    df = spark.createDataFrame([(i, p.tolist()) for i, p in enumerate(np.vstack([x, [[0.9, 0.9], [0.1, 0.8]]]))], "pid long, x array<double>")
    made = StructureScorer("line", 0.03, trees=20, psi=32, m=60).fit(df)
    made.save(spark, str(tmp_path / "m"))
    a, b = ({r["pid"]: r["score"] for r in s.transform(df).collect()} for s in (made, StructureScorer.load(spark, str(tmp_path / "m"))))
    assert a == b and len(a) == 82
    for wrong in ({"eps": 0}, {"family": "torus"}, {"b": 300}, {"kind": "other"}):
        with pytest.raises(ValueError):
            StructureScorer(**wrong)
    rows = spark.createDataFrame([(1.0, 5.0), (3.0, 5.0), (None, 5.0)], "a double, b double")
    assert [tuple(r) for r in scale(rows, ["a", "b"]).collect()] == [(0.0, 0.0), (1.0, 0.0), (None, 0.0)] and assemble(rows, ["a", "b"]).count() == 2


def test_forest_on_a_relation_finds_the_far_vector(spark):
    rng = np.random.default_rng(7)
    x = np.vstack([rng.normal(0, 0.1, (60, 3)), [[4, 4, 4]]])
    d = isolation.distance(x, x, "l2")
    pairs = spark.createDataFrame([(i, j, float(d[i, j])) for i in range(61) for j in range(61) if j % 2 == 0], "a long, b long, d double")
    got = {r["pid"]: r["score"] for r in isolation.scores_on_relation(pairs, spark.createDataFrame([(j,) for j in range(0, 61, 2)], "pid long"), trees=60, psi=16).collect()}
    assert len(got) == 61 and max(got, key=got.get) == 60
