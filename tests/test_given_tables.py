"""Queries that once differed from their SQL outside the smallest scale, or made their data up instead of reading a given table."""

import datetime
from collections import Counter

import numpy as np
import pytest

from outlyer import catalog
from outlyer.operators import isolation, measures
from outlyer.plans import dataflow, experiments, methods
from outlyer.sources import planted
from outlyer.streaming import online

D = "/root/testdata/sf0.001"


def test_a_range_of_time_ends_at_the_microsecond(spark, tmp_path):
    day = datetime.timedelta(days=1)
    at = datetime.datetime(2024, 1, 1, 0, 0, 0, 900_000)
    rows = [(1, at, 1, 1.0), (2, at + day + datetime.timedelta(microseconds=50_000), 1, 2.0), (3, at + 2 * day + datetime.timedelta(microseconds=50_000), 1, 4.0)]
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, value double").write.parquet(str(tmp_path / "events.parquet"))
    got = {r["event_id"]: r["day_sum"] for r in catalog.queries()["win_range"](spark, str(tmp_path)).collect()}
    assert got == {1: 1.0, 2: 2.0, 3: 6.0}


def test_paired_t_rounds_the_mean_and_not_its_float_noise(spark):
    """The mean is 0.2042475 exactly; as a sum of floats it is 0.20424749999999997."""
    rows = list(zip([0.255294, 0.841745, 0.673114, 0.083234], [0.016691, 0.01456, 0.755587, 0.249559], strict=True))
    got = measures.paired_t(spark.createDataFrame(rows, "a double, b double").coalesce(1), "a", "b").first()
    assert (got["n"], got["mean_diff"]) == (4, 0.204248)


FROM_TABLES = {
    "window_models": "lineitem",
    "online_depths": "events",
    "node_paths": "orders",
    "folded_collision_experiment": "orders",
    "critical_difference": "orders",
    "collision_law": "lineitem",
    "c_iso_table": "lineitem",
}


@pytest.mark.parametrize("name", sorted(FROM_TABLES))
def test_reads_its_table(spark, name):
    files = catalog.queries()[name](spark, D).inputFiles()
    assert [f.rsplit("/", 1)[1] for f in files] == [f"{FROM_TABLES[name]}.parquet"]


def test_pairs_of_query_rows_are_not_shuffled(spark, monkeypatch):
    """Sums over shared models equal a plain loop, repeated rows of an id included, with the queries in one broadcast or several."""
    rng = np.random.default_rng(3)
    rows = [(int(p), 0, int(m), float(x)) for p, m, x in zip(rng.integers(0, 90, 400), rng.integers(0, 12, 400), rng.random(400), strict=True)]
    pref = spark.createDataFrame(rows, "pid long, is_anom int, mid long, p double")
    pairs = [(x, y) for x in rows for y in rows if x[0] % 20 == 0 and x[0] != y[0] and x[2] == y[2]]
    total = lambda i, f: sum(f(r) for r in rows if r[0] == i)
    for postings in (methods.POSTINGS, 7):
        monkeypatch.setattr(methods, "POSTINGS", postings)
        shared = methods.shared_models(pref)
        assert "hashpartitioning(a#" not in shared._jdf.queryExecution().executedPlan().toString()
        n = Counter((x[0], y[0]) for x, y in pairs)
        assert sorted(map(tuple, shared.collect())) == sorted((*k, v) for k, v in n.items())
        for kind, own, mass in (("jaccard", lambda x, y: 1, lambda r: 1), ("ruzicka", min, lambda r: r[3]), ("tanimoto", lambda x, y: x * y, lambda r: r[3] ** 2)):
            both = Counter()
            for x, y in pairs:
                both[x[0], y[0]] += own(x[3], y[3])
            want = {k: 1 - v / (total(k[0], mass) + total(k[1], mass) - v) for k, v in both.items()}
            got = methods.pair_distances(pref, kind)
            assert {(r["a"], r["b"]): r["d"] for r in got.collect()} == pytest.approx(want, abs=6e-6)
    assert methods.shared_models(pref.where("false")).count() == 0


def test_every_pair_that_shares_a_model_is_counted(spark, monkeypatch):
    """Rows whose ids are not divisible by 20 are queries too, repeated rows of an id count as often as in the SQL's join."""
    rng = np.random.default_rng(4)
    rows = [(int(p), 0, int(m), 1.0) for p, m in zip(rng.integers(-40, 60, 300), rng.integers(0, 9, 300), strict=True)]
    pref = spark.createDataFrame(rows, "pid long, is_anom int, mid long, p double")
    want = Counter((x[0], y[0]) for x in rows for y in rows if x[0] != y[0] and x[2] == y[2])
    for postings in (methods.POSTINGS, 90):
        monkeypatch.setattr(methods, "POSTINGS", postings)
        assert sorted(map(tuple, methods.shared_models(pref, every=True).collect())) == sorted((*k, v) for k, v in want.items())
    got = catalog.queries()["join_shared_model"](spark, D)
    assert got.where("a % 20 <> 0").count() > 0 and got.select("a").distinct().count() == got.select("b").distinct().count()


@pytest.mark.parametrize("kind", ["hash", "oblique"])
def test_dense_splits_equal_sparse_ones(monkeypatch, kind):
    """Looking at the first models ahead changes no score, also for rows with few models or none."""
    rng = np.random.default_rng(5)
    dense = (rng.random((60, 1500)) * (rng.random((60, 1500)) < rng.choice([0, 0.001, 0.02, 0.9], (60, 1)))).astype(np.float32)
    x, scores, calls = isolation.Sparse.of(dense), [], []
    plain = isolation.Forest._hashed_all
    monkeypatch.setattr(isolation.Forest, "_hashed_all", lambda self, split, x, rows: calls.append(len(rows)) or plain(self, split, x, rows))
    for full in (isolation.FULL, 0):
        monkeypatch.setattr(isolation, "FULL", full)
        scores.append(isolation.Forest(kind, 32, seed=3).fit(x, 10).score(x))
        calls.append(-1)
    assert scores[0] == pytest.approx(scores[1], abs=1e-12)
    both = sum(calls[: calls.index(-1)]), sum(calls[calls.index(-1) + 1 : -1])
    assert kind == "oblique" or both[0] < both[1]


def test_each_method_of_a_set_is_a_task_and_ranks_read_them_once(spark, monkeypatch):
    """The parts give what one task gave, and ``method_ranks`` runs the continuous methods only once."""
    x, truth = planted.shapes("star5", 1, per=8)
    monkeypatch.setattr(experiments, "TREES", 4)
    whole = list(experiments._aucs("star5", 1, x, truth))
    apart = [r for space in ("ambient", "binary", "continuous") for e in ((0.0,) if space == "ambient" else (0.03, 0.2)) for m in ("l2", "jaccard", "tanimoto", "ruzicka", "axis", "oblique", "hash") for r in experiments._aucs("star5", 1, x, truth, (e,), (space,), m)]
    assert sorted(map(repr, whole)) == sorted(map(repr, apart)) and len(whole) == 4 + 2 * 5 + 2 * 7
    seen = []
    rows = [(k, 1, e, "continuous", m, 0.5 + e * i / 10, None) for k in ("star5", "stair3") for e in (0.03, 0.2) for i, m in enumerate(("hash", "axis"))]
    monkeypatch.setattr(experiments, "_space_aucs", lambda s, d, spaces: seen.append(spaces) or s.createDataFrame(rows, experiments._AUC))
    assert {r["method"]: r["mean_rank"] for r in experiments.method_ranks(spark, D).collect()} == {"hash": 2.0, "axis": 1.0} and seen == [("continuous",)]


@pytest.mark.parametrize("name, how", [("half_space", {"trees": 3, "window": 100}), ("window_axis", {"trees": 3, "omega": 300, "psi": 64}), ("periodic_axis", {"trees": 3, "omega": 300, "psi": 64})])
def test_rows_of_a_window_together_equal_steps(name, how):
    rng = np.random.default_rng(2)
    x = rng.random((1500, 4)) * rng.choice([1, 1.7], (1500, 1), p=[0.9, 0.1])
    one, many = (online.KERNELS[name](4, 1, **how) for _ in range(2))
    want = [one.step(row) for row in x]
    got = np.concatenate([many.run(x[a:b]) for a, b in ((0, 0), (0, 1), (1, 450), (450, 1500))])
    assert np.array_equal(got, want)


@pytest.mark.parametrize("name, how", [("cut_forest", {"trees": 2, "psi": 48}), ("projections", {"warm": 100}), ("adaptive", {"trees": 9, "omega": 200, "eta": 16})])
def test_runs_of_rows_equal_steps(name, how):
    rng = np.random.default_rng(6)
    x = np.round(rng.random((900, 4)) * rng.choice([1, 1.7], (900, 1), p=[0.9, 0.1]), 2)
    one, many = (online.KERNELS[name](4, 1, **how) for _ in range(2))
    want = [one.step(row) for row in x]
    got = np.concatenate([many.run(x[a:b]) for a, b in ((0, 0), (0, 1), (1, 450), (450, 900))])
    assert np.array_equal(got, want)


def test_half_spaces_take_many_windows_at_once(monkeypatch):
    """Only the first of many whole windows and what is left at the end are counted node by node."""
    calls, plain = [], online.HalfSpaceTrees._tree_scores
    monkeypatch.setattr(online.HalfSpaceTrees, "_tree_scores", lambda self, t, x: calls.append(len(x)) or plain(self, t, x))
    x = np.random.default_rng(7).random((2030, 3))
    one, many = (online.HalfSpaceTrees(3, window=50, trees=2) for _ in range(2))
    assert np.array_equal(many.run(x), [one.step(row) for row in x])
    assert calls == [50, 50, 30, 30] and many.size() == one.size()


def test_boxes_and_sizes_of_a_cut_forest_follow_its_points():
    forest, x = online.RandomCutForest(trees=2, psi=20), np.random.default_rng(8).integers(0, 6, (120, 2)).astype(float)
    for i, row in enumerate(x):
        forest.step(row)
        if i < 30 or i % 7:
            continue
        for root in forest.roots:
            def points(node):
                return [node[0]] if node[5] is None else points(node[5]) + points(node[6])

            todo = [root]
            while todo:
                node = todo.pop()
                own = np.array(points(node))
                assert (node[2], list(node[0]), list(node[1])) == (len(own), own.min(axis=0).tolist(), own.max(axis=0).tolist())
                todo += [n for n in node[5:7] if n is not None]
            assert sorted(points(root)) == sorted(x[i - 19 : i + 1].tolist())


def test_a_row_is_scored_once_where_keys_repeat(spark):
    """Labels travel with their rows: a join on keys that repeat gave 16 rows too many at sf0.01 and 2 by 2 rows here."""
    rows = [(f"2024-01-0{1 + i % 9}", 7, 1, 3 + i % 2, float(1 + i % 50), 100.0 + i, 0.01 * (i % 9), 0.01 * (i % 7)) for i in range(400)]
    df = spark.createDataFrame(rows, "day string, l_orderkey long, l_linenumber int, l_suppkey long, f0 double, f1 double, f2 double, f3 double")
    df = df.selectExpr("*", "int(f0 = 50) as is_anom")
    got = {r["method"]: (r["n_pos"], r["n_neg"]) for r in dataflow.suite(df, ["f0", "f1", "f2", "f3"], ["day", "l_orderkey", "l_linenumber"], "l_suppkey", {"half_space": {"trees": 2}, "projections": {}}).collect()}
    assert got == {"half_space": (8, 392), "projections": (8, 392)}


def test_auc_by_slices_equals_all_pairs(spark):
    rng = np.random.default_rng(9)
    score = np.round(np.concatenate([rng.random(300), rng.normal(0, 1e3, 80), rng.random(60) * 1e-3, [np.inf, -np.inf, np.nan, np.nan]]), 4)
    label = rng.integers(0, 2, len(score))
    rows = [("x", float(a), int(b)) for a, b in zip(score, label, strict=True)] + [("x", None, 1), ("x", None, 0), ("y", 1.0, 1), ("z", 1.0, 1), ("z", 0.0, 0)]
    rank = lambda v: (0, 0.0) if v is None else (2, 0.0) if np.isnan(v) else (1, v)  # noqa: E731  nulls first, NaN last
    own = [(rank(a), b) for g, a, b in rows if g == "x"]
    won = [2 * (a > c) + (a == c) for a, b in own for c, d in own if b == 1 and d == 0]
    df = spark.createDataFrame(rows, "g string, score double, is_anom int")
    got = measures.roc_auc(df, by=["g"])
    assert {r["g"]: r["auc"] for r in got.collect()} == {"x": pytest.approx(sum(won) / 2 / len(won), abs=1e-6), "y": None, "z": 1.0}
    assert measures.roc_auc(df.where("g = 'x'")).first()["auc"] == pytest.approx(sum(won) / 2 / len(won), abs=1e-6)
    assert "_k" in got._jdf.queryExecution().optimizedPlan().toString()
