"""Experiments on planted sets that derive from the given tables: each run is one group, dealt over the cluster.

Settings are those of the published study (pools of 10 n or 6 n models, 100 trees of 256 points, neighbourhoods from 10
up, the best taken for each method) unless a query's docstring says otherwise.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.scratch import scratch
from ..functions.rng import bottom_k
from ..operators import isolation, linkage, measures
from ..operators.families import FAMILIES, Family, sample_models, subspace
from ..sources import planted

QUERIES: dict = {}
SQL: dict[str, str] = {}
RUNS, TREES, PSI = 1, 100, 256
LOF_K = (10, 25, 50, 75, 100, 150, 200, 300, 400, 500)


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


def family_of(kind: str) -> Family:
    return FAMILIES[{"stair": "line", "star": "line", "circle": "circle", "planes": "homography", "motions": "fundamental"}[kind.rstrip("0123456789")]]


def by_run(points: DataFrame, runs: int, kernel, schema: str, parts: tuple = ()) -> DataFrame:
    """``kernel(kind, run, x, truth)`` yields result rows for each planted set and run; sets have a fixed number of points. With ``parts`` each of them is a task of its own and the kernel's last argument."""
    names = [c.split()[0] for c in schema.split(", ")]

    def work(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("pid")
        part = (parts[int(key[2])],) if parts else ()
        return pd.DataFrame(list(kernel(key[0], int(key[1]), np.array(pdf["x"].tolist()), pdf["truth"].to_numpy(), *part)), columns=names)

    spread = points.select("kind", "pid", "x", "truth", F.explode(F.sequence(F.lit(1), F.lit(runs))).alias("run"))
    spread = spread.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(max(0, len(parts) - 1)))))
    # a stated number of partitions: adaptive execution would put the few small groups into one task
    return spread.repartition(256 if parts else 64, "kind", "run", "part").groupBy("kind", "run", "part").applyInPandas(work, schema)


def shape_sets(s, d, kinds: list[str] | None = None, outliers: float = 0.5) -> DataFrame:
    sets = planted.planted_sets(s, d, outliers)
    return sets.where(F.col("kind") != "mixed") if kinds is None else sets.where(F.col("kind").isin(kinds))


@query(f"with {planted.sets_sql()} select kind, pid, truth, round(x0, 6) as x0, round(x1, 6) as x1 from sets")
def planted_sets(s, d):
    return planted.planted_sets(s, d).select("kind", "pid", "truth", F.round("x0", 6).alias("x0"), F.round("x1", 6).alias("x1"))


# --- isolation in ambient, binary and continuous space --------------------------------------------------------------


def _aucs(kind: str, run: int, x: np.ndarray, truth: np.ndarray, eps: tuple[float, ...] = (0.03, 0.2), spaces: tuple[str, ...] = ("ambient", "binary", "continuous"), only: str | None = None):
    """AUCs of all methods, or of the cuts or the distance ``only``."""
    family, y = family_of(kind), truth == 0
    multiple = 10 if family.r == 2 else 6
    models = [(family, t) for t in sample_models(x, family, multiple * len(x), run)]
    psi, each = min(PSI, len(x)), np.arange(len(x))[:, None]
    ks = sorted({min(k, len(x) - 1) for k in LOF_K})

    def distances(dist: str, p: np.ndarray):
        table = isolation.distance(p, p, dist)
        best = max((isolation.auc(isolation.lof_of(table, k), y), -k) for k in ks)
        yield f"lof_{dist}", best[0], -best[1]
        yield f"cell_{dist}", isolation.auc(isolation.Forest("table", psi, seed=run, table=table).fit(each, TREES).score(each), y), None

    def of(space: str, e: float, dense: np.ndarray, data, dists: list[str], cuts: list[str]):
        for dist in dists:
            if only in (None, dist):
                for method, auc, k in distances(dist, dense):
                    yield kind, run, e, space, method, auc, k
        for f in cuts:
            if only not in (None, f):
                continue
            yield kind, run, e, space, f, isolation.auc(isolation.Forest(f, psi, seed=run).fit(dense if f == "axis" else data, TREES).score(dense if f == "axis" else data), y), None

    if "ambient" in spaces:
        ambient = x.astype(np.float32)
        yield from of("ambient", 0.0, ambient, ambient, ["l2"], ["axis", "oblique"])
    for e in eps:
        for space, how, dists in (("binary", "binary", ["jaccard"]), ("continuous", "gauss", ["tanimoto", "ruzicka"])):
            if space in spaces:
                sparse = isolation.sparse_preference(x, models, e, how)
                yield from of(space, e, sparse.dense(), sparse, dists, ["axis", "oblique", "hash"])


_AUC = "kind string, run int, eps double, space string, method string, auc double, k int"


@query()
def auc_by_space(s, d):
    """AUC of each method in ambient, binary and continuous preference space on the planar sets, 10 n models, 100 trees, best LOF neighbourhood, two inlier thresholds, one run (the study has ten)."""
    return _space_aucs(s, d, ("ambient", "binary", "continuous"))


def _space_aucs(s, d, spaces: tuple[str, ...]) -> DataFrame:
    """One task for each set, run, space, threshold and method: a set's slowest method, not their sum, bounds the time."""
    methods = {"ambient": ("l2", "axis", "oblique"), "binary": ("jaccard", "axis", "oblique", "hash"), "continuous": ("tanimoto", "ruzicka", "axis", "oblique", "hash")}
    parts = tuple((space, e, m) for space in spaces for e in ((0.0,) if space == "ambient" else (0.03, 0.2)) for m in methods[space])
    one = lambda kind, run, x, truth, part: _aucs(kind, run, x, truth, (part[1],), (part[0],), part[2])
    return by_run(shape_sets(s, d), RUNS, one, _AUC, parts)


@query()
def auc_two_view(s, d):
    """The same in continuous preference space on 19 scenes of planes and 19 of motions, 6 n models, one run each."""
    run = lambda kind, run, x, truth: _aucs(kind, run, x, truth, (0.02,) if kind.startswith("planes") else (0.01,), ("continuous",))
    return by_run(planted.two_view_sets(s, d), 1, run, _AUC)


def _best(results: DataFrame) -> DataFrame:
    """Each method at the threshold that suits it best on a kind of set, as the neighbourhood of the local outlier factor is chosen."""
    group = F.regexp_replace("kind", "[0-9]+$", "")
    mean = results.groupBy(group.alias("family"), "space", "method", "eps").agg(F.avg("auc").alias("m"))
    top = mean.groupBy("family", "space", "method").agg(F.max_by("eps", F.struct("m", -F.col("eps"))).alias("eps"))
    return results.withColumn("family", group).join(F.broadcast(top), ["family", "space", "method", "eps"])


def _continuous(s, d) -> DataFrame:
    """:func:`_best` of the methods in continuous space. The results are written first: every use of them would run the forests again."""
    path = scratch(s, "aucs")
    _space_aucs(s, d, ("continuous",)).write.parquet(path)
    return _best(s.read.schema(_AUC).parquet(path))


@query()
def method_ranks(s, d):
    """Mean AUC and mean rank of the methods in continuous space over sets and runs, with the critical difference: own runs, not published figures."""
    best = _continuous(s, d).select("kind", "run", "method", "auc")
    ranks = measures.mean_ranks(best, "method", ["kind", "run"], "auc")
    stats = measures.run_stats(best, ["method"], "auc")
    return ranks.join(stats, "method").withColumn("cd", F.round(F.lit(measures.NEMENYI_Q[6]) * F.sqrt(F.lit(6 * 7) / (6 * F.col("blocks"))), 6))


@query()
def method_pairs(s, d):
    """Which pairs of methods differ by more than the critical difference."""
    best = _continuous(s, d)
    return measures.nemenyi_pairs(measures.mean_ranks(best, "method", ["kind", "run"], "auc"), "method", 6)


def _branches(kind: str, run: int, x: np.ndarray, truth: np.ndarray):
    models = [(family_of(kind), t) for t in sample_models(x, family_of(kind), 10 * len(x), run)]
    sparse = isolation.sparse_preference(x, models, 0.03)
    tables = {d: isolation.distance(sparse.dense(), sparse.dense(), d) for d in ("tanimoto", "ruzicka")}
    for b in (2, 4, 8, 16):
        yield kind, run, "hash", b, isolation.auc(isolation.Forest("hash", PSI, b, seed=run).fit(sparse, TREES).score(sparse), truth == 0)
        for d, table in tables.items():
            each = np.arange(len(x))[:, None]
            yield kind, run, f"cell_{d}", b, isolation.auc(isolation.Forest("table", PSI, b, seed=run, table=table).fit(each, TREES).score(each), truth == 0)


@query()
def branching_sweep(s, d):
    """AUC of hash and cell forests by branching factor, 100 trees, 10 n models; times are in bench.py. One run (the study has five)."""
    return by_run(shape_sets(s, d, ["stair4", "star5"]), RUNS, _branches, "kind string, run int, method string, b int, auc double")


def _neighbourhoods(kind: str, run: int, x: np.ndarray, truth: np.ndarray):
    models = [(family_of(kind), t) for t in sample_models(x, family_of(kind), 10 * len(x), run)]
    for space, dist in (("ambient", "l2"), ("binary", "jaccard"), ("continuous", "tanimoto")):
        p = x if space == "ambient" else isolation.preference(x, models, 0.03, "binary" if space == "binary" else "gauss")
        table = isolation.distance(p, p, dist)
        for k in [k for k in LOF_K if k < len(x)]:
            yield kind, run, space, k, isolation.auc(isolation.lof_of(table, k), truth == 0)


@query()
def lof_k_sweep(s, d):
    """AUC of the local outlier factor by number of neighbours, in each space."""
    return by_run(shape_sets(s, d), 1, _neighbourhoods, "kind string, run int, space string, k int, auc double")


# --- structures -----------------------------------------------------------------------------------------------------


def structures_of(x: np.ndarray, families: list[Family], eps: float, seed: int, multiple: int = 2) -> tuple[list, list[list]]:
    """Pools of localised models, all that are not there by chance, and the same by family."""
    near = np.argsort(isolation.distance(x, x, "l2"), axis=1, kind="stable")[:, : max(12, families[0].s + 4)]
    models = [(f, t) for f in families for t in sample_models(x, f, multiple * len(x), seed, near)]
    kept = linkage.significant(x, models, eps) or models
    return kept, [[m for m in kept if m[0].name == f.name] for f in families]


def _plan(kind: str, dims: int) -> tuple[list[Family], float]:
    if kind == "mixed":
        return [FAMILIES["line"], FAMILIES["circle"], FAMILIES["parabola"]], 0.04
    if kind.startswith("planes"):
        return [FAMILIES["homography"]], 0.02
    if kind.startswith("motions"):
        return [FAMILIES["fundamental"], FAMILIES["affine-fundamental"]], 0.02
    if kind == "trajectories":
        return [subspace(3, dims), subspace(2, dims)], 0.12
    return [family_of(kind)], 0.04


def _clusterings(kind: str, run: int, x: np.ndarray, truth: np.ndarray):
    families, eps = _plan(kind, x.shape[1])
    kept, pools = structures_of(x, families, eps, run)
    p = isolation.preference(x, kept, eps, "gauss05")
    least = max(f.s for f in families) + 1
    small = lambda c: np.where(np.bincount(c)[c] <= least, 0, c)
    found = {
        "criterion": small(linkage.criterion_linkage(x, kept, families, eps)[0]), "centroid": small(linkage.centroid_linkage(p)), "nested": small(linkage.nested_linkage(x, pools, eps)),
        "energy": linkage.energy_labelling(x, kept, eps), "multi_energy": linkage.multi_model_energy(x, kept, eps), "progressive": linkage.progressive_models(x, kept, eps),
        "factorisation": linkage.preference_factorisation(p, int(truth.max()) + 1),
    }
    for method, c in found.items():
        yield kind, run, method, float(linkage.misclassification_error(c, truth)), int(len(np.unique(c)))


_ME = "kind string, run int, method string, me double, clusters int"


@query()
def clustering_error(s, d):
    """Misclassification error of criterion linkage and six other clusterings on planar sets (20 % outliers), four two-view scenes and trajectories of ``embeddings``; two runs."""
    planar = shape_sets(s, d, ["star5", "circle4", "mixed"], 0.2).select("kind", "pid", "x", "truth")
    views = planted.two_view_sets(s, d, mismatches=0.15).where(F.col("kind").isin("planes01", "planes02", "motions01", "motions02")).select("kind", "pid", "x", "truth")
    return by_run(planar.unionByName(views).unionByName(planted.trajectory_sets(s, d).select("kind", "pid", "x", "truth")), 2, _clusterings, _ME)


def _thresholds(kind: str, run: int, x: np.ndarray, truth: np.ndarray):
    family = family_of(kind)
    near = np.argsort(isolation.distance(x, x, "l2"), axis=1, kind="stable")[:, :12]
    models = [(family, t) for t in sample_models(x, family, 2 * len(x), run, near)]
    for k in (2, 3, 5, 8):
        eps = 0.01 * k
        kept = linkage.significant(x, models, eps) or models
        for method, c in (("criterion", linkage.criterion_linkage(x, kept, [family], eps)[0]), ("centroid", linkage.centroid_linkage(isolation.preference(x, kept, eps, "gauss05")))):
            yield kind, run, k, method, float(linkage.misclassification_error(np.where(np.bincount(c)[c] <= 3, 0, c), truth))


@query()
def eps_outlier_sweep(s, d):
    """Error of criterion and centroid linkage on the star of five lines by threshold (multiples of the noise) and outlier share; one run (the study has fifty)."""
    out = None
    for share in (0.1, 0.3, 0.5):
        part = by_run(shape_sets(s, d, ["star5"], share), RUNS, _thresholds, "kind string, run int, k int, method string, me double").withColumn("outliers", F.lit(share))
        out = part if out is None else out.unionByName(part)
    return out


def _silhouettes(kind: str, run: int, x: np.ndarray, truth: np.ndarray):
    family, grid = family_of(kind), (0.02, 0.04, 0.08)
    models = [(family, t) for t in sample_models(x, family, 2 * len(x), run)]
    best = linkage.tune_eps(x, [family], models, list(grid))
    for eps in grid:
        c, _ = linkage.criterion_linkage(x, linkage.significant(x, models, eps) or models, [family], eps)
        yield kind, run, eps, int(eps == best), float(linkage.misclassification_error(np.where(np.bincount(c)[c] <= 3, 0, c), truth))


@query()
def eps_by_silhouette(s, d):
    """The threshold that the silhouette picks, with the error at each."""
    return by_run(shape_sets(s, d, ["stair3", "star5"], 0.1), 1, _silhouettes, "kind string, run int, eps double, chosen int, me double")


@query()
def recovered_structures(s, d):
    """The criterion linkage as a table: each cluster of the mixed set with its family, parameters, points and cost."""

    def work(kind, run, x, truth):
        families, eps = _plan(kind, 2)
        kept, _ = structures_of(x, families, eps, run)
        label, names = linkage.criterion_linkage(x, kept, families, eps)
        yield from ((kind, run, *r) for r in linkage.cluster_table(x, label, names, families, eps))

    return by_run(shape_sets(s, d, ["mixed"], 0.1), 1, work, "kind string, run int, cluster int, family string, theta array<double>, n int, cost double, outlier int")


@query(f"with {planted.sets_sql()}, g as (select kind, truth, count(*) as n, avg(x0) as mx, avg(x1) as my, var_pop(x0) as vx, var_pop(x1) as vy, covar_pop(x0, x1) as cxy from sets where truth > 0 and (kind like 'stair%' or kind like 'star%') group by 1, 2), "
       "l as (select *, 0.5 * atan2(2 * cxy, vx - vy) as w from g), r as (select s.kind, s.truth, n, pow(-sin(w) * (x0 - mx) + cos(w) * (x1 - my), 2) / (pow(0.04, 2) / -ln(0.05)) as q from sets s join l using (kind, truth)) "
       "select kind, truth as cluster, n, round(sum(least(q, 1)) + any_value(n) + 4, 4) as cost from r group by 1, 2, n")
def structure_costs(s, d):
    """Criterion value of every planted line: capped squared residuals of the fit from moment sums, one a point for the manifold, two a parameter."""
    lines = planted.planted_sets(s, d).where("truth > 0 and (kind like 'stair%' or kind like 'star%')")
    return linkage.line_costs(lines, ["kind", "truth"], eps=0.04).select("kind", F.col("truth").alias("cluster"), "n", F.round("cost", 4).alias("cost"))


@query(f"with {planted.sets_sql()}, g as (select kind, truth, count(*) as n, sum(x0) as sx, sum(x1) as sy, sum(x0*x0) as sxx, sum(x1*x1) as syy, sum(x0*x1) as sxy from sets where truth > 0 and kind = 'star5' group by 1, 2), "
       "m as (select a.truth as a, b.truth as b, a.n + b.n as n, a.sx + b.sx as sx, a.sy + b.sy as sy, a.sxx + b.sxx as sxx, a.syy + b.syy as syy, a.sxy + b.sxy as sxy from g a join g b on a.truth < b.truth) "
       "select a, b, n, round(degrees(0.5 * atan2(2 * (sxy / n - sx * sy / n / n), (sxx / n - sx * sx / n / n) - (syy / n - sy * sy / n / n))), 3) as angle from m")
def merged_line_fits(s, d):
    """The line of every union of two clusters from the sums of their moments, without their points."""
    sums = linkage.line_moments(planted.planted_sets(s, d).where("truth > 0 and kind = 'star5'"), ["truth"])
    a, b = sums.select(*[F.col(c).alias(f"a_{c}") for c in sums.columns]), sums.select(*[F.col(c).alias(f"b_{c}") for c in sums.columns])
    both = a.join(F.broadcast(b), F.col("a_truth") < F.col("b_truth"))  # one row a cluster
    merged = both.select(F.col("a_truth").alias("a"), F.col("b_truth").alias("b"), *[(F.col(f"a_{c}") + F.col(f"b_{c}")).alias(c) for c in ("n", "sx", "sy", "sxx", "syy", "sxy")])
    return merged.select("a", "b", "n", F.round(F.degrees(linkage.line_angle()), 3).alias("angle"))


@query(f"with {planted.sets_sql()}, c as (select kind, truth, (floor(x0 * 4))::int as cluster from sets where kind = 'stair4'), t as (select cluster, truth, count(*) as n from c group by 1, 2) select cluster, truth, n from t")
def contingency(s, d):
    """Points by cluster and class: what the misclassification error matches. Clusters here are quarters of the first axis."""
    sets = planted.planted_sets(s, d).where("kind = 'stair4'").withColumn("cluster", F.floor(F.col("x0") * 4).cast("int"))
    return linkage.contingency(sets, "cluster", "truth")


def _pools(kind: str, run: int, x: np.ndarray, truth: np.ndarray):
    family = family_of(kind)
    for multiple in (1, 2, 4, 8):
        near = np.argsort(isolation.distance(x, x, "l2"), axis=1, kind="stable")[:, :12]
        models = [(family, t) for t in sample_models(x, family, multiple * len(x), run, near)]
        kept = linkage.significant(x, models, 0.04) or models
        c, _ = linkage.criterion_linkage(x, kept, [family], 0.04)
        yield kind, run, multiple, len(kept), float(linkage.misclassification_error(np.where(np.bincount(c)[c] <= 3, 0, c), truth))


@query()
def pool_sweep(s, d):
    """Criterion linkage by size of the pool of models (multiples of n); times of sampling and clustering are in bench.py."""
    return by_run(shape_sets(s, d, ["stair4", "star5"], 0.2), 1, _pools, "kind string, run int, multiple int, kept int, me double")


# --- windows --------------------------------------------------------------------------------------------------------


@query()
def window_family_sweep(s, d):
    """AUC of the windowed scorer by window size and family (plane, sphere, quadric), 16 branches, 40 cells a side: the smallest windows, and the whole lattice as one."""
    side, out = 40, None
    grid = planted.lattice(s, d, side).where(F.col("gy") < side)
    for omega in (side, side // 2, side // 4):
        for family in ("plane", "sphere", "quadric"):
            score = isolation.windowed_scores(grid, omega if omega < side else 2 * side, family, 0.02, m=200, trees=50, psi=256, b=16)
            part = measures.roc_auc(score.join(grid.select("pid", "is_anom"), "pid")).select(F.lit(omega).alias("omega"), F.lit(family).alias("family"), "auc")
            out = part if out is None else out.unionByName(part)
    return out


@query()
def timed_window_scores(s, d):
    """The structure scorer in half-overlapping windows of twelve hours of ``events``: points are (hour, value) with planted shifts."""
    e = planted.event_stream(s, d)
    t = F.unix_timestamp(F.col("ts").cast("timestamp"))
    rows = e.select(F.col("event_id").alias("pid"), t.alias("ts"), F.array(t % 43_200 / 43_200.0, F.col("value") / 100).alias("x"))
    return isolation.timed_window_scores(rows, 43_200, trees=10, psi=64).join(e.select(F.col("event_id").alias("pid"), "is_anom"), "pid")


@query()
def relation_forest_scores(s, d):
    """A cell forest that sees ``embeddings`` as cosine distances only: every vector against 256 drawn ones."""
    e = s.read.parquet(f"{d}/embeddings.parquet").select(F.col("vec_id").alias("pid"), F.transform("embedding", lambda v: v.cast("double")).alias("e"))
    sample = bottom_k(e, 256, "relation", "pid")
    dot = F.aggregate(F.zip_with("e", "f", lambda x, y: x * y), F.lit(0.0), lambda a, v: a + v)
    pairs = e.crossJoin(F.broadcast(sample.select(F.col("pid").alias("b"), F.col("e").alias("f")))).select(F.col("pid").alias("a"), "b", (1 - dot).alias("d"))  # 256 rows
    return isolation.scores_on_relation(pairs, sample.select("pid"))


# --- ranks over the library's own scores, with SQL ------------------------------------------------------------------

_SCORES = """s as (select doc_id, lang, (quality = 0)::int as y, unnest(['distinct', 'length', 'digits', 'capitals']) as method,
  unnest([-len(list_distinct(string_split(text, ' ')))::double / len(string_split(text, ' ')), -length(text)::double, length(regexp_replace(text, '[^0-9]', '', 'g'))::double / (length(text) + 1), length(regexp_replace(text, '[^A-Z]', '', 'g'))::double / (length(text) + 1)]) as score
  from documents join labels using (doc_id) where lang is not null and text is not null),
r as (select *, rank() over (partition by lang, method order by score) + (count(*) over (partition by lang, method, score) - 1) / 2 as mid from s),
a as (select lang, method, round((sum(mid) filter (y = 1) - sum(y) * (sum(y) + 1) / 2) / (sum(y) * sum(1 - y)), 6) as auc from r group by 1, 2 having sum(y) > 0 and sum(1 - y) > 0)"""


def quality_aucs(s, d) -> DataFrame:
    """AUC of four text measures against ``quality`` for each language: lang, method, auc."""
    words, n = F.split("text", " ", -1), F.length("text") + 1
    share = lambda pattern: F.length(F.regexp_replace("text", pattern, "")) / n
    each = {"distinct": -F.size(F.array_distinct(words)) / F.size(words), "length": -F.length("text").cast("double"), "digits": share("[^0-9]"), "capitals": share("[^A-Z]")}
    docs = s.read.parquet(f"{d}/documents.parquet").where("lang is not null and text is not null").select("doc_id", "lang", F.explode(F.array(*[F.struct(F.lit(k).alias("method"), v.alias("score")) for k, v in each.items()])).alias("m")).select("doc_id", "lang", "m.*")
    labels = s.read.parquet(f"{d}/labels.parquet").select("doc_id", (F.col("quality") == 0).cast("int").alias("is_anom"))
    return measures.roc_auc(docs.join(labels, "doc_id"), by=["lang", "method"]).where("auc is not null").select("lang", "method", "auc")


@query(f"with {_SCORES} select method, round(avg(k), 6) as mean_rank, count(*) as blocks from (select method, rank() over (partition by lang order by auc desc) + (count(*) over (partition by lang, auc) - 1) / 2 as k from a) group by 1")
def mean_ranks(s, d):
    return measures.mean_ranks(quality_aucs(s, d), "method", ["lang"], "auc")


@query(f"with {_SCORES} select method, round(avg(auc), 6) as mean, round(median(auc), 6) as median, round(stddev(auc), 6) as std, round(quantile_cont(auc, 0.75) - quantile_cont(auc, 0.25), 6) as iqr, min(auc) as lo, max(auc) as hi from a group by 1")
def run_stats(s, d):
    return measures.run_stats(quality_aucs(s, d), ["method"], "auc")


@query(f"with {_SCORES} select count(*) as n, round(avg(x.auc - z.auc), 6) as mean_diff, round(avg(x.auc - z.auc) / nullif(stddev(x.auc - z.auc) / sqrt(count(*)), 0), 6) as t from a x join a z using (lang) where x.method = 'distinct' and z.method = 'digits'")
def paired_t(s, d):
    r = quality_aucs(s, d)
    return measures.paired_t(r.where("method = 'distinct'").select("lang", F.col("auc").alias("a")).join(r.where("method = 'digits'").select("lang", F.col("auc").alias("b")), "lang"), "a", "b")


@query(f"with {_SCORES}, k as (select method, avg(k) as r, count(*) as n from (select method, rank() over (partition by lang order by auc desc) + (count(*) over (partition by lang, auc) - 1) / 2 as k from a) group by 1) "
       "select x.method as a, z.method as b, round(abs(round(x.r, 6) - round(z.r, 6)), 6) as gap, round(2.569 * sqrt(20 / (6.0 * x.n)), 6) as cd, abs(round(x.r, 6) - round(z.r, 6)) > 2.569 * sqrt(20 / (6.0 * x.n)) as differs from k x join k z on x.method < z.method")
def nemenyi_pairs(s, d):
    return measures.nemenyi_pairs(mean_ranks(s, d), "method", 4)

