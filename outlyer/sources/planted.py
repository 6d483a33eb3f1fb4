"""Test inputs with known truth, derived from the given tables by counter-based draws. Nothing is written."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.rng import normal01, normal01_sql, u01, u01_sql, urange


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parallel segments of ``part`` with uniform anomalies, one for two: pid, x0, x1, is_anom, truth, x."""
    part = load(spark, sf_dir, "part").select("p_partkey", "p_retailprice")
    key = F.col("p_partkey")
    real = part.select(key.alias("pid"), (key / 1000.0).alias("x0"), ((F.col("p_retailprice") - 900) / 100 + 0.01 * normal01("seg", key)).alias("x1"), F.lit(0).alias("is_anom"), (1 + F.floor(key / 1000)).cast("int").alias("truth"))
    top = part.agg(F.max(key / 1000.0).alias("hi"))
    odd = part.where("p_partkey % 2 = 0").crossJoin(F.broadcast(top))
    odd = odd.select((-1 - key).alias("pid"), (u01("segx", key) * F.col("hi")).alias("x0"), u01("segy", key).alias("x1"), F.lit(1).alias("is_anom"), F.lit(0).alias("truth"))
    return real.unionByName(odd).withColumn("x", F.array("x0", "x1"))


SEGMENTS_SQL = f"""segments as (
  select p_partkey as pid, p_partkey / 1000.0::double as x0, (p_retailprice - 900) / 100 + 0.01 * {normal01_sql('seg', 'p_partkey')} as x1, 0 as is_anom, (1 + floor(p_partkey / 1000.0))::int as truth from part
  union all
  select -1 - p_partkey, {u01_sql('segx', 'p_partkey')} * (select max(p_partkey / 1000.0::double) from part), {u01_sql('segy', 'p_partkey')}, 1, 0 from part where p_partkey % 2 = 0)"""


def shapes(kind: str, seed: int = 1, per: int = 50, outliers: float = 0.5, noise: float = 0.01) -> tuple[np.ndarray, np.ndarray]:
    """Planted 2-D structures: stair3, stair4, star5, star11, circle3, circle4, circle5 or mixed. Points and truth (0: outlier)."""
    rng = np.random.Generator(np.random.PCG64([seed, sum(map(ord, kind))]))
    t = lambda n: rng.random(n)
    sets = []
    if kind.startswith("stair"):
        k = int(kind[5:])
        for j in range(k):
            n = per if not (k == 3 and j == 2) else per // 2
            a = t(n)
            sets.append(np.column_stack([(j + a) / k, np.full(n, (j + 0.5) / k)] if j % 2 == 0 else [np.full(n, (j + 0.5) / k), (j + a) / k]))
    elif kind.startswith("star"):
        k = int(kind[4:])
        for j in range(k):
            a = t(per) - 0.5
            w = math.pi * j / k
            sets.append(0.5 + np.column_stack([a * math.cos(w), a * math.sin(w)]))
    elif kind.startswith("circle"):
        k = int(kind[6:])
        for j in range(k):
            n = per if not (k == 3 and j == 2) else per // 2
            a = 2 * math.pi * t(n)
            centre, radius = 0.25 + 0.5 * rng.random(2), 0.1 + 0.15 * (j + 1) / k
            sets.append(centre + radius * np.column_stack([np.cos(a), np.sin(a)]))
    elif kind == "mixed":
        a, b, c = t(per), 2 * math.pi * t(per), t(per)
        sets = [np.column_stack([a, 0.2 + 0.3 * a]), [0.6, 0.65] + 0.2 * np.column_stack([np.cos(b), np.sin(b)]), np.column_stack([c, 0.1 + 3 * (c - 0.5) ** 2])]
    else:
        raise ValueError(f"unknown shape {kind}")
    x = np.vstack(sets) + rng.normal(0, noise, (sum(map(len, sets)), 2))
    truth = np.repeat(np.arange(1, len(sets) + 1), [len(s) for s in sets])
    n_out = round(len(x) * outliers / (1 - outliers)) if outliers < 1 else 0
    lo, hi = x.min(axis=0), x.max(axis=0)
    return np.vstack([x, rng.uniform(lo, hi, (n_out, 2))]), np.append(truth, np.zeros(n_out, int))


def _structures() -> list[tuple]:
    """(kind, structure, points, form, a, b, c, e): segments from (a, b) along (c, e), rims of radius c round (a, b), parabolas b + c (t - e)^2 over a + t."""
    rows: list[tuple] = []
    for k in (3, 4):
        for j in range(k):
            n = 25 if k == 3 and j == 2 else 50
            rows.append((f"stair{k}", j + 1, n, "segment", j / k, (j + 0.5) / k, 1 / k, 0.0) if j % 2 == 0 else (f"stair{k}", j + 1, n, "segment", (j + 0.5) / k, j / k, 0.0, 1 / k))
    for k in (5, 11):
        for j in range(k):
            w = math.pi * j / k
            rows.append((f"star{k}", j + 1, 50, "segment", round(0.5 - 0.5 * math.cos(w), 6), round(0.5 - 0.5 * math.sin(w), 6), round(math.cos(w), 6), round(math.sin(w), 6)))
    for k in (3, 4, 5):
        for j in range(k):
            w = 2 * math.pi * j / k
            rows.append((f"circle{k}", j + 1, 25 if k == 3 and j == 2 else 50, "rim", round(0.5 + 0.22 * math.cos(w), 6), round(0.5 + 0.22 * math.sin(w), 6), round(0.12 + 0.16 * (j + 1) / k, 6), 0.0))
    rows += [("mixed", 1, 50, "segment", 0.0, 0.2, 1.0, 0.3), ("mixed", 2, 50, "rim", 0.6, 0.65, 0.2, 0.0), ("mixed", 3, 50, "parabola", 0.0, 0.1, 3.0, 0.5)]
    return rows


STRUCTURES = _structures()


def _slots(outliers: float = 0.5) -> list[tuple]:
    """One row a point: its number, kind, structure (0: outlier) and the structure's form. The sets' sizes are fixed, whatever the table's."""
    out, kinds = [], dict.fromkeys(r[0] for r in STRUCTURES)
    for kind in kinds:
        own = [(kind, r[1], *r[3:]) for r in STRUCTURES if r[0] == kind for _ in range(r[2])]
        out += own + [(kind, 0, "outlier", 0.0, 0.0, 0.0, 0.0)] * round(len(own) * outliers / (1 - outliers))
    return [(i, *r) for i, r in enumerate(out)]


def planted_sets(spark: SparkSession, sf_dir: str, outliers: float = 0.5, noise: float = 0.01) -> DataFrame:
    """All planar sets at once: kind, pid, x0, x1, truth (0: outlier), x. The k-th point draws from the key of the k-th row of ``lineitem``."""
    from pyspark.sql import Window

    slots = spark.createDataFrame(_slots(outliers), "pid long, kind string, truth int, form string, a double, b double, c double, e double")
    n = slots.count()
    keys = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber").orderBy("l_orderkey", "l_linenumber").limit(n)  # as many rows as the sets have
    keys = keys.withColumn("pid", (F.row_number().over(Window.orderBy("l_orderkey", "l_linenumber")) - 1).cast("long"))
    ids = ["l_orderkey", "l_linenumber"]
    t, w = u01("set-t", *ids), 2 * math.pi * u01("set-t", *ids)
    x = F.when(F.col("form") == "segment", F.col("a") + F.col("c") * t).when(F.col("form") == "rim", F.col("a") + F.col("c") * F.cos(w)).otherwise(F.col("a") + t)
    y = F.when(F.col("form") == "segment", F.col("b") + F.col("e") * t).when(F.col("form") == "rim", F.col("b") + F.col("c") * F.sin(w)).otherwise(F.col("b") + F.col("c") * F.pow(t - F.col("e"), F.lit(2)))
    drawn = F.broadcast(slots).join(keys, "pid").select("kind", "pid", "truth", (x + noise * normal01("set-x", *ids)).alias("x0"), (y + noise * normal01("set-y", *ids)).alias("x1"), u01("set-ox", *ids).alias("ox"), u01("set-oy", *ids).alias("oy"))
    real = F.col("truth") > 0
    box = drawn.where(real).groupBy("kind").agg(F.min("x0").alias("lx"), F.max("x0").alias("hx"), F.min("x1").alias("ly"), F.max("x1").alias("hy"))
    out = drawn.join(F.broadcast(box), "kind")
    out = out.withColumn("x0", F.when(real, F.col("x0")).otherwise(F.col("lx") + F.col("ox") * (F.col("hx") - F.col("lx")))).withColumn("x1", F.when(real, F.col("x1")).otherwise(F.col("ly") + F.col("oy") * (F.col("hy") - F.col("ly"))))
    return out.select("kind", "pid", "x0", "x1", "truth").withColumn("x", F.array("x0", "x1"))


def sets_sql(outliers: float = 0.5, noise: float = 0.01) -> str:
    """The same sets as DuckDB common table expressions; the last is ``sets``."""
    rows = ", ".join(f"('{r[0]}', {i}, {r[1]}, {r[2]}, '{r[3]}', " + ", ".join(f"{v!r}::double" for v in r[4:]) + ")" for i, r in enumerate(STRUCTURES))
    ids = ("l_orderkey", "l_linenumber")
    t, normal = u01_sql("set-t", *ids), lambda p: normal01_sql(p, *ids)
    return f"""forms(kind, place, truth, n, form, a, b, c, e) as (values {rows}),
own as (select kind, place, truth, form, a, b, c, e, unnest(range(n)) as i from forms),
loose as (select kind, unnest(range(m)) as i from (select kind, round(sum(n) * {outliers} / (1 - {outliers}))::bigint as m from forms group by kind)),
slots as (select row_number() over (order by first_place, is_out, place, i) - 1 as pid, kind, truth, form, a, b, c, e from (
  select kind, place, 0 as is_out, i, truth, form, a, b, c, e from own union all select kind, 0, 1, i, 0, 'outlier', 0, 0, 0, 0 from loose) join (select kind, min(place) as first_place from forms group by kind) using (kind)),
keyed as (select *, row_number() over (order by l_orderkey, l_linenumber) - 1 as pid from (select l_orderkey, l_linenumber from lineitem order by l_orderkey, l_linenumber limit (select count(*) from slots))),
drawn as (select kind, pid, truth, case form when 'segment' then a + c * {t} when 'rim' then a + c * cos({2 * math.pi!r} * {t}) else a + {t} end + {noise} * {normal('set-x')} as x0,
  case form when 'segment' then b + e * {t} when 'rim' then b + c * sin({2 * math.pi!r} * {t}) else b + c * pow({t} - e, 2) end + {noise} * {normal('set-y')} as x1, {u01_sql('set-ox', *ids)} as ox, {u01_sql('set-oy', *ids)} as oy from slots join keyed using (pid)),
box as (select kind, min(x0) as lx, max(x0) as hx, min(x1) as ly, max(x1) as hy from drawn where truth > 0 group by kind),
sets as (select kind, pid, truth, case when truth > 0 then x0 else lx + ox * (hx - lx) end as x0, case when truth > 0 then x1 else ly + oy * (hy - ly) end as x1 from drawn join box using (kind))"""


def two_view_sets(spark: SparkSession, sf_dir: str, count: int = 19, structures: int = 2, per: int = 40, mismatches: float = 0.3, noise: float = 0.002) -> DataFrame:
    """Correspondences of ``count`` scenes of planes and as many of rigid motions: kind, pid, truth, x (x1, y1, x2, y2).

    The first view of a point, its depth and its mismatch are draws from the key of an ``orders`` row; a scene's maps are draws from its number.
    """
    import pandas as pd

    size = structures * per + round(structures * per * mismatches / (1 - mismatches))
    total = 2 * count * size
    keys = load(spark, sf_dir, "orders").select("o_orderkey").orderBy("o_orderkey").limit(total)
    have = keys.count()
    at = spark.range(total).select("id", F.pmod("id", F.lit(max(1, have))).alias("k"), F.floor(F.col("id") / size).cast("int").alias("scene"), F.pmod("id", F.lit(size)).cast("int").alias("i"))
    from pyspark.sql import Window

    numbered = keys.withColumn("k", (F.row_number().over(Window.orderBy("o_orderkey")) - 1).cast("long"))
    draws = F.array(*[u01(f"view{j}", "o_orderkey", "id") for j in range(6)])
    rows = at.join(F.broadcast(numbered), "k").select("id", "scene", "i", draws.alias("u"))

    def scene(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("i")
        no = int(pdf["scene"].iloc[0])
        rng = np.random.Generator(np.random.PCG64([77, no]))
        u = np.array(pdf["u"].tolist())
        truth = np.where(pdf["i"] < structures * per, pdf["i"] // per + 1, 0).astype("int32")
        x = np.zeros((len(pdf), 4))
        for j in range(1, structures + 1):
            own = truth == j
            if no < count:
                p = u[own, :2] * 0.5 + rng.random(2) * 0.5
                h = np.eye(3) + rng.normal(0, 0.25, (3, 3)) * np.array([[1, 1, 1], [1, 1, 1], [0.3, 0.3, 0]])
                q = np.column_stack([p, np.ones(len(p))]) @ h.T
                x[own] = np.hstack([p, q[:, :2] / q[:, 2:]])
            else:
                p = u[own, :3] * 2 - 1 + [*rng.uniform(-0.5, 0.5, 2), 5]
                w = rng.normal(0, 0.3, 3)
                k, angle, c = np.array([[0, -w[2], w[1]], [w[2], 0, -w[0]], [-w[1], w[0], 0]]), np.linalg.norm(w), p.mean(axis=0)
                q = (p - c) @ (np.eye(3) + math.sin(angle) / angle * k + (1 - math.cos(angle)) / angle**2 * k @ k).T + c + rng.normal(0, 0.4, 3)
                x[own] = np.hstack([p[:, :2] / p[:, 2:], q[:, :2] / q[:, 2:]])
        real = truth > 0
        x[real] += rng.normal(0, noise, (real.sum(), 4))
        lo, hi = x[real].min(axis=0), x[real].max(axis=0)
        x[~real] = lo + u[~real, 2:6] * (hi - lo)
        kind = f"planes{no + 1:02d}" if no < count else f"motions{no - count + 1:02d}"
        return pd.DataFrame({"kind": kind, "pid": pdf["id"], "truth": truth, "x": list(x)})

    return rows.groupBy("scene").applyInPandas(scene, "kind string, pid long, truth int, x array<double>")


def trajectory_sets(spark: SparkSession, sf_dir: str, motions: int = 3, per: int = 60, noise: float = 0.01, outliers: float = 0.2) -> DataFrame:
    """``embeddings`` as bases of affine subspaces, the last motion with two directions only, and other vectors as outliers: kind, pid, truth, x."""
    import pandas as pd

    total = motions * per
    need = 4 * motions + int(outliers * total)
    vectors = load(spark, sf_dir, "embeddings").orderBy("vec_id").limit(need).select("vec_id", F.transform("embedding", lambda v: v.cast("double")).alias("e"), F.lit("trajectories").alias("kind"))  # fixed number of rows

    def make(pdf: pd.DataFrame) -> pd.DataFrame:
        v = np.array(pdf.sort_values("vec_id")["e"].tolist())
        x, truth = trajectories(v, motions, per, noise, outliers)
        return pd.DataFrame({"kind": "trajectories", "pid": np.arange(len(x)), "truth": truth.astype("int32"), "x": list(x)})

    return vectors.groupBy("kind").applyInPandas(make, "kind string, pid long, truth int, x array<double>")


def two_views(kind: str = "planes", seed: int = 1, structures: int = 2, per: int = 60, mismatches: float = 0.3, noise: float = 0.002) -> tuple[np.ndarray, np.ndarray]:
    """Planted correspondences (x1, y1, x2, y2): by homographies (``planes``) or rigid motions seen by a camera (``motions``)."""
    rng = np.random.Generator(np.random.PCG64([seed, len(kind)]))
    sets = []
    for _ in range(structures):
        if kind == "planes":
            p = rng.random((per, 2)) * 0.5 + rng.random(2) * 0.5
            h = np.eye(3) + rng.normal(0, 0.25, (3, 3)) * np.array([[1, 1, 1], [1, 1, 1], [0.3, 0.3, 0]])
            q = np.column_stack([p, np.ones(per)]) @ h.T
            sets.append(np.hstack([p, q[:, :2] / q[:, 2:]]))
        else:
            p = rng.uniform(-1, 1, (per, 3)) + [*rng.uniform(-0.5, 0.5, 2), 5]
            w = rng.normal(0, 0.3, 3)
            k = np.array([[0, -w[2], w[1]], [w[2], 0, -w[0]], [-w[1], w[0], 0]])
            angle = np.linalg.norm(w)
            r = np.eye(3) + math.sin(angle) / angle * k + (1 - math.cos(angle)) / angle**2 * k @ k
            c = p.mean(axis=0)
            q = (p - c) @ r.T + c + rng.normal(0, 0.4, 3)
            sets.append(np.hstack([p[:, :2] / p[:, 2:], q[:, :2] / q[:, 2:]]))
    x = np.vstack(sets) + rng.normal(0, noise, (structures * per, 4))
    truth = np.repeat(np.arange(1, structures + 1), per)
    n_out = round(len(x) * mismatches / (1 - mismatches))
    lo, hi = x.min(axis=0), x.max(axis=0)
    return np.vstack([x, rng.uniform(lo, hi, (n_out, 4))]), np.append(truth, np.zeros(n_out, int))


def trajectories(vectors: np.ndarray, motions: int = 3, per: int = 60, noise: float = 0.01, outliers: float = 0.2, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """Points in affine subspaces spanned by given vectors; the last motion is degenerate (two directions)."""
    rng = np.random.Generator(np.random.PCG64(seed))
    sets = []
    for j in range(motions):
        basis = vectors[4 * j : 4 * j + (2 if j == motions - 1 else 3)]
        sets.append(vectors[4 * j + 3] + rng.normal(size=(per, len(basis))) @ basis)
    x = np.vstack(sets)
    x = x + rng.normal(0, noise, x.shape)
    k = int(outliers * len(x))
    return np.vstack([x, vectors[-k:]]), np.append(np.repeat(np.arange(1, motions + 1), per), np.zeros(k, int))


def line_stream(spark: SparkSession, sf_dir: str, kind: str = "scattered", also: list[str] | None = None) -> DataFrame:
    """``lineitem`` in order as a labelled stream of four scaled features: scattered (1 %), rare (0.1 %) or clustered (10 %) anomalies; with other columns ``also``."""
    rate = {"scattered": 0.01, "rare": 0.001, "clustered": 0.1}[kind]
    ids = ["l_orderkey", "l_linenumber"]
    df = load(spark, sf_dir, "lineitem").select("l_shipdate", *ids, *(also or []), (F.col("l_quantity") / 50).alias("f0"), (F.col("l_extendedprice") / 100000).alias("f1"), (F.col("l_discount") * 10).alias("f2"), (F.col("l_tax") * 12.5).alias("f3"))
    hit = u01(f"anom-{kind}", *ids) < rate
    for j in range(4):
        c = F.col(f"f{j}")
        odd = F.lit(1.6) + 0.02 * normal01(f"ball{j}", *ids) if kind == "clustered" else c * urange(f"scale{j}", 1.5, 3.0, *ids)
        df = df.withColumn(f"f{j}", F.when(hit, odd).otherwise(c))
    return df.withColumn("is_anom", hit.cast("int")).withColumn("is_anom", F.coalesce("is_anom", F.lit(0)))


def event_stream(spark: SparkSession, sf_dir: str, drift: bool = False) -> DataFrame:
    """``events`` with features value, k, gap and hour; 1 % anomalies, or five abrupt changes and 5.5 % anomalies with ``drift``."""
    from pyspark.sql import Window

    e = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", F.get_json_object("props", "$.k").cast("double").alias("k"))
    before = F.lag("ts").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    gap = F.coalesce(F.unix_timestamp(F.col("ts").cast("timestamp")) - F.unix_timestamp(before.cast("timestamp")), F.lit(0)).cast("double")
    e = e.withColumn("gap", gap).withColumn("hour", F.hour("ts").cast("double"))
    hit = u01("event", "event_id") < (0.055 if drift else 0.01)
    if drift:
        n = e.agg((F.max("event_id") - F.min("event_id") + 1).alias("n"), F.min("event_id").alias("lo"))
        e = e.crossJoin(F.broadcast(n)).withColumn("phase", F.floor((F.col("event_id") - F.col("lo")) * 6 / F.col("n")))
        e = e.withColumn("value", F.col("value") * (1 + F.col("phase")) + 100 * (F.col("phase") % 2)).withColumn("k", F.pmod(F.col("k") + 17 * F.col("phase"), F.lit(100.0)))
        e = e.withColumn("value", F.when(hit, 900 + 5 * normal01("dv", "event_id")).otherwise(F.col("value"))).withColumn("k", F.when(hit, F.lit(150.0)).otherwise(F.col("k")))
    else:
        e = e.withColumn("value", F.when(hit, F.col("value") + 400).otherwise(F.col("value")))
    return e.withColumn("is_anom", hit.cast("int"))


def lattice(spark: SparkSession, sf_dir: str, side: int = 40, hole: float = 1 / 10) -> DataFrame:
    """A smooth surface over a grid ``side`` cells wide, one cell a ``part`` row, with a jagged hole in each square of it: pid, gx, gy, x, is_anom."""
    g = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("pid"))
    gx, gy = F.pmod("pid", F.lit(side)), F.floor(F.col("pid") / side)
    u, v = gx / side, gy / side
    inside = (F.pow(u - 0.5, 2) + F.pow(v - F.floor(v) - 0.5, 2)) < hole**2
    z = 0.3 * F.sin(3 * u) + 0.2 * F.cos(2 * v) + 0.002 * normal01("surface", "pid")
    z = F.when(inside, z - 0.15 - 0.1 * u01("hole", "pid")).otherwise(z)
    return g.select("pid", gx.cast("int").alias("gx"), gy.cast("int").alias("gy"), F.array(u, v, z).alias("x"), inside.cast("int").alias("is_anom"))
