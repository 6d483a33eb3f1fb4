"""Sources, sinks, streams and user functions around the methods: what goes in and out of a scorer."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..core.estimators import StructureScorer, assemble, one_hot, scale
from ..core.scratch import drained, scratch
from ..operators import isolation, measures
from ..sources import planted
from ..sources.planted import load as T
from ..streaming import online

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


# --- features ---------------------------------------------------------------------------------------------------------


@query("with a as (select min(l_quantity) as lq, max(l_quantity) - min(l_quantity) as wq, min(l_tax) as lt, max(l_tax) - min(l_tax) as wt from lineitem) select l_orderkey, l_linenumber, round((l_quantity - lq) / wq, 6) as q, round((l_tax - lt) / wt, 6) as t from lineitem, a")
def scale_minmax(s, d):
    out = scale(T(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_quantity", "l_tax"), ["l_quantity", "l_tax"])
    return assemble(out, ["l_quantity", "l_tax"]).select("l_orderkey", "l_linenumber", F.round(F.col("x")[0], 6).alias("q"), F.round(F.col("x")[1], 6).alias("t"))


@query("with a as (select avg(value) as m, stddev_pop(value) as w from events) select event_id, round(greatest(-3, least(3, (value - m) / w)), 6) as z from events, a")
def scale_standard(s, d):
    return scale(T(s, d, "events").select("event_id", "value"), ["value"], "standard", (-3.0, 3.0)).select("event_id", F.round("value", 6).alias("z"))


@query("select event_id, (event_type = 'view')::int as event_type_view, (event_type = 'purchase')::int as event_type_purchase from events")
def one_hot_types(s, d):
    return one_hot(T(s, d, "events").select("event_id", "event_type"), "event_type", ["view", "purchase"]).drop("event_type")


# --- files --------------------------------------------------------------------------------------------------------------


def _through(s, d, form: str, **how) -> DataFrame:
    part, path = T(s, d, "part").select("p_partkey", "p_name", "p_retailprice"), scratch(s, f"part-{form}")
    part.write.format(form).options(**how).save(path)
    return s.read.format(form).schema(part.schema).options(**how).load(path)


@query("select p_partkey, p_name, p_retailprice from part")
def file_csv(s, d):
    return _through(s, d, "csv", header="true")


@query("select p_partkey, p_name, p_retailprice from part")
def file_json(s, d):
    return _through(s, d, "json")


@query("select p_partkey, p_name, p_retailprice from part")
def file_orc(s, d):
    return _through(s, d, "orc")


@query("select event_id, event_type from events where event_type in ('purchase', 'view')")
def partitioned_sink(s, d):
    """Rows by type in folders of their own; the read names two types and opens only their folders."""
    path = scratch(s, "events-by-type")
    T(s, d, "events").select("event_id", "event_type").write.partitionBy("event_type").parquet(path)
    return s.read.parquet(path).where(F.col("event_type").isin("purchase", "view")).select("event_id", "event_type")


@query("select event_id, cast(json_extract(props, '$.k') as int) as k from events")
def fn_variant(s, d):
    return T(s, d, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@query()
def agg_sketches(s, d):
    """Distinct users by merged sketches of days, quantiles of values, and how often each type occurs, all mergeable."""
    day = T(s, d, "events").groupBy(F.to_date("ts").alias("day"), "event_type").agg(F.hll_sketch_agg("user_id").alias("h"), F.count(F.lit(1)).alias("n"))
    return day.groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_union_agg("h")).alias("users"), F.sum("n").alias("n"))


# --- streams ------------------------------------------------------------------------------------------------------------


def event_source(s, d) -> DataFrame:
    """``events`` as a stream of files, event time as a timestamp."""
    schema = T(s, d, "events").schema
    return s.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(d).withColumn("ts", F.col("ts").cast("timestamp"))


@query("select event_id, event_type, value from events")
def stream_scan(s, d):
    return drained(event_source(s, d).select("event_id", "event_type", "value"), "scan")


@query("select event_id, c_mktsegment from events join customer on user_id = c_custkey")
def stream_static_join(s, d):
    static = T(s, d, "customer").select("c_custkey", "c_mktsegment")
    return drained(event_source(s, d).join(static, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"), "static-join")


@query("select count(distinct event_id) as n, count(distinct event_id) as ids from events")
def stream_dedup(s, d):
    """Every event twice in the stream; duplicates within the watermark go."""
    twice = event_source(s, d).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    out = drained(twice.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "dedup")
    return out.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("event_id").alias("ids"))


@query("select a.event_id as click, b.event_id as purchase from (select * from events where event_type = 'click') a join (select * from events where event_type = 'purchase') b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour")
def stream_stream_join(s, d):
    """Each click with the purchases of its user in the next hour; state on either side is bounded by watermarks."""
    a = event_source(s, d).where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("ta")).withWatermark("ta", "2 hours")
    b = event_source(s, d).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("tb")).withWatermark("tb", "2 hours")
    joined = a.join(b, (F.col("u") == F.col("user_id")) & (F.col("tb") >= F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("interval 1 hour")))
    return drained(joined.select("click", "purchase"), "stream-join")


@query("select day, event_type, n from (select date_trunc('day', ts) as day, event_type, count(*) as n from events group by 1, 2) where day + interval 1 day <= (select max(ts) - interval 1 hour from events)")
def stream_windows(s, d):
    """Daily counts that a watermark of one hour has closed, each written once."""
    w = event_source(s, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return drained(w.select(F.col("w.start").cast("timestamp_ntz").alias("day"), "event_type", "n"), "windows")


@query("select event_type, count(*) as n from events group by 1")
def stream_complete(s, d):
    """Running counts in complete mode; each micro-batch overwrites the folder of its number."""
    return drained(event_source(s, d).groupBy("event_type").agg(F.count(F.lit(1)).alias("n")), "complete", "complete")


# --- user functions -----------------------------------------------------------------------------------------------------

_LEN = "with s as (select lang, length(text)::double as score, (quality = 0)::int as y from documents join labels using (doc_id) where text is not null and lang is not null), r as (select *, rank() over (partition by lang order by score) + (count(*) over (partition by lang, score) - 1) / 2 as mid from s)"


@query(f"{_LEN} select lang, round((sum(mid) filter (y = 1) - sum(y) * (sum(y) + 1) / 2) / (sum(y) * sum(1 - y)), 6) as auc from r group by 1 having sum(y) > 0 and sum(1 - y) > 0")
def udaf_auc(s, d):
    """AUC as a grouped aggregate of Arrow columns; for groups that fit a task, else :func:`measures.roc_auc`."""

    @F.pandas_udf("double")
    def area(score: pd.Series, label: pd.Series) -> float:
        return isolation.auc(score.to_numpy(), label.to_numpy())

    docs = T(s, d, "documents").where("text is not null and lang is not null").select("doc_id", "lang", F.length("text").cast("double").alias("score"))
    both = docs.join(T(s, d, "labels").select("doc_id", (F.col("quality") == 0).cast("int").alias("y")), "doc_id")
    return both.groupBy("lang").agg(F.round(area("score", "y"), 6).alias("auc")).where("auc is not null and not isnan(auc)")


@query("select coalesce(a.user_id, b.user_id) as user_id, coalesce(a.n, 0) as clicks, coalesce(b.n, 0) as purchases from (select user_id, count(*) as n from events where event_type = 'click' group by 1) a full join (select user_id, count(*) as n from events where event_type = 'purchase' group by 1) b using (user_id)")
def udf_cogroup(s, d):
    """Two tables by one key in one function."""
    e = T(s, d, "events").select("user_id", "event_type")

    def both(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"user_id": [key[0]], "clicks": [len(a)], "purchases": [len(b)]})

    a, b = e.where("event_type = 'click'"), e.where("event_type = 'purchase'")
    return a.groupBy("user_id").cogroup(b.groupBy("user_id")).applyInPandas(both, "user_id long, clicks long, purchases long")


@query("select event_type, count(*) as n, round(max(value) - min(value), 4) as spread from events group by 1")
def udf_grouped_map(s, d):
    def one(key, pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"event_type": [key[0]], "n": [len(pdf)], "spread": [round(float(pdf["value"].max() - pdf["value"].min()), 4)]})

    return T(s, d, "events").select("event_type", "value").groupBy("event_type").applyInPandas(one, "event_type string, n long, spread double")


@query("select event_id, round(value * 2 + 1, 6) as v from events")
def udf_map(s, d):
    def run(frames):
        for pdf in frames:
            yield pd.DataFrame({"event_id": pdf["event_id"], "v": (pdf["value"] * 2 + 1).round(6)})

    return T(s, d, "events").select("event_id", "value").mapInPandas(run, "event_id long, v double")


@query()
def estimator_scores(s, d):
    """The structure scorer as an object, saved, loaded again and applied."""
    points, path = planted.segments(s, d), scratch(s, "scorer")
    StructureScorer("line", 0.03, trees=30, m=100).fit(points).save(s, path)
    return StructureScorer.load(s, path).transform(points)


# --- stream scorers on more streams --------------------------------------------------------------------------------------

_SCORERS = {"adaptive": {"trees": 4}, "window_axis": {"trees": 4, "omega": 1024}, "periodic_axis": {"trees": 4, "omega": 1024}, "half_space": {"trees": 4}, "cut_forest": {"trees": 2, "psi": 128}, "projections": {}}


def suite(df: DataFrame, features: list[str], order: list[str], key: str | None, scorers: dict[str, dict] | None = None) -> DataFrame:
    """AUC of each scorer on one labelled stream; with ``key`` one independent scorer a key, in order, to the end."""
    out = None
    for method, how in (scorers or _SCORERS).items():
        scored = online.replay(df, features, order, method, key=key, keep=("is_anom",), **how).dropna(subset=order).select("score", "is_anom", F.lit(method).alias("method"))
        out = scored if out is None else out.unionByName(scored)
    return measures.roc_auc(out, by=["method"], digits=9)


@query()
def stream_suite(s, d):
    """AUC of six online scorers on the scattered and rare streams of ``lineitem``, one scorer a bucket of suppliers, four trees (two for cuts)."""
    out = None
    for kind in ("scattered", "rare"):
        df = planted.line_stream(s, d, kind, also=["l_suppkey"]).withColumn("t", F.datediff("l_shipdate", F.lit("1970-01-01").cast("date")).cast("long"))
        df = df.dropna(subset=["l_orderkey", "l_linenumber"]).withColumn("bucket", F.pmod("l_suppkey", F.lit(32)))
        part = suite(df, ["f0", "f1", "f2", "f3"], ["t", "l_orderkey", "l_linenumber"], "bucket").withColumn("stream", F.lit(kind))
        out = part if out is None else out.unionByName(part)
    return out


@query()
def shingle_suite(s, d):
    """AUC of the scorers on the hourly series as vectors of 48 hours, two planted days with doubled counts; 32 trees and small windows."""
    h = T(s, d, "events").groupBy(F.date_trunc("hour", "ts").alias("hr")).agg(F.count(F.lit(1)).alias("n"))
    h = h.withColumn("no", F.row_number().over(Window.orderBy("hr")).cast("long"))  # one row an hour
    odd = F.floor(F.col("no") / 24).isin(12, 21)
    h = h.withColumn("n", F.when(odd, F.col("n") * 2).otherwise(F.col("n")).cast("double")).withColumn("odd", odd.cast("int"))
    w = Window.orderBy("no").rowsBetween(-47, 0)
    v = h.select("no", F.collect_list("n").over(w).alias("v"), F.max("odd").over(w).alias("is_anom")).where(F.size("v") == 48)
    cols = [f"l{i}" for i in range(48)]
    v = v.select("no", "is_anom", *[(F.col("v")[i] / 40).alias(c) for i, c in enumerate(cols)])
    return suite(v, cols, ["no"], None, {"adaptive": {"trees": 32, "omega": 256, "eta": 8}, "window_axis": {"trees": 32, "omega": 128, "psi": 64}, "half_space": {"trees": 32, "window": 100}, "cut_forest": {"trees": 8, "psi": 64}, "projections": {"warm": 64, "bins": 20}})


@query()
def omega_sweep(s, d):
    """Adaptive histograms on the drifting event stream by window size: AUC, and the same without a buffer."""
    features, path, out = ["value", "k", "gap", "hour"], scratch(s, "drifting-events"), None
    df = planted.event_stream(s, d, drift=True).select("event_id", *features, "is_anom")
    df.write.parquet(path)  # six replays and their labels read it
    df = s.read.schema(df.schema).parquet(path)
    for omega in (128, 512, 2048):
        for forget in ("buffer", "sampled"):
            part = suite(df, features, ["event_id"], None, {"adaptive": {"trees": 4, "omega": omega, "eta": 16, "forget": forget}}).withColumn("omega", F.lit(omega)).withColumn("forget", F.lit(forget))
            out = part if out is None else out.unionByName(part)
    return out


@query()
def state_sizes(s, d):
    """Nodes and buffered points of the adaptive scorer after a share of the event stream: bounded by the window, not by the stream."""
    df = planted.event_stream(s, d).select("event_id", "value", "k")

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        rows = pdf.sort_values("event_id")[["value", "k"]].fillna(0).to_numpy(float)
        kernel, out = online.AdaptiveHistogramForest(omega=int(key[0]), eta=16, trees=4), []
        ends = {len(rows) * q // 4: q for q in (1, 2, 3, 4)}
        for i, row in enumerate(rows, 1):
            kernel.step(row)
            if i in ends:
                out.append((int(key[0]), ends[i], kernel.size()))
        return pd.DataFrame(out, columns=["omega", "quarter", "size"])

    each = df.withColumn("omega", F.explode(F.array(F.lit(128), F.lit(512)))).groupBy("omega")
    return each.applyInPandas(run, "omega int, quarter int, size int")

