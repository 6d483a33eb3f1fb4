"""Every query with SQL equals DuckDB at the smallest scale; entry and the stream twin work."""

import os

import duckdb
import pytest

from outlyer import catalog

D = "/root/testdata/sf0.001"


def _norm(v):
    if isinstance(v, float):
        return round(v, 5) + 0.0
    if isinstance(v, (list, tuple)):
        return tuple(map(_norm, v))
    return v.isoformat() if hasattr(v, "isoformat") else v


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for f in os.listdir(D):
        c.sql(f"create view {f[:-8]} as select * from '{D}/{f}'")
    return c


@pytest.mark.parametrize("name", sorted(catalog.oracle_sql()))
def test_equals_sql(spark, duck, name):
    df = catalog.queries()[name](spark, D)
    r = duck.sql(catalog.oracle_sql()[name])
    cols = sorted(df.columns)
    assert cols == sorted(r.columns)
    mine = sorted((tuple(_norm(x[c]) for c in cols) for x in df.collect()), key=repr)
    theirs = sorted((tuple(_norm(dict(zip(r.columns, x))[c]) for c in cols) for x in r.fetchall()), key=repr)
    assert mine == theirs


def test_entry(spark):
    assert catalog.entry(spark, D).count() == 20


def test_stream_equals_batch(spark, tmp_path):
    from outlyer.sources.planted import event_stream
    from outlyer.streaming.online import replay, score_stream

    e = event_stream(spark, D).select("event_id", "event_type", "value", "k")
    e.coalesce(1).write.parquet(str(tmp_path / "in"))
    how = {"trees": 2, "omega": 64, "eta": 8}
    stream = score_stream(spark.readStream.schema(e.schema).parquet(str(tmp_path / "in")), ["value", "k"], "event_id", "event_type", **how)
    stream.writeStream.format("memory").queryName("scored").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
    got = {r["event_id"]: r["score"] for r in spark.table("scored").collect()}
    want = {r["event_id"]: r["score"] for r in replay(e, ["value", "k"], ["event_id"], key="event_type", **how).collect()}
    assert got == pytest.approx(want)
