"""Shared plumbing of the training-data operators: reads, lineage cuts, safe column handling."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_written: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``; a temporary one only where that is unset and driver and executors are one process."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    mine = getattr(shared_dir, "_own", None)
    if mine is None:
        mine = shared_dir._own = "file://" + tempfile.mkdtemp(prefix="outlyer-")
    return mine


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Write ``df`` as a table in the shared folder and read it again: later reads never depend on a lost executor."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/outlyer/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def _delete(owner: SparkSession, path: str) -> None:
    try:
        jvm = owner.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(owner.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session may be gone at exit
        pass


def written() -> int:
    """How many tables :func:`cut` has written and not deleted yet."""
    return len(_written)


def release(spark: SparkSession | None = None, since: int = 0, keep: int = 0) -> None:
    """Delete the tables that :func:`cut` wrote after the first ``since``, but for the last ``keep``; results that still read them become invalid."""
    for owner, path in _written[since : len(_written) - keep]:
        if spark is None or owner is spark:
            _delete(owner, path)
            _written.remove((owner, path))


atexit.register(release)


@contextmanager
def shuffles_freed(spark: SparkSession) -> Iterator[None]:
    """Inside, Spark deletes the shuffle files of a query as soon as it has ended; fit for steps that are written by :func:`cut`."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_of(col: str = "text") -> Column:
    """Null texts count as empty."""
    return F.coalesce(F.col(col), F.lit(""))


def guarded(docs: DataFrame, *needed: str) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """``docs`` with all columns but ``needed`` under names that nothing else uses, and the way back to its columns."""
    other = {c: f"_input_{i}" for i, c in enumerate(docs.columns) if c not in needed}
    renamed = docs.select(*[F.col(f"`{c}`").alias(other.get(c, c)) for c in docs.columns])
    return renamed, lambda df: df.select(*[F.col(other.get(c, c)).alias(c) for c in docs.columns])


BROADCAST_IDS = 2_000_000


def bounded(ids: DataFrame) -> DataFrame:
    """A written table of ids, to be broadcast where it has at most BROADCAST_IDS rows (16 MB); beyond that a join shuffles both sides."""
    return F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids


def without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows whose doc_id is not among ``ids``; a null id stays."""
    return docs.join(bounded(cut(ids.select("doc_id").where("doc_id is not null").distinct(), "ids")), "doc_id", "left_anti")


def fold_of(col: str, folds: int) -> Column:
    """crc32 of the id's decimal text, modulo ``folds``."""
    return F.pmod(F.crc32(F.col(col).cast("string").cast("binary")), F.lit(folds))


def smallest_hashes(keyed: DataFrame, most: int | dict) -> DataFrame:
    """label, h: the smallest distinct hashes ``h`` of each label, at most ``most`` (a number, or one for each label).

    Copies count once in the share that bounds the window as in the window itself, and the share leaves room
    for 50 more than three times ``most``, so no label that has rows ends without a hash.
    """
    counts = {r["label"]: r["n"] for r in keyed.groupBy("label").agg(F.approx_count_distinct("h").alias("n")).collect()}
    cap = {x: most if isinstance(most, int) else most[x] for x in counts}
    of = lambda values, other: F.coalesce(F.create_map(*[F.lit(v) for kv in values.items() for v in kv])[F.col("label")], F.lit(other)) if values else F.lit(other)
    near = keyed.where((F.shiftrightunsigned("h", 11) / F.lit(float(2**53))) <= of({x: min(1.0, (3.0 * cap[x] + 50) / max(1, n)) for x, n in counts.items()}, 1.0))
    w = Window.partitionBy("label").orderBy("h")
    picked = near.select("label", "h").distinct().withColumn("k", F.row_number().over(w)).where(F.col("k") <= of(cap, 0)).select("label", "h")
    return keyed.sparkSession.createDataFrame([(r["label"], r["h"]) for r in picked.collect()], picked.schema)


def blocks_for(rows: int, per_block: int, least: int = 16, most: int = 65_536) -> int:
    """How many hash blocks hold about ``per_block`` rows each; bounded, so per-block summaries stay small."""
    return int(min(most, max(least, -(-rows // per_block))))
