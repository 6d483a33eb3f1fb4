"""Tables and streams that are written on the way, in the folder that the driver and all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch(spark: SparkSession, name: str) -> str:
    """A new path under ``spark.checkpoint.dir``; a temporary folder only where that is unset and everything is one process."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = getattr(scratch, "_own", None) or "file://" + tempfile.mkdtemp(prefix="outlyer-")
        scratch._own = root
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def drained(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a streaming plan over what its source holds now and returns the rows it wrote.

    ``append`` goes through the exactly-once file sink. ``update`` and ``complete`` write each micro-batch to a folder of
    its number, which a repeated batch overwrites; the last batch (complete) or all (update) are read back.
    """
    spark, out = stream.sparkSession, scratch(stream.sparkSession, name)
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{out}-checkpoint")
    if mode == "append":
        writer.format("parquet").option("path", out).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    seen: list[int] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")
        seen.append(number)

    writer.foreachBatch(keep).start().awaitTermination()
    if not seen:
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(f"{out}/batch={max(seen)}")
    return spark.read.parquet(out)
