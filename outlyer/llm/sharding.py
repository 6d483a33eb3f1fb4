"""Byte-balanced sharding by Karmarkar-Karp differencing, in two levels.

Documents with equal text form a group that goes to one shard whole, whatever its size. Small groups fall into hash
blocks; each block differences its own groups into a partial partition: partial partitions with the largest spread
are combined first, oppositely ordered. The blocks' partial partitions, and the large groups as partitions of one
part, are then combined in the same way, so parts of a block go to the shards that need them. A group is large from a
64th of a shard's fair share or a quarter of a block's rows on, so there are few and no block holds a hot group.

A group larger than the fair share makes its shard larger than the others, which stay even among themselves.

Edge cases: a null text has size 1 and the checksum of an empty text, and forms one group with empty texts;
an empty table gives no rows; repeated doc ids stay separate rows; equal sizes are ordered by group digest, so
ties do not depend on the order of rows; other columns are ignored.
"""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import blocks_for, cut, text_of


def combine(partials: list[tuple[np.ndarray, list]]) -> tuple[np.ndarray, np.ndarray]:
    """Karmarkar-Karp over partial partitions.

    Each partial is (sums by label, whatever). Returns the final sums by shard and, per partial, the
    shard of each of its labels. The heap is ordered by spread; two partials are joined smallest-with-largest.
    The joins form a tree, which is walked down once at the end.
    """
    k = len(partials[0][0])
    heap, nodes = [], []
    for i, (sums, _) in enumerate(partials):
        order = np.argsort(sums, kind="stable")[::-1]
        ordered = sums[order]
        nodes.append((i, order))
        heap.append((int(ordered[-1] - ordered[0]), i, ordered))
    heapq.heapify(heap)
    while len(heap) > 1:
        _, a, x = heapq.heappop(heap)
        _, b, y = heapq.heappop(heap)
        joined = x + y[::-1]
        order = np.argsort(joined, kind="stable")[::-1]
        nodes.append((a, b, order))
        ordered = joined[order]
        heapq.heappush(heap, (int(ordered[-1] - ordered[0]), len(nodes) - 1, ordered))
    _, root, sums = heap[0]
    out = np.empty((len(partials), k), np.int64)
    stack = [(root, np.arange(k))]
    while stack:
        at, shard_of = stack.pop()  # shard_of[rank] = shard of the part with that rank
        if len(nodes[at]) == 2:
            i, order = nodes[at]
            out[i, order] = shard_of
        else:
            a, b, order = nodes[at]
            parts = np.empty(k, np.int64)
            parts[order] = shard_of
            stack += [(a, parts), (b, parts[::-1])]
    return sums, out


def differencing(sizes: np.ndarray, k: int) -> np.ndarray:
    """Part of each item by Karmarkar-Karp from single items."""
    if not len(sizes):
        return np.empty(0, np.int64)
    first = np.zeros((len(sizes), k), np.int64)
    first[:, 0] = sizes
    return combine([(row, None) for row in first])[1][:, 0]


def shard_by_bytes(docs: DataFrame, shards: int = 16, per_block: int = 20_000) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard (null under this law)."""
    spark, text = docs.sparkSession, text_of()
    raw = text.cast("binary")
    rows = cut(
        docs.select("doc_id", (F.octet_length(text) + F.lit(1)).cast("long").alias("size"), F.crc32(raw).alias("text_crc32"), F.unhex(F.md5(raw)).alias("g"), F.monotonically_increasing_id().alias("row")),
        "sizes",
    )
    head = rows.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("size"), F.lit(0)).alias("b")).first()
    blocks = blocks_for(head["n"], per_block, least=4)
    of = rows.groupBy("g").agg(F.sum("size").alias("b"), F.count(F.lit(1)).alias("n"))
    large = cut(of.where((F.col("b") > max(1, head["b"] // shards // 64)) | (F.col("n") > max(1, per_block // 4))).select("g", "b"), "large")
    # at most 64 * shards groups by bytes and 4 * blocks groups by rows
    marked = rows.join(F.broadcast(large.select("g", F.lit(True).alias("big"))), "g", "left")
    marked = cut(marked.withColumn("block", F.pmod(F.when(F.col("big"), F.xxhash64("row")).otherwise(F.xxhash64("g")), F.lit(blocks)).cast("int")).withColumn("big", F.coalesce("big", F.lit(False))), "marked")

    def local(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["doc_id", "row"], kind="stable", ignore_index=True)
        names, group = np.unique(np.array([bytes(g) for g in pdf["g"]], dtype=object), return_inverse=True)
        part = differencing(np.bincount(group, weights=pdf["size"].to_numpy(), minlength=len(names)).astype(np.int64), shards)[group]
        return pdf.assign(part=part.astype("int32"), nth=pd.Series(part).groupby(part).cumcount().to_numpy())[["doc_id", "size", "text_crc32", "block", "part", "nth"]]

    own = cut(marked.where("not big").drop("big").groupBy("block").applyInPandas(local, "doc_id long, size long, text_crc32 long, block int, part int, nth long"), "parted")
    sums: dict[int, np.ndarray] = {}
    for r in own.groupBy("block", "part").agg(F.sum("size").alias("b")).collect():  # at most blocks * shards rows
        sums.setdefault(r["block"], np.zeros(shards, np.int64))[r["part"]] = r["b"]
    whole = sorted(((r["b"], bytes(r["g"])) for r in large.collect()), key=lambda x: (-x[0], x[1]))
    partials = [(np.append(b, np.zeros(shards - 1, np.int64)), None) for b, _ in whole] + [(sums[k], None) for k in sorted(sums)]
    to = combine(partials)[1] if partials else np.empty((0, shards), np.int64)
    shard_of = spark.createDataFrame([(bytearray(g), int(to[i, 0])) for i, (_, g) in enumerate(whole)], "g binary, shard int")
    moved = spark.createDataFrame([(k, j, int(to[len(whole) + i, j])) for i, k in enumerate(sorted(sums)) for j in range(shards)], "block int, part int, shard int")

    kept = ["doc_id", "size", "text_crc32", "shard", "block", "kind", "nth"]
    small = own.join(F.broadcast(moved), ["block", "part"]).withColumn("kind", F.lit(0)).select(*kept)
    beside = Window.partitionBy("block", "shard").orderBy("doc_id", "row")
    big = marked.where("big").join(F.broadcast(shard_of), "g").withColumn("kind", F.lit(1)).withColumn("nth", (F.row_number().over(beside) - 1).cast("long")).select(*kept)
    placed = cut(small.unionByName(big), "placed")
    counts = placed.groupBy("block", "kind", "shard").agg(F.count(F.lit(1)).alias("n"))  # at most 2 * blocks * shards rows
    base = counts.select("block", "kind", "shard", F.coalesce(F.sum("n").over(Window.partitionBy("shard").orderBy("block", "kind").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    return placed.join(F.broadcast(base), ["block", "kind", "shard"]).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("base") + F.col("nth")).alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )
