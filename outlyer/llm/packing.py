"""Best-fit packing of token sequences: local best fit, then tree merges of underfull bins.

Round 0 deals pieces into hash blocks and packs each block by best-fit-decreasing. A bin at least
``full`` of the limit is final. The emptiest ``carry`` bins of a block go on as items of the next round,
where ``fan`` blocks meet; what is not carried is final as it stands, so the root sees at most
``fan * carry`` bins, about one block, whatever the input's size. No row is dropped.

Edge cases: null text is an empty document (its only id is the end id 0); an empty table gives no rows;
repeated doc ids are packed as separate rows, each with its own pieces; other columns are ignored.
"""

from __future__ import annotations

import zlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks_for, cut
from .tokens import default_vocabulary, encoded_batches

END = b"\x00\x00\x00\x00"
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def token_pieces(docs: DataFrame, limit: int = 2048, vocabulary: str | None = None) -> DataFrame:
    """One row per piece of at most ``limit`` ids: doc_id, piece, start, length, ids_crc32."""
    import pyarrow as pa

    path = vocabulary or default_vocabulary()
    schema = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())])

    def cut_up(batches):
        for ids, coded in encoded_batches(batches, path, "doc_id", "text"):
            out: list[list] = [[], [], [], [], []]
            for doc, data in zip(ids, coded, strict=True):
                data += END
                for k, at in enumerate(range(0, len(data), 4 * limit)):
                    part = data[at : at + 4 * limit]
                    for column, value in zip(out, (doc, k, at // 4, len(part) // 4, zlib.crc32(part)), strict=True):
                        column.append(value)
            yield pa.record_batch([pa.array(c, f.type) for c, f in zip(out, schema, strict=True)], schema=schema)

    return docs.select("doc_id", "text").mapInArrow(cut_up, PIECES)


def best_fit(sizes: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """Best-fit-decreasing: the bin and the offset of each item. Residuals are indexed by value, the fullest bin that still fits wins."""
    order = np.argsort(-sizes, kind="stable")
    bins, offsets = np.empty(len(sizes), np.int64), np.empty(len(sizes), np.int64)
    open_at: list[list[int]] = [[] for _ in range(limit + 1)]
    mask, used = 0, 0
    for i in order.tolist():
        need = int(sizes[i])
        fits = mask >> need
        if fits:
            room = need + (fits & -fits).bit_length() - 1
            b = open_at[room].pop()
            if not open_at[room]:
                mask &= ~(1 << room)
        else:
            room, b = limit, used
            used += 1
        bins[i], offsets[i] = b, limit - room
        left = room - need
        if left:
            if not open_at[left]:
                mask |= 1 << left
            open_at[left].append(b)
    return bins, offsets


def _merge(limit: int, full: float, carry: int, round_no: int, last: bool):
    """Packs the groups of rows that share ``bin``; returns the rows with their new bin and offset, and whether it is final."""

    def pack(pdf: pd.DataFrame) -> pd.DataFrame:
        block = int(pdf["block"].iloc[0])
        pdf = pdf.sort_values(["bin", "doc_id", "piece", "start"], kind="stable", ignore_index=True)
        keys, item = np.unique(pdf["bin"].to_numpy(), return_inverse=True)
        fill = np.bincount(item, weights=pdf["length"].to_numpy(), minlength=len(keys)).astype(np.int64)
        bins, offsets = best_fit(fill, limit)
        new = bins[item]
        fills = np.bincount(bins, weights=fill).astype(np.int64)
        done = fills >= full * limit
        if last:
            done[:] = True
        else:
            underfull = np.flatnonzero(~done)
            if len(underfull) > carry:
                done[underfull[np.argsort(fills[underfull], kind="stable")[carry:]]] = True
        return pdf.assign(offset=pdf["offset"].to_numpy() + offsets[item], bin=(np.int64(round_no) << 56) + (np.int64(block) << 32) + new, done=done[new])

    return pack


def pack(pieces: DataFrame, limit: int = 2048, full: float = 0.998, carry: int = 3750, fan: int = 16, per_block: int = 60_000) -> DataFrame:
    """Assigns sequence_id and offset to each piece (columns of :func:`token_pieces`). ``pieces`` is a written table: rows are numbered as they are read."""
    blocks = blocks_for(pieces.count(), per_block, least=4)
    rows = pieces.withColumn("bin", F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long"))
    rows = rows.withColumn("block", F.pmod(F.xxhash64("bin"), F.lit(blocks)).cast("long"))
    schema = PIECES + ", bin long, offset long, block long, done boolean"
    final, n = None, 0
    while True:
        last = blocks == 1
        packed = cut(rows.groupBy("block").applyInPandas(_merge(limit, full, carry, n, last), schema), f"pack{n}")
        done = packed.where("done")
        final = done if final is None else final.unionByName(done)
        if last:
            return final.select("doc_id", "piece", "start", "length", "ids_crc32", F.col("bin").alias("sequence_id"), "offset")
        rows = packed.where(~F.col("done")).drop("done").withColumn("block", F.floor(F.col("block") / fan).cast("long"))
        blocks, n = -(-blocks // fan), n + 1


def pack_documents(docs: DataFrame, limit: int = 2048, vocabulary: str | None = None) -> DataFrame:
    return pack(cut(token_pieces(docs, limit, vocabulary), "pieces"), limit)
