"""Benchmark decontamination by pigeonhole edit matching.

A test item with error budget k is split into k + 1 pieces: any text within k edits holds at least one piece
exactly. One automaton finds all piece hits of all items; hits of an item on nearby diagonals are verified
together by Myers' bit-parallel distance over the window they allow.

Texts are compared lower-cased with white space collapsed. Items are read in blocks of a proven byte bound
(``block_bytes``) and each block passes over all documents, so what is broadcast never grows.

Edge cases: null or empty texts and items match nothing; an item shorter than ``shortest`` characters must
occur unchanged; repeated ids give one row per row; an empty table on either side gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_of, without


def normalise(text: str | None) -> str:
    return " ".join((text or "").lower().split())


def budget(length: int, rate: float, shortest: int) -> int:
    return 0 if length < shortest else max(1, int(rate * length))


def pieces(item: str, k: int) -> list[tuple[int, str]]:
    """k + 1 consecutive pieces of near equal length, with their places."""
    ends = [len(item) * i // (k + 1) for i in range(k + 2)]
    return [(a, item[a:b]) for a, b in zip(ends, ends[1:], strict=False) if b > a]


def best_match(pattern: str, window: str, most: int) -> tuple[int, int] | None:
    """Smallest edit distance of the pattern to any part of the window and where that part ends; None above ``most``.

    One integer holds a column of vertical differences, so each window character costs a few machine-word
    operations for every 30 pattern characters.
    """
    m = len(pattern)
    masks: dict[str, int] = {}
    for i, c in enumerate(pattern):
        masks[c] = masks.get(c, 0) | 1 << i
    full, top = (1 << m) - 1, 1 << (m - 1)
    up, down, score = full, 0, m
    best = None
    for at, c in enumerate(window):
        eq = masks.get(c, 0)
        diagonal = (((eq & up) + up) ^ up) | eq | down
        plus, minus = down | ~(diagonal | up) & full, up & diagonal
        if plus & top:
            score += 1
        elif minus & top:
            score -= 1
        plus, minus = plus << 1 & full, minus << 1 & full
        up, down = minus | ~(diagonal | plus) & full, plus & diagonal
        if score <= most and (best is None or score < best[0]):
            best = (score, at + 1)
    return best


class Matcher:
    def __init__(self, items: list[tuple[int, str]], rate: float, shortest: int):
        self.items = []
        where: dict[str, list[tuple[int, int]]] = {}
        for item_id, text in items:
            text = normalise(text)
            if text:
                k = budget(len(text), rate, shortest)
                for place, piece in pieces(text, k):
                    where.setdefault(piece, []).append((len(self.items), place))
                self.items.append((item_id, text, k))
        self.where, self.automaton = where, None

    def find(self, text: str) -> list[tuple[int, int, int]]:
        """(item id, distance, end) of the best match of each item in a normalised text."""
        if self.automaton is None:
            import ahocorasick

            self.automaton = ahocorasick.Automaton()
            for piece, places in self.where.items():
                self.automaton.add_word(piece, (len(piece), places))
            if self.where:
                self.automaton.make_automaton()
        if not self.where or not text:
            return []
        diagonals: dict[int, set[int]] = {}
        for end, (length, places) in self.automaton.iter(text):
            for item, place in places:
                diagonals.setdefault(item, set()).add(end + 1 - length - place)
        found = []
        for item, starts in diagonals.items():
            item_id, pattern, k = self.items[item]
            best, done = None, -(10**9)
            for start in sorted(starts):
                if start <= done:
                    continue
                done = start + k  # one window serves all diagonals up to here
                lo, hi = max(0, start - k), start + 2 * k + len(pattern) + 1
                hit = best_match(pattern, text[lo:hi], k)
                if hit and (best is None or hit[0] < best[0]):
                    best = (hit[0], lo + hit[1])
            if best:
                found.append((item_id, *best))
        return found


def matches(docs: DataFrame, items: DataFrame, rate: float = 0.08, shortest: int = 24, block_bytes: int = 4_000_000) -> DataFrame:
    """doc_id, item_id, distance, match_end: the best match of each item in each whole document, within the item's budget."""
    import pyarrow as pa

    spark = docs.sparkSession
    schema = "doc_id long, item_id long, distance int, match_end long"
    size = items.agg(F.coalesce(F.sum(F.octet_length(text_of())), F.lit(0)).alias("b")).first()["b"]
    blocks = max(1, -(-size // block_bytes))
    out = None
    for block in range(blocks):
        part = items.where(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == block).select("item_id", "text").collect()  # about block_bytes
        shared = spark.sparkContext.broadcast(Matcher([(r["item_id"], r["text"]) for r in part], rate, shortest))

        def scan(batches, shared=shared):
            matcher = shared.value
            for batch in batches:
                rows = [(d, *hit) for d, t in zip(batch.column(0).to_pylist(), batch.column(1), strict=True) for hit in matcher.find(normalise(t.as_py()))]
                columns = list(zip(*rows, strict=True)) or [[], [], [], []]
                yield pa.record_batch([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int64(), pa.int32(), pa.int64()), strict=True)], ["doc_id", "item_id", "distance", "match_end"])

        found = docs.select("doc_id", "text").mapInArrow(scan, schema)
        out = found if out is None else out.unionByName(found)
    return out


def decontaminate(docs: DataFrame, items: DataFrame, **how) -> DataFrame:
    """Documents in which no item occurs within its budget; a row without id stays."""
    return without(docs, matches(docs, items, **how))
