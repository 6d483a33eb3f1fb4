"""MinHash near-duplicates with sequential Bayesian verification.

Equal shingle sets collapse to their smallest id first. Signatures are cut into bands; the number of bands
follows from the chosen miss probability at the threshold. Candidates are compared one signature batch at a
time: with a uniform prior, ``m`` agreements of ``n`` give a Beta posterior, and a pair is pruned once the
posterior chance of reaching the threshold is under ``prune``. Survivors are confirmed on full sets.

No bucket is expanded into all its pairs. First every member meets its bucket's smallest id; components of
those links follow; then only members of *different* components of a bucket are compared: by a join in
buckets of at most ``small`` members, and otherwise inside tasks over blocks of ``BLOCK`` members, which read
full sets and emit links only. Every cross-component pair of every bucket is looked at, so components are complete.

Edge cases: null or wordless text has no shingles, links with nothing and is kept; fewer words than a shingle
form one shingle; rows that share an id are one document; a null id gets a null component and is kept; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded, cut

ROWS, BATCH, BLOCK, BLOCK_BYTES = 5, 20, 1024, 16_000_000


def bands_for(threshold: float, miss: float, rows: int = ROWS) -> int:
    """Bands so that a pair at the threshold shares none with probability at most ``miss``."""
    return math.ceil(math.log(miss) / math.log1p(-(threshold**rows)))


def least_matches(n: int, threshold: float, prune: float) -> int:
    """Fewest agreements of ``n`` at which the posterior chance of similarity >= threshold is at least ``prune``.

    With a uniform prior that chance is P(Binomial(n + 1, threshold) <= m).
    """
    total = 0.0
    for m in range(n + 1):
        total += math.comb(n + 1, m) * threshold**m * (1 - threshold) ** (n + 1 - m)
        if total >= prune:
            return m
    return n


class WordHash(dict):
    """word -> 64-bit hash, computed once."""

    def __missing__(self, word: bytes) -> int:
        import xxhash

        value = self[word] = xxhash.xxh64_intdigest(word)
        return value


def shingle_set(text: str | None, width: int, known: WordHash) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles of ``width`` words, ASCII lower-cased, split at ASCII white space."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
    width_here = min(width, len(words))
    n = len(h) - width_here + 1
    out = np.full(n, width_here, np.uint64)
    for i in range(width_here):
        out = (out ^ h[i : i + n]) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
    out *= np.uint64(0xBF58476D1CE4E5B9)
    out ^= out >> np.uint64(32)
    return np.unique(out)


def multipliers(n: int, seed: int = 7) -> np.ndarray:
    return np.random.Generator(np.random.PCG64(seed)).integers(1, 2**63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def signature(shingles: np.ndarray, a: np.ndarray) -> np.ndarray:
    best = np.full(len(a), np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 512):
        np.minimum(best, (shingles[at : at + 512, None] * a).min(axis=0), out=best)
    return (best >> np.uint64(32)).astype(np.uint32)


def signatures(docs: DataFrame, width: int, bands: int) -> DataFrame:
    """doc_id, n_shingles, set_id (128-bit digest of the set), sig, keys (one per band)."""
    import pyarrow as pa

    schema = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("set_id", pa.binary()), ("sig", pa.binary()), ("keys", pa.list_(pa.int64()))])

    def make(batches):
        import xxhash

        known, a = WordHash(), multipliers(bands * ROWS)
        band_no = np.arange(bands, dtype=np.uint64)
        for batch in batches:
            out: list[list] = [[], [], [], [], []]
            for doc, text in zip(batch.column(0), batch.column(1), strict=True):
                s = shingle_set(text.as_py(), width, known)
                if len(known) > 800_000:
                    known.clear()
                row = (doc.as_py(), len(s), None, None, None)
                if len(s):
                    sig = signature(s, a)
                    k = band_no.copy()
                    for column in sig.reshape(bands, ROWS).T:
                        k = (k ^ column) * np.uint64(0x9E3779B97F4A7C15)
                        k ^= k >> np.uint64(31)
                    row = (doc.as_py(), len(s), xxhash.xxh128_digest(s.tobytes()), sig.tobytes(), k.view(np.int64))
                for column, value in zip(out, row, strict=True):
                    column.append(value)
            yield pa.record_batch([pa.array(c, f.type) for c, f in zip(out, schema, strict=True)], schema=schema)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(make, "doc_id long, n_shingles long, set_id binary, sig binary, keys array<long>")


def full_sets(docs: DataFrame, ids: DataFrame, width: int) -> DataFrame:
    """doc_id and its whole set as bytes, for the ids given only."""
    import pyarrow as pa

    def make(batches):
        known = WordHash()
        for batch in batches:
            sets = [shingle_set(t.as_py(), width, known).tobytes() for t in batch.column(1)]
            if len(known) > 800_000:
                known.clear()
            yield pa.record_batch([batch.column(0), pa.array(sets, pa.binary())], ["doc_id", "shingles"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(bounded(ids), "doc_id", "left_semi").mapInArrow(make, "doc_id long, shingles binary")


def surviving(a: np.ndarray, b: np.ndarray, checks: list[tuple[int, int]]) -> np.ndarray:
    """Which rows of two signature matrices survive the sequential test."""
    alive, matches, done = np.arange(len(a)), np.zeros(len(a), np.int64), 0
    for n, least in checks:
        matches = matches + (a[alive, done:n] == b[alive, done:n]).sum(axis=1)
        ok = matches >= least
        alive, matches, done = alive[ok], matches[ok], n
        if not len(alive):
            break
    return alive


def checkpoints(hashes: int, threshold: float, prune: float) -> list[tuple[int, int]]:
    ends = [*range(BATCH, hashes, BATCH), hashes]
    return [(n, least_matches(n, threshold, prune)) for n in ends]


def verified(pairs: DataFrame, sigs: DataFrame, docs: DataFrame, width: int, threshold_pct: int, checks: list[tuple[int, int]]) -> DataFrame:
    """The pairs (a, b) whose full sets reach the threshold."""
    import pyarrow as pa

    def prune(batches):
        for batch in batches:
            if batch.num_rows:
                x, y = (np.frombuffer(b"".join(batch.column(i).to_pylist()), np.uint32).reshape(batch.num_rows, -1) for i in (2, 3))
                yield pa.record_batch([batch.column(0), batch.column(1)], ["a", "b"]).take(pa.array(surviving(x, y, checks)))

    def confirm(batches):
        for batch in batches:
            keep = []
            for i in range(batch.num_rows):
                x, y = (np.frombuffer(batch.column(c)[i].as_py(), np.uint64) for c in (2, 3))
                if 100 * min(len(x), len(y)) < threshold_pct * max(len(x), len(y)):
                    continue
                common = len(np.intersect1d(x, y, assume_unique=True))
                if 100 * common >= threshold_pct * (len(x) + len(y) - common):
                    keep.append(i)
            yield pa.record_batch([batch.column(0), batch.column(1)], ["a", "b"]).take(pa.array(keep, pa.int64()))

    s = sigs.select("doc_id", "sig")
    both = pairs.join(s.select(F.col("doc_id").alias("b"), F.col("sig").alias("sb")), "b").join(s.select(F.col("doc_id").alias("a"), F.col("sig").alias("sa")), "a")
    likely = cut(both.select("a", "b", "sa", "sb").mapInArrow(prune, "a long, b long"), "likely")
    ids = cut(likely.select(F.col("a").alias("doc_id")).union(likely.select("b")).distinct(), "ids")
    sets = cut(full_sets(docs, ids, width), "sets")
    both = likely.join(sets.select(F.col("doc_id").alias("b"), F.col("shingles").alias("sb")), "b").join(sets.select(F.col("doc_id").alias("a"), F.col("shingles").alias("sa")), "a")
    return both.select("a", "b", "sa", "sb").mapInArrow(confirm, "a long, b long").distinct()


def components(edges: DataFrame) -> DataFrame:
    """(id, component): smallest id reachable over edges (a, b). Min-label exchange with pointer jumping; each round is written."""
    both = cut(edges.select("a", "b").union(edges.select("b", "a")).distinct(), "edges")
    labels = cut(both.groupBy(F.col("a").alias("id")).agg(F.least(F.min("b"), F.col("id")).alias("component")), "labels")
    while True:
        told = both.join(labels.select(F.col("id").alias("b"), F.col("component").alias("c")), "b").groupBy(F.col("a").alias("id")).agg(F.min("c").alias("c"))
        met = labels.join(told, "id").select("id", F.least("component", "c").alias("near"), F.col("component").alias("old"))
        jump = labels.select(F.col("id").alias("near"), F.col("component").alias("far"))
        new = cut(met.join(jump, "near", "left").select("id", F.least("near", F.coalesce("far", "near")).alias("component"), "old"), "labels")
        if new.where("component < old").isEmpty():
            return new.select("id", "component")
        labels = new.select("id", "component")


def cross_blocks(members: DataFrame, find) -> DataFrame:
    """Links (a, b) among members of different components of a key. members: key, id, comp, load.

    Members of a key's largest component never meet one another; the rest meet everyone, block by block.
    ``find(loads, rest, comp, ids)`` gets one cell and returns pairs of places in it.
    """
    weight = F.length("load") if dict(members.dtypes)["load"] == "binary" else F.lit(0)
    sizes = members.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("n"), F.sum(weight).alias("w"))
    top = sizes.groupBy("key").agg(F.max_by(F.struct("comp", "n", "w"), F.struct("n", "comp")).alias("t"), F.sum("n").alias("n_all"), F.sum("w").alias("w_all")).select("key", F.col("t.comp").alias("top"), F.col("t.n").alias("n_top"), F.col("t.w").alias("w_top"), "n_all", "w_all")
    m = members.join(top, "key").withColumn("rest", F.col("comp") != F.col("top"))
    blocks = lambda n, w: F.greatest(F.lit(1), F.ceil(n / F.lit(BLOCK)), F.ceil(w / F.lit(BLOCK_BYTES))).cast("int")
    m = m.withColumn("nr", blocks(F.col("n_all") - F.col("n_top"), F.col("w_all") - F.col("w_top"))).withColumn("nb", blocks(F.col("n_top"), F.col("w_top")))
    m = m.withColumn("at", F.pmod(F.xxhash64("id", "key"), F.when(F.col("rest"), F.col("nr")).otherwise(F.col("nb"))).cast("int"))
    against_big = F.transform(F.sequence(F.lit(0), F.col("nb") - 1), lambda j: F.struct(F.col("at").alias("i"), (F.col("nr") + j).alias("j")))
    against_rest = F.transform(F.sequence(F.lit(0), F.col("nr") - 1), lambda j: F.struct(F.least("at", j).alias("i"), F.greatest("at", j).alias("j")))
    from_big = F.transform(F.sequence(F.lit(0), F.col("nr") - 1), lambda i: F.struct(i.alias("i"), (F.col("nr") + F.col("at")).alias("j")))
    dealt = m.withColumn("cell", F.explode(F.when(F.col("rest"), F.concat(against_big, against_rest)).otherwise(from_big)))

    def compare(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.drop_duplicates(["id", "load"]).reset_index(drop=True)
        ids = pdf["id"].to_numpy()
        found = np.array(find(list(pdf["load"]), pdf["rest"].to_numpy(), pdf["comp"].to_numpy(), ids), np.int64).reshape(-1, 2)
        x, y = ids[found[:, 0]], ids[found[:, 1]]
        return pd.DataFrame({"a": np.minimum(x, y), "b": np.maximum(x, y)}, dtype="int64")

    return dealt.select("key", "cell", "id", "comp", "rest", "load").groupBy("key", "cell").applyInPandas(compare, "a long, b long")


def exact_links(threshold_pct: int, hashes: int, checks: list[tuple[int, int]]):
    """For :func:`cross_blocks` over full sets: signatures prune, sets decide; one link is enough for each row and other component."""

    def find(loads, rest, comp, ids):
        sets = [np.frombuffer(x, np.uint64) for x in loads]
        sig = np.stack([signature(s, multipliers(hashes)) for s in sets])
        sizes = np.array([len(s) for s in sets])
        found = []
        for i in np.flatnonzero(rest):
            fit = 100 * np.minimum(sizes, sizes[i]) >= threshold_pct * np.maximum(sizes, sizes[i])
            others = np.flatnonzero(fit & (comp != comp[i]) & (~rest | (ids > ids[i])))
            if not len(others):
                continue
            others = others[surviving(np.broadcast_to(sig[i], (len(others), hashes)), sig[others], checks)]
            if not len(others):
                continue
            flat = np.concatenate([sets[j] for j in others])
            place = np.searchsorted(sets[i], flat)
            place[place == len(sets[i])] = 0
            common = np.add.reduceat((sets[i][place] == flat).astype(np.int64), np.concatenate([[0], np.cumsum(sizes[others])[:-1]]))
            linked = others[100 * common >= threshold_pct * (sizes[i] + sizes[others] - common)]
            _, first = np.unique(comp[linked], return_index=True)
            found += [(i, linked[k]) for k in first]
        return found

    return find


def near_duplicates(docs: DataFrame, width: int = 5, threshold_pct: int = 80, miss: float = 1e-6, prune: float = 1e-7, small: int = 12) -> DataFrame:
    """doc_id, n_shingles, component_id, kept."""
    threshold = threshold_pct / 100
    bands = bands_for(threshold, miss)
    checks = checkpoints(bands * ROWS, threshold, prune)
    sigs = cut(signatures(docs, width, bands), "sigs")
    sets = cut(sigs.where("set_id is not null and doc_id is not null").groupBy("set_id").agg(F.min("doc_id").alias("rep")), "reps")
    first = sets.select("set_id", F.col("rep").alias("doc_id"))
    reps = cut(sigs.join(first, ["set_id", "doc_id"]).dropDuplicates(["set_id", "doc_id"]).select("doc_id", "sig", "keys"), "rep-sigs")
    banded = reps.select(F.col("doc_id").alias("id"), F.explode("keys").alias("key"))
    buckets = banded.groupBy("key").agg(F.min("id").alias("hub"), F.max("id").alias("top"), F.count(F.lit(1)).alias("n")).where("hub < top")
    held = cut(banded.join(buckets.select("key", "hub", "n"), "key"), "buckets")
    stars = cut(held.where("id > hub").select(F.col("hub").alias("a"), F.col("id").alias("b")).distinct(), "stars")
    links = cut(verified(stars, reps, docs, width, threshold_pct, checks), "links")
    comp = components(links)

    open_ = held.join(comp, "id", "left").withColumn("comp", F.coalesce("component", "id")).select("key", "id", "n", "comp")
    mixed = open_.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo < hi").select("key")
    open_ = cut(open_.join(mixed, "key", "left_semi"), "open")
    few, many = open_.where(F.col("n") <= small), open_.where(F.col("n") > small)
    pairs = few.alias("x").join(few.alias("y"), (F.col("x.key") == F.col("y.key")) & (F.col("x.id") < F.col("y.id")) & (F.col("x.comp") != F.col("y.comp"))).select(F.col("x.id").alias("a"), F.col("y.id").alias("b"))
    pairs = cut(pairs.distinct().join(stars, ["a", "b"], "left_anti"), "cross")
    found = [verified(pairs, reps, docs, width, threshold_pct, checks)] if not pairs.isEmpty() else []
    if not many.isEmpty():
        # once for each component that is the largest of some bucket, not once a bucket: its members there, and all others there
        sizes = many.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("m"))
        top = sizes.groupBy("key").agg(F.max_by("comp", F.struct("m", "comp")).alias("top"))
        met = cut(many.join(top, "key").select(F.col("top").alias("key"), "id", "comp").distinct(), "met")
        wanted = full_sets(docs, met.select(F.col("id").alias("doc_id")).distinct(), width)
        # rows that share an id may differ, and each of their sets meets the others
        loaded = met.join(wanted.distinct().select(F.col("doc_id").alias("id"), F.col("shingles").alias("load")), "id")
        found.append(cross_blocks(loaded, exact_links(threshold_pct, bands * ROWS, checks)))
    if found:
        more = found[0] if len(found) == 1 else found[0].union(found[1])
        more = cut(more.distinct(), "links")
        if not more.isEmpty():
            comp = components(links.union(more))

    # rows that share an id are one document: their sets are linked through it
    rep_comp = sets.join(comp.select(F.col("id").alias("rep"), "component"), "rep", "left").select("set_id", F.coalesce("component", "rep").alias("component"))
    out = sigs.select("doc_id", "n_shingles", "set_id").join(rep_comp, "set_id", "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))
