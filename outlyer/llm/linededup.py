"""Repeated runs of lines by a depth-limited suffix array, with DataFrame functions only.

Non-blank lines of a document, trimmed, form a sequence of line ids; a line that occurs once in the corpus can
be in no repeated run and splits the sequence. Prefix doubling ranks the remaining suffixes by their first 1, 2,
4, ... lines: pairs of ranks are counted, pairs that occur once leave, and the others are numbered in sorted
order by a range partitioning, so that ranks are positions in the suffix array at that depth and no task holds
one key's rows. Suffixes that agree in rank at two overlapping depths 2**k share a prefix of any length between
2**k and 2**(k+1); such a class is one interval of the longest-common-prefix array.

A repeated run counts when it has at least ``min_words`` words. Every such run is covered by its shortest
qualifying windows that start at one of its lines or end at one; windows have at most ``min_words`` lines, which
limits the depth. In each interval of equal windows the first copy by (doc_id, text digest, line) stays and later
copies are deleted, so a maximal repeated run goes in all places but the first.

Edge cases: null text stays null; blank lines belong to no run and stay; windows may overlap in one document
(a line repeated over and over keeps its first copy); rows that share an id but not a text are documents of their
own; rows alike in id and text are one document and lose the same lines; a null id is never changed; an empty table
gives no rows; other columns pass, but ``n_lines`` and ``n_removed`` are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, text_of

_BLANK = r"[\s\p{Z}]+"


ROW = ["doc_id", "tid"]  # a document: rows that share an id may differ in text


def line_table(docs: DataFrame) -> DataFrame:
    """doc_id, tid (hash of the text), place (line number in the text), seq (number among its lines that are not blank), h1, h2 (128 bits of the trimmed line), words."""
    trimmed = F.transform(F.split(text_of(), "\n", -1), lambda x, i: F.struct(i.cast("long").alias("place"), F.trim(F.regexp_replace(x, r"^[\s\p{Z}]+|[\s\p{Z}]+$", "")).alias("line")))
    lines = docs.where("doc_id is not null").select("doc_id", F.xxhash64("text").alias("tid"), F.posexplode(F.filter(trimmed, lambda x: x["line"] != "")).alias("nth", "x"))
    md = F.md5(F.col("x.line").cast("binary"))
    half = lambda a: F.conv(F.substring(md, a, 15), 16, 10).cast("long")
    return lines.select(*ROW, "x.place", (F.col("nth") + 1).alias("seq"), half(1).alias("h1"), half(17).alias("h2"), F.size(F.split("x.line", _BLANK)).cast("long").alias("words"))


def sorted_ranks(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """Numbers distinct pairs in sorted order, from 1: range partitions count by themselves and start where the last ended."""
    spark = pairs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = cut(pairs.select(a, b).repartitionByRange(parts, a, b).withColumn("part", F.spark_partition_id()), "range")
    counts = dealt.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    base = counts.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    nth = F.row_number().over(Window.partitionBy("part").orderBy(a, b))
    return dealt.withColumn("nth", nth).join(F.broadcast(base), "part").select(a, b, (F.col("base") + F.col("nth")).alias("rank"))  # base: a row per partition


def suffix_ranks(docs: DataFrame, depth: int) -> tuple[DataFrame, int]:
    """Suffixes of repeated lines: doc_id, tid, place, seq (number in the document), words, r0, r1, ...: rank by the first 2**k lines.

    A rank is null where that block is unique or runs past a unique line. Returns also how many levels there are.
    """
    lines = cut(line_table(docs), "lines")
    repeated = lines.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    ranks = cut(sorted_ranks(repeated, "h1", "h2"), "rank0")
    rows = lines.join(ranks, ["h1", "h2"]).select(*ROW, "place", "seq", "words", F.col("rank").alias("r0"))
    rows = cut(rows.dropDuplicates([*ROW, "seq"]), "level0")
    levels = 1
    while 2**levels <= depth:
        k = levels - 1
        ahead = Window.partitionBy(*ROW).orderBy("seq").rangeBetween(2**k, 2**k)  # the row 2**k lines on, if it is active
        paired = rows.withColumn("next", F.max(f"r{k}").over(ahead))
        paired = cut(paired, "paired")
        again = paired.where(f"r{k} is not null and next is not null").groupBy(f"r{k}", "next").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
        named = cut(sorted_ranks(again, f"r{k}", "next"), "named")
        rows = cut(paired.join(named.withColumnRenamed("rank", f"r{levels}"), [f"r{k}", "next"], "left").drop("next"), f"level{levels}")
        levels += 1
        if named.isEmpty():
            break
    return rows, levels


def _windows(rows: DataFrame, levels: int, min_words: int) -> DataFrame:
    """doc_id, tid, start (seq), lines, ka, kb: the shortest windows of at least ``min_words`` words from and to every active line."""
    # contiguous active lines form a stretch: seq minus the running number is constant in it
    doc = Window.partitionBy(*ROW).orderBy("seq")
    rows = rows.withColumn("stretch", F.col("seq") - F.row_number().over(doc))
    part = Window.partitionBy(*ROW, "stretch").orderBy("seq")
    rows = rows.withColumn("after", F.sum("words").over(part)).withColumn("before", F.col("after") - F.col("words"))
    rows = rows.withColumn("total", F.sum("words").over(Window.partitionBy(*ROW, "stretch")))
    on = Window.partitionBy(*ROW, "stretch").orderBy("before").rangeBetween(0, min_words - 1)
    back = Window.partitionBy(*ROW, "stretch").orderBy("after").rangeBetween(-(min_words - 1), 0)
    rows = rows.withColumn("fore", F.when(F.col("total") - F.col("before") >= min_words, F.count(F.lit(1)).over(on)))
    rows = rows.withColumn("hind", F.when(F.col("after") >= min_words, F.count(F.lit(1)).over(back)))
    level: Column = F.array(*[F.col(f"r{k}") for k in range(levels)])
    all_of = F.array_sort(F.collect_list(F.struct("seq", "fore", "hind", level.alias("r"))))
    docs = rows.groupBy(*ROW).agg(all_of.alias("s"))

    def around(x: Column, i: Column) -> Column:
        return F.array(F.struct(i.alias("i"), x["fore"].alias("n")), F.struct((i - x["hind"] + 1).cast("int").alias("i"), x["hind"].alias("n")))

    def named(w: Column) -> Column:
        k = F.floor(F.log2(w["n"].cast("double"))).cast("int")
        depth = F.call_function("shiftleft", F.lit(1), k)
        first, last = F.col("s")[w["i"]], F.col("s")[(w["i"] + w["n"] - depth).cast("int")]
        return F.struct(first["seq"].alias("start"), w["n"].alias("lines"), F.get(first["r"], k).alias("ka"), F.get(last["r"], k).alias("kb"))

    wanted = F.filter(F.flatten(F.transform("s", around)), lambda w: w["n"].isNotNull())
    return docs.select(*ROW, F.explode(F.array_distinct(F.transform(wanted, named))).alias("w")).select(*ROW, "w.*").where("ka is not null and kb is not null")


def later_copies(docs: DataFrame, min_words: int = 50) -> DataFrame:
    """doc_id, tid and ``gone``: the line numbers to delete, sorted."""
    rows, levels = suffix_ranks(docs, min_words)
    windows = cut(_windows(rows, levels, min_words), "windows")
    at = F.struct(*ROW, "start")
    first = windows.groupBy("lines", "ka", "kb").agg(F.min(at).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    again = windows.join(first, ["lines", "ka", "kb"]).where(at > F.col("first"))
    spans = again.groupBy(*ROW).agg(F.array_sort(F.collect_set(F.struct("start", "lines"))).alias("w"))
    seqs = spans.select(*ROW, F.array_distinct(F.flatten(F.transform("w", lambda x: F.sequence(x["start"].cast("long"), x["start"].cast("long") + x["lines"] - 1)))).alias("q"))
    places = rows.select(*ROW, "seq", "place").join(seqs.select(*ROW, F.explode("q").alias("seq")).withColumn("seq", F.col("seq").cast("int")), [*ROW, "seq"])
    return places.groupBy(*ROW).agg(F.array_sort(F.collect_set("place")).alias("gone"))


def dedup_lines(docs: DataFrame, min_words: int = 50) -> DataFrame:
    """``docs`` with later copies of repeated runs deleted from ``text``, plus n_lines and n_removed (0 for null text)."""
    gone = later_copies(docs.select("doc_id", "text"), min_words).select(F.col("doc_id").alias("_of"), F.col("tid").alias("_tid"), F.col("gone").alias("_gone"))
    keep = [c for c in docs.columns if c not in ("n_lines", "n_removed")]
    lines = F.split(F.col("text"), "\n", -1)
    n = F.coalesce(F.size(F.when(F.col("text").isNotNull(), lines)), F.lit(0))
    left = F.array_except(F.sequence(F.lit(0).cast("long"), (F.size(lines) - 1).cast("long")), F.col("_gone"))
    text = F.when(F.col("_gone").isNull() | F.col("text").isNull(), F.col("text")).otherwise(F.array_join(F.transform(left, lambda i: F.get(lines, i.cast("int"))), "\n"))
    joined = docs.select(*keep).join(gone, (F.col("doc_id") == F.col("_of")) & (F.xxhash64("text") == F.col("_tid")), "left")
    return joined.select(*[text.alias("text") if c == "text" else F.col(c) for c in keep], F.when(F.col("text").isNull(), 0).otherwise(n).cast("long").alias("n_lines"), F.coalesce(F.size("_gone"), F.lit(0)).cast("long").alias("n_removed"))
