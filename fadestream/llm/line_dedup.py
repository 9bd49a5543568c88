r"""Line deduplication by a suffix array over line-number sequences, all in DataFrame operations.

Documents stand one behind the other in the order of doc_id (null last), then text hash; every non-blank line (trailing blanks
ignored) has a place in that sequence. Distributed prefix doubling ranks the suffixes by their first 1, 2, 4, ... lines: the next
rank is the place of the pair (own rank, rank of the suffix half-way on) among all distinct pairs, found by a range exchange and
counts of its partitions, never by a window over all rows. Suffixes that share a rank of depth d are an interval of the suffix array
whose longest common prefix is at least d; those whose prefix is unique drop out, and the doubling goes on until no interval is
left. So a suffix leaves with the greatest depth d at which an earlier suffix shares its prefix, and its longest common prefix with
what came before lies in [d, 2d). A repeated run of L lines, d <= L < 2d, is the union of the prefixes of depth d that start in it:
the union over all suffixes gives the maximal repeated runs whole, and their later copies are deleted.

A run counts from `min_lines` lines on, or as a single line from `min_chars` characters on; shorter single lines that repeat
("Contents", a name) stay where the lines around them differ.

Results for odd input: null and blank texts have no lines and stay as they are; blank lines are no part of runs and stay; rows
equal in doc_id and text are one document, shown as often as they occur; other columns stay, but for n_lines and n_removed, which
are replaced; an empty table gives no rows; very long texts add rows, not wider ones.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Stored

MIN_LINES, MIN_CHARS = 2, 120


def _starts(dealt: DataFrame, amount: Column) -> DataFrame:
    """part -> how much the partitions before it hold."""
    counts = dealt.groupBy("part").agg(amount.alias("held"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row a partition
    return F.broadcast(counts.select("part", F.coalesce(F.sum("held").over(before), F.lit(0)).alias("start")))


def _sequence(lines: DataFrame) -> DataFrame:
    """Lines (doc_id, th, pos, ...) -> doc_id, th, base (the place of its first line among all lines), n: a row per document."""
    sizes = lines.groupBy("doc_id", "th").agg((F.max("pos") + 1).cast("long").alias("n"), F.count(F.lit(1)).alias("rows"))
    order = [F.col("doc_id").isNull(), F.col("doc_id"), F.col("th")]
    dealt = Stored(sizes.repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "order").df
    upto = Window.partitionBy("part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    return dealt.join(_starts(dealt, F.sum("n")), "part").select("doc_id", "th", (F.col("start") + F.coalesce(F.sum("n").over(upto), F.lit(0))).alias("base"), "n", "rows")


def _ranked(pairs: DataFrame) -> DataFrame:
    """Suffixes (base, pos, ...) with the ranks of both halves (a, b) -> those whose pair occurs again, with its rank and whether they are the first that has it."""
    at = F.col("base") + F.col("pos")
    again = pairs.groupBy("a", "b").agg(F.count(F.lit(1)).alias("c"), F.min(at).alias("least")).where("c > 1").select("a", "b", "least")
    dealt = Stored(again.repartitionByRange("a", "b").withColumn("part", F.spark_partition_id()), "places").df
    local = F.row_number().over(Window.partitionBy("part").orderBy("a", "b"))
    ranks = dealt.join(_starts(dealt, F.count(F.lit(1))), "part").select("a", "b", "least", (F.col("start") + local - 1).alias("rank"))
    return pairs.join(ranks, ["a", "b"]).select(*(c for c in pairs.columns if c not in "ab"), "rank", (at == F.col("least")).alias("is_first"))


def _ahead(ranks: DataFrame, step: int) -> DataFrame:
    """Ranks of suffixes with the rank `step` lines on, where the document goes on so far."""
    order = Window.partitionBy("base").orderBy("pos").rangeBetween(step, step)
    both = ranks.select("base", "pos", F.col("rank").alias("a"), F.first("rank").over(order).alias("b"))
    return both.where(F.col("b").isNotNull())


def _split(text: Column) -> Column:
    return F.split(text, "\n", -1)


def intervals(docs: DataFrame, min_lines: int = MIN_LINES, min_chars: int | None = MIN_CHARS) -> tuple[DataFrame, DataFrame]:
    """Members of the intervals: (base, pos, depth, rank, is_first), for each depth that counts; and the documents (doc_id, th, base, n)."""
    kept = F.filter(F.transform(_split(F.col("text")), lambda x: F.rtrim(x)), lambda x: F.trim(x) != "")
    long = F.lit(False) if min_chars is None else F.length
    hashed = F.transform(kept, lambda x: F.struct(F.xxhash64(x).alias("a"), F.xxhash64(F.lit("second"), x).alias("b"), (long if min_chars is None else long(x) >= min_chars).alias("long")))
    keyed = docs.where(F.col("text").isNotNull()).select("doc_id", F.xxhash64("text").alias("th"), hashed.alias("ids"))
    lines = Stored(keyed.select("doc_id", "th", F.posexplode("ids").alias("pos", "id")).select("doc_id", "th", "pos", "id.*"), "lines").df
    places = Stored(_sequence(lines), "sequence").df
    left = lines.alias("l").join(places.alias("p"), F.col("l.doc_id").eqNullSafe(F.col("p.doc_id")) & (F.col("l.th") == F.col("p.th")))
    suffixes = left.select("base", "pos", "a", "b", "long")
    if not places.where("rows > n").isEmpty():  # repeated rows
        suffixes = suffixes.dropDuplicates(["base", "pos"])
    now = Stored(_ranked(Stored(suffixes, "suffixes").df), "ranks")
    depth, found = 1, []
    while not now.df.isEmpty():
        if depth >= min_lines:
            found.append(now.df.select("base", "pos", F.lit(depth).alias("depth"), "rank", "is_first"))
        elif depth == 1:
            found.append(now.df.where("long").select("base", "pos", F.lit(1).alias("depth"), "rank", "is_first"))
        step = depth if depth >= min_lines else min(depth, min_lines - depth)
        now, depth = Stored(_ranked(_ahead(now.df, step)), "ranks"), depth + step
    if not found:
        found = [now.df.select("base", "pos", F.lit(depth).alias("depth"), "rank", "is_first")]
    return reduce(DataFrame.unionAll, found), places.select("doc_id", "th", "base", "n")


def repeated_runs(docs: DataFrame, min_lines: int = MIN_LINES, min_chars: int | None = MIN_CHARS) -> DataFrame:
    """doc_id, th, runs: array of (first, last), the stretches of a document's non-blank lines that copy earlier ones; touching runs are one stretch."""
    members, places = intervals(docs, min_lines, min_chars)
    by_doc = members.where(~F.col("is_first")).groupBy("base").agg(F.array_sort(F.collect_list(F.struct("pos", (F.col("pos") + F.col("depth") - 1).alias("last")))).alias("w"))
    lines = F.array_sort(F.array_distinct(F.flatten(F.transform("w", lambda w: F.sequence(w["pos"], w["last"])))))
    heads = lambda covered: F.filter(covered, lambda p, i: (i == 0) | (F.get(covered, i - 1) != p - 1))
    tails = lambda covered: F.filter(covered, lambda p, i: F.coalesce(F.get(covered, i + 1) != p + 1, F.lit(True)))
    covered = by_doc.select("base", lines.alias("covered"))
    runs = covered.select("base", F.zip_with(heads(F.col("covered")), tails(F.col("covered")), lambda a, b: F.struct(a.alias("first"), b.alias("last"))).alias("runs"))
    return runs.join(places, "base").select("doc_id", "th", "runs")


def line_dedup(docs: DataFrame, min_lines: int = MIN_LINES, min_chars: int | None = MIN_CHARS) -> DataFrame:
    """docs with later copies of repeated line runs removed, plus n_lines and n_removed (long): a row per input row."""
    gone = repeated_runs(docs, min_lines, min_chars)
    own = [c for c in docs.columns if c not in ("n_lines", "n_removed")]
    keyed = docs.select(F.struct(*(F.col(f"`{c}`") for c in own)).alias("__row"), F.xxhash64("text").alias("__th"))
    on = F.col("__row.doc_id").eqNullSafe(F.col("doc_id")) & (F.col("__th") == F.col("th"))
    joined = keyed.join(gone, on, "left").select("__row", "runs")
    text = F.col("__row.text")
    lines = F.coalesce(_split(text), F.array().cast("array<string>"))
    whole = F.filter(F.transform(lines, lambda x, i: F.struct(i.alias("i"), F.trim(F.rtrim(x)).alias("x"))), lambda z: z["x"] != "")
    out = joined.withColumn("at", F.when(F.col("runs").isNotNull(), F.transform(whole, lambda z: z["i"])))
    out = out.withColumn("gone", F.flatten(F.transform("runs", lambda r: F.slice("at", r["first"] + 1, r["last"] - r["first"] + 1))))
    stay = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col("gone"))
    rest = F.array_join(F.transform(stay, lambda i: F.get(lines, i)), "\n")
    out = out.withColumn("__clean", F.when(F.col("gone").isNotNull(), rest).otherwise(text))
    count = F.size(F.filter(lines, lambda x: F.trim(F.rtrim(x)) != "")).cast("long")
    return out.select(
        *(F.col("__clean").alias(c) if c == "text" else F.col("__row").getField(c).alias(c) for c in own),
        count.alias("n_lines"),
        F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_removed"),
    )
