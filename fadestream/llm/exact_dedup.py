r"""Exact deduplication by a log-structured merge index of text digests.

One scan digests all rows; its tasks are dealt to MEMTABLES memtables. A memtable flushes a run: one entry a digest (keeper, its
length, number of rows), sorted by digest, with a filter over its digests. Runs are tiered: FANOUT runs of a tier are merged into
one of the next. A merge reads the filters first: an entry that no other run of the merge may hold passes as it is, only the rest
is exchanged and merged, keeping the smallest identifier. Lookups go through a filter as well: a row whose digest no other row
shares is answered from itself. Hits are then verified byte by byte: the texts that share a digest travel, each is compared with
the text of its keeper, and texts that share a digest and differ are told apart exactly.

Results for odd input: null text counts as empty; texts of white space only equal the empty text; a null doc_id is a
row like any other (it loses ties against any id); repeated rows are copies of each other; an empty table gives no rows;
columns other than doc_id and text are neither read nor renamed.
"""

from __future__ import annotations

import functools
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Stored, key_filter, text_of

BLANKS = r"[\x20\x09-\x0D]+"
#: Rows of one group of copies that meet in one task while texts are compared.
ROWS_PER_SALT = 5000


def bare(text: Column) -> Column:
    """The text without the six ASCII blanks."""
    return F.regexp_replace(text, BLANKS, "")


def sha256(text: Column) -> Column:
    return F.sha2(text, 256)


#: Memtables of a scan; runs of a tier that are merged into one.
MEMTABLES, FANOUT = 4, 4


class Run:
    """A sorted run: digest, best (least struct of -length, id is null, id), group_size; most: no fewer than its entries."""

    def __init__(self, entries: DataFrame, most: int) -> None:
        self.stored = Stored(entries.select("digest", "best", "group_size").sortWithinPartitions("digest"), "run")
        self.most = most

    @functools.cached_property
    def may_hold(self) -> Callable[..., Column]:
        """The filter over its digests, built when a merge first asks for it."""
        return key_filter(self.stored.df.select("digest"), self.most)


class DigestIndex:
    """The index: flush() digests a table and adds a run a memtable, compact() merges tier by tier, lookup() answers digests."""

    def __init__(self, spark: SparkSession, digest: Callable[[Column], Column] = sha256, memtables: int = MEMTABLES, fanout: int = FANOUT, measure: bool = False) -> None:
        self.spark, self.digest, self.memtables, self.fanout, self.measure = spark, digest, memtables, fanout, measure
        self.tiers: list[list[Run]] = [[]]
        self.tables: list[Stored] = []
        self.passed = self.merged = 0  # entries that merges passed on unexchanged, of all that they read, if measured

    def flush(self, docs: DataFrame) -> None:
        raw = text_of()
        rows = docs.select("doc_id", F.length(raw).cast("long").alias("n"), self.digest(bare(raw)).alias("digest"), F.pmod(F.spark_partition_id(), F.lit(self.memtables)).alias("memtable"))
        table = Stored(rows, "rows", by="memtable")
        self.tables.append(table)
        most = table.df.count()
        best = F.min(F.struct((-F.col("n")).alias("n"), F.col("doc_id").isNull().alias("z"), F.col("doc_id").alias("i")))
        for m in range(self.memtables):
            own = table.df.where(F.col("memtable") == m)
            self._add(0, Run(own.groupBy("digest").agg(best.alias("best"), F.count(F.lit(1)).alias("group_size")), most))

    def _add(self, tier: int, run: Run) -> None:
        if len(self.tiers) == tier:
            self.tiers.append([])
        self.tiers[tier].append(run)
        if len(self.tiers[tier]) == self.fanout:
            runs, self.tiers[tier] = self.tiers[tier], []
            self._add(tier + 1, self._merge(runs))

    def _merge(self, runs: list[Run]) -> Run:
        """One run of several; entries that the filters of all others reject aren't exchanged."""
        alone, met = None, None
        for run in runs:
            elsewhere = F.lit(False)
            for other in runs:
                if other is not run:
                    elsewhere = elsewhere | other.may_hold("digest")
            flagged = run.stored.df.withColumn("met", elsewhere)
            a, b = flagged.where(~F.col("met")).drop("met"), flagged.where("met").drop("met")
            alone, met = (a, b) if alone is None else (alone.unionByName(a), met.unionByName(b))
        joined = met.groupBy("digest").agg(F.min("best").alias("best"), F.sum("group_size").alias("group_size"))
        out = Run(alone.unionByName(joined), sum(run.most for run in runs))
        if self.measure:
            self.merged += sum(run.stored.df.count() for run in runs)
            self.passed += alone.count()
        for run in runs:
            run.stored.drop()
        return out

    def rows(self) -> DataFrame:
        """doc_id, n, digest of everything flushed."""
        out = None
        for t in self.tables:
            out = t.df.drop("memtable") if out is None else out.unionByName(t.df.drop("memtable"))
        return out

    def compact(self) -> DataFrame:
        """Merges what is left into one run: digest, keep_id, keep_n, group_size. The longest original stays, then the smallest id (null last)."""
        left = [run for tier in self.tiers for run in tier]
        run = left[0] if len(left) == 1 else self._merge(left)
        self.tiers = [[] for _ in self.tiers[:-1]] + [[run]]
        return run.stored.df.select("digest", F.col("best.i").alias("keep_id"), (-F.col("best.n")).alias("keep_n"), "group_size")

    def lookup(self, rows: DataFrame, level: DataFrame, hit: Column) -> DataFrame:
        """rows (doc_id, n, digest) with keep_id, keep_n, group_size; rows that share their digest with none (hit is false) aren't exchanged."""
        flagged = rows.withColumn("hit", hit)
        alone = flagged.where(~F.col("hit")).select("digest", "doc_id", "n", F.col("doc_id").alias("keep_id"), F.col("n").alias("keep_n"), F.lit(1).cast("long").alias("group_size"))
        return alone.unionByName(flagged.where("hit").drop("hit").join(level, "digest").select(alone.columns))


def _verify(docs: DataFrame, index: DigestIndex, shared: DataFrame, hit: Column) -> DataFrame:
    """digest, doc_id of the rows whose bare text differs from the keeper's although the digests are equal."""
    raw = text_of()
    texts = docs.select("doc_id", F.length(raw).cast("long").alias("n"), raw.alias("text")).withColumn("bare", bare(F.col("text")))
    texts = texts.withColumn("digest", index.digest(F.col("bare"))).where(hit).drop("text")
    salts = F.ceil(F.col("group_size") / ROWS_PER_SALT).cast("int")
    texts = Stored(texts, "texts").df  # digested once, read as keepers and as the others
    hits = texts.join(shared.select("digest", "keep_id", "keep_n", salts.alias("salts")), "digest")
    is_keeper = F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("n") == F.col("keep_n"))
    hits = hits.withColumn("salt", F.pmod(F.xxhash64("doc_id", "n"), F.col("salts")).cast("int"))
    keepers = hits.where(is_keeper).groupBy("digest", "salts").agg(F.min("bare").alias("kept_bare"))
    keepers = keepers.select("digest", "kept_bare", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"))
    return hits.where(~is_keeper).join(keepers, ["digest", "salt"]).where("bare <> kept_bare").select("digest", "doc_id")


def exact_dedup(docs: DataFrame, digest: Callable[[Column], Column] = sha256) -> DataFrame:
    """doc_id, keep_id, group_size, kept, digest: one row per input row."""
    index = DigestIndex(docs.sparkSession, digest)
    index.flush(docs)
    level = index.compact()
    shared = level.where("group_size > 1")
    hit = key_filter(shared.select("digest"), shared.count())("digest")
    clash = Stored(_verify(docs, index, shared, hit).select("digest").distinct(), "clash")
    rows = index.rows()
    if clash.df.isEmpty():
        joined = index.lookup(rows, level, hit)
    else:  # digests that different texts share: settle those by the bytes themselves
        joined = _settled(docs, rows, level, clash.df, digest)
    # of repeated rows that are the keeper's equal in id and length, exactly one is kept
    mine = F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("n") == F.col("keep_n"))
    repeats = joined.where(mine).groupBy("digest", "doc_id").count().where("count > 1").limit(1)
    if repeats.isEmpty():
        joined = joined.withColumn("kept", mine)
    else:
        from pyspark.sql import Window

        order = Window.partitionBy("digest", "doc_id", "n", F.when(mine, 0).otherwise(F.xxhash64(F.monotonically_increasing_id()))).orderBy("digest")
        joined = joined.withColumn("kept", mine & (F.row_number().over(order) == 1))
    return joined.select("doc_id", "keep_id", "group_size", "kept", "digest")


def _settled(docs: DataFrame, rows: DataFrame, level: DataFrame, clash: DataFrame, digest: Callable[[Column], Column]) -> DataFrame:
    plain = rows.join(clash, "digest", "left_anti").join(level, "digest")
    raw = text_of()
    told = docs.select("doc_id", F.length(raw).cast("long").alias("n"), bare(raw).alias("bare"))
    told = told.withColumn("digest", digest(F.col("bare"))).join(clash, "digest", "left_semi")
    best = F.min(F.struct((-F.col("n")).alias("n"), F.col("doc_id").isNull().alias("z"), F.col("doc_id").alias("i")))
    least = told.groupBy("digest", "bare").agg(best.alias("best"), F.count(F.lit(1)).alias("group_size"))
    least = least.select("digest", "bare", F.col("best.i").alias("keep_id"), (-F.col("best.n")).alias("keep_n"), "group_size")
    told = told.join(least, ["digest", "bare"]).select("digest", "doc_id", "n", "keep_id", "keep_n", "group_size")
    return plain.select(told.columns).unionByName(told)


__all__ = ["BLANKS", "DigestIndex", "bare", "exact_dedup", "sha256"]
