"""From rows to numbered batches, and the arithmetic of their ages."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fadestream.sources.window_store import shared_root


def by_dense_id(df: DataFrame, id_col: str, n: int) -> DataFrame:
    """Batches of n by a dense id: arithmetic, no exchange."""
    return df.withColumn("batch_seq", F.floor(F.col(id_col) / n).cast("long"))


def ordinals(df: DataFrame, order: list[str]) -> DataFrame:
    """df with ordinal (from 0) in the given order: ranges, counts of ranges, numbering within a range; no window over all rows.

    The ranges are written to the shared folder, so counts and numbers come from the same rows whatever executors are lost.
    """
    ranged = df.repartitionByRange(*order).withColumn("__part", F.spark_partition_id())
    path = f"{shared_root(df.sparkSession, 'ordinals')}/{uuid.uuid4().hex}"
    ranged.write.parquet(path)
    ranged = df.sparkSession.read.schema(ranged.schema).parquet(path)
    counts = ranged.groupBy("__part").count()
    before = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)  # a row for each range
    starts = counts.select("__part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("__start"))
    local = F.row_number().over(Window.partitionBy("__part").orderBy(*order))
    out = ranged.join(F.broadcast(starts), "__part").withColumn("ordinal", F.col("__start") + local - 1)
    return out.drop("__part", "__start")


def by_ordinal(df: DataFrame, order: list[str], n: int) -> DataFrame:
    """Batches of n in any order, for ids with holes."""
    return ordinals(df, order).withColumn("batch_seq", F.floor(F.col("ordinal") / n).cast("long"))


def by_time(df: DataFrame, ts: str, width: str, slide: str | None = None) -> DataFrame:
    """Time batches: start and end of the window each row falls in (several with a slide)."""
    w = F.window(F.col(ts).cast("timestamp"), width, slide) if slide else F.window(F.col(ts).cast("timestamp"), width)
    return df.withColumn("__w", w).withColumn("start", F.col("__w.start")).withColumn("end", F.col("__w.end")).drop("__w")


def by_month(df: DataFrame, ts: str) -> DataFrame:
    """Calendar batches of unequal size, numbered from 0: only the distinct months are ranked."""
    month = F.date_trunc("month", F.col(ts).cast("timestamp"))
    tagged = df.withColumn("month", month)
    numbers = tagged.select("month").distinct().withColumn("batch_seq", (F.dense_rank().over(Window.orderBy("month")) - 1).cast("long"))
    return tagged.join(F.broadcast(numbers), "month")


def by_session(df: DataFrame, key: str, ts: str, gap: str) -> DataFrame:
    """A burst of one key is a batch."""
    return df.groupBy(key, F.session_window(F.col(ts).cast("timestamp"), gap).alias("s")).agg(F.count(F.lit(1)).alias("n")).select(key, F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def antiquity(df: DataFrame, cur: int, rho: float) -> DataFrame:
    """t and the weight rho^t."""
    t = F.lit(cur) - F.col("batch_seq")
    return df.withColumn("t", t).withColumn("w", F.pow(F.lit(float(rho)), t.cast("double")))


def evict(df: DataFrame, cur: int, t_max: int) -> DataFrame:
    return df.where((F.col("batch_seq") > cur - t_max) & (F.col("batch_seq") <= cur))


def calendar(spark: SparkSession, n_batches: int = 100, period: int = 10, burn_in: int = 0) -> DataFrame:
    """batch_seq, concept_id, t_index (1 on the first batch of a concept), is_drift; burn-in batches belong to concept 0."""
    return calendar_of(spark.range(n_batches + burn_in).select(F.col("id").alias("batch_seq")), period, burn_in)


def calendar_of(batches: DataFrame, period: int = 10, burn_in: int = 0) -> DataFrame:
    """The same for the batch numbers given."""
    seq = F.col("batch_seq") - burn_in
    concept = F.when(seq < 0, 0).otherwise(F.floor(seq / period) + 1).cast("int")
    index = F.when(seq < 0, 0).otherwise(seq % period + 1).cast("int")
    return batches.select("batch_seq", concept.alias("concept_id"), index.alias("t_index"), (index == 1).alias("is_drift"))


def masses(sizes: DataFrame, rho: float, t_max: int) -> DataFrame:
    """sizes (batch_seq, n) -> step, m_t, m_rho of the window that ends there: a range join of two small relations, by expanded equality."""
    reach = sizes.select(F.explode(F.sequence(F.col("batch_seq"), F.col("batch_seq") + (t_max - 1))).alias("step"), F.col("batch_seq").alias("b"), "n")
    kept = reach.join(sizes.select(F.col("batch_seq").alias("step")), "step")
    w = F.pow(F.lit(float(rho)), (F.col("step") - F.col("b")).cast("double"))
    return kept.groupBy("step").agg(F.sum("n").alias("m_t"), F.sum(w * F.col("n")).alias("m_rho"))


def draw_batches(df: DataFrame, id_col: str | Column, n: int, count: int, seed: int = 0) -> DataFrame:
    """count disjoint random batches of n: rows ranked by a hash of their id, of which only the first n * count are kept."""
    key = F.md5(F.concat_ws("-", (F.col(id_col) if isinstance(id_col, str) else id_col).cast("string"), F.lit(str(seed))).cast("binary"))
    hashed = df.withColumn("__h", key).orderBy("__h").limit(n * count)
    rank = F.row_number().over(Window.orderBy("__h")) - 1  # n * count rows, a parameter
    return hashed.withColumn("rank", rank.cast("long")).withColumn("b", F.floor(F.col("rank") / n).cast("long")).drop("__h")
