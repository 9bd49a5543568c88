"""Point views of the given tables: named numeric expressions gathered in one array, validated, scaled."""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, StructField, StructType

from fadestream.functions import vectors as V


@dataclass(frozen=True)
class FeatureSpec:
    """Names and expressions of the coordinates. policy for rows with null, nan or infinite coordinates: drop, error or impute (0)."""

    features: tuple[tuple[str, Column], ...]
    policy: str = "error"

    @property
    def d(self) -> int:
        return len(self.features)

    def view(self, df: DataFrame, point_id: Column, *keep: Column) -> DataFrame:
        """point_id, x and the columns to keep."""
        cols = [e.cast("double") for _, e in self.features]
        if self.policy == "impute":
            cols = [F.when(c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")), 0.0).otherwise(c) for c in cols]
        out = df.select(point_id.cast("string").alias("point_id"), F.array(*cols).alias("x"), *keep)
        good = V.finite_vector(F.col("x"), self.d)
        if self.policy == "drop":
            return out.where(good)
        if self.policy == "error":
            return out.withColumn("x", F.when(good, F.col("x")).otherwise(F.raise_error(F.lit("a point has a missing or infinite coordinate"))))
        return out


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def zscore(df: DataFrame, d: int, fit_on: DataFrame | None = None) -> DataFrame:
    """x standardised by the mean and deviation of fit_on (or df); a constant coordinate becomes 0."""
    stats = (fit_on if fit_on is not None else df).agg(*(F.avg(F.col("x")[j]).alias(f"m{j}") for j in range(d)), *(F.stddev_pop(F.col("x")[j]).alias(f"s{j}") for j in range(d))).first()
    z = [(F.col("x")[j] - F.lit(stats[f"m{j}"])) / F.lit(stats[f"s{j}"]) if stats[f"s{j}"] else F.lit(0.0) for j in range(d)]
    return df.withColumn("x", F.array(*z))


def minmax(df: DataFrame, d: int, fit_on: DataFrame | None = None) -> DataFrame:
    """x mapped to 0..1 by the range of fit_on (or df)."""
    stats = (fit_on if fit_on is not None else df).agg(*(F.min(F.col("x")[j]).alias(f"a{j}") for j in range(d)), *(F.max(F.col("x")[j]).alias(f"b{j}") for j in range(d))).first()
    z = [(F.col("x")[j] - F.lit(stats[f"a{j}"])) / F.lit(stats[f"b{j}"] - stats[f"a{j}"]) if stats[f"b{j}"] != stats[f"a{j}"] else F.lit(0.0) for j in range(d)]
    return df.withColumn("x", F.array(*z))


def l2_normalise(df: DataFrame) -> DataFrame:
    n = V.vec_norm(F.col("x"))
    return df.withColumn("x", F.when(n == 0, F.col("x")).otherwise(F.transform("x", lambda v: v / n)))


def code_of(col: Column, values: Sequence[str]) -> Column:
    """Place of a value in a list, -1 if it isn't there."""
    out = F.lit(-1)
    for i, v in enumerate(values):
        out = F.when(col == v, i).otherwise(out)
    return out


STATUS, PRIORITY = ["F", "O", "P"], ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
TYPES = ["click", "view", "purchase", "signup", "error"]
#: Letters in the usual order of their frequency in English text.
LETTERS = "etaoinshrdlcumwfgypbvk"


def events4(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    ts = F.col("ts").cast("timestamp")
    spec = FeatureSpec((("value", F.col("value")), ("k", F.get_json_object("props", "$.k").cast("double")), ("hour", F.hour(ts)), ("dow", F.dayofweek(ts))))
    return spec.view(e, F.col("event_id"), F.col("event_id"), ts.alias("ts"))


def lineitem_id() -> Column:
    cols = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
    return F.md5(F.concat_ws("|", *(F.col(c).cast("string") for c in cols)).cast("binary"))


def lineitem2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return FeatureSpec((("q", F.col("l_quantity")), ("p", F.col("l_extendedprice")))).view(table(spark, sf_dir, "lineitem"), lineitem_id(), F.col("l_shipdate"))


def lineitem4(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec = FeatureSpec((("q", F.col("l_quantity")), ("p", F.col("l_extendedprice")), ("d", F.col("l_discount")), ("t", F.col("l_tax"))))
    return spec.view(table(spark, sf_dir, "lineitem"), lineitem_id(), F.col("l_shipdate"))


def orders8(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer")
    per = o.groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n_orders"))
    j = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(per, "o_custkey")
    angle = F.dayofyear(F.col("o_orderdate").cast("timestamp")) * F.lit(2 * 3.141592653589793 / 366.0)
    spec = FeatureSpec(
        (("price", F.col("o_totalprice")), ("bal", F.col("c_acctbal")), ("sin", F.sin(angle)), ("cos", F.cos(angle)), ("prio", code_of(F.col("o_orderpriority"), PRIORITY)), ("status", code_of(F.col("o_orderstatus"), STATUS)), ("nation", F.col("c_nationkey")), ("n", F.col("n_orders")))
    )
    return spec.view(j, F.col("o_orderkey"), F.col("o_orderkey"))


def star18(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, o, p, s, c = (table(spark, sf_dir, t) for t in ("lineitem", "orders", "part", "supplier", "customer"))
    j = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(p, F.col("l_partkey") == F.col("p_partkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey")).join(c, F.col("o_custkey") == F.col("c_custkey"))
    ship, od = F.col("l_shipdate").cast("timestamp"), F.col("o_orderdate").cast("timestamp")
    named = [
        ("quantity", F.col("l_quantity")), ("price", F.col("l_extendedprice")), ("discount", F.col("l_discount")), ("tax", F.col("l_tax")), ("line", F.col("l_linenumber")),
        ("flag", code_of(F.col("l_returnflag"), ["A", "N", "R"])), ("status", code_of(F.col("l_linestatus"), ["F", "O"])), ("total", F.col("o_totalprice")),
        ("prio", code_of(F.col("o_orderpriority"), PRIORITY)), ("ostatus", code_of(F.col("o_orderstatus"), STATUS)), ("cbal", F.col("c_acctbal")), ("sbal", F.col("s_acctbal")),
        ("size", F.col("p_size")), ("retail", F.col("p_retailprice")), ("lag", F.datediff(ship, od)), ("month", F.month(ship)), ("home", (F.col("c_nationkey") == F.col("s_nationkey")).cast("int")),
        ("brand", F.coalesce(F.regexp_extract("p_brand", "([0-9]+)", 1).try_cast("double"), F.lit(0.0))),
    ]
    return FeatureSpec(tuple(named)).view(j, lineitem_id(), F.col("l_shipdate"))


def events20(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").withColumn("day", F.to_date(F.col("ts").cast("timestamp")))
    types = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").limit(5).collect()]
    aggs = []
    for t in types:
        v = F.when(F.col("event_type") == t, F.col("value"))
        aggs += [F.count(v).alias(f"{t}_n"), F.sum(v).alias(f"{t}_s"), F.max(v).alias(f"{t}_m"), F.avg(v).alias(f"{t}_a")]
    wide = e.groupBy("user_id", "day").agg(*aggs)
    names = [c for c in wide.columns if c not in ("user_id", "day")]
    spec = FeatureSpec(tuple((n, F.coalesce(F.col(n), F.lit(0.0))) for n in names))
    return spec.view(wide, F.concat_ws("-", "user_id", "day"), F.col("day"))


def letters22(spark: SparkSession, sf_dir: str) -> DataFrame:
    low = table(spark, sf_dir, "documents").select("doc_id", F.lower(F.coalesce(F.col("text"), F.lit(""))).alias("low"))
    codes = [ord(x) for x in LETTERS]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A letter's code is no part of another character in UTF-8."""
        for b in batches:
            texts = b.column("low").cast(pa.large_binary())
            found = np.array([np.bincount(np.frombuffer(t.as_buffer(), dtype=np.uint8), minlength=256)[codes] for t in texts], dtype=np.int32).reshape(len(texts), len(codes))
            found = pa.ListArray.from_arrays(pa.array(np.arange(len(texts) + 1, dtype=np.int32) * len(codes)), pa.array(found.ravel()))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("n"), found], names=["doc_id", "n", "found"])

    df = low.select("doc_id", F.length("low").alias("n"), "low").mapInArrow(count, StructType([low.schema["doc_id"], StructField("n", IntegerType()), StructField("found", ArrayType(IntegerType()))]))
    total = F.greatest(F.col("n"), F.lit(1))
    return FeatureSpec(tuple((x, F.col("found")[i] / total) for i, x in enumerate(LETTERS))).view(df, F.col("doc_id"), F.col("doc_id"))


def spend25(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, o, s = (table(spark, sf_dir, t) for t in ("lineitem", "orders", "supplier"))
    j = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    wide = j.groupBy("o_custkey").pivot("s_nationkey", list(range(25))).agg(F.sum("l_extendedprice"))
    total = sum((F.coalesce(F.col(str(i)), F.lit(0.0)) for i in range(25)), F.lit(0.0))
    spec = FeatureSpec(tuple((f"n{i}", F.coalesce(F.col(str(i)), F.lit(0.0)) / F.when(total == 0, 1.0).otherwise(total)) for i in range(25)))
    return spec.view(wide, F.col("o_custkey"), F.col("o_custkey"))


def embed(spark: SparkSession, sf_dir: str, d: int = 64) -> DataFrame:
    e = table(spark, sf_dir, "embeddings")
    return FeatureSpec(tuple((f"e{j}", F.col("embedding")[j]) for j in range(d))).view(e, F.col("vec_id"), F.col("vec_id"), F.col("label"))


def hash178(spark: SparkSession, sf_dir: str, bins: int = 178) -> DataFrame:
    """Tokens hashed to bins by MD5, counted, normalised to length 1."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+").alias("w"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Each different word of a batch is hashed once."""
        known: dict[bytes, int] = {}
        for b in batches:
            words = b.column("w")
            row = np.repeat(np.arange(len(words)), pc.list_value_length(words).to_numpy(zero_copy_only=False))
            told = words.flatten().dictionary_encode()
            if len(known) > 1_000_000:
                known.clear()
            names = told.dictionary.cast(pa.binary()).to_pylist()
            for w in names:
                if w not in known:
                    known[w] = int(hashlib.md5(w).hexdigest()[:8], 16) % bins if w else bins
            at = np.array([known[w] for w in names], dtype=np.int64)[told.indices.to_numpy()]
            found = np.bincount(row * (bins + 1) + at, minlength=len(words) * (bins + 1)).reshape(len(words), bins + 1)[:, :bins]
            some = np.flatnonzero(found.any(axis=1))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(some) + 1, dtype=np.int32) * bins), pa.array(found[some].astype(np.int32).ravel()))
            yield pa.RecordBatch.from_arrays([b.column("doc_id").take(pa.array(some)), lists], names=["doc_id", "found"])

    counts = docs.mapInArrow(count, StructType([docs.schema["doc_id"], StructField("found", ArrayType(IntegerType()))]))
    def scale(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            parts = b.column("all")
            n = np.add.reduceat(parts.flatten().flatten().to_numpy().reshape(-1, bins).astype(float), parts.offsets.to_numpy()[:-1] - parts.offsets[0].as_py(), axis=0) if len(parts) else np.empty((0, bins))
            x = n / np.sqrt((n * n).sum(axis=1))[:, None]
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(parts) + 1, dtype=np.int32) * bins), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), lists], names=["doc_id", "x"])

    # rows of one doc_id are one point
    per = counts.groupBy("doc_id").agg(F.collect_list("found").alias("all")).mapInArrow(scale, StructType([docs.schema["doc_id"], StructField("x", ArrayType(DoubleType()))]))
    return per.select(F.col("doc_id").cast("string").alias("point_id"), "x", "doc_id")


VIEWS: dict[str, tuple[int, Callable[[SparkSession, str], DataFrame]]] = {
    "lineitem2": (2, lineitem2), "orders8": (8, orders8), "star18": (18, star18), "events20": (20, events20), "letters22": (22, letters22), "spend25": (25, spend25),
    "embed50": (50, lambda s, d: embed(s, d, 50)), "hash178": (178, hash178), "events4": (4, events4), "lineitem4": (4, lineitem4), "embed64": (64, embed),
}
EIGHT = ["lineitem2", "orders8", "star18", "events20", "letters22", "spend25", "embed50", "hash178"]
