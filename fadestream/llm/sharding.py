r"""Sharding by sampled splitters: size-weighted key samples, quantile boundaries, range partitioning.

The key of a record is (hash of its text, hash of its id), so equal texts are neighbours. A Poisson sample in which a
record's chance grows with its bytes gives the key quantiles; records are counted exactly by range, and a range that is
overfull is subdivided by the id hash. Shards are stretches of ranges in the order of the key, cut where the bytes counted so far
reach each shard's quantile. Only a text that fills ranges of its own is placed before that, whole, on the least filled shard, and
the quantiles then follow the room that is left; a text larger than a share is placed piece by piece. So copies of one text go to
one shard, unless they are more than a share by themselves. Rows equal in id and text that together overfill a piece can't be told
apart by keys: they are written once with a piece drawn for each row. Counts by range are the only thing the driver sees: their
number is a parameter.

Results for odd input: null text has size 1 and checksum 0; an empty table gives no rows; repeated rows get slots of their
own; a null id is a key like any other; columns named like the new ones are replaced by them.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Stored, text_of

#: Ranges a shard (bounds balance: a range is under two hundredths of a share), records of the sample a range, bytes of a piece.
RANGES, PER_RANGE, PIECE_BYTES = 64, 32, 256 << 20


def _keys() -> list[Column]:
    return [F.xxhash64(text_of()).alias("__h"), F.xxhash64(F.col("doc_id"), F.lit(7)).alias("__g"), (F.octet_length(text_of()).cast("long") + 1).alias("__size")]


def splitters(keys: DataFrame, n_ranges: int, total: int) -> tuple[list[tuple[int, int]], set[int]]:
    """Upper-exclusive boundaries of the ranges from a sample of about n_ranges * PER_RANGE records, the larger the likelier, and
    the hashes of the texts that fill ranges of their own."""
    want = n_ranges * PER_RANGE
    chance = F.least(F.lit(1.0), F.col("__size") * F.lit(want / max(total, 1)))
    unit = F.pmod(F.xxhash64("__h", "__g", F.lit(11)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    sample = keys.where(unit < chance).select("__h", "__g", (F.col("__size") / chance).alias("w")).toPandas().sort_values(["__h", "__g"])
    if sample.empty:
        return [], set()
    h, g, w = sample["__h"].to_numpy(), sample["__g"].to_numpy(), sample["w"].to_numpy()
    at = np.unique(np.searchsorted(np.cumsum(w), np.arange(1, n_ranges) * w.sum() / n_ranges))
    low = np.iinfo(np.int64).min
    at = at[at < len(h)]
    often = Counter(h[at].tolist())
    # a text that attracts one boundary isn't cut; one that attracts more is larger than a range, and is cut by id
    heavy = {x for x, n in often.items() if n > 1}
    cuts = {(x, low) for x in often} | {(x + 1, low) for x in heavy if x < np.iinfo(np.int64).max}
    cuts |= {(int(h[i]), int(g[i])) for i in at.tolist() if int(h[i]) in heavy}
    return sorted(cuts), heavy


def _range_of(cuts: list[tuple[int, int]]):  # noqa: ANN202
    hs, gs = np.array([c[0] for c in cuts], dtype=np.int64), np.array([c[1] for c in cuts], dtype=np.int64)

    @F.arrow_udf("int")
    def place(h: pa.Array, g: pa.Array) -> pa.Array:
        x, y = h.to_numpy(zero_copy_only=False), g.to_numpy(zero_copy_only=False)
        lo, hi = np.searchsorted(hs, x, side="left"), np.searchsorted(hs, x, side="right")
        out = lo.copy()
        for i in np.flatnonzero(hi > lo).tolist():
            out[i] = lo[i] + np.searchsorted(gs[lo[i] : hi[i]], y[i], side="right")
        return pa.array(out.astype(np.int32))

    return place


def shard(docs: DataFrame, n_shards: int = 16) -> DataFrame:
    """docs plus size, text_crc32, shard, slot (gapless from 0 in each shard)."""
    spark = docs.sparkSession
    keys = Stored(docs.select(*_keys()), "keys").df
    total = int(keys.agg(F.sum("__size")).first()[0] or 0)
    cuts, heavy = splitters(keys, n_shards * RANGES, total)
    place = _range_of(cuts)
    counts = keys.groupBy(place("__h", "__g").alias("r")).agg(F.sum("__size").alias("b"), F.count(F.lit(1)).alias("n")).toPandas()
    full = max(1, min(PIECE_BYTES, 2 * total // (n_shards * RANGES)))
    parts = {int(r): int(-(-b // full)) for r, b in zip(counts["r"], counts["b"], strict=True)}
    schema = "r int, subs int"
    subs = spark.createDataFrame([(r, n) for r, n in parts.items()], schema)

    def pieces(df: DataFrame) -> DataFrame:
        cut = df.withColumn("__r", place("__h", "__g")).join(subs, F.col("__r") == F.col("r"))
        return cut.withColumn("__s", F.pmod(F.xxhash64("__g", F.lit(3)), F.col("subs")).cast("int")).drop("r", "subs")

    same = keys.groupBy("__h", "__g").agg(F.sum("__size").alias("b"), F.count(F.lit(1)).alias("n")).where((F.col("n") > 1) & (F.col("b") > full))
    same = same.select("__h", "__g", F.ceil(F.col("b") / full).cast("int").alias("__of")).toPandas()  # fewer than total / full
    new = {"size", "text_crc32", "shard", "slot"}
    own = [c for c in docs.columns if c not in new]
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in own)).alias("__row"), *_keys(), F.crc32(text_of().cast("binary")).alias("text_crc32"))
    tally = [F.sum("__size").alias("b"), F.count(F.lit(1)).alias("n")]
    units = ["__r", "__s", "__p"]
    if same.empty:
        rows = pieces(rows).withColumn("__p", F.lit(0))
        exact = pieces(keys).withColumn("__p", F.lit(0)).groupBy(*units).agg(*tally)
    else:
        many = F.broadcast(spark.createDataFrame(same).select(F.col("__h").alias("mh"), F.col("__g").alias("mg"), "__of"))
        at = (F.col("__h") == F.col("mh")) & (F.col("__g") == F.col("mg"))
        drawn = pieces(rows.join(many, at)).withColumn("__p", 1 + F.pmod(F.xxhash64(F.monotonically_increasing_id(), F.lit(5)), F.col("__of")).cast("int")).drop("mh", "mg", "__of")
        drawn = Stored(drawn, "drawn").df
        rows = pieces(rows.join(many, at, "left_anti")).withColumn("__p", F.lit(0)).unionByName(drawn)
        exact = pieces(keys.join(many, at, "left_anti")).withColumn("__p", F.lit(0)).groupBy(*units).agg(*tally)
        exact = exact.unionByName(drawn.groupBy(*units).agg(*tally))
    table = _deal(exact.toPandas().sort_values(units), cuts, heavy, n_shards, total)
    dealt = spark.createDataFrame(table, "pr int, ps int, pp int, shard int, start long")
    order = Window.partitionBy(*units).orderBy("__h", "__g")
    unit = (F.col("__r") == F.col("pr")) & (F.col("__s") == F.col("ps")) & (F.col("__p") == F.col("pp"))
    rows = rows.join(dealt, unit).withColumn("slot", F.col("start") + F.row_number().over(order) - 1)
    return rows.select(*(F.col("__row").getField(c).alias(c) for c in own), F.col("__size").alias("size"), "text_crc32", "shard", "slot")


def _deal(exact: pd.DataFrame, cuts: list[tuple[int, int]], heavy: set[int], n_shards: int, total: int) -> pd.DataFrame:
    """Pieces of ranges to shards: texts that fill ranges first, largest to least filled, whole where they fit a share; the rest in the order of the key, cut at the quantiles of the room left."""
    share = total / n_shards
    texts: dict[int, list] = {}
    plain: list[tuple] = []
    for row in exact[["__r", "__s", "__p", "b", "n"]].itertuples(index=False, name=None):
        low = cuts[int(row[0]) - 1][0] if row[0] > 0 else None
        if low in heavy:
            texts.setdefault(low, []).append(row)
        else:
            plain.append(row)
    load, shards = np.zeros(n_shards), {}
    units = [u for rows in texts.values() for u in ([rows] if sum(x[3] for x in rows) <= share else [[x] for x in rows])]
    for rows in sorted(units, key=lambda u: (-sum(x[3] for x in u), u[0][:3])):
        s = int(np.argmin(load))
        for row in rows:
            shards[row[:3]] = s
            load[s] += row[3]
    sizes = np.array([x[3] for x in plain], dtype=float)
    room = np.maximum(_water(load, sizes.sum()) - load, 0)
    middle = np.cumsum(sizes) - sizes / 2
    at = np.minimum(np.searchsorted(np.cumsum(room), middle, side="left"), n_shards - 1)
    shards.update((row[:3], int(s)) for row, s in zip(plain, at, strict=True))
    used, out = np.zeros(n_shards, dtype=np.int64), []
    for r, sub, p, _, n in exact[["__r", "__s", "__p", "b", "n"]].itertuples(index=False, name=None):
        s = shards[(r, sub, p)]
        out.append((int(r), int(sub), int(p), s, int(used[s])))
        used[s] += n
    return pd.DataFrame(out, columns=["pr", "ps", "pp", "shard", "start"])


def _water(load: np.ndarray, rest: float) -> float:
    """The level to which the shards are filled when `rest` more bytes are poured on them."""
    least = np.sort(load)
    for k in range(1, len(least) + 1):
        level = (rest + least[:k].sum()) / k
        if k == len(least) or level <= least[k]:
            return float(level)
    return 0.0
