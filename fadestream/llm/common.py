"""Shared plumbing of the training-data operators: shared-folder tables, safe column names, hashes."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_WRITTEN: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or a local one where that is unset (tests)."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    known = spark.sparkContext.getCheckpointDir()
    if known:
        return known.rstrip("/")
    spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="fadestream-"))
    return spark.sparkContext.getCheckpointDir().rstrip("/")


def remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def _sweep() -> None:
    for spark, path in _WRITTEN:
        try:
            remove(spark, path)
        except Exception:  # noqa: BLE001  the session may be gone at exit
            return


atexit.register(_sweep)


#: Bytes of an Arrow batch in the operators' own jobs: executor and worker each hold a batch whole. A session that sets a value keeps it.
BATCH, _BATCH_CONF, _BATCH_DEFAULT = "8m", "spark.sql.execution.arrow.maxBytesPerBatch", "67108864b"


@contextlib.contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    """Jobs that run inside send texts to Python in batches of BATCH bytes; results don't depend on it."""
    if spark.conf.get(_BATCH_CONF, _BATCH_DEFAULT) != _BATCH_DEFAULT:
        yield
        return
    spark.conf.set(_BATCH_CONF, BATCH)
    try:
        yield
    finally:
        spark.conf.unset(_BATCH_CONF)


class Stored:
    """A written intermediate: survives lost executors, cuts lineage, is dropped when no longer needed."""

    def __init__(self, df: DataFrame, label: str, by: str | None = None, **options: str) -> None:
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark)}/{label}-{uuid.uuid4().hex}"
        writer = df.write.options(**options)
        with small_batches(self.spark):
            (writer.partitionBy(by) if by else writer).parquet(self.path)
        self.schema = df.schema
        _WRITTEN.append((self.spark, self.path))

    @property
    def df(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        remove(self.spark, self.path)
        _WRITTEN[:] = [x for x in _WRITTEN if x[1] != self.path]


def stored(df: DataFrame, label: str) -> DataFrame:
    return Stored(df, label).df


def text_of(col: str = "text") -> Column:
    """Null counts as the empty text."""
    return F.coalesce(F.col(col), F.lit(""))


def tidy() -> None:
    """Give freed memory back to the system: idle workers live on and would keep what their largest texts took."""
    pa.default_memory_pool().release_unused()
    ctypes.CDLL(None).malloc_trim(0)


def slices(batches: Iterator[pa.RecordBatch], rows: int = 256) -> Iterator[pa.RecordBatch]:
    """The same rows in small parts, so what a worker makes of them stays small however many texts come at once."""
    for b in batches:
        for lo in range(0, b.num_rows, rows):
            yield b.slice(lo, rows)
        del b
        tidy()


def each(texts: pa.Array, rows: int = 256) -> Iterator[str | None]:
    """The values of an Arrow column one by one, a few in memory at a time."""
    for lo in range(0, len(texts), rows):
        yield from texts.slice(lo, rows).to_pylist()


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


#: Bits of a key filter: sixteen a key by default, never over 2**28 (32 MB to broadcast); a fuller filter lets more rows pass, none fewer.
FILTER_BITS_MAX, FILTER_BLOCK = 1 << 28, 13


def key_filter(keys: DataFrame, count: int, bits_a_key: int = 16) -> Callable[..., Column]:
    """A test that is true for every key in `keys` and for few others: rows it rejects need no join and no exchange.

    Executors deal the set bits by blocks and send each block once, so the driver gets the bitmap and no more; its size is bounded
    whatever the number of keys.
    """
    probe = keys.sparkSession.sparkContext.broadcast(bitmap(keys, count, bits_a_key))

    @F.arrow_udf("boolean")
    def passes(key: pa.Array) -> pa.Array:
        return pa.array(marked(probe.value, key.to_numpy(zero_copy_only=False)))

    return lambda *cols: passes(F.xxhash64(*cols))


class Chosen:
    """The texts of the documents whose id a key filter lets pass (all of `ids` and few others).

    The process that works on a text filters it too: a filter of its own before would be a second process for each task, which lives on
    for the rest of the session, and would carry every text through Spark's memory once more.
    """

    def __init__(self, docs: DataFrame, ids: DataFrame, count: int) -> None:
        self.rows = docs.select(F.xxhash64("doc_id").alias("at"), "text")
        self.bits = docs.sparkSession.sparkContext.broadcast(bitmap(ids, count, 16))

    def map(self, make: Callable[[Iterator[list[bytes | None]]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
        """make: the texts of a task (UTF-8), some at a time -> batches of the schema."""
        bits = self.bits

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            def texts() -> Iterator[list[bytes | None]]:
                for b in slices(batches):
                    part = b.column(1).filter(pa.array(marked(bits.value, b.column(0).to_numpy(zero_copy_only=False))))
                    if len(part):
                        yield part.cast(pa.binary()).to_pylist()

            return make(texts())

        return self.rows.mapInArrow(run, schema)


def bitmap(keys: DataFrame, count: int, bits_a_key: int = 16, hashed: bool = False) -> np.ndarray:
    """Packed bits, a power of two of them, set at the hashes of the keys (or at the keys, where they are hashes)."""
    bits = min(FILTER_BITS_MAX, max(1 << 16, 1 << int(bits_a_key * count).bit_length()))
    size = (1 << FILTER_BLOCK) // 8

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        for b in batches:
            block, at = (c.to_numpy(zero_copy_only=False) for c in b.columns)
            order = np.argsort(block, kind="stable")
            block, at = block[order], at[order]
            cuts = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), len(block)]
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                if hi > lo:
                    held.setdefault(int(block[lo]), np.zeros(size * 8, dtype=bool))[at[lo:hi] & (size * 8 - 1)] = True
        for block, hit in held.items():
            yield pa.RecordBatch.from_pydict({"block": pa.array([block], pa.int64()), "m": [np.packbits(hit).tobytes()]})

    key = F.col(keys.columns[0]) if hashed else F.xxhash64(*keys.columns)
    at = keys.select(key.bitwiseAND(F.lit(bits - 1)).alias("at"))
    dealt = at.select(F.shiftright("at", FILTER_BLOCK).alias("block"), "at").repartition("block")
    whole = np.zeros(bits // 8, dtype=np.uint8)
    for block, m in dealt.mapInArrow(fold, "block long, m binary").collect():
        whole[block * size : (block + 1) * size] = np.frombuffer(m, dtype=np.uint8)
    return whole


def marked(bits: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    at = hashes & np.int64(len(bits) * 8 - 1)
    return (bits[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1 == 1


def without(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """The rows of docs whose (doc_id, hash of the text) isn't in gone (doc_id, th; stored): only rows that may be in it are exchanged."""
    keyed = docs.withColumn("__th", F.xxhash64("text"))
    hit = key_filter(gone.select("doc_id", "th"), gone.count())(F.col("doc_id"), F.col("__th"))
    g = gone.select(F.col("doc_id").alias("__id"), F.col("th").alias("__gone"))
    left = keyed.where(hit).join(g, F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("__th") == F.col("__gone")), "left_anti")
    return keyed.where(~hit).unionByName(left).drop("__th")
