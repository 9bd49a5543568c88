r"""Benchmark decontamination by winnowing.

Of both corpora, each run of `WINDOW` consecutive words is represented by the least of the hashes of its k-word grams, so any
shared run of `WINDOW` words shares a fingerprint. Items shorter than a window are one window each, with k equal to their own
length. The test fingerprints fill a bitmap of bounded size; the scan of the documents keeps the windows whose fingerprint is
marked there, few of them by chance. These are joined with the test windows by fingerprint, and the join compares the windows word
for word, which extends the fingerprint's words to the whole run. Overlapping runs are then added up by document. Neither the
documents nor the benchmark pass through the driver.

Results for odd input: null or wordless texts have no words, no hits and the digest of the empty list; items without
words are ignored; repeated rows are answered row by row; equal item ids count once; an item with a null id hits words but
is not listed; an empty benchmark leaves every document clean; other columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Stored, bitmap, each, marked, slices, without

WINDOW, GRAM = 10, 5
#: Bits of the bitmap for each test window: the share of other fingerprints that pass it is one by that many.
BITS_A_PRINT = 512

_KEEP = bytes(c if chr(c).isdigit() or chr(c).islower() or c >= 128 else c + 32 if 65 <= c <= 90 else 32 for c in range(256))
_MULT = np.uint64(0x9E3779B97F4A7C15)


def words_of(text: str | None) -> list[bytes]:
    """Words of ASCII digits, ASCII letters (lower-cased) and all characters beyond ASCII."""
    return text.encode("utf-8", "surrogatepass").translate(_KEEP).split() if text else []


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def gram_hashes(ids: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of k word numbers."""
    n = len(ids) - k + 1
    if n <= 0:
        return np.empty(0, dtype=np.uint64)
    h = np.zeros(n, dtype=np.uint64)
    for i in range(k):
        h = _mix(h * _MULT + ids[i : i + n].astype(np.uint64))
    return h


def least_grams(hashes: np.ndarray, window: int) -> np.ndarray:
    """The fingerprint of each run of `window` hashes: the least of them."""
    n = len(hashes) - window + 1
    if n <= 0:
        return np.empty(0, dtype=np.uint64)
    least = hashes[:n].copy()
    for i in range(1, window):
        np.minimum(least, hashes[i : i + n], out=least)
    return least


def numbers(words: list[bytes]) -> np.ndarray:
    """A number from 1 up for each word; equal words have equal numbers, and few others share one (windows are compared word for word)."""
    return np.fromiter(map(zlib.crc32, words), dtype=np.int64, count=len(words)) + 1


def fingerprints_of(words: list[bytes], length: int) -> np.ndarray:
    """The winnowed fingerprint of each window of `length` words: the least hash of its grams of GRAM words, of the window itself if it's shorter than WINDOW."""
    gram = GRAM if length == WINDOW else length
    return least_grams(gram_hashes(numbers(words), gram), length - gram + 1).view(np.int64)


def test_windows(benchmark: DataFrame) -> DataFrame:
    """h (fingerprint), w (the window's words), n (how many), items: distinct windows of the items."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 64):
            hs, ws, ns, rows = [], [], [], []
            for i, text in enumerate(b.column(1).to_pylist()):
                if words := words_of(text):
                    n = min(WINDOW, len(words))
                    hs.append(fingerprints_of(words, n))
                    ws += [b" ".join(words[p : p + n]) for p in range(len(words) - n + 1)]
                    ns += [n] * len(hs[-1])
                    rows += [i] * len(hs[-1])
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(hs)), pa.array(ws, pa.binary()), pa.array(ns, pa.int32()), b.column(0).take(pa.array(rows, pa.int32()))], names=["h", "w", "n", "item"])

    kind = benchmark.schema["item_id"].dataType.simpleString()
    found = benchmark.select("item_id", "text").mapInArrow(run, f"h long, w binary, n int, item {kind}")
    return found.groupBy("h", "w", "n").agg(F.collect_set(F.col("item").cast("string")).alias("items"))


test_windows.__test__ = False


def _candidates(docs: DataFrame, lengths: list[int], tests: np.ndarray) -> DataFrame:
    """doc_id, th, n_words, at: the windows (h, w, n, starts) of a document whose fingerprint may be a test's."""
    probe = docs.sparkSession.sparkContext.broadcast(tests)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            n_words, found = [], []
            for text in b.column(2).to_pylist():
                words = words_of(text)
                at: dict[tuple[int, bytes, int], list[int]] = {}
                for n in lengths:
                    prints = fingerprints_of(words, n) if len(words) >= n else np.empty(0, dtype=np.int64)
                    for p in np.flatnonzero(marked(probe.value, _spread(prints))).tolist():
                        at.setdefault((int(prints[p]), b" ".join(words[p : p + n]), n), []).append(p)
                n_words.append(len(words))
                found.append([{"h": h, "w": w, "n": n, "starts": starts} for (h, w, n), starts in at.items()])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(n_words, pa.int64()), pa.array(found, _AT)], names=["doc_id", "th", "n_words", "at"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.xxhash64("text").alias("th"), "text").mapInArrow(run, f"doc_id {kind}, th long, n_words long, at array<struct<h: long, w: binary, n: int, starts: array<int>>>")


_AT = pa.list_(pa.struct([("h", pa.int64()), ("w", pa.binary()), ("n", pa.int32()), ("starts", pa.list_(pa.int32()))]))


def _spread(prints: np.ndarray) -> np.ndarray:
    """Fingerprints are minima, so their leading bits aren't even: mixed once more before they address a bitmap."""
    return _mix(prints.view(np.uint64) * _MULT).view(np.int64)


def _bits(tests: DataFrame, count: int) -> np.ndarray:
    """The bitmap of the test fingerprints: bounded, built by executors (see common.bitmap)."""

    @F.arrow_udf("long")
    def spread(h: pa.Array) -> pa.Array:
        return pa.array(_spread(h.to_numpy(zero_copy_only=False)))

    return bitmap(tests.select(spread("h").alias("h")), count, BITS_A_PRINT, hashed=True)


def _hits(docs: DataFrame, benchmark: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The scan (doc_id, th, n_words, at) and the hits of its documents (doc_id, th, n_hit, items): a row for each document that has any."""
    tests = Stored(test_windows(benchmark), "tests").df
    lengths = [r[0] for r in tests.select("n").distinct().collect()]  # at most WINDOW
    scan = Stored(_candidates(docs, sorted(lengths), _bits(tests, tests.count())), "scan").df
    found = scan.where(F.size("at") > 0).dropDuplicates(["doc_id", "th"]).select("doc_id", "th", F.explode("at").alias("x")).select("doc_id", "th", "x.*")
    joined = Stored(found.join(tests, ["h", "w", "n"]).select("doc_id", "th", "n", "starts", "items"), "hits").df

    @F.arrow_udf("long")
    def covered(n: pa.Array, starts: pa.Array) -> pa.Array:
        sizes = []
        for ns, ss in zip(each(n), each(starts), strict=True):
            ends = np.concatenate([np.array(s) + k for k, s in zip(ns, ss, strict=True)])
            begin = np.concatenate([np.array(s) for s in ss])
            order = np.argsort(begin, kind="stable")
            begin, reach = begin[order], np.maximum.accumulate(ends[order])
            sizes.append(int((reach - np.maximum(begin, np.concatenate([[0], reach[:-1]]))).clip(0).sum()))
        return pa.array(sizes, pa.int64())

    spans = joined.groupBy("doc_id", "th").agg(F.collect_list(F.struct("n", "starts")).alias("x"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    return scan, spans.select("doc_id", "th", covered(F.col("x.n"), F.col("x.starts")).alias("n_hit"), "items")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of docs without a benchmark window, all columns; only texts that may hold one are exchanged."""
    _, hits = _hits(docs, benchmark)
    return without(docs, Stored(hits.select("doc_id", "th"), "hit").df)


def contamination(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, n_words, n_hit, items (list of item ids, sorted as strings), items_sha256, contaminated: a row per input row."""
    scan, hits = _hits(docs, benchmark)
    hits = hits.select(F.col("doc_id").alias("id"), F.col("th").alias("t"), "n_hit", "items")
    none = F.array().cast("array<string>")
    clean = scan.where(F.size("at") == 0).select("doc_id", "n_words", F.lit(0).cast("long").alias("n_hit"), none.alias("items"))
    rest = scan.where(F.size("at") > 0).join(hits, F.col("doc_id").eqNullSafe(F.col("id")) & (F.col("th") == F.col("t")), "left")
    rest = rest.select("doc_id", "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.coalesce("items", none).alias("items"))
    rows = clean.unionByName(rest)
    return rows.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"), "items"
    )


__all__ = ["GRAM", "WINDOW", "contamination", "drop_contaminated", "gram_hashes", "least_grams", "test_windows", "words_of"]
