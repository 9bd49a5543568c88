r"""Substring deduplication over sliding sentence spans.

From every sentence the shortest run of at least two sentences and MIN_WORDS words is hashed (128 bits), forwards and
backwards, so the runs depend on nothing but what they hold. All runs are joined globally; every run but the first of its
kind (least doc_id, then text hash, then position) marks its sentences, and marked sentences are removed. A passage that
repeats keeps exactly its first copy; copies inside one document count too.

Only run hashes are exchanged. Texts are exchanged only for documents that lose something: a bounded bit filter passes the
others through. Results for odd input: null stays null and has no sentences; a text with fewer than two sentences or MIN_WORDS words has
no runs and stays whole; rows equal in doc_id and text are one document, shown as often as they occur; a null doc_id
orders last; an empty table gives no rows; other columns stay as
they are, but for n_sentences and n_removed, which are replaced.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Stored, key_filter, slices

MIN_SENTENCES, MIN_WORDS = 2, 20

_END = re.compile(r"""[.!?…]+["'”’)\]]*\s+|\n\s*""")


def sentences(text: str) -> list[str]:
    """Pieces that make up the text, each a sentence or a line with the white space after it."""
    cuts = [m.end() for m in _END.finditer(text)]
    edges = [0, *cuts] if cuts and cuts[-1] == len(text) else [0, *cuts, len(text)]
    return [text[a:b] for a, b in zip(edges, edges[1:], strict=False)]


def runs(pieces: list[str], min_sentences: int, min_words: int) -> list[tuple[int, int, bytes]]:
    """(first, end, hash) of the shortest long-enough run from each sentence, forwards and backwards; blank pieces don't count."""
    words = [p.split() for p in pieces]
    at = [i for i, w in enumerate(words) if w]
    size = [len(words[i]) for i in at]
    norm = [" ".join(words[i]) for i in at]
    found = set()
    end, total = 0, 0
    for i in range(len(at)):  # two pointers: the run [i, end)
        while end < len(at) and (total < min_words or end - i < min_sentences):
            total += size[end]
            end += 1
        if total < min_words or end - i < min_sentences:
            break
        found.add((i, end))
        total -= size[i]
    begin, total = len(at), 0
    for j in range(len(at), 0, -1):
        while begin > 0 and (total < min_words or j - begin < min_sentences):
            begin -= 1
            total += size[begin]
        if total < min_words or j - begin < min_sentences:
            break
        found.add((begin, j))
        total -= size[j - 1]
    return [(at[i], at[j - 1] + 1, xxhash.xxh3_128_digest("\n".join(norm[i:j]).encode("utf-8", "surrogatepass"))) for i, j in sorted(found)]


def _spans(docs: DataFrame, min_sentences: int, min_words: int) -> DataFrame:
    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            rows, first, end, hashes = [], [], [], []
            for i, text in enumerate(b.column(2).to_pylist()):
                if text:
                    for x, y, h in runs(sentences(text), min_sentences, min_words):
                        rows.append(i)
                        first.append(x)
                        end.append(y)
                        hashes.append(h)
            take = pa.array(rows, pa.int32())
            yield pa.RecordBatch.from_arrays(
                [pa.array(hashes, pa.binary()), b.column(0).take(take), b.column(1).take(take), pa.array(first, pa.int32()), pa.array(end, pa.int32())], names=["h", "doc_id", "th", "first", "end"]
            )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.xxhash64("text").alias("th"), "text").mapInArrow(emit, f"h binary, doc_id {kind}, th long, first int, end int")


def substring_dedup(docs: DataFrame, min_sentences: int = MIN_SENTENCES, min_words: int = MIN_WORDS) -> DataFrame:
    """docs with text cleaned, plus n_sentences and n_removed (long): a row per input row."""
    spans = Stored(_spans(docs, min_sentences, min_words), "spans").df
    order = F.struct(F.col("doc_id").isNull().alias("z"), "doc_id", "th", "first")
    kinds = spans.groupBy("h").agg(F.min(order).alias("least"), F.max(order).alias("most")).where("least <> most").select("h", "least")
    kinds = Stored(kinds, "kinds").df  # so that a hot run's side of the join can be split
    later = spans.join(kinds, "h").where(order != F.col("least"))
    marks = later.groupBy("doc_id", "th").agg(F.collect_set(F.struct("first", "end")).alias("marked"))
    marks = Stored(marks, "marks").df
    may_hit = key_filter(marks.select("doc_id", "th"), marks.count())

    docs = docs.drop("n_sentences", "n_removed")
    own = [F.col(f"`{c}`") for c in docs.columns]
    keyed = docs.select(F.struct(*own).alias("__row"), F.xxhash64("text").alias("__th"))
    hit = may_hit(F.col("__row.doc_id"), F.col("__th"))
    on = F.col("__row.doc_id").eqNullSafe(F.col("doc_id")) & (F.col("__th") == F.col("th"))
    touched = keyed.where(hit).join(marks, on, "left").select("__row", "marked")
    rest = keyed.where(~hit).select("__row", F.lit(None).cast(marks.schema["marked"].dataType).alias("marked"))
    both = touched.unionByName(rest)
    names, at = list(docs.columns), docs.columns.index("text")

    def clean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            fields = b.column(0).flatten()
            texts, total, removed = [], [], []
            for t, marked in zip(fields[at].to_pylist(), b.column(1).to_pylist(), strict=True):
                pieces = sentences(t) if t else []
                gone = {i for s in marked or () for i in range(s["first"], s["end"]) if pieces[i].strip()}
                texts.append("".join(p for i, p in enumerate(pieces) if i not in gone) if gone else t)
                total.append(sum(bool(p.strip()) for p in pieces))
                removed.append(len(gone))
            fields[at] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays([*fields, pa.array(total, pa.int64()), pa.array(removed, pa.int64())], names=[*names, "n_sentences", "n_removed"])

    new = T.StructType([*(f for f in docs.schema.fields), T.StructField("n_sentences", T.LongType()), T.StructField("n_removed", T.LongType())])
    return both.mapInArrow(clean, new)
