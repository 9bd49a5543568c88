r"""SimHash near-duplicates found through anchor points of a covering code.

Fingerprints are cut into blocks of odd length; the anchors are the words that are constant on each block (a product of
repetition codes: perfect, so every word has one nearest anchor). If two fingerprints differ in at most T bits, some word
lies within ceil(T/2) bits of one and floor(T/2) bits of the other, so both are within that many bits plus the covering
radius of that word's anchor. Each fingerprint is therefore replicated to every anchor that a word within ceil(T/2) bits
of it decodes to, fingerprints that share an anchor are compared, and no pair is missed. The blocks shrink as the number
of distinct fingerprints grows, which keeps the mean load of an anchor constant. Where fingerprints crowd, an anchor may still
attract many: those of anchors over HOT are dealt anew by the finest code, whose anchors are all words. There no anchor holds more
fingerprints than there are words within ceil(T/2) bits (65 for T = 2), however the fingerprints lie. What leaves an anchor is a
forest (at most one link a fingerprint), never all pairs.

Results for odd input: null text counts as empty; a text without words has fingerprint zero and links like any other;
fewer words than the shingle length make one shingle of all words; repeated rows share a component; a row whose doc_id is
null takes part and shows the component of its fingerprint; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Chosen, Stored, key_filter, slices, small_batches, without
from .components import components

#: Shingles whose bits are unpacked at once (64 bytes each).
CHUNK = 1 << 18
#: Fingerprints an anchor should hold on average; decides the length of the blocks.
LOAD = 64
#: Fingerprints from which an anchor's are dealt anew by the finest code.
HOT = 4096


def shingle_hashes(text: bytes, k: int, seed: int = 42) -> list[int]:
    """XXH64 of each run of k words, repeats included."""
    words = text.lower().split()
    if len(words) <= k:
        return [xxhash.xxh64_intdigest(b" ".join(words), seed)] if words else []
    h = xxhash.xxh64_intdigest
    line = b" ".join(words)
    at = np.flatnonzero(np.frombuffer(line, dtype=np.uint8) == 32).tolist()
    starts, ends = [0, *(x + 1 for x in at)], [*at, len(line)]
    return [h(line[a:b], seed) for a, b in zip(starts, ends[k - 1 :], strict=False)]


def majority(hashes: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """One fingerprint for each run of hashes: a bit is set if it is set in more than half of the run."""
    out = np.zeros(len(sizes), dtype=np.uint64)
    ends = np.cumsum(sizes)
    lo = 0
    while lo < len(sizes):
        first = ends[lo] - sizes[lo]
        hi = max(lo + 1, int(np.searchsorted(ends, first + CHUNK, side="right")))
        part, some = sizes[lo:hi], np.flatnonzero(sizes[lo:hi])
        if len(some):
            counts = np.zeros((len(some), 64), dtype=np.int64)
            begin, span = np.concatenate([[0], np.cumsum(part[some])[:-1]]), int(part.sum())
            if len(some) == 1:  # one very long text: in slices
                for i in range(0, span, CHUNK):
                    counts[0] += _bits(hashes[first + i : first + min(span, i + CHUNK)]).sum(axis=0, dtype=np.int64)
            else:
                counts = np.add.reduceat(_bits(hashes[first : first + span]), begin, axis=0, dtype=np.int32)
            packed = np.packbits(counts * 2 > part[some][:, None], axis=1)
            out[lo + some] = np.frombuffer(packed.tobytes(), dtype=">u8")
        lo = hi
    return out


def _bits(h: np.ndarray) -> np.ndarray:
    return np.unpackbits(h.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)


def prints_of(texts: list[bytes | None], k: int = 3, seed: int = 42) -> np.ndarray:
    """The fingerprint of each text, as a signed number."""
    lists = [shingle_hashes(t, k, seed) if t else [] for t in texts]
    sizes = np.array([len(x) for x in lists], dtype=np.int64)
    flat = np.fromiter((h for x in lists for h in x), dtype=np.uint64, count=int(sizes.sum()))
    return majority(flat, sizes).view(np.int64)


def fingerprints(docs: DataFrame, k: int = 3, seed: int = 42) -> DataFrame:
    """doc_id, fp (long, the 64 bits as a signed number)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(prints_of(b.column(1).cast(pa.binary()).to_pylist(), k, seed))], names=["doc_id", "fp"])

    return docs.select("doc_id", "text").mapInArrow(run, docs.select("doc_id").schema.add("fp", "long"))


def block_lengths(n: int, bits: int = 64, reach: int = 1) -> list[int]:
    """Odd block lengths that sum to bits: the longest for which an anchor holds about LOAD of n fingerprints; single bits at the end of the scale."""
    tries = []
    for length in (15, 13, 11, 9, 7, 5):
        whole, rest = divmod(bits, length)
        tries.append([length] * whole + ([rest] if rest % 2 else [rest - 1, 1] if rest else []))
    tries += [[3] * m + [1] * (bits - 3 * m) for m in range(bits // 3, -1, -1)]
    for blocks in tries:
        turned = sum({1: 1.0, 3: 0.75, 5: 0.63, 7: 0.55}.get(x, 0.5) for x in blocks)
        if n * (1 + turned) ** reach <= LOAD * 2.0 ** len(blocks):
            return blocks
    return tries[-1]


def anchors_of(fps: np.ndarray, blocks: list[int], reach: int) -> tuple[np.ndarray, np.ndarray]:
    """(index into fps, anchor) for every anchor that a word within reach bits of the fingerprint decodes to."""
    anchor = np.zeros(len(fps), dtype=np.uint64)
    need = np.empty((len(blocks), len(fps)), dtype=np.int64)  # flips that turn a block's majority
    shift = 0
    for i, length in enumerate(blocks):
        ones = np.bitwise_count((fps >> np.uint64(shift)) & np.uint64((1 << length) - 1)).astype(np.int64)
        up = ones > length // 2
        anchor |= up.astype(np.uint64) << np.uint64(i)
        need[i] = np.where(up, ones - length // 2, length // 2 + 1 - ones)
        shift += length
    rows, out = [np.arange(len(fps))], [anchor]
    for size in range(1, reach + 1):
        for group in combinations(range(len(blocks)), size):
            hit = np.flatnonzero(sum(need[i] for i in group) <= reach)
            if len(hit):
                rows.append(hit)
                out.append(anchor[hit] ^ np.uint64(sum(1 << i for i in group)))
    return np.concatenate(rows), np.concatenate(out).view(np.int64)


def forest(fps: np.ndarray, threshold: int, rows: int = 1 << 20) -> tuple[np.ndarray, np.ndarray]:
    """Links (a, b) of fingerprints that make the same components as all pairs within threshold bits: one less than each component has."""
    n = len(fps)
    root = np.arange(n)

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    left, right = [], []
    step = max(1, rows // max(n, 1))
    for lo in range(0, n - 1, step):
        near = np.bitwise_count(fps[lo : lo + step, None] ^ fps[None, lo:]) <= threshold
        a, b = np.nonzero(near)
        use = b > a
        for i, j in zip((a[use] + lo).tolist(), (b[use] + lo).tolist(), strict=True):
            x, y = find(i), find(j)
            if x != y:
                root[max(x, y)] = min(x, y)
                left.append(i)
                right.append(j)
    return fps[left], fps[right]


def leaders(fps: np.ndarray, threshold: int, rows: int = 1 << 22) -> tuple[np.ndarray, np.ndarray]:
    """(leader, follower): the best connected fingerprints lead, no two of them within threshold; each other one follows all leaders near it."""
    n = len(fps)
    degree = np.zeros(n, dtype=np.int64)
    step = max(1, rows // n)
    for lo in range(0, n, step):
        degree[lo : lo + step] = (np.bitwise_count(fps[lo : lo + step, None] ^ fps[None, :]) <= threshold).sum(axis=1)
    heads = np.empty(0, dtype=np.uint64)
    for i in np.lexsort((fps, -degree)).tolist():
        if degree[i] < 2:
            break
        if not len(heads) or np.bitwise_count(heads ^ fps[i]).min() > threshold:
            heads = np.append(heads, fps[i])
    a, b = [], []
    for head in heads:
        near = fps[(np.bitwise_count(fps ^ head) <= threshold) & (fps != head)]
        a.append(np.full(len(near), head))
        b.append(near)
    empty = np.empty(0, dtype=np.uint64)
    return (np.concatenate(a), np.concatenate(b)) if a else (empty, empty)


def anchor_links(fps: DataFrame, threshold: int, count: int, bits: int = 64, link: Callable = forest) -> DataFrame:
    """fps: distinct (family, fp) -> (family, a, b), the links that `link` makes of the fingerprints at each anchor."""
    reach = (threshold + 1) // 2

    def spread(df: DataFrame, blocks: list[int]) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                family = b.column(0).to_numpy(zero_copy_only=False)
                values = b.column(1).to_numpy(zero_copy_only=False).view(np.uint64)
                for lo in range(0, len(values), 10_000):
                    rows, anchor = anchors_of(values[lo : lo + 10_000], blocks, reach)
                    yield pa.RecordBatch.from_arrays([pa.array(family[lo + rows]), pa.array(anchor), pa.array(values[lo + rows].view(np.int64))], names=["family", "anchor", "fp"])

        return df.select("family", "fp").mapInArrow(run, "family int, anchor long, fp long")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = (np.empty(0, dtype=np.int32), np.empty(0, dtype=np.int64), np.empty(0, dtype=np.uint64))

        def linked(family: np.ndarray, anchor: np.ndarray, values: np.ndarray) -> Iterator[pa.RecordBatch]:
            cuts = np.flatnonzero((np.diff(anchor) != 0) | (np.diff(family) != 0)) + 1
            out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
            size = 0
            for lo, hi in zip([0, *cuts.tolist()], [*cuts.tolist(), len(values)], strict=True):
                if hi - lo > 1:
                    x, y = link(values[lo:hi], threshold)
                    if len(x):
                        out.append((np.full(len(x), family[lo]), x, y))
                        size += len(x)
                if out and (size > 50_000 or hi == len(values)):
                    f, x, y = (np.concatenate(z) for z in zip(*out, strict=True))
                    yield pa.RecordBatch.from_arrays([pa.array(f, pa.int32()), pa.array(x.view(np.int64)), pa.array(y.view(np.int64))], names=["family", "a", "b"])
                    out, size = [], 0
            if out:
                f, x, y = (np.concatenate(z) for z in zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(f, pa.int32()), pa.array(x.view(np.int64)), pa.array(y.view(np.int64))], names=["family", "a", "b"])

        for batch in batches:
            cols = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            family, anchor, values = (np.concatenate(z) for z in zip(held, (cols[0], cols[1], cols[2].view(np.uint64)), strict=True))
            if not len(anchor):
                continue
            last = int(np.flatnonzero((anchor != anchor[-1]) | (family != family[-1]))[-1]) + 1 if ((anchor != anchor[-1]) | (family != family[-1])).any() else 0
            if last:
                yield from linked(family[:last], anchor[:last], values[:last])
            held = (family[last:], anchor[last:], values[last:])
        if len(held[0]):
            yield from linked(*held)

    def met(dealt: DataFrame) -> DataFrame:
        return dealt.repartition("family", "anchor").sortWithinPartitions("family", "anchor").mapInArrow(compare, "family int, a long, b long")

    dealt = Stored(spread(fps, block_lengths(count, bits, reach)), "anchors").df
    hot = Stored(dealt.groupBy("family", "anchor").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > HOT).select("family", "anchor"), "hot").df
    if hot.isEmpty():
        return met(dealt)
    crowded = dealt.join(hot, ["family", "anchor"], "left_semi").select("family", "fp").distinct()
    return met(dealt.join(hot, ["family", "anchor"], "left_anti")).unionByName(met(spread(crowded, [1] * bits)))


def simhash_classes(docs: DataFrame, k: int = 3, threshold: int = 2, seed: int = 42) -> DataFrame:
    """doc_id, fp, component_id (the least doc_id reachable over links of at most threshold bits): one row per input row."""
    prints = Stored(fingerprints(docs, k, seed), "prints").df
    groups = Stored(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), "groups").df
    joined = components(anchor_links(groups.select(F.lit(0).alias("family"), "fp"), threshold, groups.count()), "a", "b")
    roots = groups.join(joined.select(F.col("node").alias("fp"), "root"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    names = roots.groupBy("root").agg(F.min("least").alias("component_id"))
    classes = roots.join(names, "root").select("fp", "component_id")
    return prints.join(classes, "fp")


#: Words of a shingle and similarity that count for near copies.
SHINGLE, SIMILAR = 5, 0.8
#: Bits in which the fingerprints of two texts may differ that are compared first.
CLOSE = 2
#: Texts of a block of a large group (two blocks are compared at a time); groups of up to PAIRED texts are joined pair by pair.
BLOCK, PAIRED = 256, 32
#: Cells of the frequency sketch, a byte each to broadcast. It only orders shingles: fewer cells cost time, never a pair.
CELLS_MAX = 1 << 24


def _texts(docs: DataFrame) -> DataFrame:
    """doc_id, th (hash of the text), key (128-bit hash of the lower-cased words), id (its first half)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            keys = [_key(t) for t in b.column(2).cast(pa.binary()).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[:2], pa.array(keys, pa.binary()), pa.array([_half(k) for k in keys], pa.int64())], names=["doc_id", "th", "key", "id"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.xxhash64("text").alias("th"), "text").mapInArrow(run, f"doc_id {kind}, th long, key binary, id long")


def _key(text: bytes | None) -> bytes:
    return xxhash.xxh3_128_digest(b" ".join((text or b"").lower().split()))


def _half(key: bytes) -> int:
    return int.from_bytes(key[:8], "big", signed=True)


def _set(text: bytes | None) -> np.ndarray:
    return np.unique(np.array(shingle_hashes(text or b"", SHINGLE), dtype=np.uint64))


def _shingled(docs: Chosen) -> DataFrame:
    """key, sh (the set of shingle hashes)."""

    def run(parts: Iterator[list[bytes | None]]) -> Iterator[pa.RecordBatch]:
        for texts in parts:
            yield pa.RecordBatch.from_arrays([pa.array([_key(t) for t in texts], pa.binary()), pa.array([_set(t).view(np.int64) for t in texts], pa.list_(pa.int64()))], names=["key", "sh"])

    return docs.map(run, "key binary, sh array<long>")


def _printed(docs: Chosen) -> DataFrame:
    """key, fp: the fingerprint of each text."""

    def run(parts: Iterator[list[bytes | None]]) -> Iterator[pa.RecordBatch]:
        for texts in parts:
            yield pa.RecordBatch.from_arrays([pa.array([_key(t) for t in texts], pa.binary()), pa.array(prints_of(texts))], names=["key", "fp"])

    return docs.map(run, "key binary, fp long").dropDuplicates(["key"])


def _met(docs: Chosen) -> DataFrame:
    """a, b: texts whose fingerprints differ in at most CLOSE bits, found at their anchors: a forest of each group, not all its pairs."""
    prints = Stored(_printed(docs), "printed").df
    groups = Stored(prints.groupBy("fp").agg(F.min("key").alias("head"), F.count(F.lit(1)).alias("n")), "heads").df
    close = anchor_links(groups.select(F.lit(0).alias("family"), "fp"), CLOSE, groups.count())
    head = lambda x: groups.select(F.col("fp").alias(x), F.col("head").alias(f"h{x}"))
    near = close.join(head("a"), "a").join(head("b"), "b").select("ha", "hb")
    same = prints.join(groups.where("n > 1"), "fp").where("key <> head").select(F.col("head").alias("ha"), F.col("key").alias("hb"))
    return near.union(same).select(F.least("ha", "hb").alias("a"), F.greatest("ha", "hb").alias("b")).distinct()


def _sets_of(docs: DataFrame, texts: DataFrame, ends: DataFrame, label: str) -> DataFrame:
    """key, sh for the texts of ends (key): only documents that may hold one are shingled."""
    ids = Stored(texts.join(ends, "key").select(F.col("least").alias("doc_id")), f"{label}-ends").df
    return Stored(_shingled(Chosen(docs, ids, ids.count())).dropDuplicates(["key"]), label).df


def _frequencies(docs: Chosen, cells: int) -> np.ndarray:
    """About how many texts hold a shingle of each cell, on a log scale; counted by task, added up by executors."""
    part = 1 << 16

    def count(parts: Iterator[list[bytes | None]]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(cells, dtype=np.uint8)
        for texts in parts:
            sets = [_set(t) for t in texts]
            at, n = np.unique(np.concatenate(sets) & np.uint64(cells - 1), return_counts=True)
            seen[at] = np.minimum(seen[at] + n, 255)
        for lo in range(0, cells, part):
            if seen[lo : lo + part].any():
                yield pa.RecordBatch.from_pydict({"block": pa.array([lo], pa.int64()), "n": [seen[lo : lo + part].tobytes()]})

    def total(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for b in batches:
            for lo, n in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                sums[lo] = sums.get(lo, 0) + np.frombuffer(n, dtype=np.uint8).astype(np.int64)
        for lo, n in sums.items():
            yield pa.RecordBatch.from_pydict({"block": pa.array([lo], pa.int64()), "n": [np.minimum(8 * np.log2(1 + n), 255).astype(np.uint8).tobytes()]})

    out = np.zeros(cells, dtype=np.uint8)
    kind = "block long, n binary"
    counts = docs.map(count, kind).repartition("block").mapInArrow(total, kind)
    with small_batches(counts.sparkSession):
        for lo, n in counts.collect():
            out[lo : lo + part] = np.frombuffer(n, dtype=np.uint8)
    return out


def _prefixes(docs: Chosen, cells: int) -> DataFrame:
    """h, id, size, pos (place from rare to frequent): the rarest shingles of each text, so many that two texts of similarity SIMILAR share one whatever the edit."""
    probe = docs.rows.sparkSession.sparkContext.broadcast(_frequencies(docs, cells))

    def run(parts: Iterator[list[bytes | None]]) -> Iterator[pa.RecordBatch]:
        for texts in parts:
            ids, kept, sizes, places = [], [], [], []
            for t in texts:
                sh = _set(t)
                if len(sh):
                    n = len(sh) - math.ceil(SIMILAR * len(sh) - 1e-9) + 1
                    kept.append(sh[np.lexsort((sh, probe.value[sh & np.uint64(cells - 1)]))[:n]])
                    ids.append(np.full(n, _half(_key(t))))
                    sizes.append(np.full(n, len(sh), dtype=np.int32))
                    places.append(np.arange(n, dtype=np.int32))
            if kept:
                cols = [np.concatenate(kept).view(np.int64), *(np.concatenate(x) for x in (ids, sizes, places))]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["h", "id", "size", "pos"])

    return docs.map(run, "h long, id long, size int, pos int")


def _verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Those of the pairs (a, b) whose whole sets are similar."""
    both = pairs.join(sets.select(F.col("key").alias("a"), F.col("sh").alias("sa")), "a").join(sets.select(F.col("key").alias("b"), F.col("sh").alias("sb")), "b")
    shared = F.size(F.array_intersect("sa", "sb"))
    return both.where(shared >= SIMILAR * (F.size("sa") + F.size("sb") - shared)).select("a", "b")


def close_pairs(left: list[np.ndarray], right: list[np.ndarray], columns: int = 1 << 22) -> np.ndarray:
    """left x right: which sets are similar, by matrix products over the shingles that occur twice."""
    sizes = np.array([len(x) for x in [*left, *right]])
    _, col, n = np.unique(np.concatenate([*left, *right]), return_inverse=True, return_counts=True)
    row, use = np.repeat(np.arange(len(sizes)), sizes), n[col] > 1
    row, col = row[use], (np.cumsum(n > 1) - 1)[col[use]]
    shared = np.zeros((len(left), len(right)))
    step = max(1, columns // len(sizes))
    order = np.argsort(col, kind="stable")
    row, col = row[order], col[order]
    for lo in range(0, int(col[-1]) + 1 if len(col) else 0, step):
        a, b = np.searchsorted(col, (lo, lo + step))
        held = np.zeros((len(sizes), step), dtype=np.float32)
        held[row[a:b], col[a:b] - lo] = 1
        shared += held[: len(left)] @ held[len(left) :].T
    return shared >= SIMILAR * (sizes[: len(left), None] + sizes[None, len(left) :] - shared)


def _compared(t: pa.Table) -> pa.Table:
    """Two blocks (or one with itself) -> links (a, b) between texts of different roots, at most one less than there are texts."""
    keys, roots, block = t["key"].to_pylist(), t["root"].to_pylist(), t["block"].to_pylist()
    flat = t["sh"].combine_chunks()
    ends = flat.offsets.to_numpy()
    values = flat.values.to_numpy(zero_copy_only=False)
    sets = [values[x:y] for x, y in zip(ends, ends[1:], strict=False)]
    i, j = t["i"][0].as_py(), t["j"][0].as_py()
    left, right = [k for k, b in enumerate(block) if b == i], [k for k, b in enumerate(block) if b == j]
    a, b = [], []
    if left and right:
        number = {r: k for k, r in enumerate(dict.fromkeys(roots))}
        at = np.array([number[r] for r in roots])
        root = list(range(len(number)))

        def find(k: int) -> int:
            while root[k] != k:
                root[k] = root[root[k]]
                k = root[k]
            return k

        hit = close_pairs([sets[k] for k in left], [sets[k] for k in right]) & (at[left][:, None] != at[right][None, :])
        for p, q in zip(*(z.tolist() for z in np.nonzero(hit)), strict=True):
            x, y = find(at[left[p]]), find(at[right[q]])
            if x != y:
                root[max(x, y)] = min(x, y)
                a.append(keys[left[p]])
                b.append(keys[right[q]])
    return pa.table({"a": pa.array(a, pa.binary()), "b": pa.array(b, pa.binary())})


def _unsettled(many: DataFrame, joined: DataFrame, sets: DataFrame) -> DataFrame | None:
    """Links (a, b) that large groups of texts (h, key) still lack, given the components joined (node, root) so far; None where all groups are whole.

    Groups that overlap make one field of texts, dealt by hash into blocks; each two blocks meet in one task, so a pair costs a
    place in a matrix and no row.
    """
    marked = many.join(joined.select(F.col("node").alias("key"), "root"), "key", "left").withColumn("root", F.coalesce("root", "key"))
    marked = Stored(marked, "marked").df
    broken = marked.groupBy("h").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.min("key").alias("lead")).where("lo <> hi").select("h", "lead")
    rest = Stored(marked.join(broken, "h"), "rest").df
    if rest.isEmpty():
        return None
    fields = components(rest.select("key", "lead"), "key", "lead").select(F.col("node").alias("key"), F.col("root").alias("field"))
    fields = Stored(fields.join(rest.select("key", "root").distinct(), "key"), "fields").df
    blocks = fields.groupBy("field").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks"))
    dealt = fields.join(blocks, "field").withColumn("block", F.pmod(F.xxhash64("key", F.lit(5)), "blocks").cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("field", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "key", "root")
    return dealt.join(sets, "key").groupBy("field", "i", "j").applyInArrow(_compared, "a binary, b binary")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, th (hash of the text), component_id, root: documents linked by a similarity of at least SIMILAR over sets of SHINGLE-word shingles.

    The anchors of the fingerprints find the first candidates, which are verified on the whole sets. What follows makes the result exact, for
    pairs that aren't in one component yet: texts of that similarity share one of the rarest shingles of each (a prefix filter), so they
    meet in the group of that shingle. Small groups are joined pair by pair, without pairs whose sizes and places rule them out. All of a
    large group are compared with its best connected text first; where that leaves a group in more than one component, every pair
    between its components is compared. Each link is verified on the whole sets.
    """
    rows = Stored(_texts(docs), "texts").df
    texts = Stored(rows.groupBy("key", "id").agg(F.min("doc_id").alias("least")), "keys").df
    count = texts.count()
    one = Chosen(docs, texts.select(F.col("least").alias("doc_id")), count)  # one document a text and few others
    met = Stored(_met(one), "met").df
    found = Stored(_verified(met, _sets_of(docs, texts, met.select(F.col("a").alias("key")).union(met.select("b")).distinct(), "met-sets")), "found").df
    early = Stored(components(found, "a", "b"), "early").df
    cells = 1 << max(16, min(CELLS_MAX.bit_length() - 1, (32 * count).bit_length()))
    prefixes = Stored(_prefixes(one, cells), "prefixes").df
    shared = Stored(prefixes.groupBy("h").agg(F.min("id").alias("lo"), F.max("id").alias("hi")).where("lo <> hi").select("h"), "shared").df
    again = key_filter(shared, shared.count())
    listed = prefixes.where(again("h")).join(shared, "h").distinct().join(texts.select("id", "key"), "id").select("h", "key", "size", "pos")
    listed = Stored(listed, "listed").df
    listed = Stored(listed.join(listed.groupBy("h").agg(F.count(F.lit(1)).alias("n")), "h"), "counted").df
    few, many = listed.where(F.col("n") <= PAIRED), Stored(listed.where(F.col("n") > PAIRED), "many").df
    # at the first shingle that two texts share, what either has from there on bounds what they share
    a, b = (few.select("h", F.col("key").alias(x), F.col("size").alias(f"s{x}"), (F.col("size") - F.col("pos")).alias(f"r{x}")) for x in "ab")
    pairs = a.join(b, "h").where(F.expr("a < b") & ((1 + SIMILAR) * F.least("ra", "rb") >= SIMILAR * (F.col("sa") + F.col("sb")) - 1e-9)).select("a", "b")
    # the text whose shingles most others hold leads: the original of edited copies rather than one of them
    score = many.groupBy("key").agg(F.sum("n").alias("score"))
    lead = many.join(score, "key").groupBy("h").agg(F.max(F.struct("score", "key", "size")).alias("lead"))
    alike = F.least("size", "lead.size") >= SIMILAR * F.greatest("size", "lead.size") - 1e-9
    led = many.join(lead, "h").where((F.col("key") != F.col("lead.key")) & alike)
    led = led.select(F.least("key", "lead.key").alias("a"), F.greatest("key", "lead.key").alias("b"))
    of = lambda x: early.select(F.col("node").alias(x), F.col("root").alias(f"r{x}"))
    open_ = pairs.union(led).distinct().join(of("a"), "a", "left").join(of("b"), "b", "left").where(F.coalesce("ra", "a") != F.coalesce("rb", "b"))
    pairs = Stored(open_.select("a", "b"), "pairs").df
    ends = pairs.select(F.col("a").alias("key")).union(pairs.select("b")).union(many.select("key")).distinct()
    sets = _sets_of(docs, texts, ends, "sets")
    links = Stored(found.union(_verified(pairs, sets)), "verified").df
    joined = components(links, "a", "b")
    more = None if many.isEmpty() else _unsettled(many, joined, sets)
    if more is not None:
        joined = components(links.union(more), "a", "b")
    roots = texts.select("key", "least").join(joined.select(F.col("node").alias("key"), "root"), "key", "left").withColumn("root", F.coalesce("root", "key"))
    roots = Stored(roots, "roots").df
    names = roots.groupBy("root").agg(F.min("least").alias("component_id"))
    return rows.select("doc_id", "th", "key").join(roots.join(names, "root").select("key", "component_id", "root"), "key").select("doc_id", "th", "component_id", "root")


def drop_near_duplicates(docs: DataFrame) -> DataFrame:
    """docs with one row of each group of near copies: the one of the least doc_id (null last), then least text hash."""
    classes = Stored(near_duplicates(docs).select("doc_id", "th", "root"), "classes").df
    order = F.struct(F.col("doc_id").isNull().alias("z"), "doc_id", "th")
    stays = Stored(classes.groupBy("root").agg(F.min(order).alias("stays"), F.count(F.lit(1)).alias("rows")), "stays").df
    # a group of one has nothing to lose: only the others meet what stays of them
    gone = classes.join(stays.where("rows > 1"), "root").where(order != F.col("stays")).select("doc_id", "th").distinct()
    kept = without(docs, Stored(gone, "gone").df)
    again = classes.groupBy("doc_id", "th").count().where("count > 1").limit(1)
    if again.isEmpty():
        return kept
    columns = kept.columns
    keyed = kept.select(F.struct(*(F.col(f"`{c}`") for c in columns)).alias("__row"), F.col("doc_id").alias("__id"), F.xxhash64("text").alias("__th"))
    return keyed.dropDuplicates(["__id", "__th"]).select(*(F.col("__row").getField(c).alias(c) for c in columns))
