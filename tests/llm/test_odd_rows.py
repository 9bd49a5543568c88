"""Repeated rows, null ids, clashing columns, empty tables and very long texts, for the operators and the stages."""

import collections
import random
import time
import zlib

import corpus_pipeline as cp
import numpy as np
import pytest
from pyspark.sql import functions as F

from fadestream.llm.exact_dedup import DigestIndex, exact_dedup
from fadestream.llm.mixing import mix, mixed
from fadestream.llm.page_model import main_texts, trained
from fadestream.llm.pii import personal_data
from fadestream.llm.quality import POOL, RIDGE, SHORT, fit, quality_scores
from fadestream.llm.sharding import shard
from fadestream.llm import simhash as sh
from fadestream.llm.simhash import simhash_classes
from fadestream.llm.substring_dedup import substring_dedup
from fadestream.llm.winnowing import contamination

KIND = "doc_id long, text string, lang string, source string, n_chars long, r int, subs int, `a.b` int, key int, n_sentences int"


def words(rng, n):
    return " ".join("".join(rng.choices("abcdefghij", k=rng.randint(3, 7))) for _ in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    rng = random.Random(8)
    a, b, c = (words(rng, 40) for _ in range(3))
    rows = [(1, a), (1, a), (1, b), (None, c), (None, c), (None, words(rng, 40)), (2, None), (3, ""), (4, a.replace(a.split()[0], "changed", 1)), (5, words(rng, 30))]
    return spark.createDataFrame([(i, t, None if k % 3 == 0 else "en", None if k % 4 == 0 else "s", 0, 1, 2, 3, 4, 5) for k, (i, t) in enumerate(rows)], KIND).repartition(3)


def ids(df):
    return collections.Counter((r["doc_id"], r["text"]) for r in df.collect())


def test_operators_answer_row_by_row(spark, odd):
    bench = spark.createDataFrame([(1, "one two")], "item_id long, text string")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    want = collections.Counter(r["doc_id"] for r in odd.collect())
    for df in (exact_dedup(odd), simhash_classes(odd), substring_dedup(odd), shard(odd, 4), mix(odd), contamination(odd, bench), quality_scores(odd, labels), personal_data(odd)):
        assert collections.Counter(r["doc_id"] for r in df.collect()) == want


def test_stages_on_odd_rows(spark, odd, tmp_path):
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    first = odd.where("doc_id = 5").first()["text"]
    spark.createDataFrame([(1, first)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    rows = ids(odd)
    assert ids(cp.quality(spark, odd, str(tmp_path))) == rows  # no labels, no model
    near = cp.near_copies(spark, odd, str(tmp_path))
    assert near.columns == odd.columns
    kept = ids(near)
    texts = {t for (i, t) in rows if i == 1}
    assert {t for (i, t) in kept if i == 1} == texts  # another text of the same id isn't lost
    assert all(n == 1 for n in kept.values()) and (4, odd.where("doc_id = 4").first()["text"]) not in kept
    assert sum(i is None for i, _ in kept) == 2  # rows without an id are told apart by text
    clean = cp.decontamination(spark, odd, str(tmp_path))
    assert clean.columns == odd.columns and ids(clean) == rows - collections.Counter({(5, first): 1})
    out = cp.sharding(spark, odd, str(tmp_path))
    assert out.columns == [*odd.columns, "size", "text_crc32", "shard", "slot"] and ids(out) == rows
    for name, stage in cp.STAGES:
        assert stage(spark, odd.where("false"), str(tmp_path)).collect() == [], name


@pytest.mark.parametrize("parts", [1, 3, 7])
def test_the_mixture_does_not_follow_the_partitions(spark, parts):
    rng = random.Random(3)
    rows = [(None if k % 2 else k % 10, words(rng, rng.randint(1, 6)), "en", "s") for k in range(300)]
    rows += rows[:40]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    taken = ids(mixed(df.repartition(parts), share=0.5))
    assert taken == ids(mixed(df.repartition(2, "text"), share=0.5))
    tokens = sum(len(t.split()) * n for (_, t), n in taken.items())
    whole = sum(len(t.split()) for _, t, _, _ in rows)
    assert 0.5 * whole - 6 <= tokens <= 0.5 * whole


def test_repeated_rows_fill_all_shards(spark):
    rows = [(7, "x" * 50)] * 4000 + [(i, f"text {i}") for i in range(100, 200)]
    out = shard(spark.createDataFrame(rows, "doc_id long, text string"), 16).collect()
    load = collections.Counter()
    slots = collections.defaultdict(list)
    for r in out:
        load[r["shard"]] += r["size"]
        slots[r["shard"]].append(r["slot"])
        assert r["text_crc32"] == zlib.crc32(r["text"].encode())
    assert len(out) == 4100 and len(load) == 16 and max(load.values()) < 1.25 * sum(load.values()) / 16
    assert all(sorted(x) == list(range(len(x))) for x in slots.values())


def test_shards_are_stretches_of_the_key(spark):
    df = spark.range(3000).select(F.col("id").alias("doc_id"), F.concat(F.lit("text "), "id").alias("text"))
    rows = sorted((r["h"], r["shard"]) for r in shard(df, 8).select(F.xxhash64("text").alias("h"), "shard").collect())
    assert [s for _, s in rows] == sorted(s for _, s in rows) and {s for _, s in rows} == set(range(8))


def test_runs_are_merged_behind_their_filters(spark):
    first = spark.range(400).select(F.col("id").alias("doc_id"), F.concat(F.lit("t"), "id").alias("text")).repartition(8)
    again = first.where("doc_id % 10 = 0").select((F.col("doc_id") + 1000).alias("doc_id"), "text")
    index = DigestIndex(spark, memtables=4, fanout=2, measure=True)
    index.flush(first)
    index.flush(again)
    level = {r["digest"]: (r["keep_id"], r["group_size"]) for r in index.compact().collect()}
    assert len(level) == 400 and sum(n for _, n in level.values()) == 440
    assert all(i < 400 and n == 1 + (i % 10 == 0) for i, n in level.values())
    assert index.passed > 0.8 * index.merged  # entries that no other run holds aren't exchanged
    assert len(index.tiers) > 2 and sum(map(len, index.tiers)) == 1


LONG = {"tags": "<a" * 500_000, "quotes": """<a '" """ * 150_000, "deep": "<div>" * 200_000, "rows": "<tr><td>" * 100_000, "ends": "<b>" * 100_000 + "<i>" * 100_000 + "</b>" * 100_000}


@pytest.mark.parametrize("kind", sorted(LONG))
def test_long_odd_pages_take_linear_time(kind):
    weights = trained()
    began = time.process_time()
    assert main_texts([LONG[kind] + "</a></b></td></tr></div>"], weights) is not None
    assert time.process_time() - began < 10


TEXTS = {"letters": "abcdefghij" * 100_000 + "@", "mail": " ".join(f"user{i}@host{i}.com" for i in range(100_000)), "digits": "1" * 1_000_000, "cards": "4111 1111 1111 1111, " * 50_000, "secrets": "token = aB3dE5gH7jK9mN1pQ3sT5vX7z " * 30_000}


def test_long_texts_take_linear_time(spark):
    df = spark.createDataFrame([(i, t) for i, t in enumerate(TEXTS.values())], "doc_id long, text string").repartition(len(TEXTS))
    began = time.time()
    got = {r["doc_id"]: r for r in personal_data(df).collect()}
    assert time.time() - began < 60
    assert got[1]["n_email"] == 100_000 and got[3]["n_card"] == 50_000 and got[4]["spans"].count("secret") == 30_000


def test_crowded_anchors_are_dealt_anew(spark, monkeypatch):
    rng = random.Random(6)
    fps = {0}
    for _ in range(400):  # a crowd about zero, all at one coarse anchor
        fps.add(sum(1 << b for b in rng.sample(range(64), rng.randint(1, 3))))
    fps |= {rng.getrandbits(64) for _ in range(200)} | {(1 << 64) - 1, (1 << 63), (1 << 63) | 1}
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    df = spark.createDataFrame([(0, signed(x)) for x in fps], "family int, fp long")
    want = {(min(signed(x), signed(y)), max(signed(x), signed(y))) for x in fps for y in fps if x < y and (x ^ y).bit_count() <= 2}

    def roots(links):
        root = {signed(x): signed(x) for x in fps}

        def find(x):
            while root[x] != x:
                x = root[x]
            return x

        for a, b in links:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
        return {x: find(x) for x in root}

    for hot in (sh.HOT, 20):
        monkeypatch.setattr(sh, "HOT", hot)
        links = [(r["a"], r["b"]) for r in sh.anchor_links(df, 2, len(fps)).collect()]
        assert {(min(x), max(x)) for x in links} <= want
        assert roots(links) == roots(want)


def independent_sentences(text):
    """Cuts after closing marks and white space, or at line ends, character by character."""
    out, now, i = [], "", 0
    while i < len(text):
        now += text[i]
        stop = text[i] in ".!?\u2026"
        i += 1
        if stop:
            while i < len(text) and text[i] in ".!?\u2026":
                now += text[i]
                i += 1
            while i < len(text) and text[i] in "\"'\u201d\u2019)]":
                now += text[i]
                i += 1
            if not (i < len(text) and text[i].isspace()):
                continue
        elif now[-1] != "\n":
            continue
        while i < len(text) and text[i].isspace():
            now += text[i]
            i += 1
        out.append(now)
        now = ""
    return out + [now] if now else out


def test_repeated_spans_equal_every_span_by_brute_force(spark):
    """Every run of at least two sentences and twenty words is looked at, not only the shortest ones: the same sentences go."""
    rng = random.Random(9)
    pool = [words(rng, rng.randint(3, 14)).capitalize() + rng.choice([".", "!", "?\"", "\n"]) for _ in range(14)]
    texts = [" ".join(rng.choice(pool) for _ in range(rng.randint(1, 9))) for _ in range(40)]
    seen, want = {}, {}
    for d, t in enumerate(texts):
        parts = independent_sentences(t)
        real = [k for k, p in enumerate(parts) if p.strip()]
        gone = set()
        for a in range(len(real)):
            for b in range(a + 2, len(real) + 1):
                run = tuple(" ".join(parts[k].split()) for k in real[a:b])
                if sum(len(x.split()) for x in run) >= 20 and seen.setdefault(run, (d, a)) != (d, a):
                    gone.update(real[a:b])
        want[d] = "".join(p for k, p in enumerate(parts) if k not in gone) if gone else t
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in substring_dedup(df).collect()}
    assert got == want and sum(want[d] != t for d, t in enumerate(texts)) > 5


def test_scores_equal_densities_written_out():
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(0, 1, (80, 3)), rng.normal(1, 2, (60, 3))])
    x[:, 0] = np.abs(x[:, 0]) + 1  # the first statistic is the logarithm of the words
    y = np.repeat([0, 1], [80, 60])
    model = fit(x, y)
    words_ = np.exp(x[:, 0]) - 1
    z = np.clip((x - x.mean(axis=0)) / (x.std(axis=0) + 1e-6), -12, 12) * np.sqrt(words_ / (words_ + SHORT))[:, None]
    centred = [z[y == c] - z[y == c].mean(axis=0) for c in (0, 1)]
    pooled = sum(c.T @ c for c in centred) / len(z)
    logs = []
    for c in (0, 1):
        cov = (1 - POOL) * np.cov(z[y == c].T, bias=True) + POOL * pooled
        cov = (1 - RIDGE) * cov + RIDGE * np.trace(cov) / 3 * np.eye(3)
        off = z - z[y == c].mean(axis=0)
        logs.append(-0.5 * np.einsum("ij,jk,ik->i", off, np.linalg.inv(cov), off) - 0.5 * np.linalg.slogdet(cov)[1])
    assert np.allclose(model.log_ratio(x), logs[1] - logs[0])
    assert np.allclose(model.score(x), 1 / (1 + np.exp(-(model.slope * (logs[1] - logs[0]) + model.offset))), atol=1e-9)
