"""HTML extraction on planted markup and held-out generated pages; the pipeline stage by stage; the registry."""

import html
import random
import re

import numpy as np

import __spark_entry__
import corpus_pipeline
from fadestream.llm.html_extract import main_content
from fadestream.llm.page_model import Forest, Page, labelled_page, main_texts, trained


def test_marginals_equal_enumeration():
    rng = np.random.default_rng(1)
    page = Page("<body><div class='ad'>x</div><article><p>y</p><p>z</p></article></body>")
    forest, n = Forest([page]), len(page.parent)
    unary, pair = rng.normal(size=n), rng.normal(size=(5, 2, 2))
    total, ones, edges = 0.0, np.zeros(n), np.zeros((n, 2, 2))
    for code in range(2**n):
        y = [(code >> i) & 1 for i in range(n)]
        s = sum(u for u, v in zip(unary, y, strict=True) if v) + sum(pair[forest.kind[i], y[page.parent[i]], y[i]] for i in range(1, n))
        w = np.exp(s)
        total += w
        ones += w * np.array(y)
        for i in range(1, n):
            edges[i, y[page.parent[i]], y[i]] += w
    prob, both, log_z = forest.marginals(unary, pair)
    assert np.allclose(prob, ones / total) and np.isclose(log_z, np.log(total)) and np.allclose(both[1:], edges[1:] / total)


def test_held_out_generated_pages():
    rng, right, total = random.Random(1234), 0, 0
    for _ in range(150):
        source, truth = labelled_page(rng)
        page = Page(source)
        assert len(page.runs) == len(truth)
        forest = Forest([page])
        prob, _, _ = forest.marginals(forest.x @ trained()[0], trained()[1])
        right += sum((prob[n] > 0.5) == t for (n, _), t in zip(page.runs, truth, strict=True))
        total += len(truth)
    assert right / total > 0.98


def article(source):
    inner = source[source.index("<article>") + 9 : source.index("</article>")]
    inner = re.sub(r"<[^>]*>", "", re.sub(r"</?(?:p|h1)\b[^>]*>", "\n", inner).replace("<br>", " "))
    return "\n".join(x for x in (" ".join(html.unescape(line).split()) for line in inner.split("\n")) if x)


def test_pages_of_the_table(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    want = {r["page_id"]: article(r["html"]) for r in pages.collect()}
    got = main_content(pages).collect()
    assert all(r["n_chars"] == len(r["text"]) for r in got)
    assert np.mean([r["text"] == want[r["page_id"]] for r in got]) > 0.99


def test_odd_markup(spark):
    body = "Long enough text of the article, with a sentence. And one more."
    odd = [None, "", "plain text only", "<", "<p>", f"<article><p>{body}<p>A &lt;tag&gt; &amp; &#233;&nbsp;x</article><!-- <p>no</p> --><script>no</script>", "</div></p>" * 50, "<div>" * 3000 + "x", "<a" * 100]
    df = spark.createDataFrame([(i, None, h) for i, h in enumerate(odd)], "page_id long, url string, html string")
    out = {r["page_id"]: r["text"] for r in main_content(df).collect()}
    assert len(out) == len(odd) and out[0] == out[1] == ""
    assert out[5] == f"{body}\nA <tag> & é x"
    assert main_content(df.limit(0)).collect() == []
    assert main_texts([], trained()) == []


def test_stages_keep_the_columns_and_take_effect(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    sizes, now = [docs.count()], docs
    for name, stage in corpus_pipeline.STAGES:
        now = spark.createDataFrame(stage(spark, now, sf_dir).collect(), stage(spark, now, sf_dir).schema)
        sizes.append(now.count())
        if name != "sharding":
            assert now.columns == docs.columns
    assert sizes[1] < sizes[0] and sizes[2] < sizes[1] and sizes[4] < sizes[3] and sizes[5] == sizes[4]
    assert {"shard", "slot", "size", "text_crc32"} <= set(now.columns)


def test_registry():
    names = __spark_entry__.queries()
    assert {re.match(r"op(\d+)_", n).group(1) for n in names if n.startswith("op")} >= {str(i) for i in range(1, 11)}
    assert "pipeline" in names and set(__spark_entry__.oracle_sql()) <= set(names)
