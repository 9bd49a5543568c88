"""The registered queries of the training-data operators and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents
from .exact_dedup import exact_dedup
from .html_extract import main_content
from .line_dedup import MIN_CHARS, MIN_LINES, line_dedup
from .mixing import DEFAULT_WEIGHT, DOMAINS, LEVELS, MAX_EPOCHS, SEED, SHARE, WEIGHTS, mix
from .pii import personal_data
from .quality import quality_scores
from .sharding import shard
from .simhash import simhash_classes
from .substring_dedup import substring_dedup
from .winnowing import WINDOW, contamination


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup(documents(spark, sf_dir)).select("doc_id", "n_sentences", "n_removed", "text")


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = shard(documents(spark, sf_dir).select("doc_id", "text"), 16)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_scores(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(documents(spark, sf_dir)).select("doc_id", "keep_id", "group_size", "kept", F.col("digest").alias("text_sha256"))


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = simhash_classes(documents(spark, sf_dir), k=3, threshold=2)
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(documents(spark, sf_dir)).drop("th")


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet")).drop("items")


def op8_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_content(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup(documents(spark, sf_dir))
    return out.select("doc_id", "n_lines", "n_removed", F.md5(F.coalesce("text", F.lit("")).cast("binary")).alias("text_md5"))


def op10_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal_data(documents(spark, sf_dir))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    found = [op1_substring_dedup, op2_sharding, op3_quality, op4_exact_dedup, op5_simhash, op6_mixing, op7_decontamination, op8_html, op9_line_dedup, op10_personal_data, pipeline]
    return {f.__name__: f for f in found}


_OP4 = r"""
WITH t AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS bare, length(coalesce(text, '')) AS n FROM documents),
r AS (SELECT doc_id, bare, first_value(doc_id) OVER w AS keep_id, count(*) OVER (PARTITION BY bare) AS group_size, row_number() OVER w AS place
      FROM t WINDOW w AS (PARTITION BY bare ORDER BY n DESC, doc_id))
SELECT doc_id, keep_id, CAST(group_size AS BIGINT) AS group_size, place = 1 AS kept, sha256(bare) AS text_sha256 FROM r
"""

_OP9 = f"""
WITH raw AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS line_no FROM documents),
trimmed AS (SELECT doc_id, line, line_no, rtrim(line, ' ') AS x FROM raw),
seq AS (SELECT doc_id, line_no, x, row_number() OVER (PARTITION BY doc_id ORDER BY line_no) AS pos FROM trimmed WHERE trim(x, ' ') <> ''),
ahead AS (SELECT doc_id, pos, list(x) OVER w AS run FROM seq WINDOW w AS (PARTITION BY doc_id ORDER BY pos ROWS BETWEEN CURRENT ROW AND {MIN_LINES - 1} FOLLOWING)),
placed AS (SELECT doc_id, pos, row_number() OVER (PARTITION BY run ORDER BY doc_id, pos) AS copy FROM ahead WHERE len(run) = {MIN_LINES}),
single AS (SELECT doc_id, pos, row_number() OVER (PARTITION BY x ORDER BY doc_id, pos) AS copy FROM seq WHERE length(x) >= {MIN_CHARS}),
gone AS (SELECT doc_id, pos + i AS pos FROM placed, range({MIN_LINES}) AS r(i) WHERE copy > 1 UNION SELECT doc_id, pos FROM single WHERE copy > 1),
lines AS (SELECT t.doc_id, t.line, t.line_no, s.pos, g.pos IS NOT NULL AS dropped
          FROM trimmed t LEFT JOIN seq s ON t.doc_id = s.doc_id AND t.line_no = s.line_no LEFT JOIN gone g ON s.doc_id = g.doc_id AND s.pos = g.pos)
SELECT doc_id, CAST(count(pos) AS BIGINT) AS n_lines, CAST(count(*) FILTER (WHERE dropped) AS BIGINT) AS n_removed,
       md5(coalesce(string_agg(line, chr(10) ORDER BY line_no) FILTER (WHERE NOT dropped), '')) AS text_md5
FROM lines GROUP BY doc_id
"""


_WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

_OP7 = f"""
WITH d AS (SELECT doc_id, {_WORDS} AS ws FROM documents),
i AS (SELECT item_id, {_WORDS} AS ws FROM benchmark),
iw AS (SELECT DISTINCT item_id, least({WINDOW}, len(ws)) AS n, array_to_string(ws[p : p + least({WINDOW}, len(ws)) - 1], ' ') AS w
       FROM (SELECT *, unnest(range(1, CAST(len(ws) - least({WINDOW}, len(ws)) + 2 AS BIGINT))) AS p FROM i WHERE len(ws) > 0)),
dw AS (SELECT doc_id, n, p, array_to_string(ws[p : p + n - 1], ' ') AS w FROM (SELECT doc_id, ws, n, unnest(range(1, CAST(len(ws) - n + 2 AS BIGINT))) AS p FROM d, (SELECT DISTINCT n FROM iw) WHERE len(ws) >= n)),
hit AS (SELECT doc_id, p, n, item_id FROM dw JOIN iw USING (n, w)),
words AS (SELECT doc_id, count(*) AS n_hit FROM (SELECT DISTINCT doc_id, unnest(range(p, p + n)) AS q FROM hit) GROUP BY doc_id),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS names FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM hit) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id)
"""


def _mix_sql() -> list[str]:
    """Water-filling level by level: a child is short if its even share at its place among its siblings exceeds its capacity."""
    parts = [
        rf"""rows_ AS (SELECT doc_id, coalesce(source, 'none') AS origin, coalesce(lang, 'none') AS language, coalesce(text, '') AS text FROM documents),
toks AS (SELECT doc_id, origin, language, CAST(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) AS BIGINT) AS tokens,
         -- CRC-32 isn't built in: the domains of the sources come from the list below
         domain FROM rows_ JOIN domains USING (origin)),
leaf AS (SELECT domain, language, origin, CAST(sum(tokens) AS BIGINT) AS tokens, CAST(sum(tokens) * {MAX_EPOCHS} AS BIGINT) AS cap FROM toks GROUP BY ALL),
root AS (SELECT least(floor(sum(tokens) * {SHARE}), sum(cap)) AS amount FROM leaf)"""
    ]
    above, parents = "root", []
    for level in LEVELS:
        keys = ", ".join([*parents, level])
        w = f"CASE {level} " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in WEIGHTS[level].items()) + f" ELSE {DEFAULT_WEIGHT} END" if WEIGHTS[level] else str(DEFAULT_WEIGHT)
        part = f"PARTITION BY {', '.join(parents)}" if parents else ""
        join = f"JOIN {above} USING ({', '.join(parents)})" if parents else f"CROSS JOIN {above}"
        parts.append(f"""{level}_c AS (SELECT {keys}, cap, CAST({w} AS DOUBLE) AS w, amount FROM (SELECT {keys}, sum(cap) AS cap FROM leaf GROUP BY {keys}) {join}),
{level}_o AS (SELECT *, row_number() OVER ({part} ORDER BY cap / w, {level}) AS place FROM {level}_c),
{level}_u AS (SELECT a.*, (a.amount - coalesce(sum(cap) OVER (e ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / (sum(w) OVER (e ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)) AS unit
  FROM {level}_o a WINDOW e AS ({part} ORDER BY place)),
{level}_s AS (SELECT *, min(CASE WHEN unit * w < cap THEN place END) OVER ({part}) AS open_at FROM {level}_u),
{level}_n AS (SELECT {keys}, CASE WHEN unit * w >= cap THEN CAST(cap AS DOUBLE) ELSE w * max(CASE WHEN place = open_at THEN unit END) OVER ({part}) END AS amount FROM {level}_s)""")
        above, parents = f"{level}_n", [*parents, level]
    parts.append(f"""plan AS (SELECT domain, language, origin, tokens AS leaf_tokens, CAST(floor(amount + 1e-6) AS BIGINT) AS budget FROM leaf JOIN {above} USING (domain, language, origin)),
split AS (SELECT *, CASE WHEN leaf_tokens > 0 THEN budget // leaf_tokens ELSE 0 END AS whole FROM plan),
keyed AS (SELECT t.*, s.budget, s.whole, s.budget - s.whole * s.leaf_tokens AS rest, md5('{SEED}:' || s.whole || ':' || t.doc_id) AS key FROM toks t JOIN split s USING (domain, language, origin)),
run AS (SELECT *, sum(tokens) OVER (PARTITION BY domain, language, origin ORDER BY key ROWS UNBOUNDED PRECEDING) AS upto FROM keyed)
SELECT doc_id, domain, language, origin, tokens, budget, CAST(least(whole + CASE WHEN upto <= rest THEN 1 ELSE 0 END, {MAX_EPOCHS}) AS BIGINT) AS copies FROM run""")
    return parts


def _domains() -> str:
    import zlib

    names = [*(f"src{i}" for i in range(1000)), "none"]
    return "domains(origin, domain) AS (VALUES " + ", ".join(f"('{n}', '{zlib.crc32(n.encode()) % DOMAINS}')" for n in names) + ")"


def oracle_sql() -> dict[str, str]:
    return {"op4_exact_dedup": _OP4, "op6_mixing": "WITH " + ",\n".join([_domains(), *_mix_sql()]), "op7_decontamination": _OP7, "op9_line_dedup": _OP9}
