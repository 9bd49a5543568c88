"""Queries of the operators, sources and functions around the methods, each with its SQL."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fadestream.functions import udtfs
from fadestream.functions import vectors as V
from fadestream.operators import batching, measures
from fadestream.operators import features as ft
from fadestream.operators.distance import assign, centroid_rows, cluster_stats
from fadestream.operators.features import table
from fadestream.plans import duck as Q
from fadestream.plans.methods import C0, CUR, EV5, NEAR0, D, K, N, em, ev, fifths, first_rows, last_batch, lim, r6
from fadestream.plans.registry import query
from fadestream.sources.datasources import read_points, write_points
from fadestream.sources.window_store import WindowStore, shared_root


def scratch(spark: SparkSession, label: str) -> str:
    return shared_root(spark, f"{label}-{uuid.uuid4().hex}")


def dims(df: DataFrame, *keep: str) -> DataFrame:
    """One row a coordinate, rounded."""
    return df.select(*keep, F.posexplode("x").alias("dim", "v")).select(*keep, "dim", F.round("v", 6).alias("value"))


def unpivot(rel: str, d: int, key: str = "id", where: str = "true", value: str = "round(CAST(v{j} AS DOUBLE), 6)") -> str:
    return " UNION ALL ".join(f"SELECT {key}, CAST({j - 1} AS INTEGER) AS dim, {value.format(j=j)} AS value FROM {rel} WHERE {where}" for j in range(1, d + 1))


# ---------------------------------------------------------------- scans and formats


@query(f"WITH {Q.EV} " + unpivot("ev", D))
def scan_parquet_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dims(ev(spark, sf_dir), "id")


@query(f"WITH {EV5} SELECT b, count(*) AS n, CAST(sum(v1) AS BIGINT) AS s FROM ev5 WHERE b BETWEEN 2 AND 4 GROUP BY b")
def scan_pruned_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    store = WindowStore(spark, scratch(spark, "window"))
    p = fifths(spark, sf_dir).persist()
    for s in [r[0] for r in p.select("batch_seq").distinct().orderBy("batch_seq").collect()]:
        store.append(p.where(F.col("batch_seq") == s), s)
    return store.window(2, 4).groupBy(F.col("batch_seq").alias("b")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("x")[0]).cast("long").alias("s"))


def _round_trip(fmt: str):  # noqa: ANN202
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        path = scratch(spark, f"points-{fmt}")
        write_points(ev(spark, sf_dir).select("point_id", "x", "batch_seq"), path, fmt)
        return dims(read_points(spark, path, fmt).withColumn("id", F.col("point_id").cast("long")), "id")

    return run


for _f in ("csv", "json", "orc", "text", "parquet"):
    query(f"WITH {Q.EV} " + unpivot("ev", D), f"scan_{_f}_roundtrip")(_round_trip(_f))


@query("SELECT event_id AS id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS a, CAST(json_extract_string(props, '$.k') AS BIGINT) AS b, CAST(json_extract_string(props, '$.k') AS BIGINT) AS c FROM events")
def fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    return e.select(
        F.col("event_id").alias("id"), F.get_json_object("props", "$.k").cast("bigint").alias("a"), F.from_json("props", "k bigint")["k"].alias("b"), F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("c")
    )


# ---------------------------------------------------------------- batches


@query(f"SELECT event_id // {N} AS batch, count(*) AS n, min(event_id) AS lo, max(event_id) AS hi FROM events GROUP BY 1")
def batch_by_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = batching.by_dense_id(table(spark, sf_dir, "events"), "event_id", N)
    return b.groupBy(F.col("batch_seq").alias("batch")).agg(F.count(F.lit(1)).alias("n"), F.min("event_id").alias("lo"), F.max("event_id").alias("hi"))


@query("WITH o AS (SELECT *, row_number() OVER (ORDER BY value, event_id) - 1 AS r FROM events) SELECT CAST(r // 100 AS BIGINT) AS batch, count(*) AS n, min(event_id) AS lo, max(event_id) AS hi FROM o GROUP BY 1")
def batch_sparse_ordinal(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = batching.by_ordinal(table(spark, sf_dir, "events"), ["value", "event_id"], 100)
    return b.groupBy(F.col("batch_seq").alias("batch")).agg(F.count(F.lit(1)).alias("n"), F.min("event_id").alias("lo"), F.max("event_id").alias("hi"))


@query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS batch, count(*) AS n, min(event_id) AS lo, max(event_id) AS hi FROM events GROUP BY 1")
def batch_tumbling_day(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = batching.by_time(table(spark, sf_dir, "events"), "ts", "1 day")
    return b.groupBy(F.date_format("start", "yyyy-MM-dd").alias("batch")).agg(F.count(F.lit(1)).alias("n"), F.min("event_id").alias("lo"), F.max("event_id").alias("hi"))


@query(f"WITH {Q.LI} SELECT CAST(b AS BIGINT) AS batch, strftime(min(mon), '%Y-%m') AS month, count(*) AS n FROM lim GROUP BY b")
def batch_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = batching.by_month(table(spark, sf_dir, "lineitem").select("l_shipdate"), "l_shipdate")
    return b.groupBy(F.col("batch_seq").alias("batch")).agg(F.date_format(F.min("month"), "yyyy-MM").alias("month"), F.count(F.lit(1)).alias("n"))


@query("SELECT strftime(s, '%Y-%m-%d %H:%M') AS batch, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts) + INTERVAL 12 HOUR * (hour(ts) // 12), date_trunc('day', ts) + INTERVAL 12 HOUR * (hour(ts) // 12) - INTERVAL 12 HOUR]) AS s FROM events) GROUP BY 1")
def batch_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = batching.by_time(table(spark, sf_dir, "events"), "ts", "24 hours", "12 hours")
    return b.groupBy(F.date_format("start", "yyyy-MM-dd HH:mm").alias("batch")).agg(F.count(F.lit(1)).alias("n"))


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w >= INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS i FROM g) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, i")
def batch_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = batching.by_session(table(spark, sf_dir, "events"), "user_id", "ts", "6 hours")
    return b.select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query(f"WITH {Q.EV}, {CUR} SELECT cur AS step, b, cur - b AS t, count(*) AS n, pow(0.5, cur - b) AS w FROM ev, cur WHERE b > cur - 4 GROUP BY cur, b")
def evict_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir)
    cur = last_batch(p)
    kept = batching.antiquity(batching.evict(p, cur, 4), cur, 0.5)
    return kept.groupBy(F.lit(cur).alias("step"), F.col("batch_seq").alias("b"), "t", "w").agg(F.count(F.lit(1)).alias("n")).select("step", "b", F.col("t").cast("long").alias("t"), "n", "w")


@query(f"WITH {Q.LI}, z AS (SELECT b, count(*) AS n FROM lim GROUP BY b) SELECT CAST(x.b AS BIGINT) AS step, CAST(sum(y.n) AS BIGINT) AS m_t, round(sum(y.n * pow(0.5, x.b - y.b)), 6) AS m_rho FROM z x JOIN z y ON y.b BETWEEN x.b - 3 AND x.b GROUP BY x.b")
def window_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    sizes = lim(spark, sf_dir).groupBy("batch_seq").agg(F.count(F.lit(1)).alias("n"))
    return batching.masses(sizes, 0.5, 4).select("step", "m_t", r6("m_rho").alias("m_rho"))


# ---------------------------------------------------------------- features

_MS = ", ".join(f"avg(v{j}) AS m{j}, stddev_pop(v{j}) AS s{j}, min(v{j}) AS a{j}, max(v{j}) AS b{j}" for j in range(1, 5))


@query(f"WITH {Q.EV}, f AS (SELECT {_MS} FROM ev WHERE b = 0), x AS (SELECT * FROM ev, f) " + unpivot("x", D, value="CASE WHEN s{j} = 0 THEN 0.0 ELSE round((v{j} - m{j}) / s{j}, 6) END"))
def feature_zscore(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir)
    return dims(ft.zscore(p, D, p.where("batch_seq = 0")), "id")


@query(f"WITH {Q.EV}, f AS (SELECT {_MS} FROM ev), x AS (SELECT * FROM ev, f) " + unpivot("x", D, value="CASE WHEN a{j} = b{j} THEN 0.0 ELSE round((v{j} - a{j}) / CAST(b{j} - a{j} AS DOUBLE), 6) END"))
def feature_minmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dims(ft.minmax(ev(spark, sf_dir), D), "id")


@query(f"WITH {Q.EV} " + unpivot("ev", D, value="round(v{j} / sqrt(v1*v1 + v2*v2 + v3*v3 + v4*v4), 6)"))
def feature_l2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dims(ft.l2_normalise(ev(spark, sf_dir)), "id")


@query("SELECT event_id AS id, " + ", ".join(f"CAST(event_type = t{i} AS INTEGER) AS is{i}" for i in range(3)) + " FROM events, (SELECT min(event_type) AS t0, max(event_type) AS t2, (SELECT DISTINCT event_type FROM events ORDER BY 1 LIMIT 1 OFFSET 1) AS t1 FROM events)")
def feature_onehot(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    types = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").collect()]
    t = [types[0], types[1], types[-1]]
    return e.select(F.col("event_id").alias("id"), *((F.col("event_type") == x).cast("int").alias(f"is{i}") for i, x in enumerate(t)))


@query("SELECT vec_id AS id, CAST(i AS INTEGER) AS dim, CAST(round(CAST(embedding[i + 1] AS DOUBLE) * 10000) AS BIGINT) AS q, round(CAST(round(CAST(embedding[i + 1] AS DOUBLE) * 10000) AS BIGINT) / 10000.0, 6) AS value FROM embeddings, range(64) AS g(i)")
def feature_fixed_point(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.posexplode("embedding").alias("dim", "v"))
    q = V.quantise(F.col("v").cast("double"), 1e4)
    return e.select("id", "dim", q.alias("q"), r6(V.dequantise(q, 1e4)).alias("value"))


def _view(name: str, sql: str) -> None:
    """A feature view: every coordinate of every point as a row."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        v = ft.VIEWS[name][1](spark, sf_dir)
        return v.select(F.col("point_id").alias("id"), F.posexplode("x").alias("dim", "v")).select("id", "dim", (F.round("v", 4) + 0.0).alias("value"))  # no negative zero

    query(sql, f"features_{name}")(run)


def _view_sql(rel: str, feats: list[str], pid: str, prelude: str = "") -> str:
    body = ", ".join(f"CAST({f} AS DOUBLE) AS v{j}" for j, f in enumerate(feats, 1))
    rows = " UNION ALL ".join(f"SELECT id, CAST({j - 1} AS INTEGER) AS dim, round(v{j}, 4) + 0.0 AS value FROM p" for j in range(1, len(feats) + 1))
    return f"WITH {prelude}p AS (SELECT CAST({pid} AS VARCHAR) AS id, {body} FROM {rel}) {rows}"


_STARS = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey"


def _code(c: str, values: list[str]) -> str:
    return f"CASE {c} " + " ".join(f"WHEN '{v}' THEN {i}" for i, v in enumerate(values)) + " ELSE -1 END"


_EVTS = ["value", "json_extract_string(props, '$.k')", "hour(ts)", "dayofweek(ts) + 1"]
_view("events4", _view_sql("events", _EVTS, "event_id"))
_view("embed50", _view_sql("embeddings", [f"embedding[{j}]" for j in range(1, 51)], "vec_id"))
_view("embed64", _view_sql("embeddings", [f"embedding[{j}]" for j in range(1, 65)], "vec_id"))
_view("letters22", _view_sql("documents", [f"(length(lower(text)) - length(replace(lower(text), '{c}', ''))) / greatest(length(lower(text)), 1)" for c in ft.LETTERS], "doc_id"))
_ANG = "dayofyear(o_orderdate) * (2 * 3.141592653589793 / 366.0)"
_view(
    "orders8",
    _view_sql(
        "orders JOIN customer ON o_custkey = c_custkey JOIN (SELECT o_custkey AS oc, count(*) AS n FROM orders GROUP BY 1) ON o_custkey = oc",
        ["o_totalprice", "c_acctbal", f"sin({_ANG})", f"cos({_ANG})", _code("o_orderpriority", ft.PRIORITY), _code("o_orderstatus", ft.STATUS), "c_nationkey", "n"],
        "o_orderkey",
    ),
)
_view(
    "spend25",
    _view_sql("s", [f"coalesce(n{i}, 0) / t" for i in range(25)], "o_custkey", "s AS (SELECT o_custkey, sum(l_extendedprice) AS t, " + ", ".join(f"sum(l_extendedprice) FILTER (s_nationkey = {i}) AS n{i}" for i in range(25)) + " FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY o_custkey), "),
)
_TY = "(SELECT list(event_type ORDER BY event_type) FROM (SELECT DISTINCT event_type FROM events))"
_view(
    "events20",
    _view_sql("w", [f"coalesce({a}{i}, 0)" for i in range(1, 6) for a in ("n", "s", "m", "a")], "user_id || '-' || strftime(day, '%Y-%m-%d')", f"t AS (SELECT {_TY} AS ty), w AS (SELECT user_id, date_trunc('day', ts) AS day, " + ", ".join(f"count(value) FILTER (event_type = ty[{i}]) AS n{i}, sum(value) FILTER (event_type = ty[{i}]) AS s{i}, max(value) FILTER (event_type = ty[{i}]) AS m{i}, avg(value) FILTER (event_type = ty[{i}]) AS a{i}" for i in range(1, 6)) + " FROM events, t GROUP BY ALL), "),
)


def _checked_sums(name: str, sql: str) -> None:
    """Views keyed by a row hash: sums of the coordinates over all rows."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        d, view = ft.VIEWS[name]
        sums = view(spark, sf_dir).agg(F.count(F.lit(1)).alias("n"), *(F.sum(F.round(F.col("x")[j] * 100).cast("bigint")).alias(f"s{j}") for j in range(d)))
        return sums.select("n", F.posexplode(F.array(*(f"s{j}" for j in range(d)))).alias("dim", "total"))

    query(sql, f"features_{name}")(run)


def _sums_sql(rel: str, feats: list[str]) -> str:
    body = ", ".join(f"CAST(sum(CAST(round(CAST({f} AS DOUBLE) * 100) AS BIGINT)) AS BIGINT) AS s{j}" for j, f in enumerate(feats))
    return f"WITH p AS (SELECT count(*) AS n, {body} FROM {rel}) " + " UNION ALL ".join(f"SELECT n, CAST({j} AS INTEGER) AS dim, s{j} AS total FROM p" for j in range(len(feats)))


_checked_sums("lineitem2", _sums_sql("lineitem", ["l_quantity", "l_extendedprice"]))
_checked_sums("lineitem4", _sums_sql("lineitem", ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]))
_checked_sums(
    "star18",
    _sums_sql(
        _STARS,
        [
            "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber", _code("l_returnflag", ["A", "N", "R"]), _code("l_linestatus", ["F", "O"]), "o_totalprice", _code("o_orderpriority", ft.PRIORITY), _code("o_orderstatus", ft.STATUS),
            "c_acctbal", "s_acctbal", "p_size", "p_retailprice", "date_diff('day', o_orderdate, l_shipdate)", "month(l_shipdate)", "CAST(c_nationkey = s_nationkey AS INTEGER)", "coalesce(TRY_CAST(regexp_extract(p_brand, '([0-9]+)', 1) AS DOUBLE), 0)",
        ],
    ),
)
_HASH = "SELECT doc_id, CAST(('0x' || substr(md5(w), 1, 8)) AS BIGINT) % 178 AS bin, CAST(count(*) AS DOUBLE) AS n FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '\\s+')) AS w FROM documents) WHERE w <> '' GROUP BY 1, 2"


@query(f"WITH c AS ({_HASH}), m AS (SELECT doc_id, sqrt(sum(n * n)) AS s FROM c GROUP BY 1) SELECT c.doc_id AS id, CAST(bin AS INTEGER) AS dim, round(n / s, 6) AS value FROM c JOIN m USING (doc_id)", "features_hash178")
def features_hash178(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dims(ft.hash178(spark, sf_dir).withColumn("id", F.col("doc_id")), "id").where("value <> 0")


# ---------------------------------------------------------------- functions


@query("SELECT event_id AS id, round(pow(value, 0.5) + sqrt(value), 6) AS a, round(ln(value + 1), 6) AS b, round(exp(-value / 100), 6) AS c, abs(event_id - 50) AS d, CAST(floor(value) AS BIGINT) AS e, event_id // 7 AS f, event_id % 7 AS g, round(sin(value) + cos(value), 6) AS h, greatest(value, 10.0) AS i, least(value, 10.0) AS j FROM events")
def fn_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    v, i = F.col("value"), F.col("event_id")
    return table(spark, sf_dir, "events").select(
        i.alias("id"), r6(F.pow(v, F.lit(0.5)) + F.sqrt(v)).alias("a"), r6(F.log(v + 1)).alias("b"), r6(F.exp(-v / 100)).alias("c"), F.abs(i - 50).alias("d"), F.floor(v).alias("e"), F.floor(i / 7).alias("f"),
        (i % 7).alias("g"), r6(F.sin(v) + F.cos(v)).alias("h"), F.greatest(v, F.lit(10.0)).alias("i"), F.least(v, F.lit(10.0)).alias("j"),
    )


@query("SELECT l_orderkey AS id, CAST(year(l_shipdate) AS INTEGER) AS y, CAST(month(l_shipdate) AS INTEGER) AS m, CAST(day(l_shipdate) AS INTEGER) AS d, CAST(dayofweek(l_shipdate) + 1 AS INTEGER) AS dow, CAST(date_diff('day', o_orderdate, l_shipdate) AS INTEGER) AS lag, strftime(date_trunc('month', l_shipdate), '%Y-%m-%d') AS mon, strftime(l_shipdate + INTERVAL 7 DAY, '%Y-%m-%d') AS week FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_linenumber = 1")
def fn_date(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, o = table(spark, sf_dir, "lineitem").where("l_linenumber = 1"), table(spark, sf_dir, "orders")
    s = F.col("l_shipdate").cast("timestamp")
    day = lambda c: F.date_format(c, "yyyy-MM-dd")
    return li.join(o, li.l_orderkey == o.o_orderkey).select(
        F.col("l_orderkey").alias("id"), F.year(s).alias("y"), F.month(s).alias("m"), F.dayofmonth(s).alias("d"), F.dayofweek(s).alias("dow"), F.datediff(s, F.col("o_orderdate").cast("timestamp")).alias("lag"),
        day(F.date_trunc("month", s)).alias("mon"), day(s + F.expr("INTERVAL 7 DAYS")).alias("week"),
    )


@query("SELECT doc_id AS id, CAST(length(text) AS INTEGER) AS n, lower(lang) AS lang, substr(text, 1, 5) AS head, CAST(len(regexp_extract_all(text, 'th')) AS INTEGER) AS th, regexp_replace(source, '[0-9]+', '#') AS src, split_part(source, 'c', 2) AS tail, concat_ws('-', lang, source) AS tag, md5(source) AS h FROM documents")
def fn_string(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select(
        F.col("doc_id").alias("id"), F.length("text").alias("n"), F.lower("lang").alias("lang"), F.substring("text", 1, 5).alias("head"), F.regexp_count("text", F.lit("th")).alias("th"), F.regexp_replace("source", "[0-9]+", "#").alias("src"),
        F.split_part("source", F.lit("c"), F.lit(2)).alias("tail"), F.concat_ws("-", "lang", "source").alias("tag"), F.md5(F.col("source").cast("binary")).alias("h"),
    )


_A8 = "[CAST(e AS DOUBLE) FOR e IN embedding]"


@query(f"WITH a AS (SELECT vec_id AS id, {_A8} AS x FROM embeddings) SELECT id, CAST(len(list_filter(x, lambda v: v > 0)) AS INTEGER) AS pos, round(list_min(x), 6) AS lo, round(list_max(x), 6) AS hi, round(list_sum(x), 6) AS total, round(list_sum(list_transform(x, lambda v: v * v)), 6) AS sq, round(list_sort(x)[1], 6) AS first, len(list_filter(x, lambda v: v > 0.2)) > 0 AS big, round(x[3], 6) AS third, CAST(len(flatten([x, x])) AS INTEGER) AS twice FROM a")
def fn_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("x"))
    total = lambda c: F.aggregate(c, F.lit(0.0), lambda s, v: s + v)
    return a.select(
        "id", F.size(F.filter("x", lambda v: v > 0)).alias("pos"), r6(F.array_min("x")).alias("lo"), r6(F.array_max("x")).alias("hi"), r6(total(F.col("x"))).alias("total"), r6(total(F.transform("x", lambda v: v * v))).alias("sq"),
        r6(F.element_at(F.array_sort("x"), 1)).alias("first"), F.exists("x", lambda v: v > 0.2).alias("big"), r6(F.element_at("x", 3)).alias("third"), F.size(F.flatten(F.array("x", "x"))).alias("twice"),
    )


@query("SELECT event_id AS id, value AS v, value * 2 AS twice, CAST(CASE WHEN value > 10 THEN 1 ELSE 0 END AS INTEGER) AS kept, round(coalesce(CASE WHEN value > 10 THEN value END, 0) + 0, 6) AS back FROM events")
def fn_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Named features in a map, filtered, transformed and read back."""
    m = F.map_from_arrays(F.array(F.lit("v")), F.array("value"))
    e = table(spark, sf_dir, "events").select("event_id", m.alias("m"))
    kept = F.map_filter("m", lambda k, v: v > 10)
    return e.select(F.col("event_id").alias("id"), F.element_at("m", "v").alias("v"), F.element_at(F.transform_values("m", lambda k, v: v * 2), "v").alias("twice"), F.size(kept).alias("kept"), r6(F.coalesce(F.try_element_at(kept, F.lit("v")), F.lit(0.0))).alias("back"))


@query(f"WITH {Q.EV}, o AS (SELECT * FROM ev WHERE id = 0) SELECT e.id, CAST(e.v1*o.v1 + e.v2*o.v2 + e.v3*o.v3 + e.v4*o.v4 AS DOUBLE) AS dot, round(sqrt(e.v1*e.v1 + e.v2*e.v2 + e.v3*e.v3 + e.v4*e.v4), 6) AS norm, round((e.v1*o.v1 + e.v2*o.v2 + e.v3*o.v3 + e.v4*o.v4) / (sqrt(e.v1*e.v1 + e.v2*e.v2 + e.v3*e.v3 + e.v4*e.v4) * sqrt(o.v1*o.v1 + o.v2*o.v2 + o.v3*o.v3 + o.v4*o.v4)), 6) AS cosine, CAST(e.v1 + o.v1 AS DOUBLE) AS plus, CAST(e.v1 - o.v1 AS DOUBLE) AS minus, e.v1 * 0.5 AS half, round((3.0 * e.v1 + 1.0 * o.v1) / 4.0, 6) AS mixed FROM ev e, o")
def fn_vector(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir)
    o = V.vec(p.where("id = 0").first()["x"])
    x = F.col("x")
    return p.select(
        "id", V.vec_dot(x, o).alias("dot"), r6(V.vec_norm(x)).alias("norm"), r6(V.vec_cosine(x, o)).alias("cosine"), V.vec_add(x, o)[0].alias("plus"), V.vec_sub(x, o)[0].alias("minus"), V.vec_scale(x, 0.5)[0].alias("half"),
        r6(V.vec_mix(x, F.lit(3.0), o, F.lit(1.0))[0]).alias("mixed"),
    )


@query(f"SELECT event_id AS id, round({Q.uniform("event_id || '-7'")}, 9) AS u, round(sqrt(-2.0 * ln({Q.uniform("event_id || '-7-a'")})) * cos(2 * pi() * {Q.uniform("event_id || '-7-b'")}), 6) AS z FROM events")
def fn_hash_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    i = F.col("event_id")
    return table(spark, sf_dir, "events").select(i.alias("id"), F.round(V.uniform_from(i, F.lit("7")), 9).alias("u"), r6(V.normal_from(i, F.lit("7"))).alias("z"))


@query("SELECT event_id AS id FROM events WHERE (value > 20 AND value BETWEEN 10 AND 200 AND event_type IN (SELECT DISTINCT event_type FROM events ORDER BY 1 LIMIT 2)) OR event_type LIKE '%v%' OR value IS NULL")
def filter_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    two = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").limit(2).collect()]
    keep = ((F.col("value") > 20) & F.col("value").between(10, 200) & F.col("event_type").isin(two)) | F.col("event_type").like("%v%") | F.col("value").isNull()
    return e.where(keep).select(F.col("event_id").alias("id"))


@query("SELECT vec_id AS id FROM embeddings WHERE len(embedding) = 64 AND NOT list_bool_or([isnan(e) OR isinf(e) OR e IS NULL FOR e IN embedding])")
def filter_finite_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").where(V.finite_vector(F.col("embedding"), 64)).select(F.col("vec_id").alias("id"))


# ---------------------------------------------------------------- joins


@query(f"WITH {Q.EV}, {C0}, {NEAR0} SELECT id, CAST(k AS INTEGER) AS k FROM a")
def join_bnl_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir)
    c = first_rows(p)
    both = p.crossJoin(F.broadcast(centroid_rows(p, c)))  # K rows on the inner side
    return both.groupBy("id").agg(F.min_by("k", F.struct(V.sq_dist(F.col("x"), F.col("c")), "k")).alias("k"))


@query(f"WITH {Q.EV}, {C0}, {NEAR0} SELECT id, a.k, round(v1 - c1, 6) AS off FROM a JOIN c0 USING (k)")
def join_broadcast_shift(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir)
    c = first_rows(p)
    return assign(p, c).join(F.broadcast(centroid_rows(p, c)), "k").select("id", "k", r6(F.col("x")[0] - F.col("c")[0]).alias("off"))


@query(f"SELECT n_name AS nation, count(*) AS n, CAST(sum(CAST(round(l_quantity) AS BIGINT)) AS BIGINT) AS q FROM {_STARS} JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def join_star_smj(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, o, p, s, c, n = (table(spark, sf_dir, t) for t in ("lineitem", "orders", "part", "supplier", "customer", "nation"))
    j = li.join(o.hint("merge"), li.l_orderkey == o.o_orderkey).join(p.hint("shuffle_hash"), li.l_partkey == p.p_partkey).join(s, li.l_suppkey == s.s_suppkey).join(c, o.o_custkey == c.c_custkey)
    return j.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).groupBy(F.col("n_name").alias("nation")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.round("l_quantity").cast("bigint")).alias("q"))


@query(f"WITH {Q.EV}, z AS (SELECT b, count(*) AS n FROM ev GROUP BY b) SELECT x.b AS step, y.b AS b, y.n FROM z x JOIN z y ON y.b > x.b - 3 AND y.b <= x.b")
def join_range_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    z = ev(spark, sf_dir).groupBy(F.col("batch_seq").alias("b")).agg(F.count(F.lit(1)).alias("n"))
    reach = z.select(F.explode(F.sequence(F.col("b"), F.col("b") + 2)).alias("step"), "b", "n")
    return reach.join(z.select(F.col("b").alias("step")), "step")


_MODELS = "m AS (SELECT DISTINCT date_trunc('day', ts) AS mts, dayofyear(ts) AS model FROM events WHERE dayofyear(ts) % 3 = 0)"


@query(f"WITH {_MODELS} SELECT event_id AS id, CAST(model AS INTEGER) AS model FROM events ASOF LEFT JOIN m ON ts >= mts")
def join_asof_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event with the newest model before it: union and a running last, within hour-independent id ranges of the model's day."""
    e = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    m = e.where(F.dayofyear("ts") % 3 == 0).select(F.date_trunc("day", "ts").alias("mts"), F.dayofyear("ts").alias("model")).distinct()
    # a model is in force until the next one: intervals of a small relation, joined by the days they cover
    nxt = F.lead("mts").over(Window.orderBy("mts"))  # one row a model
    force = m.withColumn("until", F.coalesce(nxt, F.lit("9999-01-01").cast("timestamp")))
    last = e.agg(F.max("ts")).first()[0]
    days = force.select("model", F.explode(F.sequence(F.to_date("mts"), F.to_date(F.least(F.col("until") - F.expr("INTERVAL 1 SECOND"), F.lit(last))))).alias("day"))
    return e.withColumn("day", F.to_date("ts")).join(days, "day", "left").select(F.col("event_id").alias("id"), "model")


@query(f"WITH {Q.EV}, p AS (SELECT i AS concept, i * 2 AS lo, i * 2 + 2 AS hi FROM range(10000) AS g(i)), z AS (SELECT b, count(*) AS n FROM ev GROUP BY b) SELECT b, CAST(concept AS INTEGER) AS concept, b - lo + 1 AS t_index, n FROM z JOIN p ON b >= lo AND b < hi")
def join_interval_concept(spark: SparkSession, sf_dir: str) -> DataFrame:
    z = ev(spark, sf_dir).groupBy(F.col("batch_seq").alias("b")).agg(F.count(F.lit(1)).alias("n"))
    p = spark.range(10_000).select(F.col("id").cast("int").alias("concept"), (F.col("id") * 2).alias("lo"), (F.col("id") * 2 + 2).alias("hi"))
    return z.join(F.broadcast(p), (z.b >= p.lo) & (z.b < p.hi)).select("b", "concept", (F.col("b") - F.col("lo") + 1).alias("t_index"), "n")


@query("SELECT doc_id AS id, n_chars FROM documents SEMI JOIN labels USING (doc_id)")
def join_semi_labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.col("doc_id"), "n_chars").join(table(spark, sf_dir, "labels"), "doc_id", "left_semi").withColumnRenamed("doc_id", "id")


@query(f"WITH {Q.EV} SELECT DISTINCT b FROM ev ANTI JOIN (SELECT i AS b FROM range(3) AS g(i)) d USING (b)")
def join_anti_unprocessed(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = spark.range(3).select(F.col("id").alias("batch_seq"))
    return ev(spark, sf_dir).join(done, "batch_seq", "left_anti").select(F.col("batch_seq").alias("b")).distinct()


@query(f"WITH {Q.EV}, {C0}, {NEAR0}, {CUR}, x AS (SELECT k, count(*) AS n0 FROM a, cur WHERE b <= cur // 2 GROUP BY k), y AS (SELECT k, count(*) AS n1 FROM a, cur WHERE b > cur // 2 GROUP BY k) SELECT CAST(coalesce(x.k, y.k) AS INTEGER) AS k, coalesce(n0, 0) AS n0, coalesce(n1, 0) AS n1 FROM x FULL JOIN y ON x.k = y.k")
def join_full_cluster_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir)
    a, half = assign(p, first_rows(p)), last_batch(p) // 2
    count = lambda w, n: a.where(w).groupBy("k").agg(F.count(F.lit(1)).alias(n))
    return count(F.col("batch_seq") <= half, "n0").join(count(F.col("batch_seq") > half, "n1"), "k", "full_outer").select("k", F.coalesce("n0", F.lit(0)).alias("n0"), F.coalesce("n1", F.lit(0)).alias("n1"))


@query(f"WITH {Q.EV}, {C0} SELECT k, id, CAST(d AS BIGINT) AS d2 FROM (SELECT c.k, p.id, {Q.d2('p', 'c', D)} AS d, row_number() OVER (PARTITION BY c.k ORDER BY {Q.d2('p', 'c', D)}, p.id) AS r FROM ev p CROSS JOIN c0 c) WHERE r <= 3")
def join_lateral_topm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The three points nearest to each centroid, by a lateral subquery for each of the K rows."""
    p = ev(spark, sf_dir)
    c = centroid_rows(p, first_rows(p))
    pts = p.select("id", "x")
    top = pts.select("id", V.sq_dist(F.col("x"), F.col("c").outer()).alias("d")).orderBy("d", "id").limit(3)
    return c.lateralJoin(top).select("k", "id", F.col("d").cast("long").alias("d2"))


# ---------------------------------------------------------------- aggregates


@query(f"WITH {Q.EV}, {C0}, {NEAR0} SELECT b, CAST(k AS INTEGER) AS k, count(*) AS n, CAST(sum(d2) AS BIGINT) AS sse FROM a GROUP BY b, k")
def agg_partial_final(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir)
    return cluster_stats(p, [first_rows(p)]).select(F.col("batch_seq").alias("b"), "k", F.col("n").cast("long").alias("n"), F.col("sse").cast("long").alias("sse"))


@query(f"WITH {Q.EV} " + " UNION ALL ".join(f"SELECT b, CAST({j - 1} AS INTEGER) AS dim, CAST(sum(v{j}) AS DOUBLE) AS value FROM ev GROUP BY b" for j in range(1, 5)))
def agg_vec_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = ev(spark, sf_dir).groupBy(F.col("batch_seq").alias("b")).agg(*(F.sum(F.col("x")[j]).alias(f"s{j}") for j in range(D)))
    return s.select("b", F.posexplode(F.array(*(f"s{j}" for j in range(D)))).alias("dim", "value"))


@query(f"WITH {Q.EV} SELECT b, min_by(id, (v1, id)) AS lo, max_by(id, (v1, id)) AS hi FROM (SELECT b, id, v1 FROM ev) GROUP BY b")
def agg_argmin(spark: SparkSession, sf_dir: str) -> DataFrame:
    key = F.struct(F.col("x")[0], F.col("id"))
    return ev(spark, sf_dir).groupBy(F.col("batch_seq").alias("b")).agg(F.min_by("id", key).alias("lo"), F.max_by("id", key).alias("hi"))


@query("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def agg_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query("SELECT event_type, true AS approx_close, true AS sketch_close FROM events GROUP BY 1")
def agg_approx_distinct_bounded(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = table(spark, sf_dir, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("n"), F.approx_count_distinct("user_id", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id", 12)).alias("s"))
    near = lambda c: F.abs(F.col(c) - F.col("n")) <= F.greatest(F.lit(3), F.col("n") * 0.1)
    return g.select("event_type", near("a").alias("approx_close"), near("s").alias("sketch_close"))


_AG = "count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS total"


def _grouped(kind: str):  # noqa: ANN202
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = table(spark, sf_dir, "events").select("event_type", (F.col("user_id") % 4).alias("u"), "value")
        if kind == "sets":
            g = e.groupingSets([["event_type"], ["u"], []], "event_type", "u")
        else:
            g = e.rollup("event_type", "u") if kind == "rollup" else e.cube("event_type", "u")
        return g.agg(F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("value") * 100).cast("bigint")).alias("total"), F.grouping_id().cast("long").alias("g"))

    return run


for _k, _by in (("rollup", "ROLLUP (event_type, u)"), ("cube", "CUBE (event_type, u)"), ("sets", "GROUPING SETS ((event_type), (u), ())")):
    query(f"SELECT event_type, u, {_AG}, CAST(grouping(event_type, u) AS BIGINT) AS g FROM (SELECT event_type, user_id % 4 AS u, value FROM events) GROUP BY {_by}", "agg_grouping_sets" if _k == "sets" else f"agg_{_k}")(_grouped(_k))


@query("SELECT event_type, round(quantile_cont(value, 0.25), 6) AS q1, round(quantile_cont(value, 0.5), 6) AS med, round(quantile_cont(value, 0.9), 6) AS p90, true AS approx_close, true AS sketch_close FROM events GROUP BY 1")
def agg_percentiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = table(spark, sf_dir, "events").groupBy("event_type")
    a = g.agg(
        F.percentile("value", F.lit(0.25)).alias("q1"), F.percentile("value", F.lit(0.5)).alias("med"), F.percentile("value", F.lit(0.9)).alias("p90"), F.percentile_approx("value", 0.5, 1000).alias("ap"),
        F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("value"), F.lit(0.5)).alias("kl"), F.stddev("value").alias("sd"),
    )
    near = lambda c: F.abs(F.col(c) - F.col("med")) <= F.col("sd") * 0.2
    return a.select("event_type", r6("q1").alias("q1"), r6("med").alias("med"), r6("p90").alias("p90"), near("ap").alias("approx_close"), near("kl").alias("sketch_close"))


@query("SELECT l_returnflag AS flag, CAST(sum(CAST(round(l_quantity) AS BIGINT)) FILTER (l_linestatus = 'F') AS BIGINT) AS f, CAST(sum(CAST(round(l_quantity) AS BIGINT)) FILTER (l_linestatus = 'O') AS BIGINT) AS o FROM lineitem GROUP BY 1")
def agg_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = table(spark, sf_dir, "lineitem").withColumn("q", F.round("l_quantity").cast("bigint"))
    return li.groupBy(F.col("l_returnflag").alias("flag")).pivot("l_linestatus", ["F", "O"]).sum("q").select("flag", F.col("F").alias("f"), F.col("O").alias("o"))


@query("SELECT c_custkey AS id, 'balance' AS name, CAST(round(c_acctbal) AS BIGINT) AS value FROM customer UNION ALL SELECT c_custkey, 'nation', CAST(c_nationkey AS BIGINT) FROM customer")
def agg_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"), F.round("c_acctbal").cast("bigint").alias("balance"), F.col("c_nationkey").cast("bigint").alias("nation"))
    return c.unpivot("id", ["balance", "nation"], "name", "value")


@query(f"WITH {Q.EV}, w AS (SELECT *, CAST(1 + b % 3 AS DOUBLE) AS w FROM ev), m AS (SELECT sum(w * v1) / sum(w) AS m1, sum(w * v2) / sum(w) AS m2 FROM w) SELECT round(any_value(m1), 6) AS mean, round(sum(w * (v1 - m1) * (v1 - m1)) / sum(w), 4) AS variance, round(sum(w * (v1 - m1) * (v2 - m2)) / sum(w), 4) AS covariance FROM w, m")
def agg_weighted_moments(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir).select(F.col("x")[0].alias("a"), F.col("x")[1].alias("b"), (1.0 + F.col("batch_seq") % 3).alias("w"))
    s = p.agg(*(F.sum(e).alias(n) for n, e in (("w", F.col("w")), ("a", F.expr("w * a")), ("b", F.expr("w * b")), ("aa", F.expr("w * a * a")), ("ab", F.expr("w * a * b")))))
    mean, mb = F.col("a") / F.col("w"), F.col("b") / F.col("w")
    return s.select(r6(mean).alias("mean"), F.round(F.col("aa") / F.col("w") - mean * mean, 4).alias("variance"), F.round(F.col("ab") / F.col("w") - mean * mb, 4).alias("covariance"))


@query(f"WITH {Q.EV}, {C0}, {NEAR0} SELECT CAST(k AS INTEGER) AS k, CAST(floor(sqrt(d2) / 100) AS BIGINT) AS bin, count(*) AS n, CAST(max(d2) AS DOUBLE) AS u FROM a GROUP BY 1, 2")
def agg_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir)
    return measures.distance_histogram(assign(p, first_rows(p)), 100.0)


@query("WITH " + ",\n".join([Q.EM, Q.first_rows("c10", "em", 10, Q.EM_D, "true"), Q.near("a", "em", "c10", Q.EM_D)]) + " SELECT CAST(k AS INTEGER) AS k, label, count(*) AS n FROM a GROUP BY k, label")
def agg_contingency(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = em(spark, sf_dir)
    return measures.contingency(assign(p, np.array([r["x"] for r in p.orderBy("id").limit(10).collect()])), "k", "label")


# ---------------------------------------------------------------- windows, order, sets

_BY_TYPE = "PARTITION BY event_type ORDER BY value, event_id"


@query(f"SELECT event_id AS id, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS nt, round(percent_rank() OVER w, 6) AS pr FROM events WINDOW w AS ({_BY_TYPE})")
def win_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("event_type").orderBy("value", "event_id")
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), r6(F.percent_rank().over(w)).alias("pr"))


def _batch_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir)
    return cluster_stats(p, [first_rows(p)]).groupBy(F.col("batch_seq").alias("b")).agg((F.sum("sse") / F.sum("n")).alias("e"))


_BE = "be AS (SELECT b, avg(d2) AS e FROM a GROUP BY b)"


@query(f"WITH {Q.EV}, {C0}, {NEAR0}, {_BE} SELECT b, round(e - lag(e) OVER w, 5) AS change, round(lead(e) OVER w, 5) AS next, round(first_value(e) OVER w, 5) AS first FROM be WINDOW w AS (ORDER BY b)")
def win_lag_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.orderBy("b")  # one row a batch
    return _batch_errors(spark, sf_dir).select("b", F.round(F.col("e") - F.lag("e").over(w), 5).alias("change"), F.round(F.lead("e").over(w), 5).alias("next"), F.round(F.first("e").over(w), 5).alias("first"))


@query(f"WITH {Q.EV}, z AS (SELECT b, count(*) AS n FROM ev GROUP BY b) SELECT b, CAST(sum(n) OVER (ORDER BY b ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS BIGINT) AS m_t, CAST(sum(n) OVER (ORDER BY b ROWS UNBOUNDED PRECEDING) AS BIGINT) AS so_far FROM z")
def win_rows_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    z = ev(spark, sf_dir).groupBy(F.col("batch_seq").alias("b")).agg(F.count(F.lit(1)).alias("n"))
    w = Window.orderBy("b")  # one row a batch
    return z.select("b", F.sum("n").over(w.rowsBetween(-3, 0)).alias("m_t"), F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("so_far"))


@query("SELECT event_id AS id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-86_400_000_000, 0)
    return e.select(F.col("event_id").alias("id"), F.count(F.lit(1)).over(w).alias("n"))


@query(f"WITH {Q.EV}, z AS (SELECT b, CAST(sum(v1) AS DOUBLE) AS y FROM ev GROUP BY b) SELECT x.b, round(sum(pow(0.5, x.b - z.b) * z.y), 6) AS faded FROM z x JOIN z ON z.b BETWEEN x.b - 3 AND x.b GROUP BY x.b")
def win_faded_running(spark: SparkSession, sf_dir: str) -> DataFrame:
    z = ev(spark, sf_dir).groupBy(F.col("batch_seq").alias("b")).agg(F.sum(F.col("x")[0]).alias("y"))
    return measures.faded_running(z, "b", "y", 0.5, 4).select("b", r6("faded").alias("faded"))


@query("SELECT event_id AS id, round(value / min(value) OVER (PARTITION BY event_type), 6) AS ratio FROM events")
def win_min_norm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A least value of 0 divides as doubles do (infinite, or not a number for 0 / 0), where ANSI division would raise."""
    v, least = F.col("value"), F.min("value").over(Window.partitionBy("event_type"))
    by_zero = F.when(F.isnan(v) | (v == 0), float("nan")).when(v > 0, float("inf")).when(v < 0, float("-inf"))
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), r6(F.when(least == 0, by_zero).otherwise(v / least)).alias("ratio"))


@query(f"WITH {Q.EV}, {C0}, {NEAR0} SELECT CAST(k AS INTEGER) AS k, id, CAST(rank AS INTEGER) AS rank FROM (SELECT k, id, row_number() OVER (PARTITION BY k ORDER BY d2 DESC, CAST(id AS VARCHAR)) AS rank FROM a) WHERE rank <= 3")
def sort_topk_far(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir)
    return measures.farthest(assign(p, first_rows(p)), 3).select("k", "id", "rank")


@query("SELECT event_id AS id, value FROM events ORDER BY value DESC, event_id LIMIT 20 OFFSET 40")
def sort_global_page(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), "value").orderBy(F.desc("value"), "id").offset(40).limit(20)


@query(f"WITH {EV5} SELECT id, b FROM ev5")
def set_union_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = fifths(spark, sf_dir).select("id", F.col("batch_seq").alias("b"))
    return p.where("b < 4").unionByName(p.where("b = 4"))


@query(f"WITH {EV5} SELECT v2, v3 FROM ev5 WHERE b < 2 INTERSECT SELECT v2, v3 FROM ev5 WHERE b >= 2")
def set_intersect(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = fifths(spark, sf_dir)
    side = lambda old: p.where((F.col("batch_seq") < 2) == old).select(F.col("x")[1].cast("long").alias("v2"), F.col("x")[2].cast("long").alias("v3"))
    return side(True).intersect(side(False))


@query(f"WITH {EV5} SELECT id FROM ev5 EXCEPT SELECT id FROM ev5 WHERE b > 0")
def set_except_evicted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What eviction removed is exactly the oldest batch."""
    p = fifths(spark, sf_dir)
    return batching.evict(p, 4, 5).select("id").exceptAll(batching.evict(p, 4, 4).select("id"))


@query(f"WITH {Q.EV}, {C0}, {Q.first_rows('c1', 'ev', K, D, 'b = 1')} SELECT 'past' AS role, k, c1 FROM c0 UNION ALL SELECT 'fresh', k, c1 FROM c1")
def set_union_all_centroids(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ev(spark, sf_dir)
    one = lambda role, b: centroid_rows(p, first_rows(p, K, b)).select(F.lit(role).alias("role"), "k", F.col("c")[0].alias("c1"))
    return one("past", 0).unionAll(one("fresh", 1))


@query(f"SELECT event_id AS id FROM events WHERE {Q.uniform("event_id || '-s'")} < 0.1")
def sample_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("id")).where(V.uniform_from(F.col("id"), F.lit("s")) < 0.1)


@query("WITH RECURSIVE p(t, w) AS (SELECT 0, CAST(1 AS DOUBLE) UNION ALL SELECT t + 1, w * 0.5 FROM p WHERE t < 12), d AS (SELECT CAST(floor(epoch(ts) / 86400) AS BIGINT) AS d, count(*) AS n FROM events GROUP BY 1) SELECT CAST(t AS INTEGER) AS t, w, n * w AS mass FROM p JOIN d ON t = (SELECT max(d) FROM d) - d.d")
def recursive_powers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights by recursion, met with the days of the events by their age: the faded mass of each."""
    p = spark.sql("WITH RECURSIVE p(t, w) AS (SELECT 0, 1D UNION ALL SELECT t + 1, w * 0.5D FROM p WHERE t < 12) SELECT t, w FROM p")
    d = table(spark, sf_dir, "events").groupBy(F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 86_400).alias("d")).agg(F.count(F.lit(1)).alias("n"))
    age = d.select((F.max("d").over(Window.partitionBy(F.lit(0))) - F.col("d")).alias("t"), "n")  # a row a day
    return p.join(age, "t").select("t", "w", (F.col("n") * F.col("w")).alias("mass"))


# ---------------------------------------------------------------- SQL functions


@query(f"WITH {Q.EV}, {C0}, {NEAR0} SELECT id, CAST(k AS INTEGER) AS k, CAST(d2 AS DOUBLE) AS d2, CAST((v1 - 5) * (v1 - 5) + v2 * v2 + v3 * v3 + v4 * v4 AS DOUBLE) AS s, pow(0.5, b) AS w FROM a")
def udf_sql_sqdist(spark: SparkSession, sf_dir: str) -> DataFrame:
    V.register(spark)
    p = ev(spark, sf_dir)
    c = "array(" + ", ".join("array(" + ", ".join(f"{v}D" for v in r) + ")" for r in first_rows(p).tolist()) + ")"
    return p.selectExpr("id", f"nearest_index(x, {c}) AS k", f"nearest_dist2(x, {c}) AS d2", "sq_dist(x, array(5D, 0D, 0D, 0D)) AS s", "faded_weight(0.5D, batch_seq) AS w")


@query("SELECT CAST(e AS DOUBLE) AS eps, round(pow(0.01 / CAST(e AS DOUBLE), 0.2), 6) AS rho, round(2 * sqrt(greatest((2 * pow(0.5, 3) - 1) / 3 + (1 - 0.5) / (1 + 0.5), 0) / 2000 * ln(2 / 0.05)), 8) AS gamma FROM (VALUES (0.5), (1.0), (2.0)) AS x(e)")
def udf_sql_theory(spark: SparkSession, sf_dir: str) -> DataFrame:
    V.register(spark)
    return spark.createDataFrame([(0.5,), (1.0,), (2.0,)], "eps double").selectExpr("eps", "round(choose_rho(eps, 10D, 2D), 6) AS rho", "round(drift_gamma(0.5D, 3D, 1000D, 2D, 0.05D), 8) AS gamma")


@query(f"WITH {Q.EV} SELECT id, CAST((v1 - 5) * (v1 - 5) + v2 * v2 + v3 * v3 + v4 * v4 AS DOUBLE) AS d2 FROM ev")
def udf_arrow_sqdist(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ev(spark, sf_dir).select("id", V.block_distance([5.0, 0.0, 0.0, 0.0])("x").alias("d2"))


@query(f"WITH {Q.EV} SELECT b, CAST(sum(v1) AS DOUBLE) AS s1, CAST(sum(v4) AS DOUBLE) AS s4 FROM ev GROUP BY b")
def udaf_vec_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = ev(spark, sf_dir).groupBy(F.col("batch_seq").alias("b")).agg(V.vec_sum("x").alias("s"))
    return s.select("b", F.col("s")[0].alias("s1"), F.col("s")[3].alias("s4"))


@query("SELECT * FROM (VALUES (0, 1), (1, 0), (2, 2)) AS t(i, j)")
def udtf_assignment_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    udtfs.register(spark)
    spark.createDataFrame([(0, 0, 4.0), (0, 1, 1.0), (0, 2, 3.0), (1, 0, 2.0), (1, 1, 0.0), (1, 2, 5.0), (2, 0, 3.0), (2, 1, 2.0), (2, 2, 2.0)], "i int, j int, cost double").createOrReplaceTempView("cost_rows")
    return spark.sql("SELECT i, j FROM assignment_pairs(TABLE(cost_rows) WITH SINGLE PARTITION)")


@query("SELECT CAST(k AS INTEGER) AS k, CAST(d AS INTEGER) AS dim, CAST(v AS DOUBLE) AS value FROM (VALUES (0, 0, 1.5), (0, 1, 2.0), (1, 0, -3.0), (1, 1, 0.25)) AS t(k, d, v)")
def udtf_centroid_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    udtfs.register(spark)
    return spark.sql("SELECT k, dim, value FROM centroid_rows('[[1.5, 2.0], [-3.0, 0.25]]')")


@query(
    Q.with_(EV5, Q.first_rows("c0", "ev5", K, D), Q.near("a", "ev5", "c0", D), select="SELECT c.k, round(CASE WHEN count(a.k) > 0 THEN avg(a.v1) ELSE c.c1 END, 6) AS c1, round(CASE WHEN count(a.k) > 0 THEN avg(a.v4) ELSE c.c4 END, 6) AS c4 FROM (SELECT DISTINCT b FROM ev5) z CROSS JOIN c0 c LEFT JOIN a ON a.k = c.k AND a.b = z.b GROUP BY z.b, c.k, c.c1, c.c4")
)
def udtf_lloyd_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One update of a model by each batch on its own."""
    import json

    udtfs.register(spark)
    p = fifths(spark, sf_dir)
    p.select("x", F.lit(1.0).alias("w"), F.col("batch_seq").alias("b")).createOrReplaceTempView("lloyd_points")
    model = json.dumps(first_rows(p).tolist())
    return spark.sql(f"SELECT k, round(c[0], 6) AS c1, round(c[3], 6) AS c4 FROM lloyd_step(TABLE(lloyd_points) PARTITION BY (b), '{model}')")
