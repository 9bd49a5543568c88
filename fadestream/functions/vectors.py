"""Vector arithmetic as Catalyst expressions, SQL functions of the same names, and portable hash-based random numbers."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def vec(values: Sequence[float]) -> Column:
    return F.array(*(F.lit(float(v)) for v in values))


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_sub(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def vec_scale(a: Column, s: Column | float) -> Column:
    s = s if isinstance(s, Column) else F.lit(float(s))
    return F.transform(a, lambda x: x * s)


def vec_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def vec_norm(a: Column) -> Column:
    return F.sqrt(vec_dot(a, a))


def vec_cosine(a: Column, b: Column) -> Column:
    return vec_dot(a, b) / (vec_norm(a) * vec_norm(b))


def vec_mix(a: Column, wa: Column, b: Column, wb: Column) -> Column:
    """The weighted mean of two vectors; the first where both weights are 0."""
    return F.when(wa + wb == 0, a).otherwise(F.zip_with(a, b, lambda x, y: (wa * x + wb * y) / (wa + wb)))


def sq_dist(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, d: s + d)


def sq_dist_unrolled(x: Column, c: Sequence[float]) -> Column:
    """Squared distance to a constant, one term a coordinate: stays in generated code."""
    terms = [(x[j] - F.lit(float(v))) * (x[j] - F.lit(float(v))) for j, v in enumerate(c)]
    out = terms[0]
    for t in terms[1:]:
        out = out + t
    return out


def nearest_struct(x: Column, centroids: np.ndarray) -> Column:
    """struct(d2, k) of the nearest of a few constant centroids; equal distances go to the lowest k."""
    return F.least(*(F.struct(sq_dist_unrolled(x, c).alias("d2"), F.lit(k).alias("k")) for k, c in enumerate(centroids))) if len(centroids) > 1 else F.struct(sq_dist_unrolled(x, centroids[0]).alias("d2"), F.lit(0).alias("k"))


def nearest_lambda(x: Column, centroids: Column) -> Column:
    """The same for an array of centroids in a column."""
    return F.array_min(F.transform(centroids, lambda c, i: F.struct(sq_dist(x, c).alias("d2"), i.alias("k"))))


def finite_vector(x: Column, d: int) -> Column:
    """True for an array of d finite numbers."""
    return F.coalesce((F.size(x) == d) & F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))), F.lit(False))


def quantise(v: Column, scale: float) -> Column:
    return F.round(v * F.lit(float(scale))).cast("bigint")


def dequantise(q: Column, scale: float) -> Column:
    return q.cast("double") / F.lit(float(scale))


def uniform_from(*key: Column) -> Column:
    """A number in (0, 1) from the MD5 of the key parts joined by '-': the same in any engine that has MD5."""
    h = F.conv(F.substring(F.md5(F.concat_ws("-", *(k.cast("string") for k in key)).cast("binary")), 1, 8), 16, 10).cast("bigint")
    return (h.cast("double") + 0.5) / 4294967296.0


def normal_from(*key: Column) -> Column:
    """A standard normal number from two portable uniforms."""
    u, v = uniform_from(*key, F.lit("a")), uniform_from(*key, F.lit("b"))
    return F.sqrt(-2.0 * F.log(u)) * F.cos(F.lit(2.0 * np.pi) * v)


def faded_weight(rho: Column | float, t: Column) -> Column:
    return F.pow(rho if isinstance(rho, Column) else F.lit(float(rho)), t.cast("double"))


#: SQL bodies of the temporary functions: they are inlined, so plans have no function boundary.
SQL_FUNCTIONS = {
    "sq_dist(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, d) -> s + d)",
    "vec_add(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE>": "zip_with(a, b, (x, y) -> x + y)",
    "vec_scale(a ARRAY<DOUBLE>, s DOUBLE) RETURNS ARRAY<DOUBLE>": "transform(a, x -> x * s)",
    "vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "nearest_index(x ARRAY<DOUBLE>, c ARRAY<ARRAY<DOUBLE>>) RETURNS INT": "array_min(transform(c, (v, i) -> struct(aggregate(zip_with(x, v, (p, q) -> (p - q) * (p - q)), 0D, (s, d) -> s + d) AS d2, i AS k))).k",
    "nearest_dist2(x ARRAY<DOUBLE>, c ARRAY<ARRAY<DOUBLE>>) RETURNS DOUBLE": "array_min(transform(c, v -> aggregate(zip_with(x, v, (p, q) -> (p - q) * (p - q)), 0D, (s, d) -> s + d)))",
    "faded_weight(rho DOUBLE, t BIGINT) RETURNS DOUBLE": "pow(rho, t)",
    "choose_rho(eps DOUBLE, tau DOUBLE, m DOUBLE) RETURNS DOUBLE": "CASE WHEN eps <= 0.01 THEN 1D ELSE pow(0.01D / eps, m / tau) END",
    "drift_gamma(rho DOUBLE, t DOUBLE, n DOUBLE, u DOUBLE, delta DOUBLE) RETURNS DOUBLE": "u * sqrt(greatest((2 * pow(rho, t) - 1) / t + (1 - rho) / (1 + rho), 0D) / (2 * n) * ln(2 / delta))",
}


def register(spark: SparkSession) -> None:
    """Make the functions available in SQL under their names."""
    for head, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")


def block_distance(centroid: Sequence[float]):  # noqa: ANN201
    """Arrow-batched squared distance to a constant."""
    c = np.asarray(centroid, dtype=float)

    @F.pandas_udf("double")
    def distance(x: pd.Series) -> pd.Series:
        return pd.Series(((np.stack(x.to_numpy()) - c) ** 2).sum(axis=1) if len(x) else np.empty(0))

    return distance


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vec_sum(x: pd.Series) -> list:
    """Grouped aggregate: the sum of vectors."""
    return np.stack(x.to_numpy()).sum(axis=0).tolist()
