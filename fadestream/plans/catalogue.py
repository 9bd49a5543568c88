"""All queries of the engine by name, their SQL, and the flagship."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from fadestream.operators.engine import FadingClusterer
from fadestream.operators.features import events4
from fadestream.plans import methods, operations, streams  # noqa: F401  they register their queries
from fadestream.plans.registry import QUERIES, SQL


def flagship(spark: SparkSession, sf_dir: str, n: int = 100, k: int = 5) -> DataFrame:
    """Events in batches of n through the fading clusterer with the pair start: errors and centroids of every batch."""
    from pyspark.sql import functions as F

    p = events4(spark, sf_dir).withColumn("batch_seq", F.floor(F.col("event_id") / n).cast("long")).select("point_id", "x", "batch_seq").persist()
    f, rows = FadingClusterer(k, 0.457, 12, "pair"), []
    for s in range(p.agg(F.max("batch_seq")).first()[0] + 1):
        r = f.step(p.where(F.col("batch_seq") == s), s)
        if r is not None:
            rows += [(s, r.method, c, j, float(v), r.init_faded, r.final_faded, r.since_drift(0), r.iterations, r.total_distances) for c, row in enumerate(r.centroids) for j, v in enumerate(row)]
    return spark.createDataFrame(rows, "batch_seq long, method string, k int, dim int, value double, init_faded double, final_faded double, since_drift double, iterations int, distances long")


__all__ = ["QUERIES", "SQL", "flagship"]
