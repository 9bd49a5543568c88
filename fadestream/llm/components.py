"""Connected components of a link table by alternating star contraction, all on executors.

Every round rewrites each link towards the smallest neighbour; the table is written to the shared folder
between rounds, so lineage stays short and a lost executor costs one round at most. Nothing but two numbers a
round reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Stored


def _star(links: DataFrame, large: bool) -> DataFrame:
    """One star step over links (u, v) with v < u. Large: larger neighbours go to the smallest neighbour; small: smaller ones do."""
    if large:
        both = links.union(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    else:
        both = links
    least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("c"), F.least("m", "u").alias("m"))
    moved = both.join(least, F.col("u") == F.col("c"))
    if large:
        out = moved.where("v > c").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = moved.select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select(F.col("c").alias("u"), F.col("m").alias("v")))
    return out.where("u > v").distinct()


def components(links: DataFrame, left: str, right: str, max_rounds: int = 60) -> DataFrame:
    """Links (left, right) of any orderable type -> (node, root): root is the least node reachable; every linked node has a row.

    Null ends and self-links are ignored; repeated links count once; an empty table gives an empty table.
    """
    a, b = F.col(left), F.col(right)
    now = Stored(
        links.where(a.isNotNull() & b.isNotNull() & (a != b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(),
        "links",
    )
    mark = None
    for _ in range(max_rounds):
        nxt = Stored(_star(_star(now.df, True), False), "links")
        seen = nxt.df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        now.drop()
        now = nxt
        if tuple(seen) == mark:
            break
        mark = tuple(seen)
    else:
        raise RuntimeError(f"star contraction did not settle in {max_rounds} rounds")
    stars = now.df
    return stars.select(F.col("u").alias("node"), F.col("v").alias("root")).union(stars.select(F.col("v"), F.col("v")).distinct())
