r"""Mixing sources to target weights by hierarchical budgeting, all in DataFrame operations.

Documents hang in a tree domain - language - source. The token budget flows from the root: each parent's amount is shared
among its children by weight, a child never gets more than its subtree can give (its tokens times max_epochs), and what a
short child can't use goes to its siblings first; only what all of them can't use is missing at the parent, which its own
siblings then take. Shares are found by windows over the children ordered by capacity per weight. A leaf then takes whole
epochs and, of one more epoch in a seeded order, the longest prefix that fits. Running sums go by hash bucket, then
within one, so a leaf with a third of all rows is no single task's work.

The order of a leaf's rows is the hash of seed, epoch and doc_id, then of the text; so rows that share an id, or have none (their
text stands in for it), come in the same order however the table is partitioned.

Results for odd input: null texts have no tokens and cost nothing where they stand in the order; null
language or source is the node "none"; repeated rows are taken row by row, and which of rows equal in id and text comes first makes
no difference; a null doc_id is ordered by its text; an empty table gives no rows; other columns are neither read nor renamed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Stored, text_of

LEVELS = ("domain", "language", "origin")
#: Weights of the tree's nodes; a node that isn't listed weighs DEFAULT_WEIGHT. Domains are hash classes of the source.
DOMAINS = 4
WEIGHTS = {"domain": {"0": 4.0, "1": 3.0, "2": 2.0, "3": 1.0}, "language": {"en": 6.0, "fr": 2.0, "de": 2.0, "es": 1.0}, "origin": {}}
DEFAULT_WEIGHT, SEED, MAX_EPOCHS, SHARE = 1.0, 17, 2, 0.8


def token_count(text: Column) -> Column:
    """Runs of characters other than ASCII blanks."""
    bare = F.regexp_replace(text, r"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", "")
    return F.when(bare == "", 0).otherwise(F.size(F.split(bare, r"[\x20\x09-\x0D]+", -1))).cast("long")


def _weight(level: str, weights: dict[str, dict[str, float]]) -> Column:
    out = F.lit(DEFAULT_WEIGHT)
    for name, w in weights.get(level, {}).items():
        out = F.when(F.col(level) == name, F.lit(w)).otherwise(out)
    return out


def _share(children: DataFrame, parents: list[str], level: str, weights: dict[str, dict[str, float]]) -> DataFrame:
    """children: parents, level, cap, amount (of the parent) -> the same with amount of the child."""
    every = Window.partitionBy(*parents) if parents else Window.partitionBy(F.lit(0))
    order = every.orderBy(F.col("cap") / F.col("w"), level)
    earlier = order.rowsBetween(Window.unboundedPreceding, -1)
    out = children.withColumn("w", _weight(level, weights))
    out = out.withColumn("before", F.coalesce(F.sum("cap").over(earlier), F.lit(0))).withColumn("w_left", F.sum("w").over(every) - F.coalesce(F.sum("w").over(earlier), F.lit(0.0)))
    out = out.withColumn("unit", (F.col("amount") - F.col("before")) / F.col("w_left")).withColumn("short", F.col("unit") * F.col("w") >= F.col("cap"))
    level_unit = F.first(F.when(~F.col("short"), F.col("unit")), ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    out = out.withColumn("amount", F.when(F.col("short"), F.col("cap").cast("double")).otherwise(level_unit * F.col("w")))
    return out.drop("w", "before", "w_left", "unit", "short")


def budgets(leaves: DataFrame, target: Column, weights: dict[str, dict[str, float]], max_epochs: int) -> DataFrame:
    """leaves: LEVELS, tokens -> LEVELS, tokens, budget (whole tokens)."""
    capped = leaves.withColumn("cap", F.col("tokens") * max_epochs)
    root = capped.agg(F.sum("cap").alias("cap"), F.sum("tokens").alias("t")).select(F.least(target, F.col("cap").cast("double")).alias("amount"))
    nodes, parents = root, []
    for level in LEVELS:
        keys = [*parents, level]
        children = capped.groupBy(*keys).agg(F.sum("cap").alias("cap"))
        joined = children.join(nodes, parents) if parents else children.crossJoin(F.broadcast(nodes))  # the root is one row
        nodes = _share(joined, parents, level, weights).select(*keys, "amount")
        parents = keys
    return capped.join(nodes, list(LEVELS)).select(*LEVELS, "tokens", F.floor(F.col("amount") + 1e-6).alias("budget"))


def leaf_of() -> list[Column]:
    """The leaf of a document: domain, language, origin."""
    origin = F.coalesce(F.col("source").cast("string"), F.lit("none"))
    domain = F.pmod(F.crc32(origin.cast("binary")), F.lit(DOMAINS)).cast("string")
    return [domain.alias("domain"), F.coalesce(F.col("lang").cast("string"), F.lit("none")).alias("language"), origin.alias("origin")]


def mix(docs: DataFrame, weights: dict[str, dict[str, float]] | None = None, share: float = SHARE, max_epochs: int = MAX_EPOCHS, seed: int = SEED) -> DataFrame:
    """doc_id, th (hash of the text), domain, language, origin, tokens, budget (of the leaf), copies (how often the row is taken): a row per input row."""
    rows = docs.select(
        "doc_id",
        F.xxhash64("text").alias("th"),
        *leaf_of(),
        token_count(text_of()).alias("tokens"),
    )
    rows = Stored(rows, "tokens").df
    leaves = rows.groupBy(*LEVELS).agg(F.sum("tokens").alias("tokens"))
    total = leaves.agg(F.floor(F.sum("tokens") * F.lit(share))).first()[0] or 0
    plan = Stored(budgets(leaves, F.lit(float(total)), weights or WEIGHTS, max_epochs), "budgets").df
    plan = plan.select(*LEVELS, "budget", F.when(F.col("tokens") > 0, F.floor(F.col("budget") / F.col("tokens"))).otherwise(0).cast("long").alias("whole"), (F.col("budget") - F.when(F.col("tokens") > 0, F.floor(F.col("budget") / F.col("tokens")) * F.col("tokens")).otherwise(0)).alias("left"))
    keyed = rows.join(plan, list(LEVELS)).withColumn("key", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("whole").cast("string"), F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("none "), F.col("th").cast("string")))).cast("binary")))
    keyed = keyed.withColumn("bucket", F.substring("key", 1, 3))
    sums = keyed.groupBy(*LEVELS, "bucket").agg(F.sum("tokens").alias("t"))
    earlier = Window.partitionBy(*LEVELS).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select(*LEVELS, "bucket", F.coalesce(F.sum("t").over(earlier), F.lit(0)).alias("start"))
    upto = Window.partitionBy(*LEVELS, "bucket").orderBy("key", "th").rowsBetween(Window.unboundedPreceding, 0)
    out = keyed.join(starts, [*LEVELS, "bucket"]).withColumn("run", F.col("start") + F.sum("tokens").over(upto))
    return out.select("doc_id", "th", *LEVELS, "tokens", "budget", F.least(F.col("whole") + (F.col("run") <= F.col("left")).cast("long"), F.lit(max_epochs)).cast("long").alias("copies"))


def mixed(docs: DataFrame, weights: dict[str, dict[str, float]] | None = None, share: float = SHARE, seed: int = SEED) -> DataFrame:
    """The rows of docs that an epoch at most of each leaf takes, all columns. Of rows equal in id, text and leaf as many stay as are taken."""
    plan = Stored(mix(docs, weights, share, 1, seed).select("doc_id", "th", *LEVELS, "copies"), "mixture").df
    names = ["doc_id", "th", *LEVELS]
    taken = plan.groupBy(*names).agg(F.sum("copies").alias("take"), F.count(F.lit(1)).alias("rows")).where("take > 0")
    taken = Stored(taken, "taken").df.select(*(F.col(c).alias(f"__t_{c}") for c in names), "take", "rows")
    keyed = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("__row"), F.col("doc_id"), F.xxhash64("text").alias("th"), *leaf_of())
    same = F.lit(True)
    for c in names:
        same = same & keyed[c].eqNullSafe(F.col(f"__t_{c}"))
    whole = keyed.join(taken.where("take = rows"), same, "left_semi").select("__row")
    cut = taken.where("take < rows")
    if not cut.isEmpty():
        place = F.row_number().over(Window.partitionBy(*names).orderBy(F.lit(0)))
        part = keyed.join(cut, same).withColumn("__place", place).where(F.col("__place") <= F.col("take"))
        whole = whole.unionByName(part.select("__row"))
    return whole.select(*(F.col("__row").getField(c).alias(c) for c in docs.columns))
