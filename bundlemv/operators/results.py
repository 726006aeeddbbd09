"""Comparing and reading rank tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from bundlemv.operators.blocks import block_of


def delta(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: l1, l2, largest difference of two rank tables; a missing id counts as 0."""
    both = a.select("id", F.col("rank").alias("x")).join(b.select("id", F.col("rank").alias("y")), "id", "full")
    d = F.abs(F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0)))
    return both.agg(F.sum(d).alias("l1"), F.sqrt(F.sum(d * d)).alias("l2"), F.max(d).alias("largest"))


def l1_delta(a: Column | str, b: Column | str) -> Column:
    """Sum of absolute differences, as an aggregate; a missing value counts as 0."""
    return F.sum(F.abs(F.coalesce(a, F.lit(0.0)) - F.coalesce(b, F.lit(0.0))))


def gini(values: DataFrame, col: str) -> DataFrame:
    """One row: the Gini coefficient of nonnegative numbers, from their histogram (a row per distinct value).

    c equal values after b smaller ones have the ranks b+1 .. b+c, which add up in closed form.
    """
    hist = values.where(F.col(col).isNotNull()).groupBy(F.col(col).cast("double").alias("x")).agg(F.count("*").cast("double").alias("c"))
    before = Window.orderBy("x").rowsBetween(Window.unboundedPreceding, -1)
    hist = hist.withColumn("b", F.coalesce(F.sum("c").over(before), F.lit(0.0)))
    each = F.col("x") * F.col("c")
    n, total, ranked = F.sum("c"), F.sum(each), F.sum(each * (2 * F.col("b") + F.col("c") + 1))
    return hist.agg(F.coalesce(F.when(total > 0, (ranked - (n + 1) * total) / (n * total)), F.lit(0.0)).alias("gini"))


def rank_places(ranks: DataFrame, q: int) -> DataFrame:
    """id, block and the place of a rank in its block: rank, dense rank, quarter, percent rank, cumulative share."""
    own = Window.partitionBy("block").orderBy(F.desc("rank"))
    tied = Window.partitionBy("block").orderBy(F.desc("rank"), "id")
    return ranks.withColumn("block", block_of("id", q)).select(
        "id", "block", F.rank().over(own).alias("pos"), F.dense_rank().over(own).alias("dense_pos"), F.ntile(4).over(tied).alias("quarter"),
        F.percent_rank().over(own).alias("percent"), F.cume_dist().over(own).alias("cumulative"))


def mass(a: DataFrame) -> DataFrame:
    return a.agg(F.sum("rank").alias("mass"))


def top(ranks: DataFrame, k: int) -> DataFrame:
    """id, rank, pos of the k largest; ties to smaller ids."""
    best = ranks.orderBy(F.desc("rank"), "id").limit(k)
    return best.select("id", "rank", F.row_number().over(Window.orderBy(F.desc("rank"), "id")).alias("pos"))


def top_per_block(ranks: DataFrame, q: int, k: int) -> DataFrame:
    own = ranks.withColumn("block", block_of("id", q))
    pos = F.row_number().over(Window.partitionBy("block").orderBy(F.desc("rank"), "id"))
    return own.withColumn("pos", pos).where(F.col("pos") <= k)


def top_overlap(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """One row: the share of ids that two top lists have in common."""
    return top(a, k).select("id").join(top(b, k).select("id"), "id", "left_semi").agg((F.count("*") / k).alias("overlap"))


def rank_asof(events: DataFrame, snapshots: DataFrame) -> DataFrame:
    """Events (event_id, id, ts) with the rank of the latest snapshot (id, ts, rank) at their time.

    Both are sorted together per id; one running last value answers all events.
    """
    rows = events.select("id", "ts", "event_id", F.lit(None).cast("double").alias("rank"), F.lit(1).alias("kind"))
    rows = rows.unionByName(snapshots.select("id", "ts", F.lit(None).cast("long").alias("event_id"), "rank", F.lit(0).alias("kind")))
    seen = Window.partitionBy("id").orderBy("ts", "kind").rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("latest", F.last("rank", ignorenulls=True).over(seen)).where("kind = 1").select("event_id", "id", F.col("latest").alias("rank"))
