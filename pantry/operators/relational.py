"""Operators that Spark lacks: as-of and range joins through equalities and one sort, a rank over a whole table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pantry.session import materialize


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, values: list[str], right_at: str | None = None) -> DataFrame:
    """``left`` with the latest ``values`` of ``right`` at or before its time, by key: a union and one sort a key."""
    right_at = right_at or at
    l = left.withColumn("_side", F.lit(1)).withColumn("_at", F.col(at))  # noqa: E741
    r = right.select(F.col(key), F.col(right_at).alias("_at"), F.struct(*values).alias("_v")).withColumn("_side", F.lit(0))
    both = l.unionByName(r, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy("_at", "_side").rowsBetween(Window.unboundedPreceding, 0)
    out = both.withColumn("_last", F.last("_v", ignorenulls=True).over(w)).where("_side = 1")
    return out.select(*left.columns, *(F.col("_last")[v].alias(v) for v in values))


def range_join(left: DataFrame, right: DataFrame, point: str, low: str, high: str, width: int) -> DataFrame:
    """Rows of ``left`` whose ``point`` lies in [low, high] of ``right``: intervals are cut into cells of ``width``."""
    l = left.withColumn("_cell", F.floor(F.col(point) / width))  # noqa: E741
    r = right.withColumn("_cell", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return l.join(r, "_cell").where((F.col(point) >= F.col(low)) & (F.col(point) <= F.col(high))).drop("_cell")


def top_k_per_group(df: DataFrame, group: str, order: str, k: int, ties: str) -> DataFrame:
    w = Window.partitionBy(group).orderBy(F.col(order).desc(), F.col(ties))
    return df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def global_rank(df: DataFrame, order: list[Column], out: str) -> DataFrame:
    """Add ``out``, the place from 0 in the whole table's order, without a task that sees all rows.

    A sort deals rows into ranges; each range is numbered by itself and begins where the ranges before it
    end. The offsets' table has one row a range.
    """
    dealt = materialize(df.orderBy(*order).withColumn("_range", F.spark_partition_id()), "ranked")
    sizes = dealt.groupBy("_range").agg(F.count("*").alias("_n"))
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("_range", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    place = F.row_number().over(Window.partitionBy("_range").orderBy(*order)) - 1
    ranked = dealt.withColumn("_place", place).join(F.broadcast(starts), "_range")
    return ranked.withColumn(out, F.col("_start") + F.col("_place")).drop("_range", "_start", "_place")
