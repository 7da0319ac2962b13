"""Running sums inside large groups without a task for each group.

A group may hold a third of all rows. Rows are cut into cells by the leading bits of a uniform 64-bit
key; a small table of cell totals gives each cell's start, and only inside a cell rows are ordered by
a window. Cells are partitioned by (group, cell), so hot groups spread.

Defined results: null groups are a group; null values add nothing; rows alike in key and ties take places in
any order; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def cell_of(key: Column, bits: int) -> Column:
    """The leading bits of a signed long, in its order."""
    return F.shiftright(key, 64 - bits) + F.lit(1 << (bits - 1)).cast("long")


def bits_for(rows: int, in_cell: int = 512, most: int = 20) -> int:
    """Bits that leave about ``in_cell`` rows of a table in a cell."""
    return max(4, min(most, (max(1, rows // in_cell)).bit_length()))


def running(df: DataFrame, groups: list[str], key: str, value: str, out: str, bits: int = 10, ties: tuple[str, ...] = ()) -> DataFrame:
    """Add ``out``: sum of ``value`` over the rows of the group before this one, by ``key`` then ``ties``.

    Rows alike in key and ties take places in any order. Null groups are a group.
    """
    cells = df.withColumn("_cell", cell_of(F.col(key), bits))
    totals = cells.groupBy(*groups, "_cell").agg(F.sum(value).alias("_total"))
    before = Window.partitionBy(*groups).orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1)
    names = [f"_g{i}" for i in range(len(groups))]
    starts = totals.select(*(F.col(g).alias(n) for g, n in zip(groups, names)), F.col("_cell").alias("_c"), F.coalesce(F.sum("_total").over(before), F.lit(0)).alias("_start"))
    on = F.col("_cell") == F.col("_c")
    for g, n in zip(groups, names):
        on = on & F.col(g).eqNullSafe(F.col(n))
    inside = Window.partitionBy(*groups, "_cell").orderBy(key, *ties).rowsBetween(Window.unboundedPreceding, -1)
    local = cells.withColumn("_local", F.coalesce(F.sum(value).over(inside), F.lit(0)))
    return local.join(starts, on).withColumn(out, F.col("_start") + F.col("_local")).drop("_cell", "_c", "_start", "_local", *names)


def meet(rows: DataFrame, table: DataFrame, keys: list[str], n: str, least: int = 10_000, most: int = 100_000) -> DataFrame:
    """``rows`` joined by ``keys`` with a table of one row a key, whose column ``n`` says how many rows have the key.

    Keys of very many rows, those with a ``most``-th of all from ``least`` rows on, hence at most ``most`` of them, are
    broadcast to where their rows are; the others meet by hash, and no task gets more rows of one key than that.
    Both sides should be written tables: each is read twice. Null keys do not meet.
    """
    total = table.agg(F.sum(n)).first()[0] or 0
    is_hot = F.col(n) >= max(least, -(-total // most))
    hot = F.broadcast(table.where(is_hot).drop(n))  # at most ``most`` rows
    cold = rows.join(hot.select(*keys), keys, "left_anti").join(table.where(~is_hot).drop(n), keys)
    return rows.join(hot, keys).unionByName(cold)
