"""Mixing sources to target weights by Efraimidis-Spirakis sampling.

Each document gets the exponential key -ln(u)/q, u from a seeded hash of its id and text, q its quality
weight. A source's target in words is met by complete epochs first; the fraction of an epoch that is
left goes to the documents with the smallest keys, up to the token budget.

Scale: keys are cut into cells of equal chance. One pass sums words by (source, cell); a window over
that bounded table finds the cell in which each source's budget ends; a second pass takes every
document before that cell, none after it, and orders only the documents inside it. No source, however
large, meets in one task, and texts do not move.

Defined results: null texts have size 0; null sources are one source, last in order; sources without
words get target 0; rows that repeat an id and text have one key and share its place in any order, so
the sums are the same; an empty table gives an empty result; columns called like an added one are
replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pantry.llm import text as tx
from pantry.llm.ranks import bits_for, cell_of
from pantry.session import materialize

ADDED = ("size", "source_size", "target", "taken", "copies")


def quality_weight(text: Column) -> Column:
    """Share of the characters that are neither digits nor symbols, 0.05 at least."""
    body = tx.whole(text)
    odd = F.regexp_count(body, F.lit(r"[0-9#*$%&|<>{}\[\]=_~^\\]"))
    return F.greatest(F.lit(1.0) - F.coalesce(F.try_divide(odd.cast("double"), F.char_length(body)), F.lit(0.0)), F.lit(0.05))


def targets(sources: DataFrame, source: str = "source", size: str = "source_size", weights: tuple[float, ...] = (5, 2, 1), most: float = 3.0) -> DataFrame:
    """Add ``target`` to one row a source: shares of all words by weight, none above ``most`` times its size.

    Sources by code point, null last, take the weights in turn. The water level that the repeated
    resharing of the excess ends at is found directly: sources in order of cap over weight are full as
    long as the level that the others would share lies above them. The table has one row a source.
    """
    ordered = Window.orderBy(F.col(source).asc_nulls_last())
    turn = F.array(*(F.lit(float(w)) for w in weights))
    s = sources.withColumn("_w", F.get(turn, (F.row_number().over(ordered) - 1) % len(weights)))
    s = s.withColumn("_cap", F.col(size) * F.lit(float(most))).withColumn("_ratio", F.col("_cap") / F.col("_w"))
    by_ratio = Window.orderBy("_ratio", F.col(source).asc_nulls_last())
    everything = Window.partitionBy()
    above = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    s = s.withColumn("_full", F.coalesce(F.sum("_cap").over(above), F.lit(0.0)))
    s = s.withColumn("_left", F.sum("_w").over(everything) - F.coalesce(F.sum("_w").over(above), F.lit(0.0)))
    s = s.withColumn("_level", (F.sum(size).over(everything) - F.col("_full")) / F.col("_left"))
    s = s.withColumn("_place", F.row_number().over(by_ratio))
    fits = F.when(F.col("_level") <= F.col("_ratio"), F.struct("_place", "_level"))
    s = s.withColumn("_water", F.coalesce(F.min(fits).over(everything)["_level"], F.max("_ratio").over(everything)))
    target = F.least(F.col("_cap"), F.col("_w") * F.col("_water"))
    return s.withColumn("target", target).drop("_w", "_cap", "_ratio", "_full", "_left", "_level", "_place", "_water")


def _drawn(
    df: DataFrame,
    weights: tuple[float, ...] = (5, 2, 1),
    most: float = 3.0,
    quality: Column | None = None,
    seed: int = 0,
    bits: int | None = None,
    doc_id: str = "doc_id",
    source: str = "source",
    text: str = "text",
) -> DataFrame:
    """(_row, size, source_size, target, copies): the input's rows as structs, and how often each is taken."""
    cols = df.columns
    bits = bits or bits_for(df.count())
    u = tx.unit_interval(F.xxhash64(F.lit(seed), F.col(f"`{doc_id}`"), F.col(f"`{text}`")))
    key = -F.log(u) / (quality if quality is not None else quality_weight(F.col(f"`{text}`")))
    rows = df.select(F.struct(*(F.col(f"`{c}`") for c in cols)).alias("_row"), F.col(f"`{source}`").alias("_s"), tx.n_words(F.col(f"`{text}`")).alias("size"), key.alias("_key"))
    even = ((F.lit(1.0) - F.lit(2.0) * F.exp(-F.col("_key"))) * F.lit(9.2e18)).cast("long")
    rows = rows.withColumn("_cell", cell_of(even, bits))
    cells = materialize(rows.groupBy("_s", "_cell").agg(F.sum("size").alias("words")), "mix-cells")
    sized = targets(cells.groupBy("_s").agg(F.sum("words").alias("source_size")), "_s", weights=weights, most=most)
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    sized = sized.withColumn("_epochs", epochs).withColumn("_budget", F.col("target") - F.col("_epochs") * F.col("source_size"))
    before = Window.partitionBy("_s").orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1)
    starts = cells.withColumn("_start", F.coalesce(F.sum("words").over(before), F.lit(0)))
    starts = starts.withColumnRenamed("_s", "_t").join(sized, F.col("_t").eqNullSafe(F.col("_s")))
    ends = F.max(F.when(F.col("_start") < F.col("_budget"), F.struct(F.col("_cell").alias("cell"), F.col("_start").alias("start")))).alias("_end")
    ends = starts.groupBy("_t", "source_size", "target", "_epochs", "_budget").agg(ends)
    plan = materialize(ends.select("_t", "source_size", "target", "_epochs", "_budget", F.coalesce(F.col("_end.cell"), F.lit(-1)).cast("long").alias("_last"), F.coalesce(F.col("_end.start"), F.lit(0)).cast("long").alias("_first")), "mix-plan")
    met = rows.join(plan, F.col("_s").eqNullSafe(F.col("_t")))
    clear = met.where(F.col("_cell") != F.col("_last")).withColumn("_more", F.col("_cell") < F.col("_last"))
    inside = Window.partitionBy("_s").orderBy("_key", F.col("_row")[doc_id], F.xxhash64(F.col("_row")[text])).rowsBetween(Window.unboundedPreceding, -1)
    edge = met.where(F.col("_cell") == F.col("_last")).withColumn("_at", F.col("_first") + F.coalesce(F.sum("size").over(inside), F.lit(0)))
    # The document that straddles the budget goes in if that ends nearer to it.
    edge = edge.withColumn("_more", F.col("_at") + F.col("size") / 2 <= F.col("_budget")).drop("_at")
    every = clear.unionByName(edge)
    return every.select("_row", "size", "source_size", "target", (F.col("_epochs") + F.col("_more").cast("long")).alias("copies"))


def mix(df: DataFrame, **options) -> DataFrame:
    """``df`` with ``size``, ``source_size``, ``target``, ``taken`` (words, repeats counted) and ``copies``; options as in ``_drawn``."""
    out = _drawn(df, **options).withColumn("taken", F.col("size") * F.col("copies"))
    return out.select(*(F.col("_row")[c].alias(c) for c in df.columns if c not in ADDED), *ADDED)


def mixed_documents(df: DataFrame, **options) -> DataFrame:
    """The mix itself: the rows of ``df``, each as often as it is taken."""
    out = _drawn(df, **options).where("copies > 0").select("_row", F.explode(F.array_repeat(F.lit(1), F.col("copies").cast("int"))))
    return out.select(*(F.col("_row")[c].alias(c) for c in df.columns))
