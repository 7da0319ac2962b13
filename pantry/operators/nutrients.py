"""Grams, shares and nutrients per 100 g of a recipe."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pantry.functions.lexicons import grams_of_units

TARGETS = ("fat", "protein", "sugar", "satfat", "sodium")


def conversions(spark) -> DataFrame:
    return spark.createDataFrame(grams_of_units(), "unit string, food string, grams double")


def with_grams(lines: DataFrame, conversion: DataFrame | None = None) -> DataFrame:
    """Add ``grams``: by unit, the food's own weight first; without a unit by the item's portion.

    ``lines`` has qty, unit, food and portion_g. A missing count of portions is one. The dictionary is
    code-owned, a few hundred rows at most, hence the broadcast.
    """
    table = conversion if conversion is not None else conversions(lines.sparkSession)
    own = table.where("food is not null").select(F.col("unit").alias("_u1"), F.col("food").alias("_f1"), F.col("grams").alias("_own"))
    general = table.where("food is null").select(F.col("unit").alias("_u2"), F.col("grams").alias("_general"))
    df = lines.join(F.broadcast(own), (F.col("unit") == F.col("_u1")) & (F.col("food") == F.col("_f1")), "left")
    df = df.join(F.broadcast(general), F.col("unit") == F.col("_u2"), "left")
    by_unit = F.col("qty") * F.coalesce("_own", "_general")
    by_portion = F.coalesce("qty", F.lit(1.0)) * F.col("portion_g")
    grams = F.when(F.col("unit").isNull(), by_portion).otherwise(by_unit)
    return df.withColumn("grams", grams).drop("_u1", "_f1", "_own", "_u2", "_general")


def shares(lines: DataFrame, recipe: str = "recipe_id") -> DataFrame:
    """Add ``share``: grams per 100 g of the recipe; aggregate and join, so no recipe is sorted."""
    total = lines.groupBy(recipe).agg(F.sum("grams").alias("_total"))
    return lines.join(total, recipe).withColumn("share", F.try_divide(100 * F.col("grams"), F.col("_total"))).drop("_total")


def recipe_nutrients(lines: DataFrame, recipe: str = "recipe_id", targets=TARGETS) -> DataFrame:
    """One row a recipe: total grams, lines, and each target per 100 g; recipes without grams are left out."""
    weighed = F.when(F.col("grams").isNotNull(), F.col("grams"))
    sums = [F.try_divide(F.sum(weighed * F.col(t)), F.sum(F.when(F.col(t).isNotNull(), weighed))).alias(t) for t in targets]
    return lines.groupBy(recipe).agg(F.sum("grams").alias("grams"), F.count("*").alias("n_lines"), *sums).where("grams > 0")


def losses(recipes: DataFrame, lines: DataFrame, recipe: str = "recipe_id") -> DataFrame:
    """(reason, recipes): why recipes get no vector."""
    seen = lines.groupBy(recipe).agg(F.count("*").alias("n"), F.sum("grams").alias("g"), F.count("item_id").alias("linked"))
    reason = F.when(F.col("n").isNull(), "no lines").when(F.col("linked") == 0, "not linked").when(~(F.coalesce("g", F.lit(0.0)) > 0), "no grams").otherwise("kept")
    return recipes.select(recipe).join(seen, recipe, "left").groupBy(reason.alias("reason")).agg(F.count("*").alias("recipes"))
