"""Vectors of ingredients and recipes: gram-weighted, summed, averaged.

A merge is one aggregation with a sum a dimension, combined before the exchange, instead of a row a
dimension. Beyond ``WIDE`` dimensions the sums of a partition are made in Arrow batches.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WIDE = 256


def weighted_sum(df: DataFrame, key: str, weight: Column, vec: str, dim: int) -> DataFrame:
    """(key, vec): sum of weight * vec; NULL vectors add nothing, and a key without any has a NULL vector."""
    if dim > WIDE:
        return _wide_sum(df.select(F.col(key).alias(key), weight.cast("double").alias("_w"), F.col(vec).alias("_v")), key, dim)
    sums = [F.sum(weight * F.get(F.col(vec), F.lit(i)).cast("double")).alias(f"_{i}") for i in range(dim)]
    out = df.groupBy(key).agg(*sums)
    return out.select(key, F.when(F.col("_0").isNotNull(), F.array(*(F.col(f"_{i}") for i in range(dim)))).alias("vec"))


def _wide_sum(df: DataFrame, key: str, dim: int) -> DataFrame:
    kind = dict(df.dtypes)[key]

    def partial(parts):
        for t in parts:
            t = t[t["_v"].notna() & t["_w"].notna()]
            if len(t):
                m = np.stack([np.asarray(v, float) for v in t["_v"]]) * t["_w"].to_numpy()[:, None]
                code, keys = pd.factorize(t[key])
                sums = np.zeros((len(keys), dim))
                np.add.at(sums, code, m)
                yield pd.DataFrame({key: keys, "vec": list(sums)})

    def total(t: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({key: t[key][:1], "vec": [np.sum(list(t["vec"]), axis=0)]})

    shape = f"{key} {kind}, vec array<double>"
    return df.mapInPandas(partial, shape).groupBy(key).applyInPandas(total, shape)


def scaled(vec: Column, by: Column) -> Column:
    return F.transform(vec, lambda x: x / by)


def merge_domain(lines: DataFrame, vectors: DataFrame, dim: int, scale: str = "unit", recipe: str = "recipe_id") -> DataFrame:
    """Recipe vectors by gram share; ``per100`` shares sum to 100. Foods without a vector add zero, their grams count."""
    total = F.sum("grams").alias("_g")
    grams = lines.groupBy(recipe).agg(total).where("_g > 0")
    met = lines.where("grams is not null").join(vectors, "food_key", "left")
    raw = weighted_sum(met, recipe, F.col("grams"), "vec", dim)
    unit = F.lit(1.0 if scale == "unit" else 100.0)
    return raw.join(grams, recipe).select(recipe, F.transform("vec", lambda x: x * unit / F.col("_g")).alias("vec"))


def merge_plain(lines: DataFrame, vectors: DataFrame, dim: int, how: str = "avg", recipe: str = "recipe_id") -> DataFrame:
    """Recipe vectors without quantities: the sum, or the average over all lines."""
    met = lines.join(vectors, "food_key", "left")
    out = weighted_sum(met, recipe, F.lit(1.0), "vec", dim)
    if how == "sum":
        return out
    n = lines.groupBy(recipe).agg(F.count("*").alias("_n"))
    return out.join(n, recipe).select(recipe, scaled(F.col("vec"), F.col("_n")).alias("vec"))


def merge_all(lines: DataFrame, vectors: DataFrame, dim: int, recipe: str = "recipe_id") -> DataFrame:
    """(recipe, dh, plain_sum, plain_avg) with one join and one aggregation."""
    met = lines.join(vectors, "food_key", "left")
    v = [F.get(F.col("vec"), F.lit(i)).cast("double") for i in range(dim)]
    out = met.groupBy(recipe).agg(F.sum("grams").alias("_g"), F.count("*").alias("_n"), *(F.sum(F.col("grams") * x).alias(f"_d{i}") for i, x in enumerate(v)), *(F.sum(x).alias(f"_s{i}") for i, x in enumerate(v)))
    zero = F.lit(0.0)
    return out.where("_g > 0").select(
        recipe,
        F.array(*(F.coalesce(F.col(f"_d{i}"), zero) / F.col("_g") for i in range(dim))).alias("dh"),
        F.array(*(F.coalesce(F.col(f"_s{i}"), zero) for i in range(dim))).alias("plain_sum"),
        F.array(*(F.coalesce(F.col(f"_s{i}"), zero) / F.col("_n") for i in range(dim))).alias("plain_avg"),
    )


def combine_words(foods: DataFrame, words: DataFrame, dim: int, how: str = "sum", key: str = "food_key", tokens: str = "tokens") -> DataFrame:
    """Ingredient vectors from word vectors (word, vec): unknown words add zero but count in the average."""
    each = foods.select(key, F.explode(tokens).alias("word")).join(words, "word", "left")
    out = weighted_sum(each, key, F.lit(1.0), "vec", dim)
    if how == "sum":
        return out
    n = foods.select(key, F.size(tokens).alias("_n"))
    return out.join(n, key).select(key, scaled(F.col("vec"), F.col("_n")).alias("vec"))


def last_layers(layers: Column, how: str = "sum", n: int = 4) -> Column:
    """The last ``n`` layer outputs summed, or one after the other."""
    last = F.slice(layers, -n, n)
    if how == "concat":
        return F.flatten(last)
    widened = F.transform(last, lambda v: F.transform(v, lambda x: x.cast("double")))
    zero = F.transform(F.get(widened, F.lit(0)), lambda x: x * 0)
    return F.aggregate(widened, zero, lambda a, v: F.zip_with(a, v, lambda x, y: x + y))


def layer_slices(vec: Column, layers: int = 4, width: int = 16) -> Column:
    """A stand-in for layer outputs: a ready vector cut into layers."""
    return F.array(*(F.slice(vec, 1 + i * width, width) for i in range(layers)))
