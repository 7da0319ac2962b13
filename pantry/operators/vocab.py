"""Training tokens, vocabulary and windowed co-occurrence of the distinct foods."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pantry.functions.prep import tokens
from pantry.operators.relational import global_rank


def training_tokens(foods: DataFrame, food: str = "food") -> DataFrame:
    """(food_key, tokens): one row a distinct food, over all collections: one shared space."""
    one = foods.groupBy("food_key").agg(F.min(food).alias("_f"))
    return one.select("food_key", tokens(F.col("_f")).alias("tokens"))


def vocabulary(df: DataFrame, min_count: int = 1) -> DataFrame:
    """(word, n, word_id) by count, then word."""
    n = df.select(F.explode("tokens").alias("word")).groupBy("word").agg(F.count("*").alias("n")).where(F.col("n") >= min_count)
    return global_rank(n, [F.col("n").desc(), F.col("word")], "word_id")


def cooccurrence(df: DataFrame, window: int, weighting: str = "inverse") -> DataFrame:
    """(w1, w2, weight): pairs within the window, both ways; ``inverse`` weighs a pair by 1 / distance.

    Neighbours come from a slice of the line itself, so no line is joined with itself.
    """
    here = df.select("tokens", F.posexplode("tokens").alias("i", "w1"))
    near = here.select("w1", F.posexplode(F.slice("tokens", F.col("i") + 2, F.lit(window))).alias("d", "w2"))
    weight = F.lit(1.0) / (F.col("d") + 1) if weighting == "inverse" else F.lit(1.0)
    once = near.select("w1", "w2", weight.alias("weight"))
    both = once.union(once.select(F.col("w2").alias("w1"), F.col("w1").alias("w2"), "weight"))
    return both.groupBy("w1", "w2").agg(F.sum("weight").alias("weight"))
