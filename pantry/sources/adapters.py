"""The six collections: what each brings, as a declared schema, and one shape behind them.

Adapters differ in their projection only. ``harmonize`` gives lines: (recipe_id, corpus, pos, lang, text, and the
quantity, unit and food of a line where they are given); ``headers`` gives what belongs to the recipe: title, url, instruction,
calories and the collection's own nutrients. A column that a collection lacks is null.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pantry.sources import formats

_ITEMS = "array<struct<food: string, qty: double, unit: string, grams: double>>"
SCHEMAS: dict[str, str] = {
    "A": f"recipe_id bigint, title string, instruction string, items {_ITEMS}, nutrients map<string, double>, lights map<string, string>",
    "B": "recipe_id bigint, url string, raw string, instruction string, lang string",
    "C": "recipe_id bigint, title string, url string, raw string, calories double, nutrients map<string, double>",
    "D": "recipe_id bigint, title string, instruction string, raw string",
    "E": "recipe_id bigint, title string, raw string, lang string, nutrients map<string, double>",
    "F": "recipe_id bigint, title string, raw string, instruction string",
}
HEADER = {"title": "string", "url": "string", "instruction": "string", "calories": "double", "nutrients": "map<string, double>"}
LINE = {"lang": "string", "text": "string", "qty": "double", "unit": "string", "food": "string", "grams": "double"}


def read(spark: SparkSession, path: str, corpus: str, kind: str = "json") -> DataFrame:
    """One collection's files with its declared schema: nothing is inferred, malformed rows fail."""
    return formats.read(spark, path, kind, SCHEMAS[corpus])


def _all(df: DataFrame, columns: dict[str, str]) -> list:
    return [F.col(c).cast(k).alias(c) if c in df.columns else F.lit(None).cast(k).alias(c) for c, k in columns.items()]


def headers(df: DataFrame, corpus: str) -> DataFrame:
    """(recipe_id, corpus, title, url, instruction, calories, nutrients)."""
    return df.select("recipe_id", F.lit(corpus).alias("corpus"), *_all(df, HEADER))


def harmonize(df: DataFrame, corpus: str) -> DataFrame:
    """(recipe_id, corpus, pos, lang, text, qty, unit, food, grams), one row a line or given item; empty lines are left out."""
    if "items" in df.columns:
        lines = df.select("recipe_id", F.posexplode("items").alias("pos", "i")).select("recipe_id", "pos", "i.*")
    else:
        lang = F.col("lang") if "lang" in df.columns else F.lit("en")
        lines = df.select("recipe_id", lang.alias("lang"), F.posexplode(F.split("raw", "\n")).alias("pos", "text")).where(F.trim("text") != "")
    return lines.select("recipe_id", F.lit(corpus).alias("corpus"), "pos", *_all(lines, LINE))


def long_nutrients(df: DataFrame, wanted: tuple[str, ...]) -> DataFrame:
    """(recipe_id, wanted ..., rest): the wanted ones of a wide map as columns, the sum of all others."""
    long = df.select("recipe_id", F.explode("nutrients").alias("name", "x"))
    short = F.when(F.col("name").isin(*wanted), F.col("name")).otherwise("rest")
    return long.groupBy("recipe_id").agg(*(F.sum(F.when(short == n, F.col("x"))).alias(n) for n in (*wanted, "rest")))
