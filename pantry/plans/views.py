"""Frames that several queries start from."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pantry.functions.bands import fold
from pantry.functions.lexicons import FOREIGN
from pantry.functions.rules import food_key
from pantry.operators import linking, merge, nutrients
from pantry.operators.normalize import normalize_lines
from pantry.operators.translate import Glossary
from pantry.plans import render
from pantry.session import kept

DIM = 64


def text_lines(spark: SparkSession, sf_dir: str, templates: tuple[int, ...] | None = None) -> DataFrame:
    df = render.ingredient_lines(spark, sf_dir).select("line_key", "recipe_id", "corpus", "pos", "t", "text")
    return df.where(F.col("t").isin(*templates)) if templates else df


def triples(spark: SparkSession, sf_dir: str, templates: tuple[int, ...] | None = None) -> DataFrame:
    return normalize_lines(text_lines(spark, sf_dir, templates))


def answers(df: DataFrame) -> DataFrame:
    """Add the quantity and unit (``qty``, ``unit``) that a line's text is rendered from."""
    t, q = F.col("t"), F.col("q").cast("double")
    widget = F.col("f").endswith("widget")
    qty = (
        F.when(t == 1, q + 0.5).when(t == 2, 250 * q).when(t.isin(3, 15), 1.0).when(t == 4, 1 + F.pmod(q, F.lit(10.0))).when(t == 12, 2 * q).when(t == 14, 0.25)
        .when(t == 17, F.when(widget, q).otherwise(0.5)).when(t == 7, None).otherwise(q)
    )
    own = F.get(F.array(*(F.lit(s[0]) for s in render.SPELT)), F.col("u"))
    unit = F.when(t == 2, "g").when(t == 12, "oz").when(t == 11, "packet").when(t.isin(4, 7, 15, 17, 19), None).otherwise(own)
    return df.withColumn("qty", qty).withColumn("unit", unit)


def structured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines whose quantity and unit are columns already, as the structured collection has them."""
    df = answers(render.lines_base(spark, sf_dir))
    return df.select("recipe_id", "corpus", "pos", "line_key", "l_partkey", "q", "t", "qty", "unit", F.col("f").alias("food"), food_key(F.col("f")).alias("food_key"), "name_idx")


def glossary(spark: SparkSession) -> Glossary:
    """Words of the stand-in language; a fused name is one foreign word of its own."""
    rows = [(lang, x, w) for lang, words in FOREIGN.items() for w, x in words.items()]
    rows += [("xx", FOREIGN["xx"][a] + "widget", a + "widget") for a in render.ADJ]
    return Glossary(spark.createDataFrame(rows, "lang string, foreign string, word string"))


def extracted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(recipe_id, corpus, pos, line_key, part_no, qty, unit, food, food_key) of all six collections, written once a session.

    The structured collection brings its columns; the others are texts, of which two are translated first.
    """
    cols = ["recipe_id", "corpus", "pos", "line_key", "part_no", "qty", "unit", "food", "food_key"]

    def make() -> DataFrame:
        own = structured(spark, sf_dir).where("corpus = 'A'").withColumn("part_no", F.lit(0))
        texts = normalize_lines(render.raw_lines(spark, sf_dir), translator=glossary(spark))
        return own.select(*cols).unionByName(texts.select(*cols))

    return kept(spark, f"extracted {sf_dir}", make)


def links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(key, item_id, tier, index, dist) of every extracted food, written once a session."""
    return kept(spark, f"links {sf_dir}", lambda: linking.link_foods(extracted(spark, sf_dir), items(spark, sf_dir)))


def weighed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Extracted lines with the item linked to their food, its portion and nutrients, and grams: the method up to the recipes."""

    def make() -> DataFrame:
        linked = links(spark, sf_dir).select(F.col("key").alias("food_key"), "item_id", "tier")
        facts = render.fcdb_items(spark, sf_dir).drop("text")
        lines = extracted(spark, sf_dir).join(linked, "food_key", "left").join(facts, "item_id", "left")
        return nutrients.with_grams(lines)

    return kept(spark, f"weighed {sf_dir}", make)


def recipes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(recipe_id, corpus, fold, grams, n_lines, targets)."""
    out = nutrients.recipe_nutrients(weighed(spark, sf_dir))
    return out.withColumn("corpus", render.corpus(F.col("recipe_id"))).withColumn("fold", fold(F.col("recipe_id")))


def vectors(spark: SparkSession, sf_dir: str, dim: int = DIM) -> DataFrame:
    return render.name_vectors(spark, sf_dir).withColumn("vec", F.slice("vec", 1, dim))


def recipe_features(spark: SparkSession, sf_dir: str, dim: int = DIM) -> DataFrame:
    """Recipes with dh, plain_sum, plain_avg vectors, targets and folds."""
    merged = merge.merge_all(weighed(spark, sf_dir).select("recipe_id", "food_key", "grams"), vectors(spark, sf_dir, dim), dim)
    return recipes(spark, sf_dir).join(merged, "recipe_id")


def foods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distinct foods of the rendered lines that carry a name, the fused ones included."""
    names = spark.read.parquet(f"{sf_dir}/part.parquet").select(F.col("p_name").alias("food"))
    fused = names.where(F.col("food").endswith("widget")).select(F.replace("food", F.lit(" "), F.lit("")).alias("food"))
    return names.union(fused).distinct()


def items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linking.prepare_items(render.fcdb_items(spark, sf_dir))
