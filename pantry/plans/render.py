"""Test inputs of known truth, as views of the given tables: ingredient lines, composition items, vectors."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pantry.functions.lexicons import FOREIGN
from pantry.functions.rules import food_key
from pantry.session import table

ADJ = ("blue", "cold", "hot", "large", "new", "old", "red", "small")
NOUN = ("anvil", "bolt", "gear", "gizmo", "plate", "ring", "rod", "widget")
#: Spellings of a unit: canonical, long, plural.
SPELT = (("g", "gram", "grams"), ("ml", "milliliter", "milliliters"), ("cup", "cup", "cups"), ("tbsp", "tablespoon", "tablespoons"), ("tsp", "teaspoon", "teaspoons"), ("oz", "ounce", "ounces"), ("lb", "pound", "pounds"), ("pinch", "pinch", "pinches"))
WORDS = ("one", "two", "three", "four", "five", "six", "seven", "eight", "nine", "ten")
CORPORA = ("A", "B", "C", "D", "E", "F")


def _pick(values, i: Column) -> Column:
    return F.get(F.array(*(F.lit(v) for v in values)), i)


def name_index(name: Column) -> Column:
    adj, noun = F.split_part(name, F.lit(" "), F.lit(1)), F.split_part(name, F.lit(" "), F.lit(2))
    at = lambda values, c: F.array_position(F.array(*(F.lit(v) for v in values)), c) - 1
    return (8 * at(ADJ, adj) + at(NOUN, noun)).cast("int")


def corpus(orderkey: Column) -> Column:
    return _pick(CORPORA, F.pmod(orderkey, F.lit(6)).cast("int"))


def lines_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines with the numbers that their text is rendered from."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity")
    parts = table(spark, sf_dir, "part").select("p_partkey", "p_name", "p_size")
    df = lines.join(parts, lines.l_partkey == parts.p_partkey)
    key = F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    t = F.pmod(F.col("l_orderkey") * 31 + F.col("l_linenumber") * 7 + F.col("l_partkey"), F.lit(20)).cast("int")
    return df.select(
        key.alias("line_key"),
        F.col("l_orderkey").alias("recipe_id"),
        corpus(F.col("l_orderkey")).alias("corpus"),
        F.col("l_linenumber").alias("pos"),
        "l_partkey",
        "l_suppkey",
        F.col("l_quantity").cast("int").alias("q"),
        F.col("p_name").alias("f"),
        name_index(F.col("p_name")).alias("name_idx"),
        F.pmod("l_partkey", F.lit(8)).cast("int").alias("u"),
        t.alias("t"),
    )


def ingredient_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(line_key, recipe_id, corpus, pos, t, text and the numbers): English text of every line."""
    df = lines_base(spark, sf_dir)
    f, q = F.col("f"), F.col("q").cast("string")
    f2 = F.concat_ws(" ", _pick(ADJ, F.floor(F.pmod(F.col("name_idx") + 1, F.lit(64)) / 8).cast("int")), _pick(NOUN, F.pmod(F.col("name_idx") + 1, F.lit(8))))
    spelling = F.pmod("l_suppkey", F.lit(3)).cast("int")
    u = F.get(F.get(F.array(*(F.array(*(F.lit(x) for x in s)) for s in SPELT)), F.col("u")), spelling)
    more = (F.col("q") + 1).cast("string")
    word = _pick(WORDS, F.pmod(F.col("q"), F.lit(10)))
    adj, noun = F.split_part(f, F.lit(" "), F.lit(1)), F.split_part(f, F.lit(" "), F.lit(2))
    s = lambda *x: F.concat(*(F.lit(y) if isinstance(y, str) else y for y in x))
    texts = [
        s(q, " ", u, " ", f), s(q, " 1/2 ", u, " of ", f), s(q, " (250 grams) container ", f), s("a ", u, " of ", f), s(word, " ", f),
        s(q, "-", more, " ", u, " ", f), s(q, " ", u, " ", f, " plus 2 tbsp ", f2), s(f, ", to taste"), s(q, " ", u, " ", f, " or ", f2), s(q, " ", u, " ", f, " beaten with 2 tsp ", f2),
        s(q, " ", u, " ", f, " and 3 oz ", f2), s(q, " packets of ", f), s("2 ", q, " oz packages ", f), s(q, " ", u, " ", more, " ", f), s(q, ".5 1/4 ", u, " ", f),
        s("an ", f), s(q, " ", u, " ", f, ", finely chopped. Keep dry"), F.when(noun == "widget", s(q, " ", adj, "widget")).otherwise(s("half a ", f)), s(q, " ", u, " 3.5% ", f), s(q, " cloves ", f),
    ]
    return df.withColumn("text", _pick_column(texts, F.col("t")))


def _pick_column(columns: list[Column], i: Column) -> Column:
    out = columns[-1]
    for k in range(len(columns) - 2, -1, -1):
        out = F.when(i == k, columns[k]).otherwise(out)
    return out


def foreign(text: Column, lexicon: dict[str, str]) -> Column:
    """The text with each content word of the lexicon in its foreign form."""
    for w, x in lexicon.items():
        text = F.regexp_replace(text, rf"\b{w}\b", x)
    return text


def raw_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(recipe_id, corpus, pos, line_key, lang, text) of the five raw collections in one scan; B and E are not English."""
    df = ingredient_lines(spark, sf_dir).where(F.col("corpus") != "A")
    strange = F.col("corpus").isin("B", "E")
    text = F.when(strange, foreign(F.col("text"), FOREIGN["xx"])).otherwise(F.col("text"))
    return df.select("recipe_id", "corpus", "pos", "line_key", F.when(strange, "xx").otherwise("en").alias("lang"), text.alias("text"))


def raw_source(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One raw collection."""
    return raw_lines(spark, sf_dir).where(F.col("corpus") == name)


#: What the stand-in collections say of a recipe's fat, protein and sodium themselves: not what is computed here.
OWN = {"fat": "recipe_id % 37 + 1", "protein": "recipe_id % 23 + 1", "sodium": "(recipe_id % 11 + 1) / 10"}
FILLERS = 89


def collection(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One collection as its source has it: a row a recipe with the columns of its adapter's schema."""
    from pantry.plans.views import answers
    from pantry.sources.adapters import SCHEMAS

    head = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("recipe_id"), F.col("o_totalprice").alias("calories")).where(corpus(F.col("o_orderkey")) == name)
    if name == "A":
        line = F.struct("pos", "line_key", F.struct(F.col("f").alias("food"), "qty", "unit", F.lit(None).cast("double").alias("grams")).alias("x"))
        lines = answers(lines_base(spark, sf_dir)).where(F.col("corpus") == name)
    else:
        line = F.struct("pos", "line_key", F.col("text").alias("x"))
        lines = raw_source(spark, sf_dir, name)
    bag = lines.groupBy("recipe_id").agg(F.transform(F.array_sort(F.collect_list(line)), lambda l: l["x"]).alias("items"))
    own = [x for n, e in OWN.items() for x in (F.lit(n), F.expr(e).cast("double"))]
    more = [x for i in range(FILLERS) for x in (F.lit(f"n{i}"), (F.pmod("recipe_id", F.lit(7)) + i).cast("double"))] if name == "E" else []
    more += [x for n in ("sugar", "satfat") for x in (F.lit(n), F.lit(1.0))] if name in "AE" else []
    df = head.join(bag, "recipe_id").select("*", F.create_map(*own, *more).alias("nutrients"))
    df = df.withColumn("title", F.concat(F.lit("Recipe "), F.col("recipe_id"))).withColumn("url", F.concat(F.lit("https://recipes.example/"), F.col("recipe_id")))
    df = df.withColumn("instruction", F.concat(F.lit("Mix "), F.size("items").cast("string"), F.lit(" things."))).withColumn("lang", F.lit("xx" if name in "BE" else "en"))
    if name == "A":
        df = df.withColumn("lights", F.create_map(F.lit("fat"), F.when(F.col("nutrients")["fat"] <= 3, "low").when(F.col("nutrients")["fat"] <= 17.5, "medium").otherwise("high")))
    else:
        df = df.withColumn("raw", F.array_join("items", "\n"))
    return df.select(*(c.split()[0] for c in re.split(r", (?=\w+ (?:bigint|string|double|map|array))", SCHEMAS[name])))


def fcdb_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Composition items: text, portion grams and five nutrients per 100 g, one a part."""
    p = table(spark, sf_dir, "part").select("p_partkey", "p_name", F.col("p_size").alias("s"))
    i = name_index(F.col("p_name"))
    p = p.withColumn("a", F.floor(i / 8).cast("int")).withColumn("n", F.pmod(i, F.lit(8)))
    adj, noun = F.split_part("p_name", F.lit(" "), F.lit(1)), F.split_part("p_name", F.lit(" "), F.lit(2))
    n = F.col("n")
    text = (
        F.when(n <= 1, F.concat(F.initcap(noun), F.lit("s, "), adj))
        .when(n <= 3, F.concat_ws(" ", adj, noun, F.col("s").cast("string")))
        .when(n <= 5, F.concat_ws(" ", adj, noun, F.lit("set")))
        .when(n == 6, F.concat_ws(" ", adj, F.lit("fitting")))
        .otherwise(F.concat(adj, F.lit("widgt")))
    )
    fat = 5 * n + F.col("a") + F.col("s") / 8
    return p.select(
        F.col("p_partkey").alias("item_id"),
        text.alias("text"),
        (8 * F.col("s")).cast("double").alias("portion_g"),
        fat.cast("double").alias("fat"),
        (2 * F.col("a") + n + F.col("s") / 4).cast("double").alias("protein"),
        (6 * F.abs(n - F.col("a")) + F.col("s") / 8).cast("double").alias("sugar"),
        (fat * 0.375).cast("double").alias("satfat"),
        (n * F.col("a") / 32 + F.col("s") / 64).cast("double").alias("sodium"),
    )


def fcdb_parts(spark: SparkSession, sf_dir: str) -> list[DataFrame]:
    """Three overlapping lists: the merge has duplicates to remove."""
    items = fcdb_items(spark, sf_dir)
    return [items.where("item_id % 2 = 0"), items.where("item_id % 3 = 0"), items]


def name_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(food_key, vec): a fixed vector a name, whatever form a line gives the name."""
    names = [(8 * a + n, f"{x} {y}") for a, x in enumerate(ADJ) for n, y in enumerate(NOUN)]
    forms = [(i, f) for i, name in names for f in (name, f"clove {name}", f"3.5% {name}")] + [(i, name.replace(" ", "")) for i, name in names if name.endswith("widget")]
    vecs = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("_v"), F.col("embedding").alias("vec"))
    named = spark.createDataFrame(forms, "name_idx int, name string")
    return named.join(vecs, F.col("name_idx") == F.col("_v")).select(food_key(F.col("name")).alias("food_key"), "name_idx", "vec")
