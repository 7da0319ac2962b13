"""Lines to (quantity, unit, food): the rules of preparation, units, quantities and clauses in their order.

Distinct texts are normalised once and joined back to their lines: recipe lines repeat, rules are dear.
Everything is Column expressions; the only operator that adds rows is the split at "plus".
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pantry.functions import prep, rules
from pantry.functions.lexicons import Lexicons
from pantry.session import materialize

TRIPLE = ("part_no", "qty", "qty_kind", "unit", "unit_kind", "food", "food_key", "is_food", "rules_fired")


def clause_text(text: Column, lex: Lexicons) -> Column:
    """Prepared text after ranges, triggers and conjunctions, units tagged."""
    c = rules.triggers(rules.keep_low_end(prep.prepare(text, lex)))
    return rules.joining_and(rules.tag_pairs(rules.tag_units(c, lex.units), lex.pairs))


def _fired(pairs: list[tuple[str, Column]]) -> Column:
    return F.filter(F.array(*(F.when(c, F.lit(n)) for n, c in pairs)), lambda x: x.isNotNull())


def split_parts(df: DataFrame, text: str, lex: Lexicons) -> DataFrame:
    """One row a part, numbered from 0: (…, part_no, part)."""
    marked = df.withColumn("_clause", clause_text(F.col(text), lex))
    return marked.select("*", F.posexplode_outer(rules.parts(F.col("_clause"))).alias("part_no", "part"))


def triples(df: DataFrame, text: str = "text", lex: Lexicons | None = None) -> DataFrame:
    """Every row of ``df`` with the columns of TRIPLE, one row a part; a line without text has one part without food."""
    lex = lex or Lexicons()
    df = split_parts(df, text, lex)
    df = df.withColumn("part", prep.articles(F.coalesce("part", F.lit("")), lex.units))
    df = df.withColumn("_one", rules.choose_option(F.col("part")))
    df = df.withColumn("_tagged", rules.tag_containers(rules.tag_units(rules.rearticle(F.col("_one"), lex), lex.units), lex.containers))
    df = df.withColumn("_many", rules.tag_quantities(F.col("_tagged")))
    df = df.withColumn("_fewer", rules.resolve(F.col("_many"))).withColumn("_few", rules.resolve(F.col("_fewer")))
    df = df.withColumn("_short", rules.truncate(F.col("_few"), F.col("part")))
    df = df.withColumn("_first", rules.first_pattern(F.col("_short"))).withColumn("unit", rules.unit_of(F.col("_short")))
    df = df.withColumn("qty", rules.pattern_value(F.col("_first"))).withColumn("food", prep.restore_brands(rules.food_text(F.col("_short"), lex), lex.brands))
    kind = F.when(F.col("qty").isNotNull(), "number").when(F.col("_first") != "", "bad").when(F.lower(text).rlike(prep.any_of(lex.phrases)), "user").otherwise("absent")
    fired = _fired(
        [
            ("plus", F.size(rules.parts(F.col("_clause"))) > 1),
            ("or", F.col("_one") != F.col("part")),
            ("unit", F.col("unit").isNotNull()),
            ("several", F.col("_few") != F.col("_many")),
            ("truncated", F.col("_short") != F.col("_few")),
            ("container", F.col("_tagged") != F.col("_one")),
        ]
    )
    df = df.withColumn("qty_kind", kind).withColumn("unit_kind", rules.unit_kind(F.col("unit"))).withColumn("rules_fired", fired)
    df = df.withColumn("food_key", rules.food_key(F.col("food"))).withColumn("is_food", (F.col("food") != "") & ~F.col("food").rlike(prep.any_of(lex.non_food)))
    return df.withColumn("part_no", F.coalesce("part_no", F.lit(0))).drop("_clause", "part", "_one", "_tagged", "_many", "_fewer", "_few", "_short", "_first")


def distinct_texts(df: DataFrame, text: str = "text") -> DataFrame:
    return df.select(F.col(text)).distinct()


def normalize_lines(df: DataFrame, text: str = "text", lex: Lexicons | None = None, translator=None, lang: str = "lang") -> DataFrame:
    """``df`` with TRIPLE, one row a part: distinct texts are translated and put through the rules, then joined back once.

    The distinct texts' results are written once: they are small beside the lines, and filters that a
    later join infers would otherwise be pushed into the chain of rules and repeat it. A text that very many
    lines share is one row here; on the lines' side the adaptive plan splits it.
    """
    keys = [text, lang] if translator else [text]
    once = df.select(*keys).distinct()
    if translator:
        once = translator(once.select(F.col(lang).alias("lang"), F.col(text).alias("text")))
        done = triples(once, "english", lex).select(F.col("text").alias("_text"), F.col("lang").alias("_lang"), *TRIPLE)
    else:
        done = triples(once, text, lex).select(F.col(text).alias("_text"), *TRIPLE)
    done = materialize(done, "texts")
    same = F.col(text).eqNullSafe(F.col("_text"))
    if translator:
        same = same & F.col(lang).eqNullSafe(F.col("_lang"))
    return df.join(done, same).drop("_text", "_lang")


def normalize_counted(df: DataFrame, by: tuple[str, ...] = (), text: str = "text", lex: Lexicons | None = None) -> DataFrame:
    """(by, TRIPLE, n): parts of the distinct texts and how many lines have each, for sums that need no line: nothing is joined back."""
    counted = materialize(df.groupBy(*by, text).agg(F.count("*").alias("n")), "counted")
    if not by:
        return materialize(triples(counted, text, lex).select("n", *TRIPLE), "texts")
    done = materialize(triples(counted.select(text).distinct(), text, lex).select(F.col(text).alias("_text"), *TRIPLE), "texts")
    return counted.join(done, F.col(text).eqNullSafe(F.col("_text"))).drop("_text", text)


def split_structured(df: DataFrame, text: str = "text", units=None) -> DataFrame:
    """The plain splitter for well-structured text: items at ``;``, each number, unit, name."""
    from pantry.functions.lexicons import surfaces

    items = df.select("*", F.posexplode(F.split(F.col(text), r"\s*;\s*")).alias("pos", "item"))
    shape = rf"^\s*(\d+(?:\.\d+)?)\s+({prep.any_of(units or surfaces())}s?)\s+(.*?)\.?\s*$"
    got = lambda i: F.regexp_extract("item", shape, i)
    return items.select("*", got(1).try_cast("double").alias("qty"), got(2).alias("unit"), prep.squeeze(F.translate(got(3), ",", " ")).alias("food")).where("qty is not null")


def recipe_lists(df: DataFrame, recipe: str = "recipe_id") -> DataFrame:
    """One row a recipe with its lines as one list in order, so that names and quantities cannot drift apart."""
    line = F.struct("pos", "part_no", "qty", "unit", "food")
    return df.groupBy(recipe).agg(F.array_sort(F.collect_list(line)).alias("lines"))
