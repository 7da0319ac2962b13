"""Linking foods to composition items by five tests in order of priority.

Both sides are reduced to classes first: items with the same lemma set are one class, named by its
least item, since every test sees the lemma set only. Each tier joins what is left on an equality (lemma
key, noun key, shared token, shared letters) and keeps the best class by a combining minimum, so pairs are
never shuffled; foods found leave before the next tier.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pantry.functions import prep
from pantry.functions import similarity as sim
from pantry.functions.lexicons import Lexicons
from pantry.functions.rules import food_text
from pantry.session import materialize

SETS = ("nouns", "verbs", "adjectives", "numbers")
TIERS = (1, 2, 3, 4, 5)


def prepare_items(items: DataFrame, text: str = "text", lex: Lexicons | None = None) -> DataFrame:
    """Items with ``food``: tokens and lemmas without brackets, redundant words and punctuation."""
    lex = lex or Lexicons()
    return items.withColumn("food", prep.restore_brands(food_text(prep.prepare(F.col(text), lex), lex), lex.brands))


def build_fcdb(parts: list[DataFrame]) -> DataFrame:
    """The lists merged, one item a text: the least id stays."""
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    cols = [c for c in every.columns if c != "text"]
    return every.groupBy("text").agg(F.min_by(F.struct(*cols), "item_id").alias("_i")).select("text", "_i.*")


def features(df: DataFrame, food: str = "food") -> DataFrame:
    """Token sets of ``food``, its lemma key, noun key and joined lemmas."""
    df = df.withColumn("_t", F.array_sort(F.array_distinct(prep.tokens(F.col(food)))))
    for name in SETS:
        df = df.withColumn(name, sim.tagged(F.col("_t"), name[:-1]))
    return df.withColumn("key", F.array_join("_t", " ")).withColumn("noun_key", F.array_join("nouns", " ")).withColumn("joined", F.array_join("_t", "")).drop("_t")


def food_classes(foods: DataFrame, food: str = "food") -> DataFrame:
    """One row a lemma set of the foods; different foods first, lines repeat them."""
    return features(foods.select(food).distinct(), food).where("key != ''").dropDuplicates(["key"]).drop(food)


def item_classes(items: DataFrame) -> DataFrame:
    """One row a lemma set of prepared items, named by its least item."""
    least = items.groupBy("food").agg(F.min("item_id").alias("item_id"))
    f = features(least, "food").where("key != ''")
    cols = [*SETS, "noun_key", "joined"]
    one = f.groupBy("key").agg(F.min("item_id").alias("item_id"), F.first(F.struct(*cols)).alias("_f")).select("key", "item_id", "_f.*")
    return one.select(*(F.col(c).alias(c + "_j") for c in ("key", *cols)), "item_id")


def _other(mode: str) -> Column:
    return sim.other_ratio(*(F.col(c) for c in SETS[1:]), *(F.col(c + "_j") for c in SETS[1:]), mode=mode)


def index(mode: str = "symmetric") -> Column:
    return sim.similarity_index(F.col("nouns"), F.col("nouns_j"), _other(mode))


def distance() -> Column:
    return F.levenshtein(F.col("joined"), F.col("joined_j"))


def every_token(suffix: str = "") -> Column:
    sets = [F.col(c + suffix) for c in SETS]
    return F.array_distinct(F.concat(*sets))


def _best(pairs: DataFrame, tier: int, score: Column) -> DataFrame:
    """The best class of each food: score, then distance, then least item."""
    order = F.struct((-score).alias("s"), F.col("dist"), F.col("item_id"))
    rows = (pairs if "dist" in pairs.columns else pairs.withColumn("dist", distance())).withColumn("_o", order)
    found = rows.groupBy("key").agg(F.min_by(F.struct("item_id", "index", "dist"), "_o").alias("_b"))
    return found.select("key", "_b.item_id", F.lit(tier).alias("tier"), "_b.index", "_b.dist")


def _posting(foods: DataFrame, items: DataFrame, tokens: Column, tokens_j: Column, salts: int = 8) -> DataFrame:
    """Pairs with a common token, through an equality join on it; a pair may come once for each.

    The items of a token are dealt over ``salts``, and the foods go to each: a common noun is several tasks.
    """
    left = foods.withColumn("_w", F.explode(tokens)).withColumn("_s", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    right = items.withColumn("_w", F.explode(tokens_j)).withColumn("_s", F.pmod(F.xxhash64("key_j"), F.lit(salts)).cast("int"))
    return left.join(right, ["_w", "_s"]).drop("_w", "_s")


def _pieces(text: Column) -> Column:
    """The different pairs of neighbouring letters, with a mark at both ends."""
    marked = F.concat(F.lit("^"), text, F.lit("$"))
    return F.array_distinct(F.transform(F.sequence(F.lit(1), F.length(text) + 1), lambda i: F.substring(marked, i, F.lit(2))))


def nearest_by_edits(foods: DataFrame, items: DataFrame, eq2: str = "symmetric") -> DataFrame:
    """The last tier without all pairs: the item of the least edit distance, if that is below the food's length.

    An edit changes at most two of the n + 1 pairs of neighbouring letters of a name of n, so names without a common
    pair are at least (n + 1) / 2 edits apart. A food whose best item among those with a common pair is nearer than
    that is done; only the others are compared with all items, in blocks.
    """
    near = _posting(foods, items, _pieces(F.col("joined")), _pieces(F.col("joined_j"))).dropDuplicates(["key", "item_id"])
    limit = F.length("joined") - 1
    near = near.where(F.abs(F.length("joined") - F.length("joined_j")) <= limit).withColumn("dist", distance()).where(F.col("dist") <= limit).withColumn("index", index(eq2))
    found = materialize(_best(near, 5, F.lit(0.0)).join(foods.select("key", F.length("joined").alias("_n")), "key").withColumn("sure", 2 * F.col("dist") < F.col("_n") + 1).drop("_n"), "near")
    sure = found.where("sure").drop("sure")
    pairs, score = candidates(foods.join(sure, "key", "left_anti"), items, 5, eq2)
    return sure.unionByName(_best(pairs, 5, score))


def candidates(foods: DataFrame, items: DataFrame, tier: int, eq2: str = "symmetric", tier4: str = "relaxed", block: int = 5000) -> tuple[DataFrame, Column]:
    """Pairs that satisfy the tier's test, and the score that orders them."""
    zero = F.coalesce(F.col("index"), F.lit(0.0))
    if tier == 1:
        return foods.join(items, foods.key == items.key_j).withColumn("index", index(eq2)), zero
    if tier == 2:
        pairs = foods.where("noun_key != ''").join(items, foods.noun_key == items.noun_key_j).withColumn("index", index(eq2))
        return pairs.where("index > 0"), zero
    if tier == 3:
        return _posting(foods, items, F.col("nouns"), F.col("nouns_j")).withColumn("index", index(eq2)).where("index > 0"), zero
    if tier == 4:
        pairs = _posting(foods, items, every_token(), every_token("_j")).withColumn("index", index(eq2))
        return (pairs.where("index > 0"), zero) if tier4 == "as_printed" else (pairs, _other(eq2))
    # Items in blocks, foods sent to each: an equality join that never plans a product of whole tables.
    blocks = max(1, -(-items.count() // block))
    left = foods.withColumn("_b", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    right = items.withColumn("_b", F.pmod(F.xxhash64("key_j"), F.lit(blocks)).cast("int"))
    near = left.join(right, "_b").where(F.length("joined_j") < 2 * F.length("joined")).withColumn("dist", distance())
    return near.where(F.col("dist") < F.length("joined")).withColumn("index", index(eq2)).drop("_b"), F.lit(0.0)


def link_foods(foods: DataFrame, items: DataFrame, eq2: str = "symmetric", tier4: str = "relaxed", order: tuple[int, ...] = TIERS) -> DataFrame:
    """(key, item_id, tier, index, dist) for every food class; item_id NULL where no tier matches."""
    rest = materialize(food_classes(foods), "foods")
    classes = materialize(item_classes(items), "items")
    out = None
    for tier in order:
        if tier == 5:
            best = nearest_by_edits(rest, classes, eq2)
        else:
            pairs, score = candidates(rest, classes, tier, eq2, tier4)
            best = _best(pairs, tier, score)
        found = materialize(best, f"tier{tier}")
        out = found if out is None else out.unionByName(found)
        rest = rest.join(found, "key", "left_anti")
    none = rest.select("key", F.lit(None).cast("long").alias("item_id"), F.lit(None).cast("int").alias("tier"), F.lit(None).cast("double").alias("index"), F.lit(None).cast("int").alias("dist"))
    return out.unionByName(none)


def link_bruteforce(foods: DataFrame, items: DataFrame, eq2: str = "symmetric", tier4: str = "relaxed") -> DataFrame:
    """The same by comparing all pairs; for checks on small tables."""
    pairs = food_classes(foods).crossJoin(item_classes(items)).withColumn("index", index(eq2)).withColumn("dist", distance())
    shares = F.arrays_overlap(every_token(), every_token("_j"))
    fourth = F.col("index") > 0 if tier4 == "as_printed" else shares
    tier = (
        F.when(F.col("key") == F.col("key_j"), 1)
        .when((F.col("noun_key") == F.col("noun_key_j")) & (F.col("index") > 0), 2)
        .when(F.col("index") > 0, 3)
        .when(fourth, 4)
        .when(F.col("dist") < F.length("joined"), 5)
    )
    zero = F.coalesce(F.col("index"), F.lit(0.0))
    score = F.when(F.col("tier") <= 3, zero).when(F.col("tier") == 4, F.lit(0.0) + (zero if tier4 == "as_printed" else _other(eq2))).otherwise(0.0)
    pairs = pairs.withColumn("tier", tier).where("tier is not null")
    order = F.struct(F.col("tier"), (-score).alias("s"), F.col("dist"), F.col("item_id"))
    best = pairs.groupBy("key").agg(F.min_by(F.struct("item_id", "tier", "index", "dist"), order).alias("_b"))
    return best.select("key", "_b.item_id", "_b.tier", "_b.index", "_b.dist")


def link_noun_only(foods: DataFrame, items: DataFrame) -> DataFrame:
    """The earlier way: the best noun overlap, nothing else."""
    pairs = _posting(food_classes(foods), item_classes(items), F.col("nouns"), F.col("nouns_j"))
    pairs = pairs.withColumn("index", sim.jaccard(F.col("nouns"), F.col("nouns_j")))
    return _best(pairs, 0, F.col("index")).drop("tier")


def link_cost(foods: DataFrame, items: DataFrame) -> DataFrame:
    """Candidate pairs of each tier beside all pairs."""
    f, i = materialize(food_classes(foods), "foods"), materialize(item_classes(items), "items")
    rows = [candidates(f, i, t)[0].agg(F.count("*").alias("pairs")).select(F.lit(t).alias("tier"), "pairs") for t in TIERS]
    every = f.agg(F.count("*").alias("a")).crossJoin(i.agg(F.count("*").alias("b"))).select(F.lit(0).alias("tier"), (F.col("a") * F.col("b")).alias("pairs"))
    for r in rows:
        every = every.unionByName(r)
    return every
