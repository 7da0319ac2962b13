"""The dictionaries: units with conversions, brands, redundant words, number words, lemmas, tags.

Small keyed sets that code owns. Surfaces are lemmas: plural endings are gone before they are looked up.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class Unit:
    name: str
    kind: str
    grams: float
    surfaces: tuple[str, ...]


UNITS: tuple[Unit, ...] = (
    Unit("g", "si", 1, ("g", "gr", "gram", "gramme")),
    Unit("kg", "si", 1000, ("kg", "kilo", "kilogram")),
    Unit("mg", "si", 0.001, ("mg", "milligram")),
    Unit("ml", "si", 1, ("ml", "milliliter", "millilitre")),
    Unit("dl", "si", 100, ("dl", "deciliter", "decilitre")),
    Unit("l", "si", 1000, ("l", "liter", "litre")),
    Unit("cup", "household", 240, ("cup",)),
    Unit("tbsp", "household", 15, ("tbsp", "tb", "tbs", "tbl", "tablespoon")),
    Unit("tsp", "household", 5, ("tsp", "teaspoon")),
    Unit("oz", "household", 28.35, ("oz", "ounce")),
    Unit("lb", "household", 453.59, ("lb", "lbs", "lbss", "pound")),
    Unit("floz", "household", 29.57, ("floz",)),
    Unit("pint", "household", 473.18, ("pint", "pt")),
    Unit("quart", "household", 946.35, ("quart", "qt")),
    Unit("pinch", "approx", 0.36, ("pinch",)),
    Unit("dash", "approx", 0.6, ("dash",)),
    Unit("splash", "approx", 5, ("splash",)),
    Unit("handful", "approx", 30, ("handful",)),
    Unit("thumb", "approx", 15, ("thumb",)),
    Unit("smidgen", "approx", 0.18, ("smidgen", "smidgeon")),
)

#: Units of several words, as lemmas without full stops, and the surface that stands for them.
UNIT_PHRASES: dict[str, str] = {"fl oz": "floz", "fl ounce": "floz", "fluid oz": "floz", "fluid ounce": "floz", "table spoon": "tbsp", "tea spoon": "tsp", "thumb sized": "thumb", "thumb size": "thumb"}

#: Words that are a unit only where no dictionary unit is; grams of one.
CONTAINERS: dict[str, float] = {"jar": 350, "can": 400, "packet": 40, "package": 200, "box": 250, "bottle": 500, "container": 250}

#: Unit words of certain foods only, their partner foods; grams of one.
PAIRS: dict[str, dict[str, float]] = {
    "clove": {"garlic": 3},
    "stick": {"butter": 113, "margarine": 113, "cinnamon": 3, "carrot": 6, "celery": 4},
    "sprig": {"rosemary": 1, "thyme": 1, "mint": 1, "parsley": 1},
    "link": {"sausage": 70},
    "stalk": {"celery": 40, "green onion": 15, "spring onion": 15, "broccoli": 150, "kale": 20, "cauliflower": 60},
    "sheet": {"gelatin": 2},
    "cube": {"stock": 10, "butter": 15, "margarine": 15},
    "head": {"cabbage": 900, "lettuce": 500, "cauliflower": 800},
}

BRANDS: tuple[str, ...] = ("m&m's", "7-up", "ben & jerry's", "a-1 sauce", "half & half brand 100%")
REDUNDANT: tuple[str, ...] = ("of", "fresh", "freshly", "finely", "the", "about", "approximately", "optional", "needed", "each", "additional", "extra")
REDUNDANT_PHRASES: tuple[str, ...] = ("to taste", "as needed", "if desired", "for garnish", "or more")
#: Conjunctions stay for the clause rules and go with the redundant words at the end.
PROTECTED: tuple[str, ...] = ("and", "or", "with", "plus", "to")
NON_FOOD: tuple[str, ...] = ("baking paper", "parchment paper", "aluminum foil", "skewer", "toothpick", "kitchen string")

NUMBER_WORDS: dict[str, int] = {
    "one": 1, "two": 2, "three": 3, "four": 4, "five": 5, "six": 6, "seven": 7, "eight": 8, "nine": 9, "ten": 10,
    "eleven": 11, "twelve": 12, "thirteen": 13, "fourteen": 14, "fifteen": 15, "sixteen": 16, "seventeen": 17, "eighteen": 18, "nineteen": 19, "twenty": 20,
}
NUMBER_WORDS |= {w: 10 * (i + 3) for i, w in enumerate(("thirty", "forty", "fifty", "sixty", "seventy", "eighty", "ninety"))}
VULGAR: dict[str, str] = {"½": "1/2", "⅓": "1/3", "⅔": "2/3", "¼": "1/4", "¾": "3/4", "⅕": "1/5", "⅛": "1/8", "⅜": "3/8", "⅝": "5/8", "⅞": "7/8"}
IRREGULAR: dict[str, str] = {"leaves": "leaf", "loaves": "loaf", "halves": "half", "knives": "knife", "potatoes": "potato", "tomatoes": "tomato", "cookies": "cookie", "olives": "olive", "chives": "chive", "mixed": "mix", "added": "add", "adding": "add"}
#: Words that end like plurals and are none.
INVARIANT: tuple[str, ...] = ("molasses", "schnapps", "brussels", "haggis", "bass", "swiss")

ADJECTIVES: tuple[str, ...] = ("blue", "cold", "hot", "large", "new", "old", "red", "small", "dry", "sweet", "whole", "green", "white", "black", "raw", "economy", "standard", "promo", "medium", "anodized", "burnished", "plated", "polished", "brushed")
VERBS: tuple[str, ...] = ("beaten", "chopped", "sliced", "diced", "minced", "add", "mix", "combined", "diluted", "dissolved", "sauteed")
NOUNS: tuple[str, ...] = ("anvil", "bolt", "gear", "gizmo", "plate", "ring", "rod", "widget", "set", "fitting")

#: The paper's example foreign texts cannot be had offline; this is a stand-in with the same structure.
FOREIGN: dict[str, dict[str, str]] = {"xx": {w: w[::-1] + "ax" for w in (*ADJECTIVES[:8], *NOUNS)}}


def surfaces() -> dict[str, str]:
    return {s: u.name for u in UNITS for s in u.surfaces}


def grams_of_units() -> list[tuple[str, str | None, float]]:
    """(unit, food or None, grams of one): food-specific rows win."""
    rows = [(u.name, None, float(u.grams)) for u in UNITS]
    rows += [(c, None, float(g)) for c, g in CONTAINERS.items()]
    return rows + [(u, f, float(g)) for u, foods in PAIRS.items() for f, g in foods.items()]


@dataclass(frozen=True)
class Lexicons:
    """What the normalizer looks words up in; every part can be replaced."""

    units: dict[str, str] = field(default_factory=surfaces)
    containers: tuple[str, ...] = tuple(CONTAINERS)
    pairs: dict[str, dict[str, float]] = field(default_factory=lambda: PAIRS)
    brands: tuple[str, ...] = BRANDS
    redundant: tuple[str, ...] = REDUNDANT
    phrases: tuple[str, ...] = REDUNDANT_PHRASES
    non_food: tuple[str, ...] = NON_FOOD


def as_tables(spark: SparkSession) -> dict[str, DataFrame]:
    """The four dictionaries as tables."""
    kinds = {u.name: u.kind for u in UNITS}
    units = [(s, n, kinds[n]) for s, n in surfaces().items()] + [(c, c, "container") for c in CONTAINERS] + [(p, p, "paired") for p in PAIRS]
    return {
        "units": spark.createDataFrame(units, "surface string, unit string, kind string"),
        "conversions": spark.createDataFrame(grams_of_units(), "unit string, food string, grams double"),
        "brands": spark.createDataFrame([(b,) for b in BRANDS], "phrase string"),
        "redundant": spark.createDataFrame([(w,) for w in (*REDUNDANT, *REDUNDANT_PHRASES, *PROTECTED)], "phrase string"),
    }


def write_lexicons(spark: SparkSession, path: str, version: int) -> None:
    for name, t in as_tables(spark).items():
        t.write.mode("overwrite").parquet(f"{path}/version={version}/{name}")
