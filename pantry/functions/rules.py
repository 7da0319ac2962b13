"""Units, quantities, clauses and surplus quantities on prepared text, as Column functions.

Tags live in the string itself: ``@cup`` is a unit, ``<2+1/2>`` a quantity pattern whose factors are
separated by ``*``. Every rule is then a pattern over tags and words, and the chain stays a projection
without lambdas until the value of a pattern is computed.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from pantry.functions import lexicons as lx
from pantry.functions.prep import FLOAT, FRAC, INT, NUM, START, STOP, any_of, articles, respell, squeeze, sub

U = r"@\S+"
Q = r"<[^>]*>"

#: Phrases that join two ingredients, as lemmas.
TRIGGERS = r"(?:mix|beaten) with|(?:mix|dissolved|sauteed) in|diluted(?: (?:with|in))?|combined(?: with)?|add"


def count(c: Column, pattern: str) -> Column:
    return F.regexp_count(c, F.lit(pattern))


# units ------------------------------------------------------------------------------------------


def tag_units(c: Column, units: dict[str, str] | None = None) -> Column:
    """Dictionary entities become ``@canonical``."""
    return respell(c, units or lx.surfaces(), "@")


def tag_pairs(c: Column, pairs=None) -> Column:
    """Unit words of single foods, where the partner occurs."""
    for unit, foods in (pairs or lx.PAIRS).items():
        c = sub(c, rf"^(?=(?:.* )?{any_of(foods)}{STOP})((?:.*? )?){unit}{STOP}", f"$1@{unit}")
    return c


def tag_containers(c: Column, containers=tuple(lx.CONTAINERS)) -> Column:
    """Container words go after a unit, and between a count and a listed size, which then multiply; without a unit the first is the unit."""
    word = any_of(containers)
    c = sub(c, rf"{START}({NUM}) {word} (?={NUM} {U})", "$1 ")
    c = squeeze(sub(c, rf"(@\S+(?: .*)?) {word}{STOP}", "$1"))
    return sub(c, rf"^(?!.*@)((?:.*? )?)({word}){STOP}", "$1@$2")


def unit_kind(unit: Column) -> Column:
    kinds = {u.name: u.kind for u in lx.UNITS} | dict.fromkeys(lx.CONTAINERS, "container") | dict.fromkeys(lx.PAIRS, "paired")
    out = F.lit(None).cast("string")
    for kind in sorted(set(kinds.values())):
        out = F.when(unit.isin([n for n, k in kinds.items() if k == kind]), F.lit(kind)).otherwise(out)
    return out


# clauses ----------------------------------------------------------------------------------------


def keep_low_end(c: Column) -> Column:
    """``2 to 3`` keeps 2."""
    return sub(c, rf"{START}({NUM}) to {NUM}{STOP}", "$1")


def triggers(c: Column) -> Column:
    return sub(c, rf"{START}(?:{TRIGGERS}){STOP}", "plus")


def joining_and(c: Column) -> Column:
    """The first and/with between units becomes plus, if there is no plus yet."""
    return sub(c, rf"^(?!(?:.* )?plus{STOP})(.*?{U}.*?) (?:and|with) (?=.*{U})", "$1 plus ")


def parts(c: Column) -> Column:
    """The texts between the pluses, empty ones left out."""
    return F.filter(F.transform(F.split(c, rf"{START}plus{STOP}"), lambda p: F.trim(F.regexp_replace(p, r"^[ ,.]+|[ ,.]+$", ""))), lambda p: p != "")


def choose_option(c: Column) -> Column:
    """One of the alternatives: see the rules for one and for several "or"."""
    options = F.transform(F.split(c, rf"{START}or{STOP}"), lambda p: F.trim(p))
    n, units = count(c, rf"{START}or{STOP}"), count(c, U)
    assigned = count(c, rf"{NUM} {U}")
    first = lambda pattern: F.get(F.filter(options, lambda p: p.rlike(pattern)), F.lit(0))
    with_unit = F.when((units > 1) & (assigned > 0) & (assigned < units), first(rf"{NUM} {U}")).otherwise(first(U))
    chosen = F.when((n == 1) | (units == 0), F.get(options, F.lit(0))).otherwise(with_unit)
    return F.when(n == 0, c).otherwise(F.coalesce(chosen, c))


# quantities -------------------------------------------------------------------------------------


def tag_quantities(c: Column) -> Column:
    """Number patterns become ``<...>``.

    Mixed numbers are sums; listed neighbours multiply; unlisted neighbours are patterns of their own.
    A number before a percent sign is no number here, since its token is longer.
    """
    c = sub(c, rf"{START}({INT}) ({FRAC}){STOP}", "$1+$2")
    mixed = rf"{INT}\+{FRAC}"
    c = sub(c, rf"{START}({mixed}) (?=(?:{mixed}|{NUM}){STOP})", "$1 ¦ ")
    for a, b in ((FLOAT, FRAC), (FRAC, FLOAT), (FLOAT, mixed), (FRAC, mixed)):
        keep = "(?!)" if b == mixed else b
        c = sub(c, rf"{START}({a}) (?={keep}{STOP})", "$1 ¦ ")
    number = rf"(?:{mixed}|{NUM})"
    c = sub(c, rf"{START}({number}(?: {number})*){STOP}", "<$1>")
    return squeeze(F.replace(c, F.lit("¦"), F.lit("")))


def pattern_value(pattern: Column) -> Column:
    """The number that ``<...>`` stands for; NULL for a zero denominator."""
    fraction = lambda x: F.try_divide(F.split_part(x, F.lit("/"), F.lit(1)).cast("double"), F.split_part(x, F.lit("/"), F.lit(2)).cast("double"))
    one = lambda x: F.when(x.contains("/"), fraction(x)).otherwise(x.try_cast("double"))
    summed = lambda x: F.when(x.contains("+"), one(F.split_part(x, F.lit("+"), F.lit(1))) + one(F.split_part(x, F.lit("+"), F.lit(2)))).otherwise(one(x))
    factors = F.split(F.translate(pattern, "<>", ""), " ")
    return F.when(pattern != "", F.aggregate(factors, F.lit(1.0), lambda a, x: a * summed(x)))


# surplus quantities -----------------------------------------------------------------------------


def resolve(c: Column) -> Column:
    """Drop surplus patterns, from the left, a pair at a time."""
    n = count(c, U)
    two = F.regexp_extract(c, rf"{Q} ({U}) {Q} {U}", 1) != F.regexp_extract(c, rf"{Q} {U} {Q} ({U})", 1)
    second = F.regexp_replace(c, rf"^((?:(?!{Q}).)*){Q} ({Q})(?= (?:.* )?{U})", "$1$2")
    first = F.regexp_replace(c, rf"^((?:(?!{Q}).)*{Q} {U}) {Q}{STOP}", "$1")
    pair = F.regexp_replace(c, rf"^((?:(?!{Q}).)*{Q} {U}) {Q} {U}{STOP}", "$1")
    plain = F.regexp_replace(c, rf"^((?:(?!{Q}).)*{Q}) {Q}{STOP}", "$1")
    one = F.when(c.rlike(rf"{Q} {Q} (?:.* )?{U}"), second).otherwise(first)
    return F.when(count(c, Q) < 2, c).when(n == 1, one).when((n == 2) & two, pair).when(n == 0, plain).otherwise(c)


def first_pattern(c: Column) -> Column:
    return F.regexp_extract(c, rf"({Q})", 1)


def unit_of(c: Column) -> Column:
    """The first unit after the first pattern, or else the first unit."""
    after = F.regexp_extract(c, rf"{Q}(?: .*?)? @(\S+)", 1)
    found = F.when(after != "", after).otherwise(F.regexp_extract(c, r"@(\S+)", 1))
    return F.when(found != "", found)


def truncate(c: Column, original: Column) -> Column:
    """Cut at the first stop or comma after quantity and unit, unless the part holds and/or."""
    cut = F.regexp_replace(c, rf"^(.*{Q} {U}.*?) [.,](?: .*)?$", "$1")
    return F.when(original.rlike(rf"{START}(?:and|or){STOP}"), c).otherwise(cut)


def food_text(c: Column, lex: lx.Lexicons) -> Column:
    """What is left: no first pattern, no unit, no redundant word, no loose punctuation."""
    c = F.regexp_replace(c, rf"^((?:(?!{Q}).)*){Q}", "$1")
    c = sub(sub(c, U, " "), r"[<>]", "")
    c = sub(c, rf"{START}{any_of((*lex.redundant, *lx.PROTECTED, '.', ','))}{STOP}", " ")
    return squeeze(sub(c, rf"{START}an?{STOP}", " "))


def food_key(food: Column) -> Column:
    return F.array_join(F.array_sort(F.array_distinct(F.split(food, " "))), " ")


def rearticle(c: Column, lex: lx.Lexicons) -> Column:
    return articles(c, lex.units)
