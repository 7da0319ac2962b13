"""Text preparation as Column functions: each takes and gives a string; ``prepare`` fixes their order.

Regular expressions on the string, so a chain is one projection inside generated code. Each rule names its
argument once: a chain of them stays as long as the rules are, whatever they are applied to.
"""

from __future__ import annotations

import re

from pyspark.sql import Column
from pyspark.sql import functions as F

from pantry.functions import lexicons as lx

INT, FLOAT, FRAC = r"\d+", r"\d+\.\d+", r"\d+/\d+"
NUM = rf"(?:{FRAC}|{FLOAT}|{INT})"
START, STOP = r"(?<![^ ])", r"(?![^ ])"  # token borders


def any_of(words) -> str:
    """An alternation, longest first."""
    return "(?:" + "|".join(re.escape(w) for w in sorted(words, key=lambda w: (-len(w), w))) + ")"


def sub(c: Column, pattern: str, to: str) -> Column:
    return F.regexp_replace(c, pattern, to)


def squeeze(c: Column) -> Column:
    return F.trim(sub(c, r"\s+", " "))


def vulgar(c: Column) -> Column:
    for sign, plain in lx.VULGAR.items():
        c = F.replace(c, F.lit(sign), F.lit(f" {plain}"))
    return c


def brand_token(i: int) -> str:
    return "brandx" + chr(97 + i)


def shield_brands(c: Column, brands=lx.BRANDS) -> Column:
    for i, b in sorted(enumerate(brands), key=lambda x: -len(x[1])):
        c = F.replace(c, F.lit(b), F.lit(brand_token(i)))
    return c


def restore_brands(c: Column, brands=lx.BRANDS) -> Column:
    for i, b in enumerate(brands):
        c = F.replace(c, F.lit(brand_token(i)), F.lit(b))
    return c


def brackets(c: Column) -> Column:
    return F.translate(c, "()[]{}", "")


def ranges(c: Column) -> Column:
    return sub(sub(c, r"(?<=\d)\s*[-–]\s*(?=\d)", " to "), r"[-–]", " ")


def percent(c: Column) -> Column:
    return sub(c, r"(?<!\d)%", " ")


def ampersand(c: Column) -> Column:
    return F.replace(c, F.lit("&"), F.lit(" and "))


def plus_sign(c: Column) -> Column:
    return F.replace(c, F.lit("+"), F.lit(" plus "))


def slash(c: Column) -> Column:
    return sub(c, r"(?<!\d)/|/(?!\d)", " ")


def specials(c: Column) -> Column:
    """Drop other special characters; full stops and commas outside numbers become tokens."""
    c = sub(c, r"[^\p{L}\p{N}\s%/.,]", " ")
    return sub(sub(c, r",", " , "), r"(?<!\d)\.|\.(?!\d)", " . ")


def halves(c: Column) -> Column:
    return sub(c, r"\bhalf (?:a|of|from)\b", "1/2")


def respell(c: Column, words: dict[str, str], mark: str = "") -> Column:
    """Tokens that are keys of ``words`` become their values: a set test a token, a look-up only for hits."""
    table = F.create_map(*(F.lit(x) for w, v in words.items() for x in (w, mark + v)))
    swap = lambda t: F.when(t.isin(*words), F.try_element_at(table, t)).otherwise(t)
    return F.array_join(F.transform(F.split(c, " "), swap), " ")


def number_words(c: Column) -> Column:
    """Number words, compound ones up to hundreds, and a half after them. Digits that were written stay apart: the
    mark tells them from words until compounds are made."""
    c = sub(c, rf"{START}an? hundred{STOP}", "one hundred")
    c = respell(c, {w: str(n) for w, n in lx.NUMBER_WORDS.items()}, "¤")
    c = sub(c, rf"{START}¤([2-9])0 ¤([1-9]){STOP}", "¤$1$2")
    c = sub(c, rf"{START}¤([1-9]) hundred(?: and)? ¤(\d\d){STOP}", "¤$1$2")
    c = sub(c, rf"{START}¤([1-9]) hundred(?: and)? ¤(\d){STOP}", "¤$10$2")
    c = F.replace(sub(c, rf"{START}¤([1-9]) hundred{STOP}", "¤$100"), F.lit("¤"), F.lit(""))
    return sub(c, rf"{START}({INT}) and (?:a half|1/2){STOP}", "$1 1/2")


def unit_phrases(c: Column, phrases: dict[str, str] | None = None) -> Column:
    """Units of several words as one, full stops of abbreviations dropped."""
    for words, one in (phrases or lx.UNIT_PHRASES).items():
        c = sub(c, rf"{START}{' (?:[.] )?'.join(map(re.escape, words.split()))}{STOP}(?: [.]{STOP})?", one)
    return c


def lemmas(c: Column) -> Column:
    """Of tokens: irregular words, then plural endings of words of four letters or more."""
    c = respell(c, lx.IRREGULAR)
    word = rf"\b(?!{any_of(lx.INVARIANT)}\b)"
    c = sub(c, word + r"(\p{L}{2,})ies\b", "$1y")
    c = sub(c, word + r"(\p{L}+(?:sh|ch|ss|x|zz))es\b", "$1")
    return sub(c, word + r"(\p{L}{2,}[^\W\dsuiSUI])s\b", "$1")


def redundant(c: Column, words=lx.REDUNDANT, phrases=lx.REDUNDANT_PHRASES) -> Column:
    return squeeze(sub(sub(c, rf"\b{any_of(phrases)}\b", " "), rf"{START}{any_of(words)}{STOP}", " "))


def articles(c: Column, units=None) -> Column:
    """A leading article before a unit is 1; so it is where neither unit nor number occurs."""
    unit = any_of((units or lx.surfaces()).keys())
    c = sub(c, rf"^an? (?={unit}{STOP})", "1 ")
    return sub(c, rf"^an? (?!(?:.* )?(?:{unit}|{NUM}){STOP})", "1 ")


def tokens(c: Column) -> Column:
    return F.filter(F.split(c, " "), lambda t: t != "")


def prepare(text: Column, lex: lx.Lexicons | None = None) -> Column:
    """Tokens of a line separated by single spaces, ready for the rules."""
    lex = lex or lx.Lexicons()
    c = F.lower(vulgar(F.coalesce(text, F.lit(""))))
    c = plus_sign(ampersand(percent(ranges(brackets(shield_brands(c, lex.brands))))))
    c = squeeze(specials(halves(slash(c))))
    c = unit_phrases(lemmas(number_words(c)))
    return articles(redundant(c, lex.redundant, lex.phrases), lex.units)
