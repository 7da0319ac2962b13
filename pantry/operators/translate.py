"""Translation of lines: through a glossary of words, or by a service that the user plugs in.

A translator takes distinct (lang, text) rows and gives them with ``english``. Lines in ``spoken`` pass as they are.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPOKEN = ("en",)


def needs(lang, spoken: tuple[str, ...] = SPOKEN):
    return F.col(lang).isNotNull() & ~F.col(lang).isin(*spoken)


class Glossary:
    """Words of the line's language replaced through a table (lang, foreign, word); unknown words pass.

    Words are looked up by an equality join and put back in order, so a glossary of any size works.
    """

    def __init__(self, words: DataFrame, spoken: tuple[str, ...] = SPOKEN):
        self.words, self.spoken = words, spoken

    def __call__(self, once: DataFrame) -> DataFrame:
        shape = r"^(.*?)([,.;]*)$"
        each = once.where(needs("lang", self.spoken)).select("lang", "text", F.posexplode(F.split("text", " ")).alias("i", "w"))
        each = each.withColumn("bare", F.regexp_extract("w", shape, 1)).withColumn("tail", F.regexp_extract("w", shape, 2))
        known = self.words.select(F.col("lang").alias("_l"), F.col("foreign").alias("_f"), F.col("word").alias("_w"))
        met = each.join(known, (F.col("lang") == F.col("_l")) & (F.col("bare") == F.col("_f")), "left")
        new = F.struct("i", F.concat(F.coalesce("_w", "bare"), "tail").alias("w"))
        back = met.groupBy("lang", "text").agg(F.array_join(F.transform(F.array_sort(F.collect_list(new)), lambda x: x["w"]), " ").alias("english"))
        return back.unionByName(once.where(~needs("lang", self.spoken) | F.col("lang").isNull()).select("lang", "text", F.col("text").alias("english")))


class Service:
    """Any outside service: ``call(texts, lang)`` returns as many English texts. It is called on the executors, ``batch`` texts at a time."""

    def __init__(self, call: Callable[[list[str], str], list[str]], batch: int = 64, spoken: tuple[str, ...] = SPOKEN):
        self.call, self.batch, self.spoken = call, batch, spoken

    def __call__(self, once: DataFrame) -> DataFrame:
        call, batch = self.call, self.batch

        def run(parts):
            for t in parts:
                for lang, some in t.groupby("lang"):
                    texts = some["text"].tolist()
                    english = [x for i in range(0, len(texts), batch) for x in call(texts[i : i + batch], lang)]
                    yield pd.DataFrame({"lang": lang, "text": texts, "english": english})

        foreign = once.where(needs("lang", self.spoken) & F.col("text").isNotNull()).mapInPandas(run, "lang string, text string, english string")
        rest = once.where(~needs("lang", self.spoken) | F.col("lang").isNull() | F.col("text").isNull())
        return foreign.unionByName(rest.select("lang", "text", F.col("text").alias("english")))


def translate(df: DataFrame, translator, text: str = "text", lang: str = "lang") -> DataFrame:
    """``df`` with its text in English; distinct texts are translated once."""
    once = translator(df.select(F.col(lang).alias("lang"), F.col(text).alias("text")).distinct())
    once = once.select(F.col("lang").alias("_lang"), F.col("text").alias("_old"), F.col("english").alias("_new"))
    out = df.join(once, F.col(lang).eqNullSafe(F.col("_lang")) & F.col(text).eqNullSafe(F.col("_old")), "left")
    return out.select(*(F.col("_new").alias(text) if c == text else F.col(c) for c in df.columns))
