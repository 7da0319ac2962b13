"""Line dedup across documents.

Lines are exploded and normalised, their keys hashed, distinct documents counted for each hash, and
lines over the threshold dropped everywhere but in the largest doc_id; what stays is joined again by
position. Only (hash, doc_id) pairs are shuffled for the counts, first by the pair and then, already
summed in each task, by the hash, so that a line in a third of all documents makes no hot task; its holders
are then found by a broadcast of the few hot hashes. The texts move once, to meet the hashes that their
document loses.

Defined results: a null or empty text is one empty line, and stays so; keys shorter than ``min_chars``
code points never go; a null doc_id counts as one document, smaller than every other; rows that
repeat a doc_id count as one document and lose the same lines; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pantry.llm import text as tx
from pantry.llm.ranks import meet
from pantry.session import materialize

#: Most hot keys that are broadcast, parts that a document's long list of lost keys is dealt into, documents of a hot key.
HOT = 100_000
BUCKETS = 64
LEAST_HOT = 10_000


def line_key(line: Column) -> Column:
    return tx.ascii_lower(F.btrim(line, F.lit(tx.SPACE)))


def key_hash(key: Column) -> Column:
    """128 bits: two XXH64 of different seeds."""
    return F.struct(F.xxhash64(key).alias("a"), F.xxhash64(F.lit(1), key).alias("b"))


def holders(df: DataFrame, min_chars: int, doc_id: str, text: str) -> DataFrame:
    """(hash, d): the keys that may go, each once a document."""
    lines = df.select(F.col(f"`{doc_id}`").alias("d"), F.explode(F.split(tx.whole(F.col(f"`{text}`")), "\n")).alias("line"))
    lines = lines.select("d", F.btrim("line", F.lit(tx.SPACE)).alias("line")).where(F.char_length("line") >= min_chars)
    return lines.select("d", key_hash(tx.ascii_lower(F.col("line"))).alias("hash")).groupBy("hash", "d").agg(F.lit(1).alias("one")).drop("one")


def frequent_lines(held: DataFrame, min_docs: int = 5) -> DataFrame:
    """(hash, n_docs, keeper) of the keys that at least ``min_docs`` documents hold."""
    return held.groupBy("hash").agg(F.count("*").alias("n_docs"), F.max("d").alias("keeper")).where(F.col("n_docs") >= min_docs)


def _losses(held: DataFrame, frequent: DataFrame) -> DataFrame:
    """(d, lost): the hashes that each document loses.

    Keys of very many documents are looked up where their holders are, through a broadcast of at most HOT rows.
    """
    lost = meet(held, frequent.withColumnRenamed("keeper", "_keeper"), ["hash"], "n_docs", LEAST_HOT, HOT)
    return lost.where(~F.col("d").eqNullSafe(F.col("_keeper"))).groupBy("d").agg(F.collect_list("hash").alias("lost"))


def _loses(line: Column, min_chars: int) -> Column:
    """Whether the line's key is among ``_lost``; long lists are dealt into BUCKETS by hash first (``_dealt``)."""
    key = key_hash(line_key(line))
    few = F.array_contains(F.col("_lost"), key)
    many = F.array_contains(F.get(F.col("_dealt"), F.pmod(key["a"], F.lit(BUCKETS)).cast("int")), key)
    return (F.char_length(F.btrim(line, F.lit(tx.SPACE))) >= min_chars) & F.when(F.col("_dealt").isNull(), few).otherwise(many)


def drop_frequent_lines(df: DataFrame, min_docs: int = 5, min_chars: int = 40, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``df`` with the text cut, and ``n_lines`` (before) and ``n_dropped`` added in place of columns so called."""
    cols = [c for c in df.columns if c not in ("n_lines", "n_dropped")]
    held = materialize(holders(df, min_chars, doc_id, text), "held")
    frequent = materialize(frequent_lines(held, min_docs), "frequent")
    losses = _losses(held, frequent)
    rows = df.select(F.struct(*(F.col(f"`{c}`") for c in cols)).alias("_row"), F.col(f"`{doc_id}`").alias("_id"), tx.whole(F.col(f"`{text}`")).alias("_text"))
    met = rows.join(losses, F.col("_id").eqNullSafe(F.col("d")), "left").withColumnRenamed("lost", "_lost")
    split = F.split("_text", "\n")
    dealt = F.transform(F.sequence(F.lit(0), F.lit(BUCKETS - 1)), lambda b: F.filter(F.col("_lost"), lambda h: F.pmod(h["a"], F.lit(BUCKETS)) == b))
    met = met.withColumn("_dealt", F.when(F.size("_lost") > BUCKETS, dealt))
    kept = F.when(F.col("_lost").isNotNull(), F.filter(split, lambda line: ~_loses(line, min_chars)))
    met = met.withColumn("_kept", kept).withColumn("n_lines", F.size(split).cast("long"))
    out = F.when(F.col("_kept").isNotNull(), F.array_join("_kept", "\n")).otherwise(F.col("_row")[text])
    dropped = F.when(F.col("_kept").isNotNull(), F.col("n_lines") - F.size("_kept")).otherwise(0).cast("long")
    return met.select(*(out.alias(c) if c == text else F.col("_row")[c].alias(c) for c in cols), "n_lines", dropped.alias("n_dropped"))
