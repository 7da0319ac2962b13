"""Packing by optimal length buckets.

A global histogram of document lengths goes to the driver, where dynamic programming chooses the
bucket boundaries with the least padding. Documents are numbered inside their bucket, and as many as
the token budget holds at the bucket's length form a batch. Documents stay whole.

The histogram is bounded at any size: lengths have bins of their own up to ``exact`` tokens and share
one with those within one part in 64 above it, so it has a few thousand rows. Numbering uses cells of a hash, so that no bucket
meets in one task. Lengths, not texts, are shuffled.

Defined results: a null or empty text has one token, its end; a document longer than the budget is a
batch of its own; rows that repeat are packed as often as they come; an empty table gives an empty
result.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pantry.llm import text as tx
from pantry.llm.ranks import running


def length_bin(n: Column, exact: int = 2048) -> Column:
    """The bin of a length: its largest possible length."""
    step = F.pow(F.lit(2.0), F.floor(F.log2(F.greatest(n, F.lit(1)))) - 6)
    return F.when(n <= exact, n).otherwise((F.ceil(n / step) * step).cast("long")).cast("long")


def boundaries(lengths: np.ndarray, counts: np.ndarray, buckets: int, sums: np.ndarray | None = None) -> list[int]:
    """Upper ends of at most ``buckets`` buckets with the least padding, from ascending lengths.

    ``sums`` are the tokens of each bin, if not all of its documents have the bin's length.
    """
    n = len(lengths)
    if n == 0:
        return []
    length = lengths.astype(float)
    c = np.concatenate([[0.0], np.cumsum(counts)])
    s = np.concatenate([[0.0], np.cumsum(counts * length if sums is None else sums)])
    best = np.full(n + 1, np.inf)
    best[0] = 0.0
    back = []
    for _ in range(min(buckets, n)):
        now, cut = np.full(n + 1, np.inf), np.zeros(n + 1, int)
        for j in range(1, n + 1):
            cost = best[:j] + length[j - 1] * (c[j] - c[:j]) - (s[j] - s[:j])
            cut[j] = i = int(np.argmin(cost))
            now[j] = cost[i]
        back.append(cut)
        best = now
    ends, j = [], n
    for cut in reversed(back):
        ends.append(int(lengths[j - 1]))
        j = cut[j]
    return ends[::-1]


def with_lengths(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_tokens, key): words and one end; the key spreads and orders the rows."""
    return df.select(F.col(doc_id).alias("doc_id"), (tx.n_words(F.col(text)) + 1).alias("n_tokens"), F.xxhash64(F.col(doc_id), F.col(text)).alias("key"))


def pack(lengths: DataFrame, buckets: int = 12, budget: int = 65536) -> DataFrame:
    """Add bucket, bucket_len, batch (numbered inside the bucket), place (in the batch) and padding."""
    rows = lengths.withColumn("_bin", length_bin(F.col("n_tokens")))
    # one row a bin; its longest document, not its end, is what a bucket may end at
    hist = rows.groupBy("_bin").agg(F.count("*").alias("n"), F.max("n_tokens").alias("longest"), F.sum("n_tokens").alias("tokens")).orderBy("_bin").toPandas()
    ends = boundaries(hist["longest"].to_numpy(), hist["n"].to_numpy(), buckets, hist["tokens"].to_numpy(float)) or [1]
    bucket, end = F.lit(len(ends) - 1), F.lit(ends[-1])
    for i in range(len(ends) - 2, -1, -1):
        bucket = F.when(F.col("n_tokens") <= ends[i], F.lit(i)).otherwise(bucket)
        end = F.when(F.col("n_tokens") <= ends[i], F.lit(ends[i])).otherwise(end)
    rows = rows.drop("_bin").withColumn("bucket", bucket.cast("int")).withColumn("bucket_len", end.cast("long")).withColumn("_one", F.lit(1).cast("long"))
    rows = running(rows, ["bucket"], "key", "_one", "_rank", ties=("doc_id",)).drop("_one")
    held = F.greatest(F.floor(F.lit(budget) / F.col("bucket_len")), F.lit(1))
    rows = rows.withColumn("batch", F.floor(F.col("_rank") / held).cast("long")).withColumn("place", (F.col("_rank") % held).cast("long"))
    return rows.withColumn("padding", F.col("bucket_len") - F.col("n_tokens")).drop("_rank", "key")
