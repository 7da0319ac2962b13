"""Word and line conventions shared by the text operators.

White space is the six ASCII characters 0x20 and 0x09-0x0D, words are the runs between them, and
only A-Z are lower-cased. The Spark forms are Column expressions, the Arrow forms work on a batch.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed values.
SPACE = " \t\n\x0b\f\r"
WORD = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def whole(text: Column) -> Column:
    """The text, null as empty."""
    return F.coalesce(text, F.lit(""))


def words(text: Column) -> Column:
    return F.regexp_extract_all(whole(text), F.lit(WORD), F.lit(0))


def n_words(text: Column) -> Column:
    return F.regexp_count(whole(text), F.lit(WORD)).cast("long")


def ascii_lower(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)


def fresh(df: DataFrame, *names: str) -> list[str]:
    """The names, each with as many underscores before it as make it differ from every column of ``df``."""
    taken, out = {c.lower() for c in df.columns}, []
    for n in names:
        while n in taken:
            n = "_" + n
        out.append(n)
    return out


def unit_interval(h: Column) -> Column:
    """A 64-bit hash as a double strictly between 0 and 1."""
    return (F.shiftrightunsigned(h, 12).cast("double") + F.lit(0.5)) / F.lit(float(1 << 52))


def id_crc(doc_id) -> int:
    """crc32 of the id as text; a null id counts as the empty text."""
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode())


def large(column: pa.Array) -> pa.Array:
    """The texts with 64-bit offsets, nulls as empty texts."""
    return pc.fill_null(column.cast(pa.large_string()), "")


def batch_words(texts: pa.Array, lower: bool = True) -> tuple[np.ndarray, np.ndarray, list[bytes]]:
    """Codes of all words of a batch in order, words per text, and the distinct words that codes point to."""
    split = pc.ascii_split_whitespace(pc.ascii_lower(texts) if lower else texts)
    parent, flat = pc.list_parent_indices(split), pc.list_flatten(split)
    keep = pc.not_equal(flat, "")  # white space at the ends leaves empty pieces
    parent, flat = parent.filter(keep), flat.filter(keep)
    coded = flat.dictionary_encode()
    counts = np.bincount(parent.to_numpy(zero_copy_only=False), minlength=len(texts)).astype(np.int64)
    distinct = coded.dictionary.cast(pa.large_binary()).to_pylist()
    return coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), counts, distinct


def pieces(texts: pa.Array, most: int = 1 << 24) -> list[tuple[int, int]]:
    """(begin, end) of runs of texts with about ``most`` bytes in all, so that long texts do not come together."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    cuts = np.flatnonzero(np.diff(ends // most, prepend=0)) if len(ends) else np.zeros(0, int)
    edges = np.unique(np.concatenate([[0], cuts, [len(texts)]])).tolist()
    return list(zip(edges[:-1], edges[1:]))


def word_hashes(distinct: list[bytes], seed: int = 0) -> np.ndarray:
    h = xxhash.xxh64_intdigest
    return np.fromiter((h(w, seed) for w in distinct), np.uint64, len(distinct))
