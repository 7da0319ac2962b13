"""Sharding by a k-d tree over metadata.

A node is split at the weighted median of its widest dimension until it holds one shard. All nodes of
a level are split together: a histogram of bytes over the node's key range, refined inside the bin
that holds the median until the bin is a single key or too light to matter. Per round the driver
sees one row a node; the tree it builds has as many splits as there are shards.

Dimensions are 31-bit places: log2 of the bytes, hashes of source and language, doc_id in its range.
Each is completed by 32 bits of a hash of the row, so a value that a third of all rows share can still
be split, and shards come out near equal in bytes.

A name has no width: for the hashed dimensions "widest" only means that several names are left in the node.
The law is ``bytes``. Equal texts are therefore not kept together: a group of copies may hold a third of
all bytes, and then no split into near-equal shards can. Copies do share a shard where they agree in id.

Defined results: ids may be of any type, all but numbers by their hash; null values of a dimension take its lowest place; null texts have one byte; rows that
repeat are rows of their own and may fall together; an empty table gives an empty result. Rows that
agree in id, text and metadata cannot be told apart and stay in one shard.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import NumericType

from pantry.llm import text as tx
from pantry.llm.ranks import running
from pantry.session import discard, materialize

PLACES = (1 << 31) - 1
DIMS = 4


@dataclass
class Node:
    """A leaf of the tree so far: shards [first, first + shards), to be cut at ``at`` of dimension ``dim``."""

    first: int
    shards: int
    dim: int = 0
    at: int = 0
    want: float = 0.0
    whole: int = 0
    low: int = 0
    high: int = 0
    below: int = 0


def _keyed(df: DataFrame, doc_id: str, text: str, source: str, lang: str) -> DataFrame:
    """(doc_id, size, text_crc32, tie, keys: a long for each dimension)."""
    body = tx.whole(F.col(text))
    slim = df.select(
        F.col(f"`{doc_id}`").alias("doc_id"),
        (F.octet_length(body) + 1).cast("long").alias("size"),
        F.crc32(body).alias("text_crc32"),
        F.xxhash64(F.col(f"`{doc_id}`"), body).alias("tie"),
        F.col(source).alias("_s"),
        F.col(lang).alias("_l"),
    )
    slim = materialize(slim, "kd-rows")
    name = lambda c: F.when(c.isNull(), F.lit(0)).otherwise(F.shiftrightunsigned(F.xxhash64(c), 33))
    by_id = name(F.col("doc_id"))
    if isinstance(slim.schema["doc_id"].dataType, NumericType):
        id_ = F.col("doc_id").cast("double")
        low, high = slim.agg(F.min(id_), F.max(id_)).first()
        by_id = (F.coalesce(id_, F.lit(low or 0.0)) - F.lit(low or 0.0)) / F.lit(max(1.0, (high or 0.0) - (low or 0.0))) * PLACES
    places = [F.log2(F.col("size")) / 40 * PLACES, name(F.col("_s")), name(F.col("_l")), by_id]
    tie = F.shiftrightunsigned("tie", 32)
    keys = F.array(*(F.shiftleft(F.least(F.floor(p), F.lit(PLACES)).cast("long"), 32).bitwiseOR(tie) for p in places))
    return slim.select("doc_id", "size", "text_crc32", "tie", keys.alias("keys"))


def _small(rows: DataFrame, values: list[tuple], schema: str, at_once: int = 2000) -> DataFrame:
    """A driver's table of at most one row a shard; a long one is written, some rows a statement."""
    names = ", ".join(f"{name}" for name, _ in (f.split() for f in schema.split(", ")))
    kinds = [f.split()[1] for f in schema.split(", ")]

    def some(part: list[tuple]) -> DataFrame:
        cells = ", ".join("(" + ", ".join(f"CAST({v!r} AS {k})" for v, k in zip(row, kinds)) + ")" for row in part)
        return rows.sparkSession.sql(f"SELECT * FROM VALUES {cells} AS t({names})")

    if len(values) <= at_once:
        return some(values)
    written = [materialize(some(values[i : i + at_once]), "kd-tree") for i in range(0, len(values), at_once)]
    return rows.sparkSession.read.schema(schema).parquet(*(t._pantry_path for t in written))


def _medians(rows: DataFrame, nodes: list[Node], bins: int, slack: float) -> None:
    """Set ``dim`` and ``at`` of each node: the weighted median of its widest dimension."""
    key = [F.col("keys")[d] for d in range(DIMS)]
    spans = rows.groupBy("node").agg(F.sum("size").alias("bytes"), F.array(*(F.min(k) for k in key)).alias("low"), F.array(*(F.max(k) for k in key)).alias("high"))
    by, open_ = {x.first: x for x in nodes}, {}
    for r in spans.collect():  # one row a node
        if x := by.get(r["node"]):
            x.dim = max(range(DIMS), key=lambda d: (r["high"][d] >> 32) - (r["low"][d] >> 32))
            x.low, x.high, x.below = r["low"][x.dim], r["high"][x.dim], 0
            x.want, x.whole = r["bytes"] * (x.shards // 2) / x.shards, r["bytes"]
            open_[x.first] = x
    while open_:
        asked = _small(rows, [(x.first, x.dim, x.low, x.high, x.want - x.below) for x in open_.values()], "node int, dim int, low long, high long, aim double")
        inside = rows.join(F.broadcast(asked), "node").withColumn("key", F.get("keys", F.col("dim"))).where("key >= low and key <= high")
        place = F.floor((F.col("key") - F.col("low")).cast("double") / ((F.col("high") - F.col("low")).cast("double") + 1) * bins)
        binned = inside.groupBy("node", "aim", F.least(place, F.lit(bins - 1)).alias("bin")).agg(F.sum("size").alias("bytes"), F.min("key").alias("lo"), F.max("key").alias("hi"))
        before = F.coalesce(F.sum("bytes").over(Window.partitionBy("node").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        found = binned.withColumn("before", before).where("before < aim and before + bytes >= aim").collect()  # one row a node
        for n in open_.keys() - {r["node"] for r in found}:
            by[n].at = by[n].high
            del open_[n]
        for r in found:
            x = by[r["node"]]
            below = x.below + r["before"]
            if r["lo"] == r["hi"] or r["bytes"] <= slack * x.whole:
                x.at = r["hi"] if below + r["bytes"] / 2 <= x.want else r["lo"] - 1  # to where the halves come out nearer
                del open_[x.first]
            else:
                x.low, x.high, x.below = r["lo"], r["hi"], below


def shard(df: DataFrame, shards: int = 16, target_bytes: int | None = None, bins: int = 1024, slack: float = 0.0005, doc_id: str = "doc_id", text: str = "text", source: str = "source", lang: str = "lang") -> DataFrame:
    """(doc_id, size, text_crc32, shard, slot); with ``target_bytes`` as many shards as hold that much."""
    rows = _keyed(df, doc_id, text, source, lang)
    if target_bytes:
        shards = max(1, -(-(rows.agg(F.sum("size")).first()[0] or 0) // target_bytes))
    rows = rows.withColumn("node", F.lit(0))
    nodes = [Node(0, shards)] if shards > 1 else []
    while nodes:
        _medians(rows, nodes, bins, slack)
        cuts = _small(rows, [(x.first, x.dim, x.at, x.first + x.shards // 2) for x in nodes], "node int, dim int, at long, upper int")
        upper = F.when(F.get("keys", F.col("dim")) > F.col("at"), F.col("upper")).otherwise(F.col("node"))
        level = rows.join(F.broadcast(cuts), "node", "left").withColumn("node", upper).drop("dim", "at", "upper")
        old, rows = rows, materialize(level, "kd-level")  # so that no histogram repeats the joins of earlier levels
        if hasattr(old, "_pantry_path"):
            discard(old)
        halves = [Node(f, n) for x in nodes for f, n in ((x.first, x.shards // 2), (x.first + x.shards // 2, x.shards - x.shards // 2))]
        nodes = [x for x in halves if x.shards > 1]
    out = rows.select("doc_id", "size", "text_crc32", "tie", F.col("node").alias("shard"), F.lit(1).cast("long").alias("_one"))
    return running(out, ["shard"], "tie", "_one", "slot", ties=("doc_id",)).drop("_one", "tie")
