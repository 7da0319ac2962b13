"""Streams: continuous normalization and linking, new foods, event windows, state, additive statistics.

Sources are files of a declared schema; ``run_once`` drains what is there and stops, which is also how a
scheduled job would run them. Results go through ``foreachBatch`` to a table that a batch id makes
idempotent.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from pantry.operators.normalize import TRIPLE, triples
from pantry.session import shared_dir


def publish(df: DataFrame, files: int = 2) -> str:
    """A folder that a stream can read, in place of a queue."""
    path = f"{shared_dir(df.sparkSession)}/pantry-stream-{uuid.uuid4().hex}"
    df.repartition(files).write.parquet(path)
    return path


def source(spark: SparkSession, path: str, schema) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def run_once(stream: DataFrame, mode: str = "append", each: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Drain the stream into a table and read it; in ``update`` and ``complete`` modes the table has every version."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/pantry-sink-{uuid.uuid4().hex}"
    schema = stream.schema.add("_batch", "long")

    def put(batch: DataFrame, batch_id: int) -> None:
        if each:
            each(batch, batch_id)
        # the batch id names the folder: a batch that is run again replaces itself
        batch.withColumn("_batch", F.lit(batch_id).cast("long")).write.mode("overwrite").parquet(f"{base}/data/b={batch_id}")

    q = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    written = q.lastProgress is not None
    reader = spark.read.schema(schema)
    if not written:
        return spark.createDataFrame([], schema)
    return reader.parquet(f"{base}/data/*")


def latest(versions: DataFrame, keys: list[str]) -> DataFrame:
    """The last version of each key."""
    cols = [c for c in versions.columns if c not in (*keys, "_batch")]
    return versions.groupBy(*keys).agg(F.max_by(F.struct(*cols), "_batch").alias("_l")).select(*keys, "_l.*")


def normalize_stream(lines: DataFrame, text: str = "text") -> DataFrame:
    """The rules on arriving lines: projections and a generator only, hence no state."""
    keep = [c for c in lines.columns]
    return triples(lines, text).select(*keep, *TRIPLE)


def link_stream(normalized: DataFrame, links: DataFrame) -> DataFrame:
    """Arriving foods with their item: a stream-static join."""
    return normalized.join(links.select(F.col("key").alias("food_key"), "item_id", "tier"), "food_key", "left")


def new_foods(normalized: DataFrame, at: str = "ts", delay: str = "1 day") -> DataFrame:
    return normalized.withWatermark(at, delay).select("food_key", at).dropDuplicatesWithinWatermark(["food_key"])


def windowed_counts(events: DataFrame, kind: str, at: str = "ts", delay: str = "1 day") -> DataFrame:
    """Counts and sums by event type in tumbling, sliding or session windows."""
    window = {"tumbling": F.window(at, "1 day"), "sliding": F.window(at, "1 day", "12 hours"), "session": F.session_window(at, "6 hours")}[kind]
    keys = [window.alias("w"), F.col("event_type")] if kind != "session" else [window.alias("w"), F.col("user_id")]
    out = events.withWatermark(at, delay).groupBy(*keys).agg(F.count("*").alias("n"), F.sum("value").alias("v"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *out.columns[1:])


def running_totals(events: DataFrame) -> DataFrame:
    """A user's running count and total as state."""

    def update(key: tuple, parts, state: GroupState):
        n, v = state.get if state.exists else (0, 0.0)
        for t in parts:
            n, v = n + len(t), v + float(t["value"].sum())
        state.update((n, v))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "v": [v]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, v double", "n long, v double", "update", GroupStateTimeout.NoTimeout)


def followed_by(left: DataFrame, right: DataFrame, hours: int = 1, delay: str = "1 day") -> DataFrame:
    """Pairs of events of a user, the right one at most ``hours`` after the left."""
    l = left.withWatermark("ts", delay).select(F.col("user_id").alias("lu"), F.col("ts").alias("lt"), F.col("event_id").alias("first"))  # noqa: E741
    r = right.withWatermark("ts", delay).select(F.col("user_id").alias("ru"), F.col("ts").alias("rt"), F.col("event_id").alias("second"))
    on = (F.col("lu") == F.col("ru")) & (F.col("rt") >= F.col("lt")) & (F.col("rt") <= F.col("lt") + F.expr(f"INTERVAL {hours} HOURS"))
    return l.join(r, on)
