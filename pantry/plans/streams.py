"""Queries: every stream beside its batch equivalent."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pantry.operators import linking, regress
from pantry.plans import views
from pantry.plans.truth import LINES, RECIPES, WEIGHED
from pantry.session import table
from pantry.streaming import ingest

Q, O = {}, {}


def query(sql: str | None = None):
    """Register a query, and its SQL if it has one."""

    def keep(f):
        Q[f.__name__] = f
        if sql:
            O[f.__name__] = sql
        return f

    return keep


def _stream(df: DataFrame, files: int = 2) -> DataFrame:
    return ingest.source(df.sparkSession, ingest.publish(df, files), df.schema)


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with a zoned time: streams need it."""
    spark.conf.set("spark.sql.session.timeZone", "UTC")
    return table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


@query(f"WITH {LINES} SELECT line_key, part_no, qty, unit, food FROM tw WHERE t IN (1, 6)")
def stream_normalize(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = views.text_lines(spark, sf_dir, (1, 6)).select("line_key", "text")
    return ingest.run_once(ingest.normalize_stream(_stream(lines))).select("line_key", "part_no", "qty", "unit", "food")


@query(f"WITH {WEIGHED} SELECT lk.tier::INT AS tier, count(*) AS n FROM (SELECT * FROM tw WHERE t = 0) x LEFT JOIN lk ON array_to_string(list_sort(string_split(food, ' ')), ' ') = lk.key GROUP BY lk.tier")
def stream_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = views.text_lines(spark, sf_dir, (0,)).select("line_key", "text")
    links = linking.link_foods(views.foods(spark, sf_dir), views.items(spark, sf_dir))
    return ingest.run_once(ingest.link_stream(ingest.normalize_stream(_stream(lines)), links)).groupBy("tier").agg(F.count("*").alias("n"))


@query(f"WITH {LINES} SELECT DISTINCT array_to_string(list_sort(list_distinct(string_split(food, ' '))), ' ') AS food_key FROM tw WHERE t = 4")
def stream_new_foods(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = views.text_lines(spark, sf_dir, (4,)).select("line_key", "text").withColumn("ts", F.lit("2020-01-01").cast("timestamp"))
    return ingest.run_once(ingest.new_foods(ingest.normalize_stream(_stream(lines)))).select("food_key")


def _windows(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    counts = ingest.windowed_counts(_stream(_events(spark, sf_dir), 1), kind, delay="3650 days")
    keys = ["start", "end", "user_id" if kind == "session" else "event_type"]
    # sessions cannot be updated, so they are completed
    got = ingest.run_once(counts, "complete" if kind == "session" else "update")
    got = ingest.latest(got, keys)
    text = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss")
    return got.select(text("start").alias("start"), text("end").alias("end"), keys[2], "n", F.round("v", 4).alias("v"))


_F = "'%Y-%m-%d %H:%M:%S'"


@query(f"SELECT strftime(s, {_F}) AS start, strftime(s + INTERVAL 1 DAY, {_F}) AS \"end\", event_type, count(*) AS n, round(sum(value), 4) AS v FROM (SELECT *, date_trunc('day', ts) AS s FROM events) GROUP BY ALL")
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windows(spark, sf_dir, "tumbling")


@query(f"SELECT strftime(s, {_F}) AS start, strftime(s + INTERVAL 1 DAY, {_F}) AS \"end\", event_type, count(*) AS n, round(sum(value), 4) AS v FROM (SELECT *, time_bucket(INTERVAL 12 HOURS, ts, TIMESTAMP '2000-01-01') - k * INTERVAL 12 HOURS AS s FROM events, (VALUES (0), (1)) AS t(k)) GROUP BY ALL")
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windows(spark, sf_dir, "sliding")


@query(f"WITH a AS (SELECT *, CASE WHEN ts <= lag(ts) OVER w + INTERVAL 6 HOURS THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), b AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM a) SELECT strftime(min(ts), {_F}) AS start, strftime(max(ts) + INTERVAL 6 HOURS, {_F}) AS \"end\", user_id, count(*) AS n, round(sum(value), 4) AS v FROM b GROUP BY user_id, s")
def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windows(spark, sf_dir, "session")


@query()
def stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows closed by a short watermark: what came too late is not in them."""
    e = _events(spark, sf_dir)
    got = ingest.run_once(ingest.windowed_counts(_stream(e, 4), "tumbling", delay="1 hour"))
    return got.agg(F.sum("n").alias("counted")).crossJoin(e.agg(F.count("*").alias("sent")))


@query("SELECT user_id, count(*) AS n, round(sum(value), 4) AS v FROM events GROUP BY user_id")
def stream_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _events(spark, sf_dir).select("user_id", "value")
    got = ingest.run_once(ingest.running_totals(_stream(e)), "update")
    return ingest.latest(got, ["user_id"]).select("user_id", "n", F.round("v", 4).alias("v"))


@query("SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _events(spark, sf_dir)
    l, r = (_stream(e.where(F.col("event_type") == t), 1) for t in ("click", "purchase"))  # noqa: E741
    return ingest.run_once(ingest.followed_by(l, r, delay="3650 days")).select("first", "second")


@query(f"WITH {RECIPES} SELECT fold, count(*)::DOUBLE AS n, round(sum(fat), 3) AS fat, round(sum(fat * fat), 1) AS fat2 FROM r GROUP BY fold")
def stream_gram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Statistics are additive: each micro-batch's sums are added up, and equal those of one scan."""
    r = views.recipes(spark, sf_dir).withColumn("x", F.array(F.lit(0.0))).select("fold", "x", "fat")
    sums: dict[int, list[float]] = {}

    def add(batch: DataFrame, _: int) -> None:
        for row in regress.gram(batch, "x", 1, ("fat",)).collect():  # one matrix a fold
            old = sums.get(row["fold"], [0.0] * 9)
            sums[row["fold"]] = [a + b for a, b in zip(old, row["stats"])]

    ingest.run_once(_stream(r), each=add)
    return spark.createDataFrame([(f, s[0], round(s[2], 3), round(s[8], 1)) for f, s in sums.items()], "fold int, n double, fat double, fat2 double")
