"""Exact top-k inner products by a Voronoi join.

Vectors and queries are assigned to their nearest pivot. A group's summary is its radius and its few
smallest distances to the pivot. For a query q and a vector x of a group with pivot p,
q.p - |q||x-p| <= q.x, so the summaries alone give each query a score that its k-th best reaches; the
least of these over a query group is the group's threshold. For a query group with pivot p and radius
r, q.x <= p.x + r|x|, so a vector is sent to the query group only if that reaches the threshold. Each
group is then solved by integer block products, and the parts' best are merged.

Bounds are widened by a rounding margin; scores are exact integers. Groups are cut into blocks of a
bounded number of vectors and queries, so a hot group becomes many tasks.

Defined results: vectors that are null or hold null or non-finite components, and rows without an id,
take no part; missing components of shorter vectors count as 0; rows that share the query's id are its
own; a query id that comes more than once asks once (its least vector); candidate rows that repeat are
candidates each; ties go to the smaller id; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pantry.operators.relational import global_rank
from pantry.session import materialize

INTEGERS = ("bigint", "int", "smallint", "tinyint")


def quantised(vector: Column, scale: int = 256) -> Column:
    return F.transform(vector, lambda x: F.floor(x.cast("double") * scale).cast("long"))


def _usable(vector: Column) -> Column:
    finite = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < float("inf"))
    return vector.isNotNull() & F.forall(vector, finite)


def _padded(lists: pa.ListArray, dim: int, kind: str) -> np.ndarray:
    """Rows of ``dim`` integers, shorter vectors filled with zeros."""
    lengths = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = pc.list_flatten(lists).to_numpy(zero_copy_only=False)
    out = np.zeros((len(lists), dim), kind)
    row = np.repeat(np.arange(len(lists)), lengths)
    out[row, np.arange(len(flat)) - np.repeat(np.cumsum(lengths) - lengths, lengths)] = flat
    return out


def _rows(m: np.ndarray) -> pa.Array:
    return pa.array([r.tobytes() for r in np.ascontiguousarray(m)], pa.binary())


def _matrix(column, dim: int, kind: str) -> np.ndarray:
    return np.frombuffer(b"".join(column), kind).reshape(-1, dim).astype(np.int64)


def _products(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Exact integer products, through doubles where no sum can leave their exact range."""
    most = float(np.abs(q).max(initial=0)) * float(np.abs(x).max(initial=0)) * max(1, q.shape[1])
    return (q.astype(float) @ x.astype(float).T).astype(np.int64) if most < 2**52 else q @ x.T


def _best(ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best, ties to the smaller id."""
    if len(scores) > 4 * k:
        least = np.partition(scores, len(scores) - k)[len(scores) - k]
        near = np.flatnonzero(scores >= least)
    else:
        near = np.arange(len(scores))
    return near[np.lexsort((ids[near], -scores[near]))[:k]]


def _by_rank(df: DataFrame, queries: Column, vec_id: str, **options) -> DataFrame:
    """``top_k`` for ids that are no integers: they are numbered in their order, and named again in the end."""
    ids = global_rank(df.select(F.col(f"`{vec_id}`").alias("name")).where("name is not null").distinct(), [F.col("name")], "id")
    ids = materialize(ids.select("name", F.col("id").cast("long").alias("id")), "knn-ids")
    rows = df.select(F.col(f"`{vec_id}`").alias("name"), F.col(f"`{options['vector']}`").alias("embedding"), queries.alias("asks")).join(ids, "name")
    found = top_k(rows, F.col("asks"), vec_id="id", **(options | {"vector": "embedding"}))
    name = lambda of: ids.select(F.col("id").alias(of), F.col("name").alias(f"{of}_name"))
    out = found.join(name("query_id"), "query_id").join(name("vec_id"), "vec_id")
    return out.select(F.col("query_id_name").alias("query_id"), "rank", F.col("vec_id_name").alias("vec_id"), "score")


def top_k(df: DataFrame, queries: Column, k: int = 5, pivots: int | None = None, scale: int = 256, vec_id: str = "vec_id", vector: str = "embedding", block: int = 8192, query_block: int = 2048) -> DataFrame:
    """(query_id, rank, vec_id, score): the k rows with the highest products for each row where ``queries`` holds.

    Without ``pivots`` there is one for every 64 queries, 1024 at most. A vector goes once to each block of up
    to ``query_block`` queries that it may reach, whose products are made some queries at a time.
    """
    if dict(df.dtypes)[vec_id] not in INTEGERS:
        return _by_rank(df, queries, vec_id, k=k, pivots=pivots, scale=scale, vector=vector, block=block, query_block=query_block)
    spark = df.sparkSession
    rows = df.where(F.col(vec_id).isNotNull() & _usable(F.col(vector))).select(F.col(vec_id).cast("long").alias("id"), quantised(F.col(vector), scale).alias("v"), F.coalesce(queries, F.lit(False)).alias("asks"))
    most = F.max(F.greatest(F.coalesce(F.array_max("v"), F.lit(0)), -F.coalesce(F.array_min("v"), F.lit(0))))
    size = rows.agg(F.max(F.size("v")).alias("dim"), F.count("*").alias("n"), F.sum(F.col("asks").cast("long")).alias("q"), most.alias("most")).first()
    dim, n, n_q = max(1, size["dim"] or 1), size["n"], size["q"] or 0
    kind = "<i2" if (size["most"] or 0) < 1 << 15 else "<i4" if size["most"] < 1 << 31 else "<i8"
    pivots = pivots or max(1, min(1024, n_q // 64))
    # A bounded sample of pivots, the same at every run.
    chosen = pa.array([r["v"] for r in rows.orderBy(F.xxhash64("id"), "id").limit(pivots).collect()], pa.list_(pa.int64()))
    p = _padded(chosen, dim, "<i8").astype(float) if len(chosen) else np.zeros((1, dim))
    p2 = (p**2).sum(1)

    def assign(batches):
        for b in (whole.slice(i, 2048) for whole in batches for i in range(0, whole.num_rows, 2048)):
            m = _padded(b.column("v"), dim, kind)
            v = m.astype(float)
            d2 = (v**2).sum(1)[:, None] - 2 * v @ p.T + p2
            g = d2.argmin(1)
            yield pa.RecordBatch.from_arrays([b.column("id"), _rows(m), b.column("asks"), pa.array(g.astype(np.int32)), pa.array(np.linalg.norm(v - p[g], axis=1))], ["id", "v", "asks", "g", "d"])

    placed = materialize(rows.mapInArrow(assign, "id long, v binary, asks boolean, g int, d double"), "knn-placed")

    def first(d: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The least distances of k + 1 different ids: rows that share an id count once."""
        order = np.lexsort((ids, d))
        order = order[np.sort(np.unique(ids[order], return_index=True)[1])[: k + 1]]
        return d[order], ids[order]

    def summarise(parts):
        near_, far = {}, {}
        for t in parts:
            for g, some in t.groupby("g"):
                d, ids = near_.get(g, (np.zeros(0), np.zeros(0, np.int64)))
                near_[g] = first(np.concatenate([d, some["d"].to_numpy()]), np.concatenate([ids, some["id"].to_numpy()]))
                far[g] = max(far.get(g, 0.0), some["d"].max())
        if near_:
            yield pd.DataFrame({"g": list(near_), "near": [d for d, _ in near_.values()], "ids": [i for _, i in near_.values()], "far": list(far.values())})

    def join_summaries(t: pd.DataFrame) -> pd.DataFrame:
        d, ids = first(np.concatenate(list(t["near"])), np.concatenate(list(t["ids"])))
        return pd.DataFrame({"g": t["g"][:1], "near": [d], "ids": [ids], "far": [t["far"].max()]})

    shape = "g int, near array<double>, ids array<long>, far double"
    summaries = placed.select("g", "d", "id").mapInPandas(summarise, shape).groupBy("g").applyInPandas(join_summaries, shape).collect()  # one row a pivot

    asked = placed.where("asks").groupBy("id").agg(F.min(F.struct("v", "g", "d")).alias("m")).select("id", "m.v", "m.g", "m.d")
    group_of = np.concatenate([np.full(len(s["near"]), s["g"]) for s in summaries]) if summaries else np.zeros(0, int)
    near_id = np.concatenate([np.asarray(s["ids"], np.int64) for s in summaries]) if summaries else np.zeros(0, np.int64)
    near_d = np.concatenate([np.asarray(s["near"]) for s in summaries]) if summaries else np.zeros(0)

    def thresholds(parts):
        for t in parts:
            q = _matrix(t["v"], dim, kind).astype(float)
            norm = np.linalg.norm(q, axis=1)
            low = (q @ p.T)[:, group_of] - norm[:, None] * near_d
            low[t["id"].to_numpy()[:, None] == near_id[None, :]] = -np.inf  # the query's own rows are no results
            least = np.partition(low, -k, axis=1)[:, -k] if low.shape[1] >= k else np.full(len(t), -np.inf)
            yield pd.DataFrame({"g": t["g"], "low": least, "d": t["d"]})

    groups = asked.mapInPandas(thresholds, "g int, low double, d double").groupBy("g").agg(F.min("low").alias("low"), F.max("d").alias("r"), F.count("*").alias("n")).collect()  # one row a pivot
    at = np.array([g["g"] for g in groups], int)
    low, radius = np.array([g["low"] for g in groups]), np.array([g["r"] for g in groups])
    parts_x = max(1, -(-n // block))

    def send(batches):
        for b in batches:
            for start in range(0, b.num_rows, 1024):
                some = b.slice(start, 1024)
                x = _matrix(some.column("v").to_pylist(), dim, kind).astype(float)
                norm = np.linalg.norm(x, axis=1)
                reach = x @ p[at].T + norm[:, None] * radius
                margin = 1e-9 * (norm[:, None] * (np.linalg.norm(p[at], axis=1) + radius) + 1)
                row, col = np.nonzero(reach + margin >= low - margin)
                sent_ = some.take(pa.array(row))
                yield pa.RecordBatch.from_arrays([pa.array(at[col].astype(np.int32)), sent_.column("id"), sent_.column("v")], ["h", "id", "v"])

    sent = placed.select("id", "v").mapInArrow(send, "h int, id long, v binary")
    cuts = spark.createDataFrame([(int(g["g"]), max(1, -(-g["n"] // query_block))) for g in groups], "h int, blocks int")
    cuts = F.broadcast(cuts)  # one row a pivot
    sent = sent.join(cuts, "h").withColumn("bx", F.pmod(F.xxhash64("id", "v"), F.lit(parts_x)).cast("int")).withColumn("bq", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    asked = asked.withColumnRenamed("g", "h").join(cuts, "h").withColumn("bq", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int")).withColumn("bx", F.explode(F.sequence(F.lit(0), F.lit(parts_x - 1))))

    def solve(q: pd.DataFrame, x: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(q) and len(x):
            ids, asks = x["id"].to_numpy(), q["id"].to_numpy()
            have, want = _matrix(x["v"], dim, kind), _matrix(q["v"], dim, kind)
            for i, own in enumerate(asks):
                if i % 256 == 0:
                    scores = _products(want[i : i + 256], have)
                others = np.flatnonzero(ids != own)
                best = others[_best(ids[others], scores[i % 256, others], k)]
                out.append(pd.DataFrame({"query_id": own, "vec_id": ids[best], "score": scores[i % 256, best]}))
        return pd.concat(out) if out else pd.DataFrame({"query_id": np.zeros(0, int), "vec_id": np.zeros(0, int), "score": np.zeros(0, int)})

    key = ["h", "bq", "bx"]
    found = asked.select(*key, "id", "v").groupBy(key).cogroup(sent.select(*key, "id", "v").groupBy(key)).applyInPandas(solve, "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
