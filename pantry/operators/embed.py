"""Word and ingredient vectors: skip-gram, CBOW, GloVe, two document models, nearest foods.

Vocabulary-sized parameters go to every partition; ``MOST_MB`` checks that before a broadcast. Epochs
are partition-local passes of negative sampling whose parameters are averaged by token count.
"""

from __future__ import annotations

from itertools import product

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.ml.feature import Word2Vec
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pantry.operators.vocab import cooccurrence, vocabulary
from pantry.session import materialize

MOST_MB = 512
#: Lines that a partition trains on, and partitions whose parameters are averaged.
LINES_A_PART, MOST_PARTS = 50_000, 256
DIMS, WINDOWS, COMBINE = (50, 100, 200), (2, 3, 5, 10), ("sum", "avg")


def embedding_grid() -> list[tuple[str, str, int, int, str]]:
    """(algorithm, architecture, dim, window, combine) of every setting; 0 where a setting does not apply."""
    grid = [("word2vec", a, d, w, c) for a, d, w, c in product(("cbow", "sg"), DIMS, WINDOWS, COMBINE)]
    grid += [("glove", "", d, w, c) for d, w, c in product(DIMS, WINDOWS, COMBINE)]
    grid += [("doc2vec", a, d, w, c) for a, d, w, c in product(("dm", "dbow"), DIMS, WINDOWS, COMBINE)]
    return grid + [("bert", "", 0, 0, c) for c in ("sum", "concat")]


def word2vec_sg(df: DataFrame, dim: int, window: int, seed: int = 1, epochs: int = 1) -> DataFrame:
    parts = max(1, min(MOST_PARTS, df.count() // LINES_A_PART))
    model = Word2Vec(vectorSize=dim, windowSize=window, minCount=1, seed=seed, maxIter=epochs, numPartitions=parts, inputCol="tokens", outputCol="vec").fit(df.select("tokens"))
    return model.getVectors().select("word", vector_to_array("vector").alias("vec"))


def _sampler(counts: np.ndarray) -> np.ndarray:
    p = counts**0.75
    return np.cumsum(p / p.sum())


def _ascend(inputs: np.ndarray, outputs: np.ndarray, used: list[np.ndarray], target: int, negatives: np.ndarray, rate: float) -> float:
    """One negative-sampling step: ``used`` are views of the input rows whose mean predicts ``target``."""
    hidden = np.mean(used, axis=0)
    at = np.concatenate([[target], negatives])
    truth = np.zeros(len(at))
    truth[0] = 1
    out = outputs[at]
    p = 1 / (1 + np.exp(-np.clip(out @ hidden, -12, 12)))
    g = (truth - p) * rate
    back = g @ out
    np.add.at(outputs, at, g[:, None] * hidden)
    for row in used:
        row += back / len(used)
    return float(-np.log(np.maximum(np.where(truth > 0, p, 1 - p), 1e-9)).sum())


def negative_sampling(df: DataFrame, dim: int, window: int, mode: str, epochs: int = 3, negatives: int = 5, rate: float = 0.05, seed: int = 1, min_count: int = 1) -> tuple[DataFrame, DataFrame, list[float]]:
    """Train ``cbow``, ``dm`` or ``dbow``: (word vectors, line vectors, loss an epoch).

    Lines are dealt by key and sorted inside a partition, and draws are seeded by epoch and line, so a
    rerun repeats. Line vectors live where their line lives; word parameters are averaged after an epoch.
    """
    spark = df.sparkSession
    vocab = vocabulary(df, min_count).select("word", "n").orderBy(F.col("n").desc(), "word")
    if vocab.count() * dim * 16 > MOST_MB << 20:
        raise ValueError("the vocabulary is too large for partition-local training; raise min_count")
    words = vocab.toPandas()
    id_of = {w: i for i, w in enumerate(words["word"])}
    cumulative = _sampler(words["n"].to_numpy(float))
    rng = np.random.default_rng(seed)
    w_in, w_out = (rng.random((len(words), dim)) - 0.5) / dim, np.zeros((len(words), dim))
    lines = materialize(df.select("food_key", "tokens").repartition(max(4, min(MOST_PARTS, df.count() // LINES_A_PART)), "food_key").sortWithinPartitions("food_key").withColumn("vec", F.lit(None).cast("array<double>")), "lines")
    losses: list[float] = []
    for epoch in range(epochs):
        sent = spark.sparkContext.broadcast((id_of, cumulative, w_in, w_out))
        step = rate * (1 - epoch / epochs)

        def train(parts, sent=sent, step=step, epoch=epoch):
            ids, cum, a, b = sent.value
            a, b = a.copy(), b.copy()
            loss, seen = 0.0, 0
            for t in parts:
                vecs = []
                for key, toks, old in zip(t["food_key"], t["tokens"], t["vec"]):
                    draw = np.random.default_rng([seed, epoch, *key.encode()])
                    line = [ids[w] for w in toks if w in ids]
                    own = (draw.random(dim) - 0.5) / dim if old is None else np.asarray(old, float).copy()
                    for i, target in enumerate(line):
                        around = line[max(0, i - window) : i] + line[i + 1 : i + 1 + window]
                        used = [a[j] for j in around] if mode != "dbow" else []
                        used += [own] if mode != "cbow" else []
                        if used:
                            loss += _ascend(a, b, used, target, np.searchsorted(cum, draw.random(negatives)), step)
                            seen += 1
                    vecs.append(own)
                yield pd.DataFrame({"food_key": t["food_key"], "tokens": t["tokens"], "vec": vecs, "kind": "line", "seen": 0, "loss": 0.0})
            yield pd.DataFrame({"food_key": [None], "tokens": [None], "vec": [np.concatenate([a.ravel(), b.ravel()])], "kind": "words", "seen": seen, "loss": loss})

        out = materialize(lines.mapInPandas(train, "food_key string, tokens array<string>, vec array<double>, kind string, seen long, loss double"), "epoch")
        # one row a partition, each of the checked size of the parameters
        parts = [r for r in out.where("kind = 'words' and seen > 0").select("vec", "seen", "loss").toLocalIterator()]
        total = sum(r["seen"] for r in parts)
        if total:
            flat = sum(np.asarray(r["vec"]) * (r["seen"] / total) for r in parts)
            w_in, w_out = flat[: w_in.size].reshape(w_in.shape), flat[w_in.size :].reshape(w_out.shape)
            losses.append(sum(r["loss"] for r in parts) / total)
        lines = out.where("kind = 'line'").select("food_key", "tokens", "vec")
    vectors = spark.createDataFrame([(w, [float(x) for x in v]) for w, v in zip(words["word"], w_in)], "word string, vec array<double>")
    return vectors, lines, losses


def _row_solver(sent, own_key: str, other_key: str, dim: int, ridge: float, x_max: float, power: float):
    """The ridge problem of one word; its ridge pulls to the word's last solution, so no turn can undo another."""

    def solve(t: pd.DataFrame) -> pd.DataFrame:
        ids, far, own = sent.value
        f = far[[ids[w] for w in t[other_key]]]
        x = t["weight"].to_numpy(float)
        weight = np.minimum(1, (x / x_max) ** power)
        z = np.hstack([f[:, :dim], np.ones((len(f), 1))])
        y = np.log(x) - f[:, dim]
        start = own[ids[t[own_key].iloc[0]]]
        left = (z * weight[:, None]).T @ z + ridge * np.eye(dim + 1)
        best = np.linalg.solve(left, (z * weight[:, None]).T @ y + ridge * start)
        loss = float((weight * (z @ best - y) ** 2).sum())
        return pd.DataFrame({"word": [t[own_key].iloc[0]], "vec": [best], "loss": [loss]})

    return solve


def glove(df: DataFrame, dim: int, window: int, rounds: int = 4, seed: int = 1, ridge: float = 0.05, x_max: float = 100.0, power: float = 0.75) -> tuple[DataFrame, list[float]]:
    """Weighted least squares on log co-occurrence by alternating solves: (word, vec) and the loss a round.

    Each word's row is one small ridge problem against the other side's factors; sides take turns.
    """
    spark = df.sparkSession
    cooc = materialize(cooccurrence(df, window), "cooc")
    words = [r["w1"] for r in cooc.select("w1").distinct().orderBy("w1").toLocalIterator()]
    if len(words) * dim * 16 > MOST_MB << 20:
        raise ValueError("the vocabulary is too large for broadcast factors; raise min_count")
    id_of = {w: i for i, w in enumerate(words)}
    rng = np.random.default_rng(seed)
    sides = [np.hstack([(rng.random((len(words), dim)) - 0.5) / dim, np.zeros((len(words), 1))]) for _ in range(2)]
    losses: list[float] = []
    for turn in range(2 * rounds):
        mine, other = turn % 2, 1 - turn % 2
        own_key, other_key = (("w1", "w2"), ("w2", "w1"))[mine]
        solve = _row_solver(spark.sparkContext.broadcast((id_of, sides[other], sides[mine])), own_key, other_key, dim, ridge, x_max, power)
        rows = cooc.groupBy(own_key).applyInPandas(solve, "word string, vec array<double>, loss double").toLocalIterator()
        total = 0.0
        for r in rows:
            sides[mine][id_of[r["word"]]] = r["vec"]
            total += r["loss"]
        losses.append(total)
    vec = sides[0][:, :dim] + sides[1][:, :dim]
    return spark.createDataFrame([(w, [float(x) for x in v]) for w, v in zip(words, vec)], "word string, vec array<double>"), losses


class LayerProvider:
    """Layer outputs of an encoder for token lists. Weights of a trained one cannot be had offline: this
    stand-in is a seeded random attention stack, and its results are never called by a trained model's name.
    """

    def __init__(self, width: int = 16, layers: int = 4, seed: int = 1):
        self.width, self.layers, self.seed = width, layers, seed

    def encode(self, toks: list[str]) -> np.ndarray:
        x = np.stack([np.random.default_rng([self.seed, *w.encode()]).normal(size=self.width) for w in toks])
        out = []
        for k in range(self.layers):
            m = np.random.default_rng([self.seed, k]).normal(size=(self.width, self.width)) / np.sqrt(self.width)
            a = np.exp(x @ m @ x.T / np.sqrt(self.width) - (x @ m @ x.T).max() / np.sqrt(self.width))
            x = np.tanh(x + (a / a.sum(1, keepdims=True)) @ x @ m)
            out.append(x.mean(0))
        return np.stack(out)

    def transform(self, df: DataFrame) -> DataFrame:
        """(food_key, layers)."""

        def run(parts):
            for t in parts:
                yield pd.DataFrame({"food_key": t["food_key"], "layers": [[list(v) for v in self.encode(list(w))] if len(w) else None for w in t["tokens"]]})

        return df.select("food_key", "tokens").mapInPandas(run, "food_key string, layers array<array<double>>")


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return F.try_divide(dot(a, b), norm(a) * norm(b))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x))


#: Rows of a block product, and the rounding that it may be off by beside what six decimals round.
ROWS, MARGIN = 8192, 1.2e-5


def _best_of(found: pd.DataFrame, k: int) -> pd.DataFrame:
    """Of (q, id, cosine) all that may be among a query's k best by the cosine's six decimals, ties to the smaller id; no cosine comes last."""
    rank = found["cosine"].where(~found["none"], -2.0).fillna(3.0)  # as Spark sorts: not a number is above all
    found = found.assign(_r=rank).sort_values(["q", "_r", "id"], ascending=[True, False, True], kind="stable")
    found = found[found.groupby(["q", "_r"]).cumcount() < k]
    least = found[found.groupby("q").cumcount() < k].groupby("q")["_r"].agg(["min", "size"])
    least = found["q"].map(least["min"].where(least["size"] == k, -np.inf))
    return found[found["_r"] >= least - 2e-6].drop(columns="_r")


class _Nearest:
    """The k nearest of a stream of vectors for some queries: block products in single precision find the rows near a
    query's k-th best, whose cosines are then summed in doubles, component after component."""

    def __init__(self, ids: np.ndarray, vectors: list, k: int):
        self.ids, self.k = ids, k
        self.lengths = np.array([-1 if v is None else len(v) for v in vectors])
        self.sides = {n: _Side(np.flatnonzero(self.lengths == n), vectors, n) for n in np.unique(self.lengths)}
        self.least = np.full(len(ids), -np.inf, np.float32)
        self.found: list[pd.DataFrame] = []
        self.held = 0

    def add(self, ids: np.ndarray, vectors: list) -> None:
        lengths = np.array([-1 if v is None else len(v) for v in vectors])
        order = np.argsort(ids, kind="stable")
        for n, q in self.sides.items():
            x = _Side(np.flatnonzero((lengths == n) & (n >= 0)), vectors, n)
            bare = np.ones(len(ids), bool)
            bare[x.at[x.norm != 0]] = False  # rows without a cosine: only the first of them can be results
            bare = order[bare[order]]
            for i in range(0, len(q.at), 2048):
                some = np.arange(i, min(i + 2048, len(q.at)))
                self._products(q, some, x, np.flatnonzero(x.norm != 0), ids)
            for j in q.at:
                first = bare[: self.k + int((ids[bare[: self.k + 1]] == self.ids[j]).any())] if len(bare) else bare
                if len(first):
                    self._keep(np.full(len(first), j), ids[first], np.zeros(len(first)), np.ones(len(first), bool))

    def _products(self, q: _Side, some: np.ndarray, x: _Side, rows: np.ndarray, ids: np.ndarray) -> None:
        if not len(rows):
            return
        at = q.at[some]
        s = q.unit[some] @ x.unit[rows].T
        s[~q.plain[some]], s[:, ~x.plain[rows]] = 3, 3  # compared in full
        mine = pd.merge(pd.DataFrame({"id": self.ids[at], "i": np.arange(len(at))}), pd.DataFrame({"id": ids[x.at[rows]], "j": np.arange(len(rows))}), on="id")
        s[mine["i"], mine["j"]] = -np.inf
        if len(rows) >= self.k:
            self.least[at] = np.maximum(self.least[at], np.partition(s, -self.k, axis=1)[:, -self.k])
        i, j = np.nonzero(s >= np.maximum(np.minimum(self.least[at], 1)[:, None] - np.float32(MARGIN), np.float32(-1e30)))
        for k in range(0, len(i), 1 << 20):
            a, b = some[i[k : k + (1 << 20)]], rows[j[k : k + (1 << 20)]]
            dot = np.zeros(len(a))
            for c in range(q.m.shape[1]):
                dot += q.m[a, c] * x.m[b, c]
            below = q.norm[a] * x.norm[b]
            with np.errstate(all="ignore"):
                self._keep(q.at[a], ids[x.at[b]], dot / below, below == 0)

    def _keep(self, q, ids, cosine, none) -> None:
        self.found.append(pd.DataFrame({"q": q, "id": ids, "cosine": cosine, "none": none}))
        self.held += len(q)
        if self.held > 1 << 22:
            self.found = [_best_of(pd.concat(self.found), self.k)]
            self.held = len(self.found[0]) // 2

    def best(self) -> pd.DataFrame | None:
        return _best_of(pd.concat(self.found), self.k) if self.found else None


class _Side:
    """Vectors of one length: values, norms and single-precision directions."""

    def __init__(self, at: np.ndarray, vectors: list, n: int):
        self.at = at
        self.m = np.array([vectors[i] for i in at], float).reshape(len(at), n) if n > 0 else np.zeros((len(at), 0))
        with np.errstate(all="ignore"):
            square = np.zeros(len(at))
            for c in range(self.m.shape[1]):
                square += self.m[:, c] * self.m[:, c]
            self.norm = np.sqrt(square)
            self.unit = (self.m / np.where(self.norm == 0, 1, self.norm)[:, None]).astype(np.float32)
        self.plain = np.isfinite(self.norm) & (self.norm > 1e-140) | (self.norm == 0)
        self.unit[~self.plain] = 0


def nearest(vectors: DataFrame, queries: DataFrame, k: int, key: str = "vec_id", vec: str = "embedding", most: int = 10_000) -> DataFrame:
    """(query, rank, key, cosine): exact; queries go in blocks of about ``most``, which is what makes the broadcasts safe."""
    spark = vectors.sparkSession
    kind = dict(vectors.dtypes)[key]
    blocks = max(1, -(-queries.count() // most))
    # a vector that holds a null has no cosine
    whole = lambda df: df.where(F.col(key).isNotNull()).select(key, F.when(F.forall(vec, lambda x: x.isNotNull()), F.transform(vec, lambda x: x.cast("double"))).alias("_v"))
    wide = spark.sparkContext.defaultParallelism
    rows = whole(vectors)
    rows = rows if vectors.rdd.getNumPartitions() >= wide else rows.repartition(wide)
    out = None
    for i in range(blocks):
        some = queries if blocks == 1 else queries.where(F.pmod(F.xxhash64(key), F.lit(blocks)) == i)
        asked = whole(some).toArrow()  # ``most`` rows
        sent = spark.sparkContext.broadcast((asked.column(0).to_pandas().to_numpy(), asked.column(1).to_pandas().tolist()))

        def search(batches, sent=sent):
            best = _Nearest(*sent.value, k)
            for b in (whole_.slice(i, ROWS) for whole_ in batches for i in range(0, whole_.num_rows, ROWS)):
                best.add(b.column(0).to_pandas().to_numpy(), b.column(1).to_pandas().tolist())
            found = best.best() if len(best.ids) else None
            if found is not None and len(found):
                names = [pa.array(best.ids[found["q"]]), pa.array(found["id"].to_numpy()), pa.array(found["cosine"].to_numpy(float), mask=found["none"].to_numpy(bool))]
                yield pa.RecordBatch.from_arrays(names, ["query", key, "cosine"])

        pairs = rows.mapInArrow(search, f"query {kind}, {key} {kind}, cosine double")
        out = pairs if out is None else out.unionByName(pairs)
    w = Window.partitionBy("query").orderBy(F.col("cosine").desc(), key)
    return out.withColumn("cosine", F.round("cosine", 6)).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def as_vectors(spark: SparkSession, df: DataFrame, vec: str) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    return df.withColumn("_vector", array_to_vector(F.transform(vec, lambda x: x.cast("double"))))
