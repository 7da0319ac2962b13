"""Toxicity by a factorization machine over hashed terms.

score = sigmoid(b + sum_i w_i x_i + sum_{i<j} <v_i, v_j> x_i x_j), x_i = 1 if a term of the text hashes
to i. The pair term learns what single weights miss, such as an insult beside a mention of a group.

Training reads at most ``max_rows`` labelled documents a class, chosen by a hash of the id, and takes
their whole texts; class weights restore the labels' proportions. A term has weights if it relates to the label
by itself (chi-square of ``least_chi2``) or together with another term (``interacting``), so that a pair of two
terms that say nothing alone is learned too. The model has at most 2**hash_bits terms, whatever
the input; scoring is one pass without a shuffle.

Defined results: null and empty texts have no terms and get the score of the intercept; a document
with several labels counts as toxic if one says so, null labels are left out; without labels of both
classes every score is the share of toxic labels (0 if there are none); repeated rows have a row each; an
empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pantry.llm import text as tx

EDGES = b"\"'`.,;:!?()[]{}<>*_-#|"


@dataclass
class Model:
    """place: index of a hashed term's weights or -1."""

    hash_bits: int
    place: np.ndarray
    b: float
    w: np.ndarray
    v: np.ndarray


def terms(texts: pa.Array, hash_bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(text number, hashed term), each pair once, in order."""
    codes, counts, distinct = tx.batch_words(texts)
    hashed = (tx.word_hashes([w.strip(EDGES) or w for w in distinct], 5) >> np.uint64(64 - hash_bits)).astype(np.int64)
    row = np.repeat(np.arange(len(texts)), counts)
    pairs = np.unique((row << hash_bits) | hashed[codes]) if len(codes) else np.zeros(0, np.int64)
    return pairs >> hash_bits, pairs & ((1 << hash_bits) - 1)


def logits(m: Model, n: int, row: np.ndarray, term: np.ndarray) -> np.ndarray:
    at = m.place[term]
    row, at = row[at >= 0], at[at >= 0]
    out = np.full(n, m.b) + np.bincount(row, m.w[at], n)
    for f in range(m.v.shape[1]):
        x = m.v[at, f]
        out += 0.5 * (np.bincount(row, x, n) ** 2 - np.bincount(row, x * x, n))
    return out


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(z / 2))


def interacting(row: np.ndarray, term: np.ndarray, y: np.ndarray, size: int, least_rows: int = 40, least_chi2: float = 40.0, block: int = 512) -> np.ndarray:
    """Whether each term is in a pair that meets in ``least_rows`` rows and there differs in label from the sum of both.

    The sum of both: the log-odds of one term's rows plus the other's, less those of all rows. All pairs of terms
    that are in enough rows are counted, by products of blocks of the matrix rows x terms.
    """
    out = np.zeros(size, bool)
    of = np.flatnonzero(np.bincount(term, minlength=size) >= least_rows)
    place = np.full(size, -1)
    place[of] = np.arange(len(of))
    row, at = row[place[term] >= 0], place[term[place[term] >= 0]]
    order = np.argsort(at, kind="stable")
    row, at = row[order], at[order]
    odds = lambda hit, n: np.log((hit + 0.5) / (n - hit + 0.5))
    own = odds(np.bincount(at, y[row], len(of)), np.bincount(at, minlength=len(of)))
    rank = np.empty(len(y), np.int64)  # rows of label 1 first
    rank[np.argsort(-y, kind="stable")] = np.arange(len(y))
    ones = int(y.sum())

    def dense(a: int) -> np.ndarray:
        lo, hi = np.searchsorted(at, [a, a + block])
        x = np.zeros((len(y), min(block, len(of) - a)), np.float32)
        x[rank[row[lo:hi]], at[lo:hi] - a] = 1
        return x

    for a in range(0, len(of), block):
        left = dense(a)
        for b in range(a, len(of), block):
            right = left if a == b else dense(b)
            hit = left[:ones].T @ right[:ones]
            n = hit + left[ones:].T @ right[ones:]
            r = sigmoid(own[a : a + block, None] + own[None, b : b + block] - odds(ones, len(y)))
            far = (n >= least_rows) & ((hit - n * r) ** 2 >= least_chi2 * (n * r * (1 - r) + 1))
            if a == b:
                np.fill_diagonal(far, False)
            out[of[a : a + block]] |= far.any(1)
            out[of[b : b + block]] |= far.any(0)
    return out


def fit(row: np.ndarray, term: np.ndarray, y: np.ndarray, weight: np.ndarray, hash_bits: int, factors: int = 8, least_chi2: float = 12.0, l2: float = 0.0005, steps: int = 600, rate: float = 0.05, seed: int = 7) -> Model:
    """Adam over all rows at once; the same rows in the same order give the same model."""
    size, n = 1 << hash_bits, len(y)
    share = float((y * weight).sum() / weight.sum())
    place = np.full(size, -1)
    hit, all_ = np.bincount(term, y[row], size), np.bincount(term, minlength=size).astype(float)
    p = y.mean()
    with np.errstate(all="ignore"):
        chi2 = (hit - all_ * p) ** 2 / (all_ * p * (1 - p)) * n / np.maximum(n - all_, 1)
    chosen = np.flatnonzero(((all_ >= 3) & (chi2 >= least_chi2)) | interacting(row, term, y, size))
    place[chosen] = np.arange(len(chosen))
    m = Model(hash_bits, place, float(np.log(share / (1 - share))), np.zeros(len(chosen)), np.random.default_rng(seed).normal(0, 0.05, (len(chosen), factors)))
    at = place[term]
    row, at = row[at >= 0], at[at >= 0]
    grads = {"b": np.zeros(1), "w": m.w, "v": m.v}
    first = {k: np.zeros_like(g) for k, g in grads.items()}
    second = {k: np.zeros_like(g) for k, g in grads.items()}
    total = weight.sum()
    for step in range(1, steps + 1):
        sums = np.stack([np.bincount(row, m.v[at, f], n) for f in range(factors)], 1)
        squares = np.bincount(row, (m.v[at] ** 2).sum(1), n)
        z = m.b + np.bincount(row, m.w[at], n) + 0.5 * ((sums**2).sum(1) - squares)
        err = weight * (sigmoid(z) - y) / total
        e = err[row]
        pull = e[:, None] * (sums[row] - m.v[at])
        grads = {
            "b": np.array([err.sum()]),
            "w": np.bincount(at, e, len(chosen)) + l2 * m.w / 10,
            "v": np.stack([np.bincount(at, pull[:, f], len(chosen)) for f in range(factors)], 1) + l2 * m.v,
        }
        for k, g in grads.items():
            first[k] = 0.9 * first[k] + 0.1 * g
            second[k] = 0.999 * second[k] + 0.001 * g * g
            move = rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
            if k == "b":
                m.b -= float(move[0])
            else:
                setattr(m, k, getattr(m, k) - move)
    return m


def train(docs: DataFrame, labels: DataFrame, learns: Column, max_rows: int = 4000, hash_bits: int = 18, doc_id: str = "doc_id", text: str = "text", label: str = "toxic", **options) -> Model:
    """The model from the labelled documents whose id satisfies ``learns``."""
    known = labels.where(F.col(label).isNotNull() & F.col(doc_id).isNotNull() & learns).groupBy(F.col(doc_id).alias("_id")).agg(F.max(F.col(label).cast("int")).alias("_y"))
    totals = {r["_y"]: r["n"] for r in known.groupBy("_y").agg(F.count("*").alias("n")).collect()}
    # Of a large class only hashes below a cut compete, so that no partition sends max_rows rows to the driver.
    cut = lambda y: 1.3 * max_rows / max(1, totals.get(y, 0))
    of_class = lambda y: known.where((F.col("_y") == y) & (tx.unit_interval(F.xxhash64("_id")) < cut(y))).orderBy(F.xxhash64("_id"), "_id").limit(max_rows)
    sample = of_class(1).unionByName(of_class(0))
    ids = [(r["_id"], r["_y"]) for r in sample.collect()]  # at most 2 * max_rows ids
    empty = Model(hash_bits, np.full(1 << hash_bits, -1), 0.0, np.zeros(0), np.zeros((0, 1)))
    share = totals.get(1, 0) / max(1, sum(totals.values()))
    if not 0 < share < 1:
        empty.b = 40.0 if share else -40.0
        return empty
    chosen = docs.sparkSession.createDataFrame(ids, known.schema)

    def extract(batches):
        for b in batches:
            row, term = terms(tx.large(b.column("t")), hash_bits)
            ends = np.concatenate([[0], np.cumsum(np.bincount(row, minlength=b.num_rows))]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([b.column("_id").cast(pa.string()), b.column("_y"), pa.ListArray.from_arrays(ends, pa.array(term.astype(np.int32)))], ["_id", "_y", "terms"])

    met = docs.select(F.col(doc_id).alias("_d"), F.col(text).alias("t")).join(F.broadcast(chosen), F.col("_d") == F.col("_id"))
    rows = met.select("_id", "_y", "t").mapInArrow(extract, "_id string, _y int, terms array<int>").toPandas().sort_values("_id", kind="stable")
    if rows["_y"].nunique() < 2:
        empty.b = 40.0 if share > 0.5 else -40.0
        return empty
    y = rows["_y"].to_numpy().astype(float)
    in_sample = np.bincount(rows["_y"], minlength=2)
    weight = np.where(y > 0, totals[1] / in_sample[1], totals[0] / in_sample[0])
    row = np.repeat(np.arange(len(rows)), [len(t) for t in rows["terms"]])
    term = np.concatenate([np.asarray(t, np.int64) for t in rows["terms"]])
    return fit(row, term, y, weight / weight.mean(), hash_bits, **options)


def score(docs: DataFrame, model: Model, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, score) for every row."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # bounded by 2**hash_bits terms

    def run(batches):
        for b in batches:
            row, term = terms(tx.large(b.column(1)), sent.value.hash_bits)
            z = logits(sent.value, b.num_rows, row, term)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sigmoid(z))], ["doc_id", "score"])

    slim = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))
    return slim.mapInArrow(run, f"doc_id {dict(slim.dtypes)['doc_id']}, score double")
