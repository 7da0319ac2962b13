"""LM scoring by deleted interpolation.

P(w | h) = l_b * c(h w) / c(h) + (1 - l_b) * (m * c(w) / N + (1 - m) / (V + 1)): maximum-likelihood
bigrams and unigrams over a uniform floor. The bucket b of a context is the power of two of its count.
Training documents fall in ``folds``; each fold's events are held out against the counts of the others
(the fold's own counts deleted), and expectation-maximisation on those held-out counts learns m and l_b.
The likelihood of one weight depends on an event only through the ratio of its two parts, so EM runs on
a histogram of ratios (1/64 wide in the logarithm, each bin with its mean ratio), bounded at any size.

Counts never meet a hot key or a driver. Documents are dealt into blocks by hash. A block asks, for each
range of 64-bit n-gram hashes, for the sorted distinct hashes that it holds, with its own counts; the
range's task adds all blocks' counts and answers each block with the totals in the order it asked. So
"the" is one hash a block, however frequent. An answered block writes, for each document, the few numbers a token that the weights still need, and the last step
applies the learned weights. All of it grows with the corpus and none with a vocabulary on one machine.

Two n-grams whose 63-bit hashes agree would share a count: for 10^9 different n-grams that is
expected in 0.05 pairs.

Defined results: a null or empty text is the end token alone; null ids train in fold and remainder of
the empty text; repeated rows count as often as they come; without training text N and V are 0 and
every token has the uniform probability; an empty table gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pantry.llm import text as tx
from pantry.session import materialize, release

END = b"\n"
BIN = 64.0
MIX = np.uint64(0x9E3779B97F4A7C15)


def _finish(x: np.ndarray) -> np.ndarray:
    """A 64-bit mixer (the finaliser of SplitMix64)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Block:
    """Tokens of a block's documents, and its distinct n-grams in the order of their hashes.

    The lowest bit of a hash is 1 for a word and 0 for a pair.
    """

    def __init__(self, ids: list, texts: pa.Array):
        codes, counts, distinct = tx.batch_words(texts)
        end = len(distinct)
        ends = np.cumsum(counts + 1) - 1
        tokens = np.full(len(codes) + len(counts), end, np.int64)
        inside = np.ones(len(tokens), bool)
        inside[ends] = False
        tokens[inside] = codes
        self.tokens, self.starts, self.lengths = tokens, ends - counts, counts + 1
        self.before = np.concatenate([[end], tokens[:-1]]) if len(tokens) else tokens
        crc = np.fromiter((tx.id_crc(i) for i in ids), np.int64, len(ids))
        self.crc = crc
        word = tx.word_hashes([*distinct, END])
        self.pairs = self.before * (end + 1) + tokens
        self.word_keys = _finish(word ^ MIX) | np.uint64(1)
        self.hash = word
        self.n_words = end + 1

    def pair_keys(self, pairs: np.ndarray) -> np.ndarray:
        a, b = self.hash[pairs // self.n_words], self.hash[pairs % self.n_words]
        return _finish(a * MIX + (b ^ (b >> np.uint64(29)))) & ~np.uint64(1)


def _fold(crc: np.ndarray, held: int, modulus: int, folds: int) -> np.ndarray:
    """Fold of each document, -1 where it is held out of training."""
    return np.where(crc % modulus == held, -1, crc // modulus % folds)


def _planes(x: np.ndarray) -> bytes:
    """64-bit numbers by byte planes, compressed: of sorted keys and small counts little is left."""
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(x.view(np.uint8).reshape(-1, 8).T).tobytes())


def _numbers(b: bytes, kind=np.uint64) -> np.ndarray:
    plain = zstandard.ZstdDecompressor().decompress(b)
    return np.ascontiguousarray(np.frombuffer(plain, np.uint8).reshape(8, -1).T).view(kind).ravel()


def _steps(keys: np.ndarray) -> bytes:
    """Ascending keys as their differences."""
    return _planes(np.diff(keys, prepend=np.uint64(0)))


def _block(t: pa.Table) -> Block:
    texts = t.column("text").combine_chunks()
    return Block(t.column("doc_id").to_pylist(), texts.cast(pa.large_string()))


def _counted(block: Block, fold: np.ndarray, folds: int) -> tuple[np.ndarray, np.ndarray]:
    """The block's keys in ascending order and its counts, folds x keys."""
    of_token = np.repeat(fold, block.lengths)
    words = np.stack([np.bincount(block.tokens[of_token == f], minlength=block.n_words) for f in range(folds)])
    marked = np.sort(block.pairs * (folds + 1) + of_token + 1)
    pair = marked // (folds + 1)
    first = np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]])) if len(pair) else np.zeros(0, int)
    which = marked - pair * (folds + 1)
    pairs = [np.add.reduceat((which == f + 1).astype(np.int64), first) if len(first) else np.zeros(0, np.int64) for f in range(folds)]
    keys = np.concatenate([block.word_keys, block.pair_keys(pair[first])])
    order = np.argsort(keys, kind="stable")
    return keys[order], np.concatenate([words, np.stack(pairs)], axis=1)[:, order]


def _part(keys: np.ndarray, ranges: int) -> np.ndarray:
    return ((keys >> np.uint64(32)) * np.uint64(ranges) >> np.uint64(32)).astype(np.int64)


def em(n: np.ndarray, ratio: np.ndarray, rounds: int = 200) -> float:
    """Weight of the better-informed part: maximises sum n log(l * ratio + 1 - l)."""
    if n.sum() <= 0:
        return 0.0
    weight = 0.5
    for _ in range(rounds):
        weight = float((n * weight * ratio / (weight * ratio + 1 - weight)).sum() / n.sum())
    return min(max(weight, 0.0), 0.999999)


class Totals:
    """What all blocks' answers share: tokens N (all, and without each fold), words V, weight m."""

    def __init__(self, stats: pd.DataFrame, folds: int):
        word = stats[stats["kind"] == "n"]
        self.per_fold = np.bincount(word["a"].astype(int), word["x"], folds).astype(float) if len(word) else np.zeros(folds)
        self.n = float(self.per_fold.sum())
        self.v = float(stats.loc[stats["kind"] == "v", "x"].sum())
        held = stats[stats["kind"] == "u"]
        if len(held):
            left = self.n - self.per_fold[held["a"].astype(int)]
            mean = (held["y"] / held["x"]).to_numpy()
            self.m = em(held["x"].to_numpy(), mean / np.maximum(left, 1) * (self.v + 1))
        else:
            self.m = 0.0

    def lower(self, word: np.ndarray, n: np.ndarray | float) -> np.ndarray:
        return self.m * word / np.maximum(n, 1) + (1 - self.m) / (self.v + 1)


def _bucket(context: np.ndarray) -> np.ndarray:
    """0 for a context never seen, else 1 + floor(log2 count)."""
    return np.where(context > 0, np.frexp(np.maximum(context, 1))[1], 0).astype(np.uint8)


def _ratios(pair, context, lower) -> np.ndarray:
    return np.where(context > 0, pair / np.maximum(context, 1) / lower, 0.0)


def score(df: DataFrame, held: int = 2, modulus: int = 7, folds: int = 2, block_mb: float | None = None, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) for every row.

    Rows whose crc32(doc_id) leaves ``held`` by ``modulus`` are held out of training. A block has 5 MB of
    text, above 30 GB of input by its square root more: messages then keep about a hundred n-grams each, and
    blocks, ranges and what a task holds all grow with the root (290 MB a block at 100 TB).
    """
    spark = df.sparkSession
    id_kind = dict(df.dtypes)[doc_id]
    slim = df.select(F.col(doc_id).alias("doc_id"), tx.whole(F.col(text)).alias("text"))
    size = slim.agg(F.sum(F.octet_length("text")).alias("b"), F.count("*").alias("n")).first()
    total_mb = (size["b"] or 0) / (1 << 20)
    block_mb = block_mb or 5 * max(1.0, (total_mb / 30_000) ** 0.5)
    blocks = max(1, math.ceil(total_mb / block_mb), math.ceil(size["n"] / (40_000 * block_mb)))
    ranges = max(1, blocks)
    dealt = slim.withColumn("block", F.pmod(F.xxhash64("doc_id", "text"), F.lit(blocks)).cast("int"))

    def ask(t: pa.Table) -> pa.Table:
        block = _block(t)
        keys, counts = _counted(block, _fold(block.crc, held, modulus, folds), folds)
        part = _part(keys, ranges)
        at = np.searchsorted(part, np.arange(ranges + 1))
        used = np.flatnonzero(np.diff(at))
        return pa.table(
            {
                "part": pa.array(used.astype(np.int32)),
                "block": pa.array(np.full(len(used), t.column("block")[0].as_py(), np.int32)),
                "keys": pa.array([_steps(keys[at[p] : at[p + 1]]) for p in used], pa.binary()),
                "counts": pa.array([_planes(np.ascontiguousarray(counts[:, at[p] : at[p + 1]]).ravel()) for p in used], pa.binary()),
            }
        )

    asked = dealt.groupBy("block").applyInArrow(ask, "part int, block int, keys binary, counts binary")

    def answer(key: tuple, t: pd.DataFrame) -> pd.DataFrame:
        keys = [np.cumsum(_numbers(k), dtype=np.uint64) for k in t["keys"]]
        lengths = [len(k) for k in keys]
        counts = np.concatenate([_numbers(c, np.int64).reshape(folds, -1) for c in t["counts"]], axis=1)
        all_ = np.concatenate(keys)
        order = np.argsort(all_, kind="stable")
        first = np.concatenate([[True], np.diff(all_[order]) != 0])
        sums = np.add.reduceat(counts[:, order], np.flatnonzero(first), axis=1)
        spot = np.empty(len(all_), np.int64)
        spot[order] = np.cumsum(first) - 1
        out, at = [], 0
        for b, n in zip(t["block"], lengths):
            out.append(("answer", b, key[0], _planes(np.ascontiguousarray(sums[:, spot[at : at + n]]).ravel()), 0, 0.0, 0.0))
            at += n
        words = sums[:, (all_[order][first] & np.uint64(1)) == 1]
        out.append(("v", 0, 0, None, 0, float((words.sum(0) > 0).sum()), 0.0))
        for f in range(folds):
            out.append(("n", 0, 0, None, f, float(words[f].sum()), 0.0))
            left, here = words.sum(0) - words[f], words[f]
            some = here > 0
            bins = np.floor(np.log(np.maximum(left[some], 1e-9)) * BIN).astype(np.int64)
            for b in np.unique(bins):
                w = bins == b
                out.append(("u", 0, int(b), None, f, float(here[some][w].sum()), float((here[some] * left[some])[w].sum())))
        return pd.DataFrame(out, columns=["kind", "block", "part", "counts", "a", "x", "y"])

    answers = materialize(asked.groupBy("part").applyInPandas(answer, "kind string, block int, part int, counts binary, a int, x double, y double"), "lm-answers")
    release(spark)
    stats = answers.where("kind != 'answer'").groupBy("kind", "a", "part").agg(F.sum("x").alias("x"), F.sum("y").alias("y")).toPandas()  # bounded by bins and folds
    totals = Totals(stats, folds)

    def weigh(docs: pa.Table, told: pa.Table) -> pa.Table:
        block = _block(docs)
        fold = _fold(block.crc, held, modulus, folds)
        order = np.argsort(told.column("part").to_numpy())
        answered = told.column("counts").to_pylist()
        counts = np.concatenate([_numbers(answered[i], np.int64).reshape(folds, -1) for i in order], axis=1)
        pairs, spot = np.unique(block.pairs, return_inverse=True)
        keys = np.concatenate([block.word_keys, block.pair_keys(pairs)])
        by_key = np.empty_like(counts)
        by_key[:, np.argsort(keys, kind="stable")] = counts
        of_word, of_pair = by_key[:, : block.n_words], by_key[:, block.n_words :]
        word, context, pair = of_word[:, block.tokens], of_word[:, block.before], of_pair[:, spot]
        all_word, all_context, all_pair = word.sum(0), context.sum(0), pair.sum(0)
        lower = totals.lower(all_word, totals.n)
        ratio = _ratios(all_pair, all_context, lower).astype(np.float32)
        bucket = _bucket(all_context)
        add = lambda x: np.add.reduceat(x, block.starts) if len(block.starts) else x[:0]
        ends = block.starts + block.lengths
        rows = pa.table(
            {
                "kind": pa.array(["doc"] * len(fold)),
                "doc_id": docs.column("doc_id").combine_chunks(),
                "held_out": pa.array(fold < 0),
                "n_tokens": pa.array(block.lengths),
                "n_known": pa.array(add((all_word > 0).astype(np.int64))),
                "base": pa.array(add(np.log10(all_word + 1.0))),
                "lower": pa.array(add(np.log10(lower))),
                "ratios": pa.array([ratio[a:b].tobytes() for a, b in zip(block.starts, ends)], pa.binary()),
                "buckets": pa.array([bucket[a:b].tobytes() for a, b in zip(block.starts, ends)], pa.binary()),
            }
        )
        of_token = np.repeat(fold, block.lengths)
        bins = []
        for f in range(folds):
            mine = of_token == f
            c, w, p = (x[mine] - y[f][mine] for x, y in ((all_context, context), (all_word, word), (all_pair, pair)))
            r = _ratios(p, c, totals.lower(w, totals.n - totals.per_fold[f]))
            code = _bucket(c).astype(np.int64) * 100_000 + np.where(r > 0, np.floor(np.log(np.maximum(r, 1e-300)) * BIN) + 50_000, 0).astype(np.int64)
            u, at = np.unique(code, return_inverse=True)
            n = len(u)
            bins.append(pa.table({"kind": pa.array(["bin"] * n), "doc_id": pa.nulls(n, rows.schema.field("doc_id").type), "held_out": pa.array(np.zeros(n, bool)), "n_tokens": pa.array(u), "n_known": pa.array(np.zeros(n, np.int64)), "base": pa.array(np.bincount(at, minlength=n).astype(float)), "lower": pa.array(np.bincount(at, r, n)), "ratios": pa.nulls(n, pa.binary()), "buckets": pa.nulls(n, pa.binary())}))
        return pa.concat_tables([rows, *bins]).combine_chunks()

    shape = f"kind string, doc_id {id_kind}, held_out boolean, n_tokens long, n_known long, base double, lower double, ratios binary, buckets binary"
    told = answers.where("kind = 'answer'").select("block", "part", "counts")
    weighed = materialize(dealt.groupBy("block").cogroup(told.groupBy("block")).applyInArrow(weigh, shape), "lm-weighed")
    release(spark)
    hist = weighed.where("kind = 'bin'").groupBy("n_tokens").agg(F.sum("base").alias("n"), F.sum("lower").alias("r")).toPandas()  # bounded by buckets and bins
    weights = np.zeros(256)
    of = hist["n_tokens"].to_numpy() // 100_000
    for b in np.unique(of):
        mine = hist[of == b]
        weights[b] = em(mine["n"].to_numpy(), (mine["r"] / mine["n"]).to_numpy()) if b else 0.0
    slots = float(totals.n + totals.v + 1)

    def finish(batches):
        for b in batches:
            gained = []
            for r, k in zip(b.column("ratios").to_pylist(), b.column("buckets").to_pylist()):
                l = weights[np.frombuffer(k, np.uint8)]  # noqa: E741
                gained.append(float(np.log10(1 - l + l * np.frombuffer(r, np.float32)).sum()))
            n = b.column("n_tokens").to_numpy()
            base = b.column("base").to_numpy() - n * np.log10(slots)
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), b.column("held_out"), b.column("n_tokens"), b.column("n_known"), pa.array(np.full(len(n), int(totals.n))), pa.array(base), pa.array(b.column("lower").to_numpy() + gained)],
                ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
            )

    return weighed.where("kind = 'doc'").drop("kind").mapInArrow(finish, f"doc_id {id_kind}, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
