"""Regression trees and forests of many targets and candidates, grown together.

Features are binned once, a byte each; one scan a level adds up, for nodes of all trees, rows and targets by feature and
bin. Of the two sides of a split only the one of fewer rows is read, the other is the node less that side; two features
are counted together by the pair of their bins. The driver gets these sums, which do not grow with the rows, and chooses
the splits. Parameters are those of Spark ML's trees: 32 bins, least variance, and for forests a Poisson(1) number of
copies of a row and a third of the features at each node. A candidate of fewer trees or less depth is the start of a
larger forest and the top of its trees: a search grows only the largest.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pantry.operators.regress import matrix, tree_predictions

BINS = 32
CHUNK = 1 << 16
#: Sums of the trees of a scan, and their nodes, in a worker.
STATE_MB = 128
_POISSON = np.repeat(np.arange(9), np.diff(np.round(np.cumsum([0, *np.exp(-1) / np.cumprod([1, 1, *range(2, 8)])]) * 65536).astype(int), append=65536)).astype(np.float64)


@dataclass
class Tree:
    """A tree for one target; ``number`` is its place in a forest, -1 for a tree of all rows and features."""

    target: str
    depth: int
    number: int = -1
    without: tuple[int, ...] = ()
    seed: int = 1
    nodes: list[list] = field(default_factory=list)  # as regress.tree_nodes, thresholds are bins
    open: list[int] = field(default_factory=list)
    read: list[int] = field(default_factory=list)  # nodes of the open level whose rows a scan counts
    parents: list[tuple[int, int]] = field(default_factory=list)  # of each of these: the parent's place in the level before, and its sibling

    def features(self, dim: int) -> np.ndarray:
        """The features that each open node may split by."""
        if self.number < 0:
            return np.tile(np.arange(dim), (len(self.open), 1))
        take = -(-dim // 3)
        return np.stack([np.sort(np.random.default_rng((self.seed, self.number, at)).permutation(dim)[:take]) for at in self.open])

    def place(self, bins: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """The number of each of these rows' node among those to read, -1 for rows in others."""
        _, _, feature, threshold, left, _ = (np.array(c) for c in zip(*self.nodes))
        leaf = feature < 0
        feature, threshold = np.where(leaf, 0, feature), np.where(leaf, BINS, threshold).astype(np.uint8)
        at, flat, begin = np.zeros(len(rows), np.int64), bins.ravel(), rows * bins.shape[1]
        for _ in range(self.nodes[self.read[0]][0]):
            at = left.take(at) + (flat.take(begin + feature.take(at)) > threshold.take(at))  # a leaf is its own left, the right follows the left
        slot = np.full(len(self.nodes), -1)
        slot[self.read] = np.arange(len(self.read))
        return slot.take(at)

    def grown(self, splits: np.ndarray) -> None:
        """Take the level's splits: (rows, mean, feature or -1, bin, mean and rows of the left, of the right) an open node."""
        level, self.open, was = self.nodes[self.open[0]][0] + 1, [], self.open
        self.read, self.parents = [], []
        for place, (at, (_, mean, feature, at_bin, *sides)) in enumerate(zip(was, splits)):
            self.nodes[at][1] = float(mean)
            if feature >= 0:
                first = len(self.nodes)
                self.nodes[at][2:] = [int(feature), float(at_bin), first, first + 1]
                for k, (value, n) in enumerate((sides[:2], sides[2:])):
                    self.nodes.append([level, float(value), -1, 0.0, first + k, first + k])
                    if level < self.depth and n > 1:
                        self.open.append(first + k)
                if self.open and self.open[-1] >= first:
                    less = int(sides[3] < sides[1])
                    self.read.append(first + less)
                    self.parents.append((place, first + 1 - less))

    def completed(self, got: np.ndarray, before: np.ndarray | None) -> np.ndarray:
        """The sums of the open nodes from those of the nodes that were read, and those of the level before."""
        if before is None:
            return got
        known = {}
        for i, (at, (parent, sibling)) in enumerate(zip(self.read, self.parents)):
            known[at], known[sibling] = got[:, i], before[:, parent] - got[:, i]
        return np.stack([known[at] for at in self.open], 1)


@dataclass
class Forest:
    """The mean of its trees on raw features."""

    trees: list[list]
    depth: int

    def predict(self, x: np.ndarray) -> np.ndarray:
        return sum(tree_predictions(t, x, (self.depth,))[self.depth] for t in self.trees) / len(self.trees)


def edges(df: DataFrame, x: str, dim: int) -> np.ndarray:
    """Inner ends of the bins of each feature (dim x 31), quantiles of all rows."""
    at = F.array(*(F.lit((k + 1) / BINS) for k in range(BINS - 1)))
    r = df.where(F.col(x).isNotNull()).agg(*(F.percentile_approx(F.get(x, F.lit(i)), at, 2000) for i in range(dim))).first()
    return np.array([v if v is not None else [0.0] * (BINS - 1) for v in r], float)


def binned(df: DataFrame, x: str, ends: np.ndarray, targets) -> DataFrame:
    """(_row, fold, _b, targets): the number of each feature's bin as a byte. To be written once: row numbers are drawn in it."""
    sent = df.sparkSession.sparkContext.broadcast(ends)

    def run(parts):
        for t in parts:
            if t.num_rows:
                m = matrix(t.column("_b")).astype(float)
                b = np.empty(m.shape, np.uint8)
                for j, (e, v) in enumerate(zip(sent.value, m.T)):
                    b[:, j] = np.searchsorted(e, v)
                cells = pa.FixedSizeBinaryArray.from_buffers(pa.binary(b.shape[1]), len(b), [None, pa.py_buffer(b)]).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([cells if c == "_b" else t.column(c) for c in t.schema.names], t.schema.names)

    rows = df.where(F.col(x).isNotNull()).select(F.monotonically_increasing_id().alias("_row"), F.col("fold").cast("int").alias("fold"), F.col(x).alias("_b"), *(F.col(t).cast("double").alias(t) for t in targets))
    return rows.mapInArrow(run, "_row long, fold int, _b binary, " + ", ".join(f"{t} double" for t in targets))


def copies(rows: np.ndarray, number: int, seed: int) -> np.ndarray:
    """How often a forest's tree takes each row: Poisson(1) from a hash, the same in every scan."""
    with np.errstate(over="ignore"):
        h = rows.astype(np.uint64) + np.uint64((seed * 1_000_003 + number + 1) * 0x9E3779B97F4A7C15 % (1 << 64))
        for shift, by in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            h = (h ^ (h >> np.uint64(shift))) * np.uint64(by)
        h ^= h >> np.uint64(31)
    return _POISSON[h >> np.uint64(48)]


def _matrix(t: pd.DataFrame) -> np.ndarray:
    return np.frombuffer(b"".join(t["_b"]), np.uint8).reshape(len(t), -1)


def _chunks(parts) -> Iterator[pd.DataFrame]:
    held: list = []
    for t in parts:
        held.append(t)
        if sum(map(len, held)) >= CHUNK:
            yield pd.concat(held)
            held = []
    if sum(map(len, held)):
        yield pd.concat(held)


def paired(bins: np.ndarray) -> np.ndarray:
    """(pairs of neighbouring features, rows): both bins in one number; an odd last feature is paired with nothing."""
    even = bins if bins.shape[1] % 2 == 0 else np.hstack([bins, np.zeros((len(bins), 1), np.uint8)])
    return np.ascontiguousarray((even[:, ::2].astype(np.uint16) * BINS + even[:, 1::2]).T)


def sums(tree: Tree, bins: np.ndarray, pairs: np.ndarray, mine: np.ndarray, y: np.ndarray, weight: np.ndarray | None) -> np.ndarray:
    """(2, nodes to read, features, bins): rows and the target's sum of the rows that are ``mine``."""
    rows = np.flatnonzero(mine & np.isfinite(y))
    slot = tree.place(bins, rows)
    if (slot < 0).any():
        rows, slot = rows[slot >= 0], slot[slot >= 0]
    w = None if weight is None else weight[rows]
    wy = y[rows] if weight is None else w * y[rows]
    k, cell = len(tree.read), BINS * BINS
    first, out = slot * cell, np.empty((2, k, 2 * len(pairs), BINS))
    for j, codes in enumerate(pairs):
        at = first + codes.take(rows)
        for i, v in enumerate((w, wy)):
            both = np.bincount(at, v, k * cell).reshape(k, BINS, BINS)
            out[i, :, 2 * j], out[i, :, 2 * j + 1] = both.sum(2), both.sum(1)
    return out[:, :, : bins.shape[1]]


def best_splits(hist: np.ndarray, features: np.ndarray) -> np.ndarray:
    """What ``Tree.grown`` takes, from a tree's sums: the split of most variance, the first of those equal but for rounding."""
    hist = hist[:, np.arange(len(features))[:, None], features]
    n, s = hist[0].cumsum(2), hist[1].cumsum(2)
    all_n, all_s = n[:, :1, -1:], s[:, :1, -1:]
    with np.errstate(divide="ignore", invalid="ignore"):
        gain = s**2 / n + (all_s - s) ** 2 / (all_n - n) - all_s**2 / all_n
        gain = np.where((n > 0) & (n < all_n), gain, -1.0).reshape(len(n), -1)
        at = (gain >= gain.max(1, keepdims=True) - 1e-12 * (all_s**2 / np.maximum(all_n, 1))[:, :, 0]).argmax(1)
        i, (f, b) = np.arange(len(n)), np.unravel_index(at, n.shape[1:])
        nl, sl, n0, s0 = n[i, f, b], s[i, f, b], all_n[:, 0, 0], all_s[:, 0, 0]
        ok = gain[i, at] > 1e-10 * np.abs(s0 * s0 / np.maximum(n0, 1)) + 1e-12
        mean = np.where(n0 > 0, s0 / n0, 0.0)
        return np.stack([n0, mean, np.where(ok, features[i, f], -1), b, sl / nl, nl, (s0 - sl) / (n0 - nl), n0 - nl], 1)


def _groups(trees: list[Tree], dim: int) -> Iterator[list[Tree]]:
    """Trees whose sums fit a worker together."""
    some, used = [], 0
    for t in trees:
        need = len(t.read) * dim * BINS * 16
        if some and used + need > STATE_MB << 20:
            yield some
            some, used = [], 0
        some, used = [*some, t], used + need
    if some:
        yield some


def grow(df: DataFrame, trees: list[Tree], dim: int) -> None:
    """Grow all trees on a ``binned`` table, a scan a level and group of trees."""
    context = df.sparkSession.sparkContext
    never = set.intersection(*(set(t.without) for t in trees))
    df = df.where(~F.col("fold").isin(*never)) if never else df
    df = df.coalesce(2 * context.defaultParallelism)  # each task gives the sums of a scan's trees once
    before: dict = {}  # the sums of the level above, by tree
    for t in trees:
        t.nodes, t.open, t.read = [[0, 0.0, -1, 0.0, 0, 0]], [0], [0]
    while some := [t for t in trees if t.open]:
        found = {}
        for group in _groups(sorted(some, key=lambda t: t.number), dim):
            sent = context.broadcast(group)

            def add(parts):
                out: dict = {}
                for t in _chunks(parts):
                    bins, fold, row = _matrix(t), t["fold"].to_numpy(), t["_row"].to_numpy()
                    pairs, last, weight, mine = paired(bins), None, None, None
                    for i, tree in enumerate(sent.value):  # noqa: B023
                        if (key := (tree.number, tree.seed, tree.without)) != last:  # trees of a number follow each other
                            last, weight, mine = key, None if tree.number < 0 else copies(row, *key[:2]), ~np.isin(fold, tree.without)
                            mine = mine if weight is None else mine & (weight > 0)
                        out[i] = out.get(i, 0) + sums(tree, bins, pairs, mine, t[tree.target].to_numpy(float), weight)
                for i, v in out.items():
                    yield pd.DataFrame({"tree": [i], "sums": [v.tobytes()]})

            def together(t: pd.DataFrame) -> pd.DataFrame:
                return pd.DataFrame({"tree": t["tree"][:1], "sums": [sum(np.frombuffer(b) for b in t["sums"]).tobytes()]})

            shape = "tree int, sums binary"
            for r in df.mapInPandas(add, shape).groupBy("tree").applyInPandas(together, shape).toLocalIterator():  # a number a node, feature and bin
                t = group[r["tree"]]
                found[id(t)] = t.completed(np.frombuffer(bytes(r["sums"])).reshape(2, -1, dim, BINS), before.get(id(t)))
            sent.unpersist()
        for t in some:
            if id(t) in found:
                t.grown(best_splits(found[id(t)], t.features(dim)))
            else:
                t.open = []
        before = found


def planned(targets, candidates: list[tuple[int, int]], without: tuple[int, ...] = (), seed: int = 1) -> list[Tree]:
    """The trees that hold all (trees, depth) of forests; (0, depth) is a single tree."""
    out = []
    for t in targets:
        for i in range(-1, max(n for n, _ in candidates)):
            depths = [d for n, d in candidates if (n > i if i >= 0 else n == 0)]
            if depths:
                out.append(Tree(t, max(depths), i, without, seed))
    return out


def of_candidate(trees: list[Tree], target: str, n: int) -> list[int]:
    """The places of a candidate's trees."""
    return [i for i, t in enumerate(trees) if t.target == target and (0 <= t.number < n if n else t.number < 0)]


def validated(df: DataFrame, trees: list[Tree], targets, candidates: list[tuple[int, int]], valid: int) -> list[tuple[int, int, str, float]]:
    """(trees, depth, target, RMSE on the validation fold) of candidates, all in one scan of a ``binned`` table."""
    sent = df.sparkSession.sparkContext.broadcast([t.nodes for t in trees])
    cases = [(n, d, t, of_candidate(trees, t, n)) for t in targets for n, d in candidates]
    depths = [sorted({d for _, d, _, own in cases if i in own}) for i in range(len(trees))]

    def measure(parts):
        out = np.zeros((len(cases), 2))
        for t in _chunks(parts):
            bins = _matrix(t)
            hats = [tree_predictions(nodes, bins, tuple(d)) if d else {} for nodes, d in zip(sent.value, depths)]
            for k, (_, d, target, own) in enumerate(cases):
                e = sum(hats[i][d] for i in own) / len(own) - t[target].to_numpy(float)
                e = e[np.isfinite(e)]
                out[k] += (e**2).sum(), len(e)
        yield pd.DataFrame({"k": np.arange(len(cases), dtype=np.int32), "squared": out[:, 0], "n": out[:, 1]})

    each = df.where(F.col("fold") == valid).mapInPandas(measure, "k int, squared double, n double")
    error = {r["k"]: r["e"] for r in each.groupBy("k").agg(F.sqrt(F.try_divide(F.sum("squared"), F.sum("n"))).alias("e")).collect()}
    return [(n, d, t, float("nan") if error.get(k) is None else float(error[k])) for k, (n, d, t, _) in enumerate(cases)]


def forest(trees: list[Tree], target: str, n: int, depth: int, ends: np.ndarray) -> Forest:
    """A candidate's trees with thresholds of the features instead of bins."""
    raw = lambda nodes: [(d, v, f, float(ends[f][int(b)]) if f >= 0 else 0.0, left, right) for d, v, f, b, left, right in nodes]
    return Forest([raw(trees[i].nodes) for i in of_candidate(trees, target, n)], depth)
