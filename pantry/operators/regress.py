"""Regressions from sufficient statistics, trees and forests from Spark ML, a small network; search and folds.

One scan gives, for each fold, the sums of products of (1, x, targets). Every linear model, penalty,
target and fold is then solved on the driver from matrices of (d + 6)^2 numbers a fold, and a fold's
training statistics are the total less its own.

Objectives: ridge |y - Xb|^2 / n + l |b|^2; lasso and elastic net |y - Xb|^2 / (2 n) + l (a |b|_1 +
(1 - a) |b|^2 / 2). The intercept is free of penalty.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import product

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pantry.functions.bands import hit
from pantry.operators.nutrients import TARGETS
from pantry.session import materialize

GRID = {"lambda": tuple(10.0**e for e in range(-4, 3)), "alpha": (0.1, 0.5, 0.9), "depth": (3, 5, 8)}
REGRESSORS = ("linear", "ridge", "lasso", "enet", "tree", "forest", "mlp")


def gram(df: DataFrame, x: str, dim: int, targets=TARGETS, by: str = "fold") -> DataFrame:
    """(by, stats): the flattened matrix of sums of products of (1, x, targets)."""
    side = 1 + dim + len(targets)
    kind = dict(df.dtypes)[by]
    shape = f"{by} {kind}, stats array<double>"

    def partial(parts):
        sums: dict = {}
        for t in parts:
            m = np.hstack([np.ones((len(t), 1)), np.stack(t[x].to_numpy()) if len(t) else np.zeros((0, dim)), t[list(targets)].to_numpy(float)])
            for g in t[by].unique():
                mine = m[(t[by] == g).to_numpy()]
                sums[g] = sums.get(g, 0) + mine.T @ mine
        if sums:
            yield pd.DataFrame({by: list(sums), "stats": [s.ravel() for s in sums.values()]})

    def total(t: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({by: t[by][:1], "stats": [np.sum(np.stack(t["stats"].to_numpy()), axis=0)]})

    assert side > 1
    return df.where(F.col(x).isNotNull()).select(by, x, *targets).mapInPandas(partial, shape).groupBy(by).applyInPandas(total, shape)


@dataclass
class Stats:
    """Sums of products of (1, x, targets)."""

    m: np.ndarray
    dim: int

    @property
    def n(self) -> float:
        return self.m[0, 0]

    def centred(self, target: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
        """X'X / n and X'y / n around the means, the means of x and of y."""
        d, t = self.dim, 1 + self.dim + target
        mx, my = self.m[0, 1 : d + 1] / self.n, self.m[0, t] / self.n
        xx = self.m[1 : d + 1, 1 : d + 1] / self.n - np.outer(mx, mx)
        return xx, self.m[1 : d + 1, t] / self.n - mx * my, mx, my

    def sse(self, target: int, b0: float, b: np.ndarray) -> float:
        """Squared error of a linear model on these rows, without reading them."""
        t = 1 + self.dim + target
        c = np.zeros(len(self.m))
        c[0], c[1 : self.dim + 1], c[t] = -b0, -b, 1
        return float(c @ self.m @ c)


def collect_stats(df: DataFrame, dim: int, by: str = "fold") -> dict[int, Stats]:
    """The folds' statistics on the driver: one matrix a fold."""
    out = {}
    for r in df.collect():
        side = int(round(len(r["stats"]) ** 0.5))
        out[r[by]] = Stats(np.array(r["stats"]).reshape(side, side), dim)
    return out


def total(stats: dict[int, Stats], without: tuple = ()) -> Stats:
    some = next(iter(stats.values()))
    return Stats(sum((s.m for f, s in stats.items() if f not in without), np.zeros_like(some.m)), some.dim)


def fit_ridge(s: Stats, target: int, lam: float) -> tuple[float, np.ndarray]:
    xx, xy, mx, my = s.centred(target)
    b = np.linalg.pinv(xx + lam * np.eye(s.dim), hermitian=True) @ xy
    return float(my - mx @ b), b


def fit_linear(s: Stats, target: int) -> tuple[float, np.ndarray]:
    return fit_ridge(s, target, 0.0)


def fit_enet(s: Stats, target: int, lam: float, alpha: float, sweeps: int = 500, tol: float = 1e-8) -> tuple[float, np.ndarray]:
    """Cyclic coordinate descent on the centred products."""
    xx, xy, mx, my = s.centred(target)
    b, left = np.zeros(s.dim), xy.copy()  # left = xy - xx b
    down = np.diag(xx) + lam * (1 - alpha)
    for _ in range(sweeps):
        moved = 0.0
        for j in range(s.dim):
            rho = left[j] + xx[j, j] * b[j]
            new = float(np.sign(rho) * max(abs(rho) - lam * alpha, 0.0) / down[j]) if down[j] > 0 else 0.0
            if new != b[j]:
                left -= xx[j] * (new - b[j])
                moved, b[j] = max(moved, abs(new - b[j])), new
        if moved < tol:
            break
    return float(my - mx @ b), b


def fit_enets(s: Stats, problems: list[tuple[int, float, float]], sweeps: int = 500, tol: float = 1e-8) -> list[tuple[float, np.ndarray]]:
    """``fit_enet`` of many (target, lambda, alpha) on the same rows, side by side; each stops when it has settled."""
    at = [s.centred(t) for t in sorted({t for t, _, _ in problems})]
    xx, mx = at[0][0], at[0][2]
    xy, my = ({t: c[i] for t, c in zip(sorted({t for t, _, _ in problems}), at)} for i in (1, 3))
    left = np.stack([xy[t] for t, _, _ in problems])
    out, b, live = np.zeros_like(left), np.zeros_like(left), np.arange(len(problems))
    lam, alpha = (np.array(v, float) for v in zip(*(p[1:] for p in problems)))
    for _ in range(sweeps):
        moved = np.zeros(len(live))
        for j in range(s.dim):
            down = xx[j, j] + lam * (1 - alpha)
            rho = left[:, j] + xx[j, j] * b[:, j]
            new = np.where(down > 0, np.sign(rho) * np.maximum(np.abs(rho) - lam * alpha, 0.0) / np.where(down > 0, down, 1.0), 0.0)
            step = new - b[:, j]
            left -= step[:, None] * xx[j]
            np.maximum(moved, np.abs(step), out=moved)
            b[:, j] = new
        out[live] = b
        on = moved >= tol
        if not on.any():
            break
        if not on.all():
            left, b, live, lam, alpha = left[on], b[on], live[on], lam[on], alpha[on]
    return [(float(my[t] - mx @ v), v) for (t, _, _), v in zip(problems, out)]


def fit_lasso(s: Stats, target: int, lam: float) -> tuple[float, np.ndarray]:
    return fit_enet(s, target, lam, 1.0)


def candidates(model: str) -> list[dict[str, float]]:
    if model == "linear":
        return [{}]
    if model in ("ridge", "lasso"):
        return [{"lam": v} for v in GRID["lambda"]]
    return [{"lam": v, "alpha": a} for v, a in product(GRID["lambda"], GRID["alpha"])]


FIT = {"linear": fit_linear, "ridge": fit_ridge, "lasso": fit_lasso, "enet": fit_enet}


def grid_search(stats: dict[int, Stats], model: str, target: int, without: tuple = ()) -> dict[str, float]:
    """The candidate with the least validation error over the folds, all from statistics; ``without`` for nesting."""
    used = [f for f in stats if f not in without]
    error = lambda c: sum(stats[f].sse(target, *FIT[model](total(stats, (*without, f)), target, **c)) for f in used)
    return min(candidates(model), key=error)


def fit_all(s: Stats, model: str, cases: list[tuple[int, dict]]) -> list[tuple[float, np.ndarray]]:
    """The models of (target, candidate) pairs on the same rows."""
    if model in ("lasso", "enet") and cases:
        return fit_enets(s, [(t, c["lam"], c.get("alpha", 1.0)) for t, c in cases])
    return [FIT[model](s, t, **c) for t, c in cases]


def grid_searches(stats: dict[int, Stats], model: str, targets: list[int], without: tuple = ()) -> list[dict[str, float]]:
    """``grid_search`` of several targets: candidates of all of them are fitted together."""
    some = candidates(model)
    cases = [(t, c) for t in targets for c in some]
    error = np.zeros(len(cases))
    for f in stats:
        if f not in without:
            fits = fit_all(total(stats, (*without, f)), model, cases)
            error += [stats[f].sse(t, *m) for (t, _), m in zip(cases, fits)]
    return [some[int(k)] for k in error.reshape(len(targets), len(some)).argmin(1)]


def random_candidates(space: dict[str, tuple], n: int, seed: int) -> list[dict]:
    """``n`` different points of the cross product, the same for a seed."""
    every = [dict(zip(space, p)) for p in product(*space.values())]
    picked = np.random.default_rng(seed).permutation(len(every))[:n]
    return [every[i] for i in sorted(picked)]


def cross_predict(df: DataFrame, x: str, models: dict[int, dict[str, tuple[float, np.ndarray]]], by: str = "fold") -> DataFrame:
    """Add a prediction a target: each row by the model that did not see its fold. Coefficients are literals' array."""
    spark = df.sparkSession
    rows = [(f, [float(b0) for b0, _ in m.values()], [[float(v) for v in b] for _, b in m.values()]) for f, m in models.items()]
    names = list(next(iter(models.values())))
    coef = spark.createDataFrame(rows, f"{by} int, _b0 array<double>, _b array<array<double>>")
    out = df.join(F.broadcast(coef), by)  # one row a fold
    for i, t in enumerate(names):
        z = F.zip_with(F.col(x), F.get(F.col("_b"), F.lit(i)), lambda a, b: a * b)
        out = out.withColumn(f"hat_{t}", F.aggregate(z, F.get(F.col("_b0"), F.lit(i)), lambda a, v: a + v))
    return out.drop("_b0", "_b")


def average_accuracy(df: DataFrame, targets=TARGETS, prefix: str = "hat_", by: tuple[str, ...] = (), scale: float = 1.0) -> DataFrame:
    """(by, target, accuracy): the hit rate in percent, averaged over the folds."""
    hits = df.groupBy(*by, "fold").agg(*(F.avg(100 * hit(t, F.col(t), F.col(prefix + t), scale)).alias(t) for t in targets))
    each = hits.select(*by, "fold", F.explode(F.array(*(F.struct(F.lit(t).alias("target"), F.col(t).alias("a")) for t in targets))).alias("_e"))
    return each.select(*by, "fold", "_e.*").groupBy(*by, "target").agg(F.avg("a").alias("accuracy"))


def with_constant(df: DataFrame, how: str, targets=TARGETS, by: tuple[str, ...] = (), exact: bool = False) -> DataFrame:
    """Add the mean or median of the training folds as the prediction of every target; medians are exact or sketches."""
    if how == "mean":
        sums = df.groupBy(*by, "fold").agg(F.count("*").alias("_n"), *(F.sum(t).alias(f"_{t}") for t in targets))
        names = ["_n", *(f"_{t}" for t in targets)]
        whole = sums.groupBy(*by).agg(*(F.sum(n).alias(f"_all{n}") for n in names)) if by else sums.agg(*(F.sum(n).alias(f"_all{n}") for n in names))
        joined = sums.join(whole, list(by)) if by else sums.crossJoin(whole)
        guess = joined.select(*by, "fold", *(((F.col(f"_all_{t}") - F.col(f"_{t}")) / (F.col("_all_n") - F.col("_n"))).alias(f"hat_{t}") for t in targets))
    elif exact:
        df = materialize(df, "medians")
        guess = left_out_medians(df, targets, by)
    else:
        # a median a fold left out, all by filters of one aggregation: rows are not copied
        folds = [r[0] for r in df.select("fold").distinct().collect()]
        middle = lambda t: F.percentile_approx(t, 0.5, 10000).cast("double")
        cut = [F.struct(F.lit(k).alias("fold"), *(middle(F.when(F.col("fold") != k, F.col(t))).alias(f"hat_{t}") for t in targets)) for k in folds]
        guess = (df.groupBy(*by).agg(F.array(*cut).alias("_a")).select(*by, F.explode("_a").alias("_g")) if by else df.agg(F.array(*cut).alias("_a")).select(F.explode("_a").alias("_g"))).select(*by, "_g.*")
    return df.join(F.broadcast(guess), [*by, "fold"])


def left_out_medians(df: DataFrame, targets=TARGETS, by: tuple[str, ...] = (), halves: tuple[float, ...] = (2e-4, 2e-2, 0.5)) -> DataFrame:
    """(by, fold, hat_target): the exact median of the other folds, without holding a group's values.

    Sketches a little below and above the middle enclose it; one scan counts what lies below and keeps the few values
    between, whose order decides. Where a sketch did not enclose it the next width is taken, the last from least to largest.
    """
    spark = df.sparkSession
    folds = sorted(r[0] for r in df.select("fold").distinct().collect())
    cases = [(k, t) for k in folds for t in targets]
    if not cases:
        return spark.createDataFrame([], ", ".join([*(f"{c} {dict(df.dtypes)[c]}" for c in by), f"fold {dict(df.dtypes)['fold']}", *(f"hat_{t} double" for t in targets)]))
    own = [F.when(F.col("fold") != k, F.col(t).cast("double")) for k, t in cases]
    for half in halves:
        edge = lambda c: F.array(F.min(c), F.max(c)) if half >= 0.5 else F.percentile_approx(c, F.array(F.lit(0.5 - half), F.lit(0.5 + half)), 10_000)  # noqa: B023, E731
        edges = df.groupBy(*by).agg(*(edge(c).alias(f"_e{i}") for i, c in enumerate(own)))
        edges = F.broadcast(spark.createDataFrame(edges.collect(), edges.schema))  # one row a group
        met = df.join(edges, list(by)) if by else df.crossJoin(edges)
        low, high = ([F.get(f"_e{i}", F.lit(j)) for i in range(len(own))] for j in (0, 1))
        sums = [F.struct(F.lit(i).alias("case"), F.count(c).alias("n"), F.count(F.when(c < low[i], 1)).alias("below")) for i, c in enumerate(own)]
        sums = met.groupBy(*by).agg(F.array(*sums).alias("_s")).select(*by, F.explode("_s").alias("_s")).select(*by, "_s.*")
        between = F.filter(F.array(*(F.struct(F.lit(i).alias("case"), F.when((c >= low[i]) & (c <= high[i]), c).alias("v")) for i, c in enumerate(own))), lambda x: x["v"].isNotNull())
        values = met.select(*by, F.explode(between).alias("_v")).groupBy(*by, "_v.case", "_v.v").agg(F.count("*").alias("k"))
        upto = F.sum("k").over(Window.partitionBy(*by, "case").orderBy("v"))
        at = lambda r: F.min(F.when(F.col("below") + F.col("upto") > r, F.col("v")))
        found = values.withColumn("upto", upto).join(sums, [*by, "case"]).groupBy(*by, "case", "n").agg(at(F.floor((F.col("n") - 1) / 2)).alias("a"), at(F.floor(F.col("n") / 2)).alias("b"), F.min("below").alias("below"))
        found = found.withColumn("sure", F.col("b").isNotNull() & (F.col("below") <= F.floor((F.col("n") - 1) / 2)))
        found = materialize(found.select(*by, "case", (0.5 * F.col("a") + 0.5 * F.col("b")).alias("m"), "sure"), "middles")  # a row a group, fold and target
        if half == halves[-1] or not found.where("not sure").count():
            break
    names = spark.createDataFrame([(i, k, t) for i, (k, t) in enumerate(cases)], f"case int, fold {dict(df.dtypes)['fold']}, target string")
    return found.join(F.broadcast(names), "case").groupBy(*by, "fold").agg(*(F.max(F.when(F.col("target") == t, F.col("m"))).alias(f"hat_{t}") for t in targets))


def errors(df: DataFrame, targets=TARGETS) -> DataFrame:
    """(target, rmse, mae, r2)."""
    rows = F.explode(F.array(*(F.struct(F.lit(t).alias("target"), F.col(t).alias("y"), F.col(f"hat_{t}").alias("p")) for t in targets)))
    e = df.select(rows.alias("_r")).select("_r.*")
    sq = (F.col("y") - F.col("p")) * (F.col("y") - F.col("p"))
    return e.groupBy("target").agg(F.sqrt(F.avg(sq)).alias("rmse"), F.avg(F.abs(F.col("y") - F.col("p"))).alias("mae"), (1 - F.sum(sq) / F.var_pop("y") / F.count("*")).alias("r2"))


def fit_tree(df: DataFrame, x: str, target: str, depth: int = 5, seed: int = 1):
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.regression import DecisionTreeRegressor

    return DecisionTreeRegressor(featuresCol="_v", labelCol=target, maxDepth=depth, seed=seed).fit(df.withColumn("_v", array_to_vector(x)))


def fit_forest(df: DataFrame, x: str, target: str, depth: int = 5, trees: int = 10, seed: int = 1):
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.regression import RandomForestRegressor

    return RandomForestRegressor(featuresCol="_v", labelCol=target, maxDepth=depth, numTrees=trees, seed=seed).fit(df.withColumn("_v", array_to_vector(x)))


def in_parallel(jobs: list, at_once: int = 4) -> list:
    """Results of functions that start Spark jobs of their own, side by side."""
    from multiprocessing.pool import ThreadPool

    with ThreadPool(at_once) as pool:
        return pool.map(lambda f: f(), jobs)


def rmse(model, df: DataFrame, x: str, target: str) -> float:
    from pyspark.ml.evaluation import RegressionEvaluator

    return RegressionEvaluator(labelCol=target).evaluate(model.transform(_as_vector(df, x)))


def tree_nodes(model) -> list[tuple]:
    """(depth, prediction, feature or -1, threshold, left, right) of each node of a fitted tree, the root first."""
    out: list = []

    def visit(node, depth: int) -> int:
        at = len(out)
        out.append(None)
        if node.numDescendants() == 0:
            out[at] = depth, node.prediction(), -1, 0.0, at, at
        else:
            out[at] = depth, node.prediction(), node.split().featureIndex(), node.split().threshold(), visit(node.leftChild(), depth + 1), visit(node.rightChild(), depth + 1)
        return at

    visit(model._call_java("rootNode"), 0)
    return out


def tree_predictions(nodes: list[tuple], x: np.ndarray, depths: tuple[int, ...]) -> dict[int, np.ndarray]:
    """The predictions of a tree cut at each depth: a greedy tree of less depth is the top of a deeper one."""
    _, value, feature, threshold, left, right = (np.array(c) for c in zip(*nodes))
    at, out, rows = np.zeros(len(x), int), {}, np.arange(len(x))
    for depth in range(max(depths) + 1):
        if depth in depths:
            out[depth] = value[at]
        inner = feature[at] >= 0
        below = np.where(x[rows, np.maximum(feature[at], 0)] <= threshold[at], left[at], right[at])
        at = np.where(inner, below, at)
    return out


def grid_search_tree(df: DataFrame, x: str, targets, depths=GRID["depth"], test: int = 0, valid: int = 1) -> list[tuple[int, str, float]]:
    """(depth, target, RMSE on the validation fold) of every depth; the test fold is not read.

    One tree a target is grown to the greatest depth, the others are its tops; one scan measures all of them.
    """
    train, held = df.where(~F.col("fold").isin(test, valid)), df.where(F.col("fold") == valid)
    trees = {t: tree_nodes(fit_tree(train, x, t, max(depths))) for t in targets}  # one at a time: each keeps its binned rows
    sent = df.sparkSession.sparkContext.broadcast(trees)

    def measure(parts):
        sums = np.zeros((len(trees), len(depths) + 1))
        for t in parts:
            if len(t):
                m = np.stack(t["_x"].to_numpy())
                for i, (name, nodes) in enumerate(sent.value.items()):
                    hats, y = tree_predictions(nodes, m, tuple(depths)), t[name].to_numpy(float)
                    sums[i] += [*(((hats[d] - y) ** 2).sum() for d in depths), len(t)]
        yield pd.DataFrame([(name, int(d), sums[i, j], int(sums[i, -1])) for i, name in enumerate(trees) for j, d in enumerate(depths)], columns=["target", "depth", "squared", "n"])

    each = held.select(F.col(x).alias("_x"), *targets).mapInPandas(measure, "target string, depth int, squared double, n long")
    found = {(r["target"], r["depth"]): r["e"] for r in each.groupBy("target", "depth").agg(F.sqrt(F.sum("squared") / F.sum("n")).alias("e")).collect()}
    return [(d, t, found[t, d]) for t in targets for d in depths]


def random_search_forest(df: DataFrame, x: str, targets, n: int, seed: int = 1, space: dict[str, tuple] | None = None, test: int = 0, valid: int = 1) -> list[tuple[int, int, str, float]]:
    """(trees, depth, target, RMSE on the validation fold) of ``n`` candidates; the test fold is not read."""
    train, held = df.where(~F.col("fold").isin(test, valid)).cache(), df.where(F.col("fold") == valid)
    some = random_candidates(space or {"trees": (5, 10, 20), "depth": (3, 5, 8)}, n, seed)
    jobs = [lambda c=c, t=t: (c["trees"], c["depth"], t, rmse(fit_forest(train, x, t, c["depth"], c["trees"]), held, x, t)) for t in targets for c in some]
    out = in_parallel(jobs)
    train.unpersist()
    return out


def _as_vector(df: DataFrame, x: str) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    return df.withColumn("_v", array_to_vector(x))


def predict_ml(model, df: DataFrame, x: str, out: str) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    return model.transform(df.withColumn("_v", array_to_vector(x))).withColumnRenamed("prediction", out).drop("_v")


@dataclass
class Linear:
    """A fitted linear model."""

    b0: float
    b: np.ndarray

    def predict(self, x: np.ndarray) -> np.ndarray:
        return x @ self.b + self.b0


@dataclass
class Network:
    """One hidden layer for one target, trained on the folds that are not in ``without``; inputs and target are scaled."""

    target: str
    hidden: int
    rate: float
    without: tuple[int, ...] = ()
    seed: int = 1
    scale: tuple | None = None
    weights: tuple[np.ndarray, ...] | None = None
    loss: float = float("nan")

    def start(self, stats: dict, targets) -> None:
        at = list(targets).index(self.target)
        s = total(stats, self.without)
        xx, _, mx, my = s.centred(at)
        t = 1 + s.dim + at
        self.scale = mx, np.sqrt(np.maximum(np.diag(xx), 1e-12)), my, float(np.sqrt(max(s.m[t, t] / s.n - my**2, 1e-12)))
        rng = np.random.default_rng(self.seed)
        self.weights = rng.normal(size=(s.dim, self.hidden)) / np.sqrt(s.dim), np.zeros(self.hidden), rng.normal(size=self.hidden) / np.sqrt(self.hidden), np.zeros(1)

    def predict(self, x: np.ndarray) -> np.ndarray:
        mx, sx, my, sy = self.scale
        a, b, c, d = self.weights
        return (np.maximum((x - mx) / sx @ a + b, 0) @ c + d) * sy + my

    def passes(self, x: np.ndarray, y: np.ndarray, n: int, batch: int, seed: int) -> tuple[list[np.ndarray], float]:
        """Weights after ``n`` passes of Adam over these rows in batches, and the squared error of the last."""
        mx, sx, my, sy = self.scale
        z, r = (x - mx) / sx, (y - my) / sy
        w = [v.copy() for v in self.weights]
        first, second = ([np.zeros_like(v) for v in w] for _ in range(2))
        rng, step, loss = np.random.default_rng(seed), 0, 0.0
        for _ in range(n):
            order, loss = rng.permutation(len(z)), 0.0
            for k in range(0, len(z), batch):
                i, step = order[k : k + batch], step + 1
                pre = z[i] @ w[0] + w[1]
                h = np.maximum(pre, 0)
                e = h @ w[2] + w[3] - r[i]
                back = np.outer(e, w[2]) * (pre > 0)
                loss += float((e**2).sum())
                for j, g in enumerate((z[i].T @ back, back.sum(0), h.T @ e, np.array([e.sum()]))):
                    g = g / len(i)
                    first[j], second[j] = 0.9 * first[j] + 0.1 * g, 0.999 * second[j] + 0.001 * g**2
                    w[j] -= self.rate * (first[j] / (1 - 0.9**step)) / (np.sqrt(second[j] / (1 - 0.999**step)) + 1e-8)
        return w, loss


def matrix(x: pa.Array) -> np.ndarray:
    """A column of lists of one length as rows, without an object a row."""
    return x.flatten().to_numpy(zero_copy_only=False).reshape(len(x), -1)


def numbers(x: pa.Array) -> np.ndarray:
    return x.to_numpy(zero_copy_only=False)


def passes_together(nets: list[Network], x: np.ndarray, ys: np.ndarray, n: int, batch: int, seed: int) -> list[tuple[list[np.ndarray], float]]:
    """What ``Network.passes`` gives for each of some networks of one size and the same training folds.

    They take the same rows in the same order, so a batch is one product with all their weights side by side. The
    arithmetic has the precision of ``x``.
    """
    g, h, d, kind = len(nets), nets[0].hidden, x.shape[1], x.dtype
    mx, sx = (np.asarray(v, kind) for v in nets[0].scale[:2])
    z = (x - mx) / sx
    r = ((ys - np.array([m.scale[2] for m in nets])) / np.array([m.scale[3] for m in nets])).astype(kind)
    w = [np.hstack([m.weights[0] for m in nets]), np.concatenate([m.weights[1] for m in nets]), np.stack([m.weights[2] for m in nets]), np.concatenate([m.weights[3] for m in nets])]
    sizes = np.cumsum([0, *(v.size for v in w)])
    p = np.concatenate([v.ravel() for v in w]).astype(kind)
    a, b, c, e0 = (p[i:j].reshape(v.shape) for v, i, j in zip(w, sizes, sizes[1:]))  # views: a step moves them
    rates = np.array([m.rate for m in nets])
    rate = np.concatenate([np.tile(np.repeat(rates, h), d), np.repeat(rates, h), np.repeat(rates, h), rates]).astype(kind)
    first, second, grad, step_by = (np.zeros_like(p) for _ in range(4))
    ga, gb, gc, ge = (grad[i:j].reshape(v.shape) for v, i, j in zip(w, sizes, sizes[1:]))
    unit, net = np.arange(g * h), np.repeat(np.arange(g), h)
    out = np.zeros((g * h, g), kind)  # the output weights of each network in a column of its own
    rng, step, loss = np.random.default_rng(seed), 0, np.zeros(g)
    for _ in range(n):
        order, loss = rng.permutation(len(z)), np.zeros(g)
        for k in range(0, len(z), batch):
            i, step = order[k : k + batch], step + 1
            zi = z.take(i, 0)
            hid = zi @ a
            hid += b
            np.maximum(hid, 0, out=hid)
            out[unit, net] = c.ravel()
            e = hid @ out
            e += e0
            e -= r.take(i, 0)
            loss += np.einsum("ij,ij->j", e, e)
            back = e @ out.T
            back *= hid > 0
            np.matmul(zi.T, back, out=ga)
            back.sum(0, out=gb)
            gc.ravel()[:] = (hid.T @ e)[unit, net]
            e.sum(0, out=ge)
            grad *= 1 / len(i)
            np.subtract(grad, first, out=step_by)
            step_by *= 0.1
            first += step_by
            grad *= grad
            grad -= second
            grad *= 0.001
            second += grad
            np.sqrt(second, out=step_by)
            step_by *= (1 - 0.999**step) ** -0.5
            step_by += 1e-8
            np.divide(first, step_by, out=step_by)
            step_by *= rate
            step_by *= 1 / (1 - 0.9**step)
            p -= step_by
    cut = lambda v, i: v[..., i * h : (i + 1) * h].astype(float)
    return [([cut(a, i), cut(b, i), c[i].astype(float), e0[i : i + 1].astype(float)], float(loss[i])) for i in range(g)]


def fit_networks(df: DataFrame, x: str, nets: list[Network], stats: dict, targets=TARGETS, rounds: int = 4, passes: int = 6, batch: int = 128, most_rows: int = 200_000) -> list[list[float]]:
    """Train all networks in the same scans; their losses a round.

    In a round every partition takes some passes over its rows (``most_rows`` at a time), and the weights are averaged
    by rows. Candidates, targets and folds are networks side by side, so a search costs no further scan. Passes are
    made in single precision, weights averaged in double.
    """
    spark, losses = df.sparkSession, [[] for _ in nets]
    for n in nets:
        n.start(stats, targets)
    slim = df.select(F.col(x).alias("_x"), "fold", *targets)
    for turn in range(rounds):
        sent = spark.sparkContext.broadcast(nets)

        def learn(parts, sent=sent, turn=turn):
            held, sums = [], {}

            def flush():
                m, fold = np.concatenate([t[0] for t in held]), np.concatenate([t[1] for t in held])
                y = {c: np.concatenate([t[2][c] for t in held]) for c in targets}
                alike: dict = {}
                for i, net in enumerate(sent.value):
                    alike.setdefault((tuple(net.without), net.hidden), []).append(i)
                for (without, _), some in alike.items():
                    mine = ~np.isin(fold, without)
                    if mine.any():
                        together = [sent.value[i] for i in some]
                        ys = np.stack([y[net.target][mine] for net in together], 1)
                        for i, (w, loss) in zip(some, passes_together(together, m[mine], ys, passes, batch, turn)):
                            flat = np.concatenate([v.ravel() for v in w]) * mine.sum()
                            old = sums.get(i, (0.0, 0.0, 0))
                            sums[i] = old[0] + flat, old[1] + loss, old[2] + int(mine.sum())

            for t in parts:
                if t.num_rows:
                    held.append((matrix(t.column("_x")).astype(np.float32), numbers(t.column("fold")), {c: numbers(t.column(c)) for c in targets}))
                if sum(len(t[1]) for t in held) >= most_rows:
                    flush()
                    held.clear()
            if held:
                flush()
            if sums:
                yield pa.RecordBatch.from_pydict({"net": pa.array(list(sums), pa.int32()), "w": [v[0].tobytes() for v in sums.values()], "loss": [v[1] for v in sums.values()], "n": [v[2] for v in sums.values()]})

        got = slim.mapInArrow(learn, "net int, w binary, loss double, n long").collect()  # the weights once a partition and network
        for i, net in enumerate(nets):
            mine = [r for r in got if r["net"] == i]
            n = sum(r["n"] for r in mine)
            if n:
                flat, at, new = sum(np.frombuffer(bytes(r["w"])) for r in mine) / n, 0, []
                for v in net.weights:
                    new.append(flat[at : at + v.size].reshape(v.shape))
                    at += v.size
                net.weights, net.loss = tuple(new), sum(r["loss"] for r in mine) / n
                losses[i].append(net.loss)
    return losses


def apply_networks(df: DataFrame, x: str, nets: dict[str, Network], keep: tuple[str, ...]) -> DataFrame:
    """(keep, name, target, hat) of named networks."""
    sent = df.sparkSession.sparkContext.broadcast(nets)
    kinds = dict(df.dtypes)

    def run(parts):
        for t in parts:
            if len(t):
                m = np.stack(t["_x"].to_numpy())
                for name, net in sent.value.items():
                    yield t[list(keep)].assign(name=name, target=net.target, hat=net.predict(m))

    shape = ", ".join([*(f"{c} {kinds[c]}" for c in keep), "name string, target string, hat double"])
    return df.select(*keep, F.col(x).alias("_x")).mapInPandas(run, shape)


def apply_models(df: DataFrame, x: str, models: list[tuple[str, str, object]], keep: str) -> DataFrame:
    """(name, target, keep, y, hat) of (name, target, model with ``predict``), all models in one scan."""
    sent = df.sparkSession.sparkContext.broadcast(models)
    targets = sorted({t for _, t, _ in models})

    def run(parts):
        for t in parts:
            if t.num_rows:
                m, n = matrix(t.column("_x")).astype(float), t.num_rows
                for name, target, model in sent.value:
                    yield pa.RecordBatch.from_arrays([pa.repeat(name, n), pa.repeat(target, n), t.column(keep), t.column(target), pa.array(model.predict(m))], ["name", "target", keep, "y", "hat"])

    shape = f"name string, target string, {keep} {dict(df.dtypes)[keep]}, y double, hat double"
    return df.select(keep, F.col(x).alias("_x"), *(F.col(t).cast("double").alias(t) for t in targets)).mapInArrow(run, shape)


def registry() -> list[tuple[str, str, int, int, str, str, int]]:
    """Every model of the experiment: settings x targets x the six of the identity."""
    from pantry.operators.embed import embedding_grid

    return [(*g, t, i) for g in embedding_grid() for t in TARGETS for i in range(6)]


def coshare_moments(lines: DataFrame, by: str = "fold", recipe: str = "recipe_id") -> DataFrame:
    """(by, food_i, food_j, moment): sums of share products, once for every embedding setting.

    Foods of a recipe are paired inside the recipe's own list, so lines are not joined with themselves.
    """
    food = lines.groupBy(recipe, by, "food_key").agg(F.sum("share").alias("w"))
    lists = food.groupBy(recipe, by).agg(F.collect_list(F.struct("food_key", "w")).alias("l"))
    pairs = lists.select(by, "l", F.explode("l").alias("i")).select(by, "i", F.explode("l").alias("j"))
    return pairs.groupBy(by, F.col("i.food_key").alias("food_i"), F.col("j.food_key").alias("food_j")).agg(F.sum(F.col("i.w") * F.col("j.w")).alias("moment"))


def predict_by_food(lines: DataFrame, scores: DataFrame, b0: float, recipe: str = "recipe_id") -> DataFrame:
    """Predictions of a linear model on merged vectors without making them: (food_key, score) by shares that sum to 1."""
    met = lines.join(scores, "food_key", "left")
    return met.groupBy(recipe).agg((F.lit(b0) + F.sum(F.col("share") * F.coalesce("score", F.lit(0.0)))).alias("hat"))
