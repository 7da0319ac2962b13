"""The experiment: every embedding, merge, target and fold from two scans of the recipes.

A recipe is one row: the numbers of its foods, their grams, its targets. One scan multiplies these bags with the
vectors of all settings and adds up, for each cell (say collection and fold), the sums of products that every
linear model is solved from. A second scan applies all models, scores them and adds up hits and errors. No merged
vector is ever written or moved; both scans shuffle one small row a partition, cell and model.

The vectors of the foods go to every executor: ``embed.MOST_MB`` checks their size. Settings whose sums would not
fit a worker together are scanned in groups (``STATE_MB``).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pantry.functions import bands
from pantry.operators import nutrients
from pantry.operators.embed import MOST_MB
from pantry.operators.nutrients import TARGETS
from pantry.operators.regress import GRID, Stats, total

STATE_MB = 128
KINDS = ("dh", "avg", "sum")


def bags(lines: DataFrame, foods: list[str], by: tuple[str, ...] = ("corpus",), recipe: str = "recipe_id") -> DataFrame:
    """(recipe, by, fold, ids, grams, targets): one row a recipe with grams; foods without a number have the last one, -1."""
    known = lines.sparkSession.createDataFrame([(f, i) for i, f in enumerate(foods)], "food_key string, _id int")
    met = lines.join(known, "food_key", "left")
    line = F.struct(F.coalesce("_id", F.lit(-1)).alias("i"), F.coalesce("grams", F.lit(0.0)).alias("g"))
    bag = met.groupBy(recipe, *by).agg(F.collect_list(line).alias("_l"))
    out = nutrients.recipe_nutrients(lines, recipe).join(bag, recipe)
    return out.select(recipe, *by, bands.fold(F.col(recipe)).alias("fold"), F.col("_l.i").alias("ids"), F.col("_l.g").alias("grams"), *TARGETS)


class Bags:
    """The foods and weights of a batch of recipes, flat: made once a batch for all settings."""

    def __init__(self, t: pd.DataFrame | pa.RecordBatch):
        if isinstance(t, pa.RecordBatch):
            sizes = t.column("ids").value_lengths().to_numpy().astype(np.int64)
            self.ids, grams = (t.column(c).flatten().to_numpy() for c in ("ids", "grams"))
        else:
            sizes = np.fromiter(map(len, t["ids"]), np.int64, len(t))
            self.ids, grams = np.concatenate(t["ids"].to_numpy()), np.concatenate(t["grams"].to_numpy())
        self.begin = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        self.row, self.rows = np.repeat(np.arange(len(sizes)), sizes), len(sizes)
        self.weight = {"dh": grams / np.repeat(np.add.reduceat(grams, self.begin), sizes), "avg": np.repeat(1 / sizes, sizes), "sum": np.ones(len(self.ids))}

    def merged(self, vectors: np.ndarray, kind: str) -> np.ndarray:
        """The recipes' vectors: gram-weighted, averaged or summed."""
        return np.add.reduceat(vectors[self.ids] * self.weight[kind][:, None], self.begin)

    def by_food(self, kind: str, foods: int) -> np.ndarray:
        """The recipes' weights by food: times the vectors of a setting they are its merged vectors."""
        return np.bincount(self.row * foods + self.ids % foods, self.weight[kind], self.rows * foods).reshape(self.rows, foods)


def merged(recipes: DataFrame, vectors: np.ndarray, kind: str, keep: tuple[str, ...]) -> DataFrame:
    """(keep, vector named as the merge): each recipe's vector, made where its bag lies."""
    sent, kinds = _sent(recipes.sparkSession, {"": vectors}), dict(recipes.dtypes)

    def run(parts):
        for t in parts:
            if t.num_rows:
                x = Bags(t).merged(sent.value[""], kind)
                ends = pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32))
                yield pa.RecordBatch.from_arrays([*(t.column(c) for c in keep), pa.ListArray.from_arrays(ends, pa.array(x.ravel()))], [*keep, kind])

    return recipes.select(*keep, "ids", "grams").mapInArrow(run, ", ".join([*(f"{c} {kinds[c]}" for c in keep), f"{kind} array<double>"]))


def _few_foods(vectors: dict[str, np.ndarray]) -> bool:
    """Whether sums by food are smaller than those of all settings together: then they serve every setting."""
    side = lambda n: (n + 1 + len(TARGETS)) ** 2
    return bool(vectors) and side(len(next(iter(vectors.values())))) < sum(side(v.shape[1]) for v in vectors.values())


def _of_setting(s: Stats, v: np.ndarray) -> Stats:
    """The sums of a setting from those by food: merged vectors are linear in the foods' weights."""
    n, d = v.shape
    t = np.zeros((len(s.m), len(s.m) - n + d))
    t[0, 0], t[1 : n + 1, 1 : d + 1], t[n + 1 :, d + 1 :] = 1, v, np.eye(len(s.m) - n - 1)
    return Stats(t.T @ s.m @ t, d)


def _sent(spark, vectors: dict[str, np.ndarray]):
    if sum(v.nbytes for v in vectors.values()) > MOST_MB << 20:
        raise ValueError("the vectors are too large for a broadcast: score fewer settings at a time")
    return spark.sparkContext.broadcast(vectors)


def _groups(vectors: dict[str, np.ndarray], cells: int, kinds: tuple[str, ...]) -> Iterator[dict[str, np.ndarray]]:
    """Settings whose sums fit a worker together."""
    some, used = {}, 0
    for name, v in vectors.items():
        need = (v.shape[1] + 1 + len(TARGETS)) ** 2 * 8 * cells * len(kinds)
        if some and used + need > STATE_MB << 20:
            yield some
            some, used = {}, 0
        some[name], used = v, used + need
    if some:
        yield some


def statistics(recipes: DataFrame, vectors: dict[str, np.ndarray], kinds: tuple[str, ...] = ("dh", "avg"), by: str = "fold") -> dict[tuple[str, str], dict[str, Stats]]:
    """{(setting, merge): {cell: sums of products of (1, x, targets)}}; ``by`` is a column of at most some hundred values."""
    out: dict = {}
    if _few_foods(vectors):
        once = statistics(recipes, {"": np.eye(len(next(iter(vectors.values()))))}, kinds, by)
        return {(name, kind): {c: _of_setting(s, v) for c, s in once["", kind].items()} for name, v in vectors.items() for kind in kinds}
    cells = recipes.select(by).distinct().count()
    for some in _groups(vectors, cells, kinds):
        sent = _sent(recipes.sparkSession, some)

        def partial(parts, sent=sent):
            sums: dict = {}
            for t in parts:
                if not len(t):
                    continue
                y = t[list(TARGETS)].to_numpy(float)
                cell, bag = t["cell"].to_numpy(), Bags(t)
                for name, v in sent.value.items():
                    for kind in kinds:
                        m = np.hstack([np.ones((len(t), 1)), bag.merged(v, kind) if name else bag.by_food(kind, len(v)), y])
                        for c in np.unique(cell):
                            mine = m[cell == c]
                            key = name, kind, c
                            sums[key] = sums.get(key, 0) + mine.T @ mine
            if sums:
                keys = list(sums)
                yield pd.DataFrame({"setting": [k[0] for k in keys], "merge": [k[1] for k in keys], "cell": [k[2] for k in keys], "stats": [sums[k].tobytes() for k in keys]})

        def add(t: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"setting": t["setting"][:1], "merge": t["merge"][:1], "cell": t["cell"][:1], "stats": [sum(np.frombuffer(b) for b in t["stats"]).tobytes()]})

        shape = "setting string, merge string, cell string, stats binary"
        slim = recipes.select(F.col(by).cast("string").alias("cell"), "ids", "grams", *TARGETS)
        for r in slim.mapInPandas(partial, shape).groupBy("setting", "merge", "cell").applyInPandas(add, shape).toLocalIterator():  # a matrix a cell and model
            side = some[r["setting"]].shape[1] + 1 + len(TARGETS)
            out.setdefault((r["setting"], r["merge"]), {})[r["cell"]] = Stats(np.frombuffer(bytes(r["stats"])).reshape(side, side), some[r["setting"]].shape[1])
    return out


def ridge_path(s: Stats, penalties: tuple[float, ...]) -> list[tuple[np.ndarray, np.ndarray]]:
    """(intercepts, coefficients d x targets) for each penalty from one decomposition, all targets at once."""
    d = s.dim
    mx, my = s.m[0, 1 : d + 1] / s.n, s.m[0, d + 1 :] / s.n
    xx = s.m[1 : d + 1, 1 : d + 1] / s.n - np.outer(mx, mx)
    xy = s.m[1 : d + 1, d + 1 :] / s.n - np.outer(mx, my)
    w, q = np.linalg.eigh(xx)
    p = q.T @ xy
    out = []
    for lam in penalties:
        b = q @ (p / np.maximum(w + lam, 1e-12)[:, None])
        out.append((my - mx @ b, b))
    return out


def squared_errors(s: Stats, b0: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared error a target of linear models on these rows, without reading them."""
    c = np.vstack([-b0[None, :], -b, np.eye(len(b0))])
    return ((s.m @ c) * c).sum(0)


def tuned_ridge(stats: dict, held: tuple = (), penalties: tuple[float, ...] = GRID["lambda"]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(intercepts, coefficients, penalty a target): the penalty by cross-validation over the cells that are not
    ``held``, then a model of all of them. With a held cell the choice never sees it."""
    used = [c for c in stats if c not in held]
    if len(used) > 1:
        error = sum(np.stack([squared_errors(stats[c], *m) for m in ridge_path(total(stats, (*held, c)), penalties)]) for c in used)
    else:
        error = np.zeros((len(penalties), len(TARGETS)))
    best = error.argmin(0)
    path = ridge_path(total(stats, held), penalties)
    at = range(len(TARGETS))
    return np.array([path[k][0][t] for t, k in zip(at, best)]), np.stack([path[k][1][:, t] for t, k in zip(at, best)], 1), np.array(penalties)[best]


def searched(stats: dict, penalties: tuple[float, ...] = GRID["lambda"]) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """The model of each cell from all others, with the penalty a target that is best over all cells: one decomposition a cell."""
    paths = {c: ridge_path(total(stats, (c,)), penalties) for c in stats}
    best = sum(np.stack([squared_errors(stats[c], *m) for m in paths[c]]) for c in stats).argmin(0)
    pick = lambda path: (np.array([path[k][0][t] for t, k in enumerate(best)]), np.stack([path[k][1][:, t] for t, k in enumerate(best)], 1))
    return {c: pick(path) for c, path in paths.items()}


@dataclass
class Model:
    """Linear models of all targets by cell; without a setting a constant."""

    name: str
    setting: str | None
    merge: str
    cells: dict[str, tuple[np.ndarray, np.ndarray]]


def _loads(models: list[Model], vectors: dict[str, np.ndarray]) -> Iterator[list[Model]]:
    """Models whose vectors fit a broadcast together."""
    some, names, used = [], set(), 0
    for m in models:
        need = vectors[m.setting].nbytes if m.setting and m.setting not in names else 0
        if some and need and used + need > MOST_MB << 20:
            yield some
            some, names, used, need = [], set(), 0, vectors[m.setting].nbytes
        some, used = [*some, m], used + need
        names.add(m.setting)
    if some:
        yield some


def measure(recipes: DataFrame, vectors: dict[str, np.ndarray], models: list[Model], by: str = "fold", scale: float = 1.0) -> DataFrame:
    """(model, cell, target, n, hits, squared, absolute): all models applied in one scan, each cell by its own. Where the
    vectors do not fit a broadcast together it is a scan for each load of models."""
    if _few_foods({m.setting: vectors[m.setting] for m in models if m.setting}):
        return _measured_by_food(recipes, vectors, models, by, scale)
    if len(loads := list(_loads(models, vectors))) > 1:
        return reduce(DataFrame.unionByName, (measure(recipes, vectors, some, by, scale) for some in loads))
    sent, known = _sent(recipes.sparkSession, {k: vectors[k] for k in {m.setting for m in models if m.setting}}), recipes.sparkSession.sparkContext.broadcast(models)

    def run(parts):
        sums: dict = {}
        for t in parts:
            if not len(t):
                continue
            y, cell, bag = t[list(TARGETS)].to_numpy(float), t["cell"].to_numpy(), Bags(t)
            width = scale * np.stack([bands.width(name, y[:, i]) for i, name in enumerate(TARGETS)], 1)
            x: dict = {}
            for m in known.value:
                key = m.setting, m.merge
                if m.setting and key not in x:
                    x = {key: bag.merged(sent.value[m.setting], m.merge)}  # models of a merge follow each other
                for c in np.unique(cell):
                    if c not in m.cells:
                        continue
                    mine = cell == c
                    b0, b = m.cells[c]
                    hat = b0 + (x[key][mine] @ b if m.setting else 0.0)
                    e = np.abs(hat - y[mine])
                    got = np.stack([np.full(len(TARGETS), mine.sum()), (e <= width[mine]).sum(0), (e**2).sum(0), e.sum(0)])
                    sums[m.name, c] = sums.get((m.name, c), 0) + got
        rows = [(name, c, t, *map(float, v[:, i])) for (name, c), v in sums.items() for i, t in enumerate(TARGETS)]
        yield pd.DataFrame(rows, columns=["model", "cell", "target", "n", "hits", "squared", "absolute"])

    slim = recipes.select(F.col(by).cast("string").alias("cell"), "ids", "grams", *TARGETS)
    each = slim.mapInPandas(run, "model string, cell string, target string, n double, hits double, squared double, absolute double")
    return each.groupBy("model", "cell", "target").agg(*(F.sum(c).alias(c) for c in ("n", "hits", "squared", "absolute")))


def _measured_by_food(recipes: DataFrame, vectors: dict[str, np.ndarray], models: list[Model], by: str, scale: float) -> DataFrame:
    """``measure`` from the scores that each model gives the foods: all models of a merge and cell are one product."""
    foods = len(next(iter(vectors.values())))
    plans: dict = {}  # (merge, cell): names, intercepts, scores of the foods
    for m in models:
        for c, (b0, b) in m.cells.items():
            names, starts, scores = plans.setdefault((m.merge if m.setting else "sum", c), ([], [], []))
            names.append(m.name)
            starts.append(b0)
            scores.append(vectors[m.setting] @ b if m.setting else np.zeros((foods, len(TARGETS))))
    packed = {k: (n, np.concatenate(b0), np.hstack(v)) for k, (n, b0, v) in plans.items()}
    if sum(v.nbytes for _, _, v in packed.values()) > MOST_MB << 20:
        raise ValueError("the models are too large for a broadcast: score fewer settings at a time")
    sent = recipes.sparkSession.sparkContext.broadcast(packed)

    def run(parts):
        sums: dict = {}
        for t in parts:
            if not len(t):
                continue
            y, cell, bag = t[list(TARGETS)].to_numpy(float), t["cell"].to_numpy(), Bags(t)
            width = scale * np.stack([bands.width(name, y[:, i]) for i, name in enumerate(TARGETS)], 1)
            for merge in sorted({k for k, _ in sent.value}):
                w = bag.by_food(merge, foods)
                for c in np.unique(cell):
                    if (merge, c) not in sent.value:
                        continue
                    names, b0, scores = sent.value[merge, c]
                    mine = cell == c
                    e = (w[mine] @ scores + b0).reshape(-1, len(names), len(TARGETS))
                    e -= y[mine][:, None, :]
                    np.abs(e, out=e)
                    got = np.stack([np.full(e.shape[1:], mine.sum()), (e <= width[mine][:, None, :]).sum(0), np.einsum("nmt,nmt->mt", e, e), e.sum(0)])
                    sums[merge, c] = sums.get((merge, c), 0) + got
        rows = [(name, c, t, *map(float, v[:, j, i])) for (merge, c), v in sums.items() for j, name in enumerate(sent.value[merge, c][0]) for i, t in enumerate(TARGETS)]
        yield pd.DataFrame(rows, columns=["model", "cell", "target", "n", "hits", "squared", "absolute"])

    slim = recipes.select(F.col(by).cast("string").alias("cell"), "ids", "grams", *TARGETS)
    each = slim.mapInPandas(run, "model string, cell string, target string, n double, hits double, squared double, absolute double")
    return each.groupBy("model", "cell", "target").agg(*(F.sum(c).alias(c) for c in ("n", "hits", "squared", "absolute")))


def constants(stats: dict, cells: list[str], groups: dict[str, list[str]]) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """The mean predictor of each cell: the targets' means over the other cells of its group."""
    out = {}
    for cells_ in groups.values():
        for c in cells_:
            s = total({k: stats[k] for k in cells_}, (c,))
            out[c] = s.m[0, 1 + s.dim :] / max(s.n, 1), np.zeros((0, len(TARGETS)))
    return {c: out[c] for c in cells}


def medians(recipes: DataFrame, by: tuple[str, ...] = ("corpus",), exact: bool = False) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """The median predictor of each cell (by, fold): of the other folds, by one aggregation with filters. Approximate
    medians are mergeable sketches; exact ones keep every different value."""
    folds = sorted(r[0] for r in recipes.select("fold").distinct().collect())
    middle = (lambda x: F.percentile(x, F.lit(0.5))) if exact else (lambda x: F.percentile_approx(x, 0.5, 10_000).cast("double"))
    cut = [middle(F.when(F.col("fold") != k, F.col(t))).alias(f"{t}_{k}") for k in folds for t in TARGETS]
    rows = (recipes.groupBy(*by).agg(*cut) if by else recipes.agg(*cut)).collect()  # one row a group
    name = lambda r, k: "|".join([*(str(r[c]) for c in by), str(k)])
    return {name(r, k): (np.array([r[f"{t}_{k}"] if r[f"{t}_{k}"] is not None else 0.0 for t in TARGETS]), np.zeros((0, len(TARGETS)))) for r in rows for k in folds}


def accuracy(measured: DataFrame, *groups: str) -> DataFrame:
    """(model, groups, target, accuracy): hit rates in percent, averaged over the folds; a cell is its group's parts and the fold."""
    parts = F.split("cell", r"\|")
    each = measured.select("model", *(F.get(parts, F.lit(i)).alias(g) for i, g in enumerate(groups)), "target", (100 * F.col("hits") / F.col("n")).alias("a"))
    return each.groupBy("model", *groups, "target").agg(F.avg("a").alias("accuracy"))
