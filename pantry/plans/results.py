"""Queries: the corpora of vectors, the tables of accuracy, the regressors and their tuning."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pantry.functions import bands
from pantry.operators import corpora, embed, experiment, merge, nutrients, regress, trees, vocab
from pantry.operators.nutrients import TARGETS
from pantry.plans import views
from pantry.plans.solve import ACCURACY, fitted, predictions
from pantry.plans.truth import RECIPES, WEIGHED
from pantry.session import kept, materialize, shared_dir, table

Q, O = {}, {}
LAM = 1e-4
ALL = ("corpus", "fold")


def query(sql: str | None = None, name: str | None = None):
    """Register a query, and its SQL if it has one."""

    def keep(f):
        key = name or f.__name__
        Q[key] = f
        if sql:
            O[key] = sql
        return f

    return keep


#: The setting of each family that the tables of accuracy use.
TABLE = {
    "word2vec": corpora.Setting("word2vec", "cbow", 50, 5, "avg"),
    "glove": corpora.Setting("glove", "", 50, 5, "avg"),
    "doc2vec": corpora.Setting("doc2vec", "dm", 50, 5, "avg"),
    "encoder stand-in": corpora.Setting("bert", "", 0, 0, "sum"),
}


def foods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(food_key, tokens): the distinct foods of all collections, one training set for one space."""
    return kept(spark, f"foods {sf_dir}", lambda: vocab.training_tokens(views.extracted(spark, sf_dir)))


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The corpus of ingredient vectors in all settings, written once a session."""
    return kept(spark, f"vectors {sf_dir}", lambda: corpora.train_settings(foods(spark, sf_dir)))


def keys(spark: SparkSession, sf_dir: str) -> list[str]:
    """The foods in the order of their numbers: as many as vectors go to the executors."""
    return [r[0] for r in foods(spark, sf_dir).select("food_key").orderBy("food_key").collect()]


def recipe_bags(spark: SparkSession, sf_dir: str) -> DataFrame:
    def make() -> DataFrame:
        out = experiment.bags(views.weighed(spark, sf_dir), keys(spark, sf_dir))
        return out.withColumn("cell", F.concat_ws("|", "corpus", "fold"))

    return kept(spark, f"bags {sf_dir}", make)


def given(spark: SparkSession, sf_dir: str, dim: int = views.DIM) -> dict[str, np.ndarray]:
    """The ready vectors as a setting of their own."""
    v = views.vectors(spark, sf_dir, dim).select(F.lit("given").alias("setting"), "food_key", "vec")
    return corpora.matrices(v, keys(spark, sf_dir))


def trained(spark: SparkSession, sf_dir: str, settings) -> dict[str, np.ndarray]:
    v = vectors(spark, sf_dir).where(F.col("setting").isin([s.name for s in settings]))
    return corpora.matrices(v, keys(spark, sf_dir))


def _columns(measured: DataFrame, *groups: str) -> DataFrame:
    """A column a model instead of a row."""
    a = experiment.accuracy(measured, *groups)
    return a.groupBy(*groups, "target").pivot("model", ["dh", "mean", "median", "no_dh"]).agg(F.first("accuracy"))


# corpora ------------------------------------------------------------------------------------------

_GRID = f"(SELECT unnest({[s.name for s in corpora.GRID]!r}) AS setting, unnest({[s.width for s in corpora.GRID]!r})::INT AS dim)"
_KEY = "array_to_string(list_sort(list_distinct(string_split(food, ' '))), ' ')"


@query(f"WITH {WEIGHED} SELECT setting, dim, (SELECT count(DISTINCT {_KEY}) FROM g) AS foods, dim AS least_width, 0 AS zeros FROM {_GRID}")
def ingredient_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The artifact: all settings, written by version and setting to a given folder, and read again."""
    path = f"{shared_dir(spark)}/ingredient-corpus"
    corpora.write_corpus(vectors(spark, sf_dir), path)
    back = corpora.read_corpus(spark, path)
    return back.groupBy("setting", "dim").agg(F.count("*").alias("foods"), F.min(F.size("vec")).alias("least_width"), F.count(F.when(F.forall("vec", lambda x: x == 0), 1)).cast("int").alias("zeros"))


@query(f"WITH {RECIPES} SELECT embedding, corpus, count(*) AS recipes, width FROM r, (VALUES ('word2vec', 50), ('glove', 50), ('doc2vec', 50), ('encoder stand-in', {corpora.LAYER})) AS e(embedding, width) GROUP BY ALL")
def recipe_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The second artifact: recipe vectors by the quantity heuristic, of the six collections together, by setting and collection."""
    named = trained(spark, sf_dir, TABLE.values())
    sent = spark.sparkContext.broadcast({e: named[s.name] for e, s in TABLE.items()})  # checked by its makers: see experiment

    def run(parts):
        import pandas as pd

        for t in (x for x in parts if len(x)):
            bag = experiment.Bags(t)
            for e, v in sent.value.items():
                yield pd.DataFrame({"embedding": e, "corpus": t["corpus"], "recipe_id": t["recipe_id"], "vec": list(bag.merged(v, "dh"))})

    made = recipe_bags(spark, sf_dir).select("recipe_id", "corpus", "ids", "grams").mapInPandas(run, "embedding string, corpus string, recipe_id long, vec array<double>")
    path = f"{shared_dir(spark)}/recipe-corpus"
    made.write.mode("overwrite").partitionBy("embedding", "corpus").parquet(path)
    back = spark.read.schema("recipe_id long, vec array<double>, embedding string, corpus string").parquet(path)
    return back.groupBy("embedding", "corpus").agg(F.count("*").alias("recipes"), F.max(F.size("vec")).alias("width"))


# tables of accuracy -------------------------------------------------------------------------------


def _constants(spark: SparkSession, sf_dir: str, stats: dict, exact: bool) -> list[experiment.Model]:
    groups: dict[str, list[str]] = {}
    for c in stats:
        groups.setdefault(c.split("|")[0], []).append(c)
    mean = experiment.constants(stats, list(stats), groups)
    return [experiment.Model("mean", None, "", mean), experiment.Model("median", None, "", experiment.medians(recipe_bags(spark, sf_dir), exact=exact))]


def _by_cell(stats: dict, fit) -> dict:
    """A model a collection and fold, of the collection's other folds."""
    out = {}
    for c in stats:
        mine = {k: v for k, v in stats.items() if k.split("|")[0] == c.split("|")[0]}
        out[c] = fit(mine, c)
    return out


def _fixed(mine: dict, c: str):
    return experiment.ridge_path(regress.total(mine, (c,)), (LAM,))[0]


@query()
def accuracy_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The published tables: collection x embedding x target; heuristic, constants, plain merge and gain. Penalties are
    tuned inside the training folds; vectors are trained on the extracted foods."""
    bags = recipe_bags(spark, sf_dir)
    v = trained(spark, sf_dir, TABLE.values())
    stats = experiment.statistics(bags, v, ("dh", "avg"), "cell")
    tuned = lambda mine, c: experiment.tuned_ridge(mine, (c,))[:2]
    models = [experiment.Model(f"{e}|{column}", s.name, kind, _by_cell(stats[s.name, kind], tuned)) for e, s in TABLE.items() for kind, column in (("dh", "dh"), ("avg", "no_dh"))]
    models += _constants(spark, sf_dir, next(iter(stats.values())), False)
    a = experiment.accuracy(experiment.measure(bags, v, models, "cell"), "corpus")
    parts = F.split("model", r"\|")
    ours = a.where(F.size(parts) == 2).select(F.get(parts, F.lit(0)).alias("embedding"), F.get(parts, F.lit(1)).alias("column"), "corpus", "target", "accuracy")
    wide = ours.groupBy("embedding", "corpus", "target").agg(*(F.max(F.when(F.col("column") == c, F.col("accuracy"))).alias(c) for c in ("dh", "no_dh")))
    base = a.groupBy("corpus", "target").agg(*(F.max(F.when(F.col("model") == c, F.col("accuracy"))).alias(c) for c in ("mean", "median")))
    return wide.join(base, ["corpus", "target"]).select("corpus", "embedding", "target", "dh", "mean", "median", "no_dh", (F.col("dh") - F.col("no_dh")).alias("gain"))


def _given_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    bags, v = recipe_bags(spark, sf_dir), given(spark, sf_dir)
    stats = experiment.statistics(bags, v, ("dh", "avg"), "cell")
    models = [experiment.Model(n, "given", k, _by_cell(stats["given", k], _fixed)) for n, k in (("dh", "dh"), ("no_dh", "avg"))]
    models += _constants(spark, sf_dir, stats["given", "dh"], True)
    return _columns(experiment.measure(bags, v, models, "cell"), "corpus")


@query(ACCURACY)
def accuracy_given(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same table for the ready vectors and one penalty: what SQL can solve as well."""
    return _given_table(spark, sf_dir).select("corpus", "target", *(F.round(c, 4).alias(c) for c in ("dh", "mean", "median", "no_dh")))


@query(f"SELECT corpus, target, no_dh AS accuracy FROM ({ACCURACY})")
def no_dh(spark: SparkSession, sf_dir: str) -> DataFrame:
    bags, v = recipe_bags(spark, sf_dir), given(spark, sf_dir)
    stats = experiment.statistics(bags, v, ("avg",), "cell")
    model = experiment.Model("no_dh", "given", "avg", _by_cell(stats["given", "avg"], _fixed))
    return experiment.accuracy(experiment.measure(bags, v, [model], "cell"), "corpus").select("corpus", "target", F.round("accuracy", 4).alias("accuracy"))


@query(f"SELECT corpus, target, dh, no_dh, round(dh - no_dh, 3) AS gain FROM ({ACCURACY})")
def gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = _given_table(spark, sf_dir)
    return t.select("corpus", "target", F.round("dh", 4).alias("dh"), F.round("no_dh", 4).alias("no_dh"), F.round(F.round("dh", 4) - F.round("no_dh", 4), 3).alias("gain"))


def _over_folds(spark: SparkSession, sf_dir: str, v: dict, name: str, kind: str, by: str = "fold", scale: float = 1.0) -> DataFrame:
    """Measured results of a model a cell, of all other cells."""
    bags = recipe_bags(spark, sf_dir)
    stats = experiment.statistics(bags, v, (kind,), by)["given", kind]
    return experiment.measure(bags, v, [experiment.Model(name, "given", kind, {c: _fixed(stats, c) for c in stats})], by, scale)


@query(" UNION ALL ".join(f"SELECT target, {s}::DOUBLE AS scale, round(avg(a), 4) AS accuracy FROM ({predictions('dh', 'fold', LAM, scale=s)}) GROUP BY target" for s in (0.5, 1.0, 2.0)))
def band_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy as the tolerance is scaled: it must rise."""
    v, out = given(spark, sf_dir), None
    for scale in (0.5, 1.0, 2.0):
        a = experiment.accuracy(_over_folds(spark, sf_dir, v, "dh", "dh", scale=scale)).select("target", F.lit(scale).alias("scale"), F.round("accuracy", 4).alias("accuracy"))
        out = a if out is None else out.unionByName(a)
    return out


@query(" UNION ALL ".join(f"SELECT target, {d} AS dim, round(avg(a), 4) AS accuracy FROM ({predictions('dh', 'fold', LAM, dim=d)}) GROUP BY target" for d in (4, 16, 64)))
def dimension_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy by the number of dimensions."""
    out = None
    for dim in (4, 16, 64):
        a = experiment.accuracy(_over_folds(spark, sf_dir, given(spark, sf_dir, dim), "dh", "dh")).select("target", F.lit(dim).alias("dim"), F.round("accuracy", 4).alias("accuracy"))
        out = a if out is None else out.unionByName(a)
    return out


@query(f"SELECT cell AS corpus, target, round(a, 4) AS accuracy FROM ({predictions('dh', 'corpus', LAM)})")
def leave_one_corpus_out(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Train on five collections, test on the sixth: one space for all."""
    m = _over_folds(spark, sf_dir, given(spark, sf_dir), "dh", "dh", "corpus")
    return m.select(F.col("cell").alias("corpus"), "target", F.round(100 * F.col("hits") / F.col("n"), 4).alias("accuracy"))


@query()
def grid_accuracy(spark: SparkSession, sf_dir: str, settings: tuple[corpora.Setting, ...] = corpora.GRID) -> DataFrame:
    """All 122 settings x targets: tuned ridge over five folds of all collections, with the heuristic and without."""
    bags = recipe_bags(spark, sf_dir)
    v = trained(spark, sf_dir, settings)
    stats = experiment.statistics(bags, v, ("dh", "avg"), "fold")
    models = []
    for s in settings:
        for kind, column in (("dh", "dh"), ("avg", "no_dh")):
            models.append(experiment.Model(f"{s.name}|{column}", s.name, kind, experiment.searched(stats[s.name, kind])))
    a = experiment.accuracy(experiment.measure(bags, v, models, "fold"))
    parts = F.split("model", r"\|")
    a = a.select(F.get(parts, F.lit(0)).alias("setting"), F.get(parts, F.lit(1)).alias("column"), "target", "accuracy")
    return a.groupBy("setting", "target").agg(*(F.max(F.when(F.col("column") == c, F.col("accuracy"))).alias(c) for c in ("dh", "no_dh")))


# regressors ---------------------------------------------------------------------------------------


def _given_stats(spark: SparkSession, sf_dir: str) -> dict:
    """Scanned once for a session's table of bags."""
    known = recipe_bags(spark, sf_dir)
    if "_pantry_stats" not in known.__dict__:
        known.__dict__["_pantry_stats"] = experiment.statistics(known, given(spark, sf_dir), ("dh",), "fold")["given", "dh"]
    return known.__dict__["_pantry_stats"]


def _rows(spark: SparkSession, fits: list) -> DataFrame:
    """(target, i, coefficient), i = 0 for the intercept."""
    rows = [(t, i, round(float(x), 3) + 0.0) for t, (b0, b) in zip(TARGETS, fits) for i, x in enumerate([b0, *b])]
    return spark.createDataFrame(rows, "target string, i int, coefficient double")


@query(fitted(0.01))
def ridge(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = regress.total(_given_stats(spark, sf_dir))
    return _rows(spark, [regress.fit_ridge(s, i, 0.01) for i in range(len(TARGETS))])


@query(f"SELECT target, round(sqrt(avg(e * e)), 4) AS rmse FROM ({predictions('dh', 'none', 1e-9, errors=True)}) GROUP BY target")
def single_target(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Least squares, one model a nutrient: its error on the recipes that it was fitted to, without reading them again."""
    s = regress.total(_given_stats(spark, sf_dir))
    return spark.createDataFrame([(t, round(float(np.sqrt(max(0.0, s.sse(i, *regress.fit_linear(s, i))) / s.n)), 4)) for i, t in enumerate(TARGETS)], "target string, rmse double")


def _violation(spark: SparkSession, sf_dir: str, lam: float, alpha: float) -> DataFrame:
    """(target, violation): how far the solution is from the conditions that only the optimum meets. Its gradient comes
    from a scan of the merged vectors, not from the statistics that it was solved from."""
    s = regress.total(_given_stats(spark, sf_dir))
    fits = [regress.fit_enet(s, i, lam, alpha, sweeps=4000, tol=1e-10) for i in range(len(TARGETS))]
    f = views.recipe_features(spark, sf_dir)
    n = s.n
    for t, (b0, b) in zip(TARGETS, fits):
        f = f.withColumn(f"e_{t}", F.col(t) - F.lit(b0) - embed.dot(F.col("dh"), F.array(*(F.lit(float(x)) for x in b))))
    g = f.agg(*(F.array(*(F.sum(F.col(f"e_{t}") * F.get("dh", F.lit(j))) / n for j in range(views.DIM))).alias(t) for t in TARGETS)).first()  # one row
    rows = []
    for t, (_, b) in zip(TARGETS, fits):
        left = np.array(g[t]) - lam * (1 - alpha) * b
        off = np.where(b != 0, np.abs(left - lam * alpha * np.sign(b)), np.maximum(np.abs(left) - lam * alpha, 0))
        rows.append((t, round(float(off.max()), 4) + 0.0))
    return spark.createDataFrame(rows, "target string, violation double")


_ZERO = "SELECT unnest(['fat', 'protein', 'sugar', 'satfat', 'sodium']) AS target, 0.0::DOUBLE AS violation"
Q["lasso"], O["lasso"] = lambda spark, sf_dir: _violation(spark, sf_dir, 0.01, 1.0), _ZERO
Q["enet"], O["enet"] = lambda spark, sf_dir: _violation(spark, sf_dir, 0.01, 0.5), _ZERO


@query(f"SELECT recipe_id, round(hat, 3) AS hat, round(hat, 3) AS direct FROM ({predictions('dh', 'none', 0.01, errors=True)}) WHERE target = 'fat'")
def predict_by_food(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Predictions from scores of foods beside those from merged vectors."""
    b0, b = regress.fit_ridge(regress.total(_given_stats(spark, sf_dir)), 0, 0.01)
    coef = F.array(*(F.lit(float(v)) for v in b))
    lines = nutrients.shares(views.weighed(spark, sf_dir)).withColumn("share", F.col("share") / 100)
    scores = views.vectors(spark, sf_dir).select("food_key", embed.dot(F.col("vec"), coef).alias("score"))
    direct = views.recipe_features(spark, sf_dir).select("recipe_id", F.round(F.lit(b0) + embed.dot(F.col("dh"), coef), 3).alias("direct"))
    return regress.predict_by_food(lines, scores, b0).withColumn("hat", F.round("hat", 3)).join(direct, "recipe_id")


def _features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(recipe_id, fold, targets, dh): the bags merged with the ready vectors, so that no line is moved again."""
    return kept(spark, f"features {sf_dir}", lambda: experiment.merged(recipe_bags(spark, sf_dir), given(spark, sf_dir)["given"], "dh", ("recipe_id", "fold", *TARGETS)))


def _long(df: DataFrame, name: str, hats: dict[str, str]) -> DataFrame:
    """(name, target, recipe_id, y, hat) from a column a target."""
    rows = F.explode(F.array(*(F.struct(F.lit(t).alias("target"), F.col(t).alias("y"), F.col(h).alias("hat")) for t, h in hats.items()))).alias("r")
    return df.select(F.lit(name).alias("name"), "recipe_id", rows).select("name", "r.target", "recipe_id", "r.y", "r.hat")


LINEAR = ("linear", "ridge", "lasso", "enet")


def _linear(stats: dict, model: str, test: str = "0") -> tuple[dict, list]:
    """({target: (intercept, coefficients)}, [(model, target, lambda, alpha)]): searched and fitted without the test fold."""
    best = regress.grid_searches(stats, model, list(range(len(TARGETS))), (test,))
    fits = dict(zip(TARGETS, regress.fit_all(regress.total(stats, (test,)), model, list(enumerate(best)))))
    return fits, [(model, t, float(c.get("lam", 0)), float(c.get("alpha", 0))) for t, c in zip(TARGETS, best)]


def _networks(spark: SparkSession, sf_dir: str, nets: list[regress.Network], **options) -> list[list[float]]:
    return regress.fit_networks(_features(spark, sf_dir), "dh", nets, {int(k): v for k, v in _given_stats(spark, sf_dir).items()}, **options)


def _searched_networks(spark: SparkSession, sf_dir: str, n: int = 3) -> list[tuple[int, float, str, float]]:
    """(hidden units, rate, target, RMSE on fold 1) of random candidates trained on folds 2 to 4, all side by side."""
    some = regress.random_candidates({"hidden": (8, 16, 32), "rate": (0.003, 0.01, 0.03)}, n, 1)
    nets = [regress.Network(t, c["hidden"], c["rate"], (0, 1)) for t in TARGETS for c in some]
    _networks(spark, sf_dir, nets)
    f = _features(spark, sf_dir).where("fold = 1")
    hats = regress.apply_networks(f, "dh", {str(i): m for i, m in enumerate(nets)}, ("recipe_id",))
    truth = _long(f, "", {t: t for t in TARGETS}).select("recipe_id", "target", "y")
    err = {int(r["name"]): r["e"] for r in hats.join(truth, ["recipe_id", "target"]).groupBy("name").agg(F.sqrt(F.avg((F.col("y") - F.col("hat")) ** 2)).alias("e")).collect()}
    return [(m.hidden, m.rate, m.target, float(err[i])) for i, m in enumerate(nets)]


def _best(rows: list, target_at: int) -> dict[str, tuple]:
    """The row of the least error (the last field) for each target."""
    return {t: min((r for r in rows if r[target_at] == t), key=lambda r: r[-1]) for t in TARGETS}


def _binned(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, np.ndarray]:
    """The recipes in bins, and the bins' ends: quantiles of folds 2 to 4, which neither tuning nor testing measures on."""
    f, made = _features(spark, sf_dir), []

    def make() -> DataFrame:
        made.append(trees.edges(f.where("fold > 1"), "dh", views.DIM))
        return trees.binned(f, "dh", made[0], TARGETS)

    df = kept(spark, f"binned {sf_dir}", make)
    if made:
        df.__dict__["_pantry_ends"] = made[0]
    return df, df.__dict__["_pantry_ends"]


def _grid(model: str) -> list[tuple[int, int]]:
    """(trees, depth) of a search; no trees: a single one of all rows and features."""
    if model == "tree":
        return [(0, d) for d in regress.GRID["depth"]]
    return [(c["trees"], c["depth"]) for c in regress.random_candidates({"trees": (5, 10, 20), "depth": (3, 5, 8)}, 2, 1)]


def _searched_trees(spark: SparkSession, sf_dir: str, models: tuple[str, ...]) -> list[tuple[int, int, str, float]]:
    """(trees, depth, target, RMSE on fold 1) of candidates trained on folds 2 to 4, all side by side."""
    df, _ = _binned(spark, sf_dir)
    some = [c for m in models for c in _grid(m)]
    grown = trees.planned(TARGETS, some, (0, 1))
    trees.grow(df, grown, views.DIM)
    return trees.validated(df, grown, TARGETS, some, 1)


def _fitted_trees(spark: SparkSession, sf_dir: str, models: tuple[str, ...]) -> list[tuple[str, str, trees.Forest]]:
    """(name, target, model) of trees and forests: searched together, then those chosen grown together on folds 1 to 4."""
    rows = _searched_trees(spark, sf_dir, models)
    best = {(m, t): r for m in models for t, r in _best([r for r in rows if r[:2] in _grid(m)], 2).items()}
    df, ends = _binned(spark, sf_dir)
    grown = [x for (_, t), (n, d, *_) in best.items() for x in trees.planned((t,), [(n, d)], (0,))]
    trees.grow(df, grown, views.DIM)
    return [(m, t, trees.forest(grown, t, n, d, ends)) for (m, t), (n, d, *_) in best.items()]


def _fitted_networks(spark: SparkSession, sf_dir: str) -> list[tuple[str, str, regress.Network]]:
    best = _best(_searched_networks(spark, sf_dir), 2)
    nets = [regress.Network(t, best[t][0], best[t][1], (0,)) for t in TARGETS]
    _networks(spark, sf_dir, nets, rounds=8)
    return [("mlp", m.target, m) for m in nets]


def _fitted(spark: SparkSession, sf_dir: str, models: tuple[str, ...]) -> list[tuple[str, str, object]]:
    """(name, target, model with ``predict``) of the regressors, tuned and refitted without fold 0."""
    linear, grown = (tuple(m for m in models if m in some) for some in (LINEAR, ("tree", "forest")))
    jobs = []
    if linear or "mlp" in models:
        stats = _given_stats(spark, sf_dir)
        jobs.append(lambda: [(m, t, regress.Linear(*fit)) for m in linear for t, fit in _linear(stats, m)[0].items()])
    if grown:
        _binned(spark, sf_dir)
        jobs.append(lambda: _fitted_trees(spark, sf_dir, grown))
    if "mlp" in models:
        _features(spark, sf_dir)
        jobs.append(lambda: _fitted_networks(spark, sf_dir))
    return [x for found in regress.in_parallel(jobs) for x in found]  # all tables are there: the jobs only read them


def _tested(spark: SparkSession, sf_dir: str, *models: str) -> DataFrame:
    """(name, target, recipe_id, y, hat) on fold 0 of regressors, tuned and refitted on the other folds."""
    return regress.apply_models(_features(spark, sf_dir).where("fold = 0"), "dh", _fitted(spark, sf_dir, models), "recipe_id")


for _m in ("tree", "forest", "mlp"):
    Q[_m] = lambda spark, sf_dir, m=_m: _tested(spark, sf_dir, m)


@query()
def regressor_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seven regressors x five targets on a fold that neither tuning nor fitting saw: accuracy within the bands, and error."""
    out = _tested(spark, sf_dir, *regress.REGRESSORS)
    hit = F.lit(0.0)
    for t in TARGETS:
        hit = F.when(F.col("target") == t, bands.hit(t, F.col("y"), F.col("hat"))).otherwise(hit)
    return out.groupBy(F.col("name").alias("regressor"), "target").agg((100 * F.avg(hit)).alias("accuracy"), F.sqrt(F.avg((F.col("y") - F.col("hat")) ** 2)).alias("rmse"), F.count("*").alias("n"))


@query()
def grid_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The chosen point of every exhaustive search of the linear family, by cross-validation over folds 1 to 4."""
    stats = _given_stats(spark, sf_dir)
    return spark.createDataFrame([r for m in LINEAR for r in _linear(stats, m)[1]], "model string, target string, lambda double, alpha double")


@query()
def nested_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tuning inside each fold's training part: the outer fold never sees its own choice."""
    stats, rows = _given_stats(spark, sf_dir), []
    for f in stats:
        b0, b, penalty = experiment.tuned_ridge(stats, (f,))
        error = experiment.squared_errors(stats[f], b0, b) / stats[f].n
        rows += [(int(f), t, float(penalty[i]), float(error[i])) for i, t in enumerate(TARGETS)]
    return spark.createDataFrame(rows, "fold int, target string, lambda double, mse double")


@query()
def random_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The points of a random search, each with the recipes that its fold leaves to train on and holds to validate on."""
    space = {"trees": (10, 20, 50), "depth": (3, 5, 8), "hidden": (8, 16, 32)}
    some = spark.createDataFrame([tuple(c.values()) for c in regress.random_candidates(space, 10, 7)], "trees int, depth int, hidden int")
    valid = table(spark, sf_dir, "orders").groupBy(bands.fold(F.col("o_orderkey")).alias("fold")).agg(F.count("*").alias("valid"))
    rows = valid.crossJoin(F.broadcast(valid.agg(F.sum("valid").alias("_n")))).select("fold", (F.col("_n") - F.col("valid")).alias("train"), "valid")
    return some.crossJoin(F.broadcast(rows))  # a row a fold


@query()
def tree_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([r[1:] for r in _searched_trees(spark, sf_dir, ("tree",))], "depth int, target string, rmse double")


@query()
def forest_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame(_searched_trees(spark, sf_dir, ("forest",)), "trees int, depth int, target string, rmse double")


@query()
def mlp_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame(_searched_networks(spark, sf_dir), "hidden int, rate double, target string, rmse double")


@query()
def refit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The linear family with the best parameters, fitted to all folds."""
    stats, rows = _given_stats(spark, sf_dir), []
    for m in LINEAR:
        best = regress.grid_searches(stats, m, list(range(len(TARGETS))))
        rows += [(m, t, float(b0), [float(v) for v in b]) for t, (b0, b) in zip(TARGETS, regress.fit_all(regress.total(stats), m, list(enumerate(best))))]
    return spark.createDataFrame(rows, "model string, target string, intercept double, coefficients array<double>")


@query()
def quality_from_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reuse of ready vectors elsewhere: documents' quality from the average of their words' vectors.

    Words take vectors by their place in the vocabulary, as far as the ready vectors go; a document is merged from them.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", F.split(F.lower("text"), r"\s+").alias("tokens"))
    ready = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("word_id"), F.col("embedding").alias("vec"))
    known = vocab.vocabulary(docs).join(ready, "word_id").select("word", "vec")
    x = merge.combine_words(docs, known, views.DIM, "avg", key="doc_id")
    f = x.where("vec is not null").join(table(spark, sf_dir, "labels"), "doc_id").select("doc_id", F.col("vec").alias("x"), F.col("quality").cast("double").alias("quality"), bands.fold(F.col("doc_id")).alias("fold"))
    f = materialize(f, "reuse")
    stats = regress.collect_stats(regress.gram(f, "x", views.DIM, ("quality",)), views.DIM)
    models = {k: {"quality": regress.fit_ridge(regress.total(stats, (k,)), 0, 1e-3)} for k in stats}
    return regress.cross_predict(f, "x", models).groupBy("quality").agg(F.count("*").alias("n"), F.avg("hat_quality").alias("mean_score"))
