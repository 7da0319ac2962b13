"""Queries on keys, values and shapes that the given small tables do not have, beside their SQL."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from pantry.plans import catalog
from tests.oracle import connect, rows

QUERIES, SQL = catalog.queries(), catalog.oracle_sql()


def _equals_sql(name, df, con):
    got = con.execute(SQL[name])
    cols = [d[0] for d in got.description]
    assert rows(df.columns, df.collect()) == rows(cols, got.fetchall())


def test_argmax_of_long_keys(spark, sf_dir, tmp_path):
    """Part keys of seven digits, as 60 copies of the table have them."""
    import duckdb

    part = spark.read.parquet(f"{sf_dir}/part.parquet")
    more = part.unionByName(part.withColumn("p_partkey", F.col("p_partkey") + 1_000_000 + F.col("p_size") * 7))
    more.coalesce(1).write.parquet(f"{tmp_path}/part.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW part AS SELECT * FROM '{tmp_path}/part.parquet/*.parquet'")
    _equals_sql("agg_argmax", QUERIES["agg_argmax"](spark, str(tmp_path)), con)


def test_exact_medians_hold_no_values(spark):
    """Medians by enclosing equal those of all values: ties, nulls, few rows, skewed folds; no plan aggregates by exact percentile."""
    from pantry.operators import regress

    rng = np.random.default_rng(3)
    data = [(int(i % 5), ["a", "b"][i % 7 == 0], float(v) if i % 11 else None, float(i % 5) * 100 + float(rng.integers(0, 3))) for i, v in enumerate(rng.normal(size=5003))]
    df = spark.createDataFrame([*data, (1, "c", 2.0, 5.0), (2, "c", 3.0, 6.0)], "fold int, g string, x double, y double")
    for by, halves in (((), (2e-4, 2e-2, 0.5)), (("g",), (2e-4, 2e-2, 0.5)), (("g",), (1e-9, 0.5))):
        got = {tuple(r[c] for c in (*by, "fold")): (r["hat_x"], r["hat_y"]) for r in regress.left_out_medians(df, ("x", "y"), by, halves).collect()}
        t = df.toPandas()
        for where, mine in t.groupby(list(by)) if by else [((), t)]:
            for k in range(5):
                rest = mine[mine["fold"] != k]
                assert got[(*where, k)] == pytest.approx((rest["x"].median(), rest["y"].median()), nan_ok=True)
    plan = regress.with_constant(df, "median", ("x", "y"), exact=True)._jdf.queryExecution().optimizedPlan().toString()
    assert "percentile(" not in plan


def _nearest_by_hand(vectors, asks, k):
    out = {}
    for q in asks:
        scored = []
        for i, v in vectors:
            if i != q[0]:
                ok = v is not None and q[1] is not None and None not in v and None not in q[1] and len(v) == len(q[1]) and any(v) and any(q[1])
                c = float(np.dot(v, q[1]) / (np.linalg.norm(v) * np.linalg.norm(q[1]))) if ok else None
                scored.append((1, 0.0, i) if c is None else (0, -round(c, 6), i))
        out[q[0]] = [(i, None if none else -c) for none, c, i in sorted(scored)[:k]]
    return out


def test_nearest_of_copies_and_odd_vectors(spark):
    """Copies, near copies under the sixth decimal, missing and zero vectors, other lengths: as all pairs give them."""
    from pantry.operators import embed

    rng = np.random.default_rng(5)
    base = rng.normal(size=(40, 8)).round(3)
    vectors = [(i, [float(x) for x in base[i % 40] * (1 + i % 3)]) for i in range(400)]
    vectors += [(1000 + i, [float(x) for x in base[i] + 1e-7 * (i % 5)]) for i in range(40)]
    vectors += [(2000, None), (2001, [0.0] * 8), (2002, [1.0, None] + [1.0] * 6), (2003, [1.0, 2.0]), (2004, [2.0, 4.1])]
    df = spark.createDataFrame(vectors, "vec_id long, embedding array<double>")
    asks = [v for v in vectors if v[0] % 50 == 0 or v[0] > 1990]
    want = _nearest_by_hand(vectors, asks, 5)
    got: dict = {}
    for most in (10_000, 7):
        got = {}
        for r in embed.nearest(df, df.where(F.col("vec_id").isin([a[0] for a in asks])), 5, most=most).orderBy("query", "rank").collect():
            got.setdefault(r["query"], []).append((r["vec_id"], r["cosine"]))
        assert {q: [i for i, _ in v] for q, v in got.items()} == {q: [i for i, _ in v] for q, v in want.items()}
        plan = embed.nearest(df, df.where("vec_id % 50 = 0"), 5)._jdf.queryExecution().optimizedPlan().toString()
        assert "Join" not in plan


def _features(spark, n=600, dim=6):
    rng = np.random.default_rng(9)
    x = rng.normal(size=(n, dim))
    y = np.stack([x[:, 0] * 2 + x[:, 1], np.abs(x[:, 2]) + x[:, 3]], 1)
    data = [(i, i % 5, [float(v) for v in x[i]], float(y[i, 0]), float(y[i, 1])) for i in range(n)]
    return x, y, spark.createDataFrame(data, "recipe_id long, fold int, x array<double>, a double, b double").repartition(2)


def test_networks_side_by_side(spark):
    """Networks of one size in one product learn what each learns alone."""
    from pantry.operators import regress

    x, y, df = _features(spark)
    stats = regress.collect_stats(regress.gram(df, "x", 6, ("a", "b")), 6)
    nets = [regress.Network(t, 8, rate, (0, 1)) for t in ("a", "b") for rate in (0.003, 0.03)]
    for m in nets:
        m.start(stats, ("a", "b"))
    ys = np.stack([y[:, "ab".index(m.target)] for m in nets], 1)
    together = regress.passes_together(nets, x, ys, 3, 128, 2)
    for m, own, (w, loss) in zip(nets, ys.T, together):
        alone, least = m.passes(x, own, 3, 128, 2)
        assert loss == pytest.approx(least) and all(np.allclose(p, q) for p, q in zip(w, alone))


def test_trees_of_all_depths_from_one(spark, monkeypatch):
    """The top of a deep tree is the tree of less depth; a search fits one tree a target."""
    from pantry.operators import regress

    _, _, df = _features(spark)
    fit, fitted = regress.fit_tree, []
    monkeypatch.setattr(regress, "fit_tree", lambda df, x, t, depth=5, seed=1: fitted.append(t) or fit(df, x, t, depth, seed))
    got = {(d, t): e for d, t, e in regress.grid_search_tree(df, "x", ("a", "b"), (2, 4))}
    assert fitted == ["a", "b"]
    train, held = df.where("fold > 1"), df.where("fold = 1")
    for (d, t), e in got.items():
        assert e == pytest.approx(regress.rmse(fit(train, "x", t, d), held, "x", t))


def test_trees_grown_together(spark):
    """A tree from bins as fine as the values splits as Spark ML's; a candidate is the start and top of a larger forest."""
    from pantry.operators import regress, trees

    rng = np.random.default_rng(2)
    x = rng.integers(0, 20, (900, 7)).astype(float)
    y = np.stack([np.where(x[:, 0] > 9, 40, 0) + 3 * x[:, 1] + rng.normal(size=900), x[:, 2] * x[:, 3]], 1)
    df = spark.createDataFrame([(i % 5, [float(v) for v in x[i]], float(y[i, 0]), float(y[i, 1])) for i in range(900)], "fold int, x array<double>, a double, b double").repartition(3).localCheckpoint()
    ends = np.tile(np.minimum(np.arange(31), 19) + 0.5, (7, 1))
    path = trees.binned(df, "x", ends, ("a", "b")).localCheckpoint()
    some = [(0, 2), (0, 4), (3, 2), (6, 4)]
    grown = trees.planned(("a", "b"), some, (0, 1))
    assert [t.depth for t in grown if t.target == "a"] == [4] * 7
    trees.grow(path, grown, 7)
    train, held = df.where("fold > 1"), df.where("fold = 1")
    got = {(n, d, t): e for n, d, t, e in trees.validated(path, grown, ("a", "b"), some, 1)}
    valid = np.arange(900) % 5 == 1
    for (n, d, t), e in got.items():
        if not n:
            assert e == pytest.approx(regress.rmse(regress.fit_tree(train, "x", t, d), held, "x", t))
        hat = trees.forest(grown, t, n, d, ends).predict(x[valid])
        assert e == pytest.approx(np.sqrt(np.mean((hat - y[valid, "ab".index(t)]) ** 2)))
    few = trees.planned(("a", "b"), [(3, 2)], (0, 1))
    trees.grow(path, few, 7)
    assert {(n, d, t): e for n, d, t, e in trees.validated(path, few, ("a", "b"), [(3, 2)], 1)} == pytest.approx({k: e for k, e in got.items() if k[0] == 3})
    assert got[6, 4, "a"] < 0.5 * y[:, 0].std()


def test_trees_read_the_smaller_side():
    """The sums of a level from the smaller sides and the level above are those of all its rows, feature by feature."""
    from pantry.operators import trees

    rng = np.random.default_rng(1)
    bins, weight = rng.integers(0, 32, (700, 5)).astype(np.uint8), rng.integers(0, 3, 700).astype(float)
    y = np.where(bins[:, 0] > 20, 5.0, bins[:, 1]) + rng.normal(size=700)
    for number, w in ((-1, None), (0, weight)):
        tree = trees.Tree("a", 4, number)
        tree.nodes, tree.open, tree.read, before = [[0, 0.0, -1, 0.0, 0, 0]], [0], [0], None
        for _ in range(4):
            mine = np.ones(700, bool) if w is None else w > 0
            full = tree.completed(trees.sums(tree, bins, trees.paired(bins), mine, y, w), before)
            read, tree.read = tree.read, tree.open
            slot, n = tree.place(bins, np.arange(700)), np.ones(700) if w is None else w
            for k in range(len(tree.open)):
                for f in range(5):
                    at = slot == k
                    assert np.allclose(full[0, k, f], np.bincount(bins[at, f], n[at], 32)) and np.allclose(full[1, k, f], np.bincount(bins[at, f], (n * y)[at], 32))
            whole = sum(n[np.isin(slot, np.arange(len(tree.open)))])
            counted = sum(n[np.isin(slot, [i for i, at in enumerate(tree.open) if at in read])])
            assert before is None or counted <= whole / 2 + 1e-9
            before = full
            tree.grown(trees.best_splits(full, tree.features(5)))
        assert len(tree.nodes) > 15


def test_networks_in_single_precision(spark):
    """Passes in single precision stay near those in double, and training uses them."""
    from pantry.operators import regress

    x, y, df = _features(spark)
    stats = regress.collect_stats(regress.gram(df, "x", 6, ("a", "b")), 6)
    nets = [regress.Network(t, 8, 0.01, (0, 1)) for t in ("a", "b")]
    for m in nets:
        m.start(stats, ("a", "b"))
    for (w, loss), (w2, loss2) in zip(regress.passes_together(nets, x.astype(np.float32), y, 4, 128, 1), regress.passes_together(nets, x, y, 4, 128, 1)):
        assert loss == pytest.approx(loss2, rel=1e-3) and loss != loss2 and all(np.allclose(p, q, atol=1e-3) for p, q in zip(w, w2))
    losses = regress.fit_networks(df, "x", nets, stats, ("a", "b"), rounds=3)
    assert all(v[-1] < v[0] for v in losses)


def test_features_from_bags(spark, sf_dir, monkeypatch):
    """The regressors' features are the operator's merge of the lines, without moving the lines again."""
    from pantry.plans import results, views
    from pantry.session import discard

    want = {r["recipe_id"]: r for r in views.recipe_features(spark, sf_dir).collect()}
    discard(results._features(spark, sf_dir))
    monkeypatch.setattr(views, "recipe_features", lambda *a: 1 / 0)
    got = results._features(spark, sf_dir).collect()
    assert len(got) == len(want)
    for r in got:
        w = want[r["recipe_id"]]
        assert np.allclose(r["dh"], w["dh"]) and r["fold"] == w["fold"] and r["fat"] == pytest.approx(w["fat"])


def test_food_classes_of_different_foods(spark):
    """Tokens are taken of each different food once: the scan is grouped before they are."""
    from pantry.operators import linking

    df = spark.createDataFrame([("red ring",), ("ring red",), ("red ring",), ("",), (None,)], "food string")
    out = linking.food_classes(df)
    assert [r["key"] for r in out.collect()] == ["red ring"]
    assert out._jdf.queryExecution().optimizedPlan().toString().count("Aggregate") == 2


def test_penalties_side_by_side():
    """Lasso and elastic net of all targets and penalties together are those of each alone, settled or not."""
    from pantry.operators import regress

    rng = np.random.default_rng(6)
    stats = {}
    for f in range(4):
        x = rng.normal(size=(80, 9)) @ rng.normal(size=(9, 9))
        m = np.hstack([np.ones((80, 1)), x, x @ rng.normal(size=(9, 3)) + rng.normal(size=(80, 3))])
        stats[f] = regress.Stats(m.T @ m, 9)
    s = regress.total(stats)
    some = [(t, lam, a) for t in (2, 0, 1) for lam in (1e-4, 0.1, 100.0) for a in (0.1, 1.0)]
    for sweeps in (3, 500):
        for (t, lam, a), (b0, b) in zip(some, regress.fit_enets(s, some, sweeps)):
            want0, want = regress.fit_enet(s, t, lam, a, sweeps)
            assert b0 == pytest.approx(want0) and np.allclose(b, want)
    for model in ("linear", "ridge", "lasso", "enet"):
        assert regress.grid_searches(stats, model, [0, 1, 2], (3,)) == [regress.grid_search(stats, model, t, (3,)) for t in range(3)]


def test_regressors_in_one_scan(spark, sf_dir, monkeypatch):
    """The seven regressors share one scan of statistics, no Spark ML fit and one scan of predictions."""
    from pantry.operators import experiment, regress
    from pantry.plans import results

    for name in ("fit_tree", "fit_forest"):
        monkeypatch.setattr(regress, name, lambda *a, **k: 1 / 0)
    scans, real = [], experiment.statistics
    monkeypatch.setattr(experiment, "statistics", lambda *a, **k: scans.append(1) or real(*a, **k))
    results.recipe_bags(spark, sf_dir).__dict__.pop("_pantry_stats", None)
    got = {(r.regressor, r.target): r for r in results.regressor_accuracy(spark, sf_dir).collect()}
    assert len(scans) == 1 and len(got) == 35
    test = results._features(spark, sf_dir).where("fold = 0")
    assert {r.n for r in got.values()} == {test.count()}
    spread = test.agg(F.stddev_pop("fat")).first()[0]
    assert all(got[m, "fat"].rmse < spread for m in regress.REGRESSORS)


@pytest.mark.parametrize("name", ["embedding_grid", "lexicon_counts", "random_candidates", "registry_counts"])
def test_reads_a_given_table(spark, sf_dir, name):
    df = QUERIES[name](spark, sf_dir)
    assert df.inputFiles() and df.count() > 0


def test_candidates_with_their_rows(spark, sf_dir):
    n = spark.read.parquet(f"{sf_dir}/orders.parquet").count()
    got = QUERIES["random_candidates"](spark, sf_dir).collect()
    assert len(got) == 50 and len({(r.trees, r.depth, r.hidden) for r in got}) == 10
    assert {r.train + r.valid for r in got} == {n} and sum(r.valid for r in got) == 10 * n


def test_lexicon_uses(spark, tmp_path):
    """Words and phrases of the dictionaries in documents, by hand."""
    from pantry.plans import extraction

    two = next(p for v in extraction._PHRASES.values() for p in v if " " in p)
    spark.createDataFrame([(1, f"cup of {two} cup"), (2, "Cup cups"), (3, None)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.dictionary: (r.n, r.uses) for r in QUERIES["lexicon_counts"](spark, str(tmp_path)).collect()}
    for name, v in extraction._PHRASES.items():
        words = f"cup of {two} cup".split(" ")
        want = sum(words[i : i + len(p.split(" "))] == p.split(" ") for p in v for i in range(len(words)))
        assert got[name] == (len(v), want)


def test_settings_from_sums_by_food(spark, monkeypatch):
    """Many settings over few foods: one scan's sums by food give the statistics and measures of each setting."""
    from pantry.operators import experiment
    from pantry.operators.nutrients import TARGETS

    rng = np.random.default_rng(4)
    data = []
    for i in range(300):
        n = int(rng.integers(1, 5))
        data.append((i, i % 3, [int(x) for x in rng.integers(-1, 5, n)], [float(x) for x in rng.random(n) + 0.1], *(float(x) for x in rng.random(5) * 9)))
    df = spark.createDataFrame(data, "recipe_id long, fold int, ids array<int>, grams array<double>, " + ", ".join(f"{t} double" for t in TARGETS)).repartition(2)
    vectors = {f"s{k}": rng.normal(size=(6, 4)) for k in range(9)}
    assert experiment._few_foods(vectors) and not experiment._few_foods({"s0": vectors["s0"]})

    def all_of():
        stats = experiment.statistics(df, vectors, ("dh", "avg"))
        models = [experiment.Model(f"{s}|{k}", s, k, experiment.searched(stats[s, k])) for s in vectors for k in ("dh", "avg")]
        models.append(experiment.Model("mean", None, "", experiment.constants(stats["s0", "dh"], list(stats["s0", "dh"]), {"": list(stats["s0", "dh"])})))
        got = {(r.model, r.cell, r.target): (r.n, r.hits, r.squared, r.absolute) for r in experiment.measure(df, vectors, models).collect()}
        return stats, got

    stats, got = all_of()
    monkeypatch.setattr(experiment, "_few_foods", lambda v: False)
    plain, want = all_of()
    assert all(np.allclose(stats[k][c].m, plain[k][c].m) for k in plain for c in plain[k])
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k]) for k in want)


def test_grid_has_every_setting(spark, sf_dir):
    """The query gives all settings, not those of the least dimension."""
    from pantry.operators import corpora
    from pantry.operators.nutrients import TARGETS

    got = QUERIES["grid_accuracy"](spark, sf_dir).where("dh is not null and no_dh is not null").collect()
    assert len(got) == 610 and {(r.setting, r.target) for r in got} == {(s.name, t) for s in corpora.GRID for t in TARGETS}


def test_measure_in_loads(spark, monkeypatch):
    """Vectors beyond a broadcast go in loads of models; every model is measured once, as in one scan."""
    from pantry.operators import experiment
    from pantry.operators.nutrients import TARGETS

    rng = np.random.default_rng(8)
    data = [(i % 2, [int(x) for x in rng.integers(0, 40_000, 3)], [1.0, 2.0, 3.0], *(float(x) for x in rng.random(5) * 9)) for i in range(40)]
    df = spark.createDataFrame(data, "fold int, ids array<int>, grams array<double>, " + ", ".join(f"{t} double" for t in TARGETS))
    vectors = {f"s{k}": rng.normal(size=(40_001, 2)) for k in range(3)}  # 0.6 MB each
    cells = lambda: {c: (rng.normal(size=5), rng.normal(size=(2, 5))) for c in "01"}
    models = [experiment.Model(f"{s}|{k}", s, k, cells()) for s in vectors for k in ("dh", "avg")] + [experiment.Model("mean", None, "", cells())]
    read = lambda: sorted(tuple(r) for r in experiment.measure(df, vectors, models).collect())
    want = read()
    monkeypatch.setattr(experiment, "MOST_MB", 1)
    assert [len(x) for x in experiment._loads(models, vectors)] == [2, 2, 3]
    got = read()
    assert [r[:4] for r in got] == [r[:4] for r in want] and len(got) == 70 and np.allclose([r[4:] for r in got], [r[4:] for r in want])


def test_keep_one_goes_through_fingerprints(spark, monkeypatch):
    """The pipeline's near-duplicates are linked by fingerprints, then verified: a linked pair under the similarity stays."""
    from pantry.llm import simhash

    words = [f"w{i}" for i in range(200)]
    texts = {1: words, 2: words, 3: [f"u{i}" for i in range(50)], 4: [f"t{i}" for i in range(60)]}
    df = spark.createDataFrame([(i, ("  " if i == 2 else " ").join(t)) for i, t in texts.items()], "doc_id long, text string")
    named = df.withColumnRenamed("doc_id", "node")
    assert [tuple(r) for r in simhash.candidate_links(named).collect()] in ([(1, 2)], [(2, 1)])
    made = []
    real = simhash.candidate_links
    monkeypatch.setattr(simhash, "candidate_links", lambda *a: made.append(1) or real(*a).union(spark.createDataFrame([(3, 4)], "a long, b long")))
    assert {r.doc_id for r in simhash.keep_one(df).collect()} == {1, 3, 4} and made
