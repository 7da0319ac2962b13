"""Linking, merges, solvers and measures: brute force, identities, known answers."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from pantry.functions import bands
from pantry.functions import similarity as sim
from pantry.operators import corpora, embed, experiment, linking, merge, regress
from pantry.operators.nutrients import TARGETS
from pantry.plans import methods, results, views
from pantry.session import materialize


def test_worked_similarity(spark):
    a, b = F.array(F.lit("ring")), F.array(F.lit("ring"), F.lit("set"))
    blue = F.array(F.lit("blue"))
    r = spark.range(1).select(sim.jaccard(a, b).alias("e1"), sim.smoothed(blue, blue).alias("e2"), sim.jaccard(F.array().cast("array<string>"), F.array().cast("array<string>")).alias("none")).first()
    assert (r.e1, r.none) == (0.5, None) and r.e2 == pytest.approx(2 / 3)


@pytest.mark.parametrize("tier4", ["relaxed", "as_printed"])
@pytest.mark.parametrize("eq2", ["symmetric", "as_printed"])
def test_cascade_equals_brute_force(spark, sf_dir, tier4, eq2):
    foods, items = views.foods(spark, sf_dir), views.items(spark, sf_dir)
    fast = {r.key: (r.item_id, r.tier) for r in linking.link_foods(foods, items, eq2, tier4).where("item_id is not null").collect()}
    slow = {r.key: (r.item_id, r.tier) for r in linking.link_bruteforce(foods, items, eq2, tier4).collect()}
    assert fast == slow and len(fast) > 50


def test_printed_fourth_tier_adds_nothing(spark, sf_dir):
    out = linking.link_foods(views.foods(spark, sf_dir), views.items(spark, sf_dir), tier4="as_printed")
    assert out.where("tier = 4").count() == 0


def test_nearest_by_edits_equals_all_pairs(spark):
    """Names near, far and of one letter: what common pieces cannot decide is compared in full."""
    import random

    r = random.Random(4)
    word = lambda n: "".join(r.choice("abc") for _ in range(n))
    foods = spark.createDataFrame([(word(r.randint(1, 9)),) for _ in range(60)], "food string")
    items = spark.createDataFrame([(i, word(r.randint(1, 9))) for i in range(50)], "item_id long, food string")
    f, i = linking.food_classes(foods), linking.item_classes(items)
    pairs, score = linking.candidates(f, i, 5)
    want = sorted(tuple(x) for x in linking._best(pairs, 5, score).select("key", "item_id", "dist").collect())
    assert sorted(tuple(x) for x in linking.nearest_by_edits(f, i).select("key", "item_id", "dist").collect()) == want


def test_linking_plans_no_product(spark, sf_dir):
    f, i = linking.food_classes(views.foods(spark, sf_dir)), linking.item_classes(views.items(spark, sf_dir))
    for tier in linking.TIERS:
        plan = linking.candidates(f, i, tier)[0]._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan and "NestedLoop" not in plan


@pytest.fixture(scope="module")
def features(spark, sf_dir):
    return materialize(views.recipe_features(spark, sf_dir, 8), "test")


@pytest.fixture(scope="module")
def stats(features):
    return regress.collect_stats(regress.gram(features, "dh", 8), 8)


def test_equal_grams_make_the_heuristic_an_average(spark, sf_dir):
    lines = views.weighed(spark, sf_dir).withColumn("grams", F.lit(7.0))
    out = merge.merge_all(lines, views.vectors(spark, sf_dir, 4), 4)
    assert out.where(F.exists(F.zip_with("dh", "plain_avg", lambda a, b: F.abs(a - b)), lambda x: x > 1e-9)).count() == 0


def test_wide_merge_equals_narrow(spark, sf_dir):
    lines = views.weighed(spark, sf_dir).join(views.vectors(spark, sf_dir, 8), "food_key")
    narrow = merge.weighted_sum(lines, "recipe_id", F.col("grams"), "vec", 8)
    wide = merge._wide_sum(lines.select("recipe_id", F.col("grams").alias("_w"), F.col("vec").alias("_v")), "recipe_id", 8).withColumnRenamed("vec", "w")
    assert narrow.join(wide, "recipe_id").where(F.exists(F.zip_with("vec", "w", lambda a, b: F.abs(a - b)), lambda x: x > 1e-6)).count() == 0


def test_merge_has_one_exchange_for_its_sums(spark, sf_dir):
    df = spark.createDataFrame([(1, 2.0, [1.0, 2.0])], "recipe_id long, grams double, vec array<double>")
    plan = merge.weighted_sum(df, "recipe_id", F.col("grams"), "vec", 2)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1


def test_gram_path_equals_least_squares(features, stats):
    rows = features.select("dh", "fat").collect()
    x, y = np.array([r.dh for r in rows]), np.array([r.fat for r in rows])
    want = np.linalg.lstsq(np.hstack([np.ones((len(x), 1)), x]), y, rcond=None)[0]
    b0, b = regress.fit_linear(regress.total(stats), 0)
    assert np.allclose([b0, *b], want, atol=1e-6)
    assert regress.total(stats).sse(0, b0, b) == pytest.approx(((y - b0 - x @ b) ** 2).sum(), rel=1e-6)


def test_lasso_meets_its_conditions(stats):
    s, lam = regress.total(stats), 0.05
    _, b = regress.fit_lasso(s, 0, lam)
    xx, xy, _, _ = s.centred(0)
    g = xy - xx @ b
    assert np.all(np.abs(g) <= lam + 1e-6) and np.allclose(g[b != 0], lam * np.sign(b[b != 0]), atol=1e-6)


def test_ridge_tends_to_least_squares(stats):
    s = regress.total(stats)
    assert np.allclose(regress.fit_ridge(s, 1, 1e-12)[1], regress.fit_linear(s, 1)[1], atol=1e-5)


def test_moments_give_the_gram_matrix(spark, sf_dir, stats):
    from pantry.operators import nutrients

    lines = nutrients.shares(views.weighed(spark, sf_dir)).withColumn("share", F.col("share") / 100).withColumn("fold", bands.fold(F.col("recipe_id")))
    vec = {r.food_key: np.array(r.vec, float) for r in views.vectors(spark, sf_dir, 8).collect()}
    got = np.zeros((8, 8))
    for r in regress.coshare_moments(lines).where("fold = 0").collect():
        got += r.moment * np.outer(vec[r.food_i], vec[r.food_j])
    assert np.allclose(got, stats[0].m[1:9, 1:9], atol=1e-6)


def test_predictions_need_no_vectors(spark, sf_dir):
    assert results.predict_by_food(spark, sf_dir).where(F.abs(F.col("hat") - F.col("direct")) > 1e-3).count() == 0


def test_published_order_of_methods(spark, sf_dir):
    """Extracted and linked lines, trained vectors, tuned models: the heuristic beats the plain merge and the constants,
    for every embedding and target on average over the collections."""
    t = results.accuracy_tables(spark, "/root/testdata/sf0.01")
    assert t.count() == 120
    for r in t.groupBy("embedding", "target").agg(*(F.avg(c).alias(c) for c in ("dh", "mean", "median", "no_dh"))).collect():
        assert r.dh > r.no_dh and r.dh > max(r.mean, r.median), r


def test_bands_widen_accuracy(spark, sf_dir):
    by = {}
    for r in results.band_ablation(spark, sf_dir).collect():
        by.setdefault(r.target, {})[r.scale] = r.accuracy
    assert all(v[0.5] <= v[1.0] <= v[2.0] for v in by.values())


def test_merging_collections_together_is_the_union_of_merges(spark, sf_dir):
    """Merges are linear in lines: six collections at once, or one by one."""
    lines, v = views.weighed(spark, sf_dir), views.vectors(spark, sf_dir, 4)
    whole = {(r.recipe_id): r.dh for r in merge.merge_all(lines, v, 4).collect()}
    apart = {r.recipe_id: r.dh for c in "ABCDEF" for r in merge.merge_all(lines.where(F.col("corpus") == c), v, 4).collect()}
    assert whole.keys() == apart.keys() and all(np.allclose(whole[k], apart[k]) for k in whole)


def test_extraction_feeds_the_recipes(spark, sf_dir):
    """Every line's food is linked, and the structured collection keeps its own quantities."""
    w = views.weighed(spark, sf_dir)
    assert w.where("item_id is null").count() == 0
    own = views.structured(spark, sf_dir).where("corpus = 'A'")
    a = w.where("corpus = 'A'")
    assert a.count() == own.count() and a.agg(F.sum("qty")).first() == own.agg(F.sum("qty")).first()


def test_one_scan_equals_merged_vectors(spark, sf_dir, features, stats):
    """Bags of foods give the same sums of products as vectors merged by Spark."""
    v = results.given(spark, sf_dir, 8)
    got = experiment.statistics(results.recipe_bags(spark, sf_dir), v, ("dh",), "fold")["given", "dh"]
    assert set(got) == {str(f) for f in stats}
    for f, s in stats.items():
        assert np.allclose(got[str(f)].m, s.m, rtol=1e-9, atol=1e-6)


def test_ridge_path_equals_ridge(stats):
    s = regress.total(stats)
    for lam in (1e-3, 1.0):
        b0, b = experiment.ridge_path(s, (lam,))[0]
        for i in range(len(TARGETS)):
            one = regress.fit_ridge(s, i, lam)
            assert np.allclose(b[:, i], one[1], atol=1e-6) and b0[i] == pytest.approx(one[0], abs=1e-6)
            assert experiment.squared_errors(s, b0, b)[i] == pytest.approx(s.sse(i, *one), rel=1e-6, abs=1e-6)


def test_medians_need_no_copies(spark, sf_dir):
    bags = results.recipe_bags(spark, sf_dir)
    t = bags.select("corpus", "fold", "fat").toPandas()
    for cell, (m, _) in experiment.medians(bags, exact=True).items():
        c, f = cell.split("|")
        assert m[0] == pytest.approx(t[(t.corpus == c) & (t.fold != int(f))].fat.median())


def test_settings_train_and_differ():
    tokens = [["blue", "ring"], ["red", "ring"], ["red", "rod", "set"], ["blue", "rod"], ["old", "rod", "set"]] * 3
    line = np.repeat(np.arange(len(tokens)), [len(t) for t in tokens])
    words = sorted({w for t in tokens for w in t})
    token = np.array([words.index(w) for t in tokens for w in t])
    for mode in ("sg", "cbow", "dm", "dbow"):
        losses = corpora._predictive(token, line, len(words), mode, 6, 2, 20, np.random.default_rng(0))[2]
        assert losses[-1] < losses[0], mode
    losses = corpora._glove(token, line, len(words), 6, 2, 60, np.random.default_rng(0))[1]
    assert losses[-1] < 0.2 * losses[0]
    one, again = (corpora.train(tokens, "word2vec", "sg", 6, 2) for _ in range(2))
    assert np.array_equal(one["sum"], again["sum"]) and np.allclose(one["sum"][0], 2 * one["avg"][0])
    assert len(corpora.GRID) == 122 and len({s.name for s in corpora.GRID}) == 122


def test_neighbours_stay_in_their_line():
    line = np.array([0, 0, 0, 1, 1])
    a, b = corpora.neighbours(line, 2)
    assert sorted(zip(a.tolist(), b.tolist())) == [(0, 1), (0, 2), (1, 0), (1, 2), (2, 0), (2, 1), (3, 4), (4, 3)]


def test_corpus_is_kept_and_read_by_setting(spark, tmp_path):
    df = spark.createDataFrame([("a", "word2vec", 2, "x", [1.0, 2.0]), ("b", "glove", 2, "x", [3.0, 4.0])], "setting string, algorithm string, dim int, food_key string, vec array<double>")
    corpora.write_corpus(df, str(tmp_path), 3)
    one = corpora.read_corpus(spark, str(tmp_path), 3, "b")
    assert [tuple(r) for r in one.select("food_key", "vec").collect()] == [("x", [3.0, 4.0])]
    assert "PartitionFilters: [isnotnull(setting" in one._jdf.queryExecution().executedPlan().toString()


def test_a_service_translates_distinct_texts_once(spark):
    from pantry.operators.translate import Service, translate

    def call(texts, lang):
        return [f"{lang}:{t.upper()}" for t in texts]

    df = spark.createDataFrame([(1, "hi", "xx"), (2, "hi", "xx"), (3, "hi", "en"), (4, None, "xx"), (5, "ho", None)], "i int, text string, lang string")
    got = {r.i: r.text for r in translate(df, Service(call, batch=1)).collect()}
    assert got == {1: "xx:HI", 2: "xx:HI", 3: "hi", 4: None, 5: "ho"}


def test_registry_identity():
    n = {}
    for algorithm, *_ in regress.registry():
        n[algorithm] = n.get(algorithm, 0) + 1
    assert n == {"word2vec": 1440, "glove": 720, "doc2vec": 1440, "bert": 60}


def test_losses_fall(spark, sf_dir):
    df = methods.food_tokens(spark, sf_dir)
    for mode in ("cbow", "dm", "dbow"):
        losses = embed.negative_sampling(df, 8, 2, mode, epochs=4)[2]
        assert losses[-1] < losses[0]
    losses = embed.glove(df, 8, 2, rounds=3)[1]
    assert all(b <= a + 1e-6 for a, b in zip(losses, losses[1:]))
    net = regress.Network("fat", 8, 0.01, (0,))
    mlp = results._networks(spark, sf_dir, [net], rounds=3, passes=2)[0]
    assert mlp[-1] < mlp[0]


def test_training_repeats(spark, sf_dir):
    df = methods.food_tokens(spark, sf_dir)
    a, b = ({r.word: tuple(r.vec) for r in embed.negative_sampling(df, 4, 2, "cbow", epochs=2)[0].collect()} for _ in range(2))
    assert a == b


def test_tolerance_ranges(spark):
    y = spark.createDataFrame([(5.0,), (10.0,), (40.0,), (41.0,)], "y double")
    assert [r[0] for r in y.select(bands.tolerance("fat", F.col("y"))).collect()] == pytest.approx([1.5, 2.0, 8.0, 8.0])


def test_global_rank(spark):
    from pantry.operators.relational import global_rank

    df = spark.range(500).select((F.col("id") * 7919 % 500).alias("v")).repartition(5)
    assert global_rank(df, [F.col("v").desc()], "at").where("at <> 499 - v").count() == 0


def test_filters_and_columns_reach_the_scan(spark, sf_dir):
    from pantry.plans.catalog import queries

    plan = queries()["filter_cmp"](spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(p_size), GreaterThan(p_size,10), LessThanOrEqual(p_size,30)]" in plan
    assert "p_retailprice" not in plan


def test_searches(spark, sf_dir):
    chosen = results.mlp_search(spark, sf_dir).collect()
    assert len(chosen) == 15 and all(r.rmse > 0 for r in chosen)
    assert results.nested_search(spark, sf_dir).count() == 25


@pytest.mark.parametrize("model", ["lasso", "tree", "mlp"])
def test_regressors_learn(spark, sf_dir, model):
    """Better than the spread of the target on a fold that neither the search nor the fit saw."""
    f = results._features(spark, sf_dir).where("fold = 0")
    got = results._tested(spark, sf_dir, model).where("target = 'fat'").agg(F.sqrt(F.avg((F.col("y") - F.col("hat")) ** 2)).alias("e"), F.count("*").alias("n")).first()
    assert got.n == f.count() and got.e < f.agg(F.stddev_pop("fat")).first()[0]


def test_nearest_in_blocks(spark, sf_dir):
    e = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    asked = e.where("vec_id % 50 = 0")
    rows = lambda most: sorted(tuple(r) for r in embed.nearest(e, asked, 3, most=most).collect())
    assert len(rows(10_000)) == 3 * asked.count()
    assert rows(4) == rows(10_000)


def test_lsh_recall(spark, sf_dir):
    got = {r["query"]: r["recall"] for r in methods.Q["lsh_topk"](spark, sf_dir).collect()}
    e = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    assert set(got) == {r.vec_id for r in e.where("vec_id % 50 = 0").collect()}
    assert sum(got.values()) / len(got) >= 0.9
