"""Queries: linking, weights and nutrients, vectors, merges, regressions, measures and workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pantry.functions import bands
from pantry.functions import similarity as sim
from pantry.operators import embed, linking, merge, nutrients, regress, vocab
from pantry.operators.nutrients import TARGETS
from pantry.plans import render, views
from pantry.plans.truth import FOLD, ITEMS, RECIPES, WEIGHED, linked
from pantry.session import materialize, table
from pantry.sources import adapters

Q, O = {}, {}


def query(sql: str | None = None, name: str | None = None):
    """Register a query, and its SQL if it has one."""

    def keep(f):
        key = name or f.__name__
        Q[key] = f
        if sql:
            O[key] = sql
        return f

    return keep


# linking ------------------------------------------------------------------------------------------


def _pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linking.food_classes(views.foods(spark, sf_dir)).crossJoin(linking.item_classes(views.items(spark, sf_dir)))


def _summed(name: str, value, sql: str) -> None:
    """An equation over all pairs of names and item classes, summed a food."""
    Q[name] = lambda spark, sf_dir: _pairs(spark, sf_dir).withColumn("x", value()).groupBy("key").agg(F.count("*").alias("n"), F.count("x").alias("known"), F.round(F.sum("x"), 4).alias("total"))
    O[name] = f"WITH {ITEMS} SELECT key, count(*) AS n, count({sql}) AS known, round(sum({sql}), 4) AS total FROM pr GROUP BY key"


_summed("eq1", lambda: sim.jaccard(F.col("nouns"), F.col("nouns_j")), "e1")
_summed("eq2_symmetric", lambda: linking._other("symmetric"), "e2")
_summed("eq2_printed", lambda: linking._other("as_printed"), "e2p")
_summed("eq3", lambda: linking.index(), "e1 * e2")


@query(f"WITH {ITEMS} SELECT DISTINCT array_to_string(toks, ' ') AS key, array_to_string(list_sort(ns), ' ') AS nouns, array_to_string(list_sort(adjs), ' ') AS adjectives FROM fd")
def pos_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = linking.food_classes(views.foods(spark, sf_dir))
    return f.select("key", F.array_join("nouns", " ").alias("nouns"), F.array_join("adjectives", " ").alias("adjectives"))


@query(f"WITH {ITEMS} SELECT array_to_string(toks, ' ') AS key, item_id, array_to_string(ns, ' ') AS nouns FROM it")
def fcdb_prepared(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linking.item_classes(views.items(spark, sf_dir)).select(F.col("key_j").alias("key"), "item_id", F.array_join("nouns_j", " ").alias("nouns"))


def _tier(name: str, tier: int, where: str, score: str, tier4: str = "relaxed") -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        f, i = materialize(linking.food_classes(views.foods(spark, sf_dir)), "foods"), materialize(linking.item_classes(views.items(spark, sf_dir)), "items")
        pairs, score_ = linking.candidates(f, i, tier, tier4=tier4)
        return linking._best(pairs, tier, score_).select("key", "item_id", F.round("index", 6).alias("index"), "dist")

    Q[name] = run
    O[name] = f"WITH {ITEMS} SELECT key, item_id, round(idx, 6) AS index, dist FROM {linked(where, score, '0')}"


_tier("tier1", 1, "ftoks = toks", "coalesce(idx, 0)")
_tier("tier2", 2, "list_sort(fns) = ns AND idx > 0", "idx")
_tier("tier3", 3, "idx > 0", "idx")
_tier("tier4_printed", 4, "shares AND idx > 0", "idx", "as_printed")
_tier("tier4_relaxed", 4, "shares", "e2")
_tier("tier5", 5, "dist < flen", "0")


def _link(spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    return linking.link_foods(views.foods(spark, sf_dir), views.items(spark, sf_dir), **options)


_FULL = f"WITH {ITEMS}, l AS (SELECT DISTINCT array_to_string(toks, ' ') AS key FROM fd), m AS (SELECT l.key, x.item_id, x.tier, x.idx, x.dist FROM l LEFT JOIN {linked()} x USING (key))"


@query(f"{_FULL} SELECT key, item_id, tier::INT AS tier, round(idx, 6) AS index, dist FROM m")
def link_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _link(spark, sf_dir).withColumn("index", F.round("index", 6))


@query(f"{_FULL} SELECT tier::INT AS tier, count(*) AS n FROM m GROUP BY tier")
def link_tier_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _link(spark, sf_dir).groupBy("tier").agg(F.count("*").alias("n"))


@query(f"WITH {ITEMS} SELECT key, item_id, tier::INT AS tier, round(idx, 6) AS index, dist FROM {linked()}")
def link_brute(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linking.link_bruteforce(views.foods(spark, sf_dir), views.items(spark, sf_dir)).withColumn("index", F.round("index", 6))


@query(f"WITH {ITEMS} SELECT key, item_id, round(e1, 6) AS index, dist FROM (SELECT *, row_number() OVER (PARTITION BY key ORDER BY -e1, dist, item_id) AS k FROM pi WHERE e1 > 0) WHERE k = 1")
def link_noun_only(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linking.link_noun_only(views.foods(spark, sf_dir), views.items(spark, sf_dir)).withColumn("index", F.round("index", 6))


@query(f"WITH {ITEMS} SELECT 0 AS tier, count(*) AS pairs FROM pi UNION ALL SELECT 1, count(*) FROM pi WHERE ftoks = toks UNION ALL SELECT 2, count(*) FROM pi WHERE list_sort(fns) = ns AND idx > 0 UNION ALL SELECT 3, sum(len(list_intersect(fns, ns)))::BIGINT FROM pi UNION ALL SELECT 4, sum(len(list_intersect(ftoks, toks)))::BIGINT FROM pi UNION ALL SELECT 5, count(*) FROM pi WHERE dist < flen")
def link_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linking.link_cost(views.foods(spark, sf_dir), views.items(spark, sf_dir))


@query(f"{_FULL} SELECT count(*) AS foods, count(item_id) AS linked, count(item_id)::DOUBLE / count(*) AS share FROM m")
def link_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _link(spark, sf_dir).agg(F.count("*").alias("foods"), F.count("item_id").alias("linked"), F.avg(F.col("item_id").isNotNull().cast("double")).alias("share"))


_REORDER = "CASE WHEN shares THEN 1 WHEN ftoks = toks THEN 2 WHEN dist < flen THEN 3 END"


@query(f"WITH {ITEMS}, o AS (SELECT key, item_id, {_REORDER} AS k, CASE WHEN shares THEN e2 ELSE 0 END AS sc, dist FROM pi WHERE {_REORDER} IS NOT NULL) SELECT key, item_id, (CASE k WHEN 1 THEN 4 WHEN 2 THEN 1 ELSE 5 END)::INT AS tier FROM (SELECT *, row_number() OVER (PARTITION BY key ORDER BY k, -sc, dist, item_id) AS r FROM o) WHERE r = 1")
def link_order_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _link(spark, sf_dir, order=(4, 1, 5)).where("item_id is not null").select("key", "item_id", "tier")


# weights and nutrients ----------------------------------------------------------------------------


@query(f"WITH {WEIGHED} SELECT unit, count(*) AS n, round(sum(grams), 2) AS grams FROM g WHERE unit IS NOT NULL GROUP BY unit")
def grams_unit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.weighed(spark, sf_dir).where("unit is not null").groupBy("unit").agg(F.count("*").alias("n"), F.round(F.sum("grams"), 2).alias("grams"))


@query(f"WITH {WEIGHED} SELECT line_key, part_no, grams FROM g WHERE unit IS NULL")
def grams_portion(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.weighed(spark, sf_dir).where("unit is null").select("line_key", "part_no", "grams")


@query(f"WITH {WEIGHED} SELECT line_key, part_no, round(100 * grams / sum(grams) OVER (PARTITION BY recipe_id) + 1e-9, 4) AS share FROM g")
def grams_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nutrients.shares(views.weighed(spark, sf_dir)).select("line_key", "part_no", F.round(F.col("share") + 1e-9, 4).alias("share"))


@query(f"WITH {RECIPES} SELECT recipe_id, n_lines, {', '.join(f'round({t} + 1e-9, 4) AS {t}' for t in TARGETS)} FROM r")
def recipe_nutrients(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.recipes(spark, sf_dir).select("recipe_id", "n_lines", *(F.round(F.col(t) + 1e-9, 4).alias(t) for t in TARGETS))


@query(f"WITH {WEIGHED} SELECT line_key, part_no, item_id, tier::INT AS tier, {', '.join(TARGETS)} FROM g")
def ingredient_nutrients(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.weighed(spark, sf_dir).select("line_key", "part_no", "item_id", "tier", *TARGETS)


@query("SELECT reason, count(*) AS recipes FROM (SELECT CASE WHEN l_orderkey IS NULL THEN 'no lines' ELSE 'kept' END AS reason FROM orders LEFT JOIN (SELECT DISTINCT l_orderkey FROM lineitem) ON o_orderkey = l_orderkey) GROUP BY reason")
def recipe_losses(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("recipe_id"))
    return nutrients.losses(orders, views.weighed(spark, sf_dir))


@query(f"WITH {RECIPES} SELECT recipe_id, round(2.5 * sodium + 1e-9, 4) AS salt FROM r")
def salt(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.recipes(spark, sf_dir).select("recipe_id", F.round(bands.salt(F.col("sodium")) + 1e-9, 4).alias("salt"))


_OFF = {n: f"abs({n} - ({e})::DOUBLE) / ({e})::DOUBLE" for n, e in render.OWN.items()}


@query(f"WITH {RECIPES} SELECT corpus, count(*) AS n, {', '.join(f'round(avg({e}), 6) AS {n}_error' for n, e in _OFF.items())} FROM r WHERE corpus IN ('A', 'C', 'E') GROUP BY corpus")
def nutrient_reconcile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Collections with nutrients of their own against those that the links give: the mean relative difference."""
    r = views.recipes(spark, sf_dir)
    e = lambda n: F.round(F.avg(F.abs(F.col(n) - F.col("own")[n]) / F.col("own")[n]), 6).alias(f"{n}_error")
    own = None
    for c in "ACE":
        h = adapters.headers(render.collection(spark, sf_dir, c), c).select("recipe_id", F.col("nutrients").alias("own"))
        own = h if own is None else own.unionByName(h)
    return r.join(own, "recipe_id").groupBy("corpus").agg(F.count("*").alias("n"), *(e(n) for n in render.OWN))


@query(f"SELECT o_orderkey AS recipe_id, round(({render.OWN['fat'].replace('recipe_id', 'o_orderkey')})::DOUBLE, 4) AS fat, round(({render.OWN['sodium'].replace('recipe_id', 'o_orderkey')})::DOUBLE, 4) AS sodium, ({render.FILLERS} * (o_orderkey % 7) + {sum(range(render.FILLERS))} + o_orderkey % 23 + 3)::DOUBLE AS rest FROM orders WHERE o_orderkey % 6 = 4 AND o_orderkey IN (SELECT l_orderkey FROM lineitem)")
def nutrient_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The wide map of 94 nutrients: to rows, and back to the columns that are wanted."""
    out = adapters.long_nutrients(render.collection(spark, sf_dir, "E"), ("fat", "sodium"))
    return out.select("recipe_id", *(F.round(c, 4).alias(c) for c in ("fat", "sodium", "rest")))


# vocabulary and vectors ---------------------------------------------------------------------------

_TOKENS = "tk AS (SELECT DISTINCT p_name, string_split(p_name, ' ') || string_split(lower(p_type), ' ') AS w FROM part)"


def food_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(food_key, tokens): names with their type words as context."""
    p = table(spark, sf_dir, "part").select("p_name", F.lower("p_type").alias("k")).distinct()
    return p.select(F.concat_ws("|", "p_name", "k").alias("food_key"), F.concat(F.split("p_name", " "), F.split("k", " ")).alias("tokens"))


@query(f"WITH {_TOKENS} SELECT word, n, row_number() OVER (ORDER BY n DESC, word) - 1 AS word_id FROM (SELECT unnest(w) AS word, count(*) AS n FROM tk GROUP BY 1)", "vocab")
def vocab_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vocab.vocabulary(food_tokens(spark, sf_dir))


for _w in (2, 3, 5, 10):
    Q[f"cooc_w{_w}"] = lambda spark, sf_dir, w=_w: vocab.cooccurrence(food_tokens(spark, sf_dir), w).withColumn("weight", F.round("weight", 4))
    O[f"cooc_w{_w}"] = f"WITH {_TOKENS}, p AS (SELECT w, unnest(range(1, len(w) + 1)) AS i FROM tk), q AS (SELECT w[i] AS w1, w[j] AS w2, abs(i - j) AS d FROM p, range(1, 40) AS x(j) WHERE j <= len(w) AND i <> j AND abs(i - j) <= {_w}) SELECT w1, w2, round(sum(1.0::DOUBLE / d), 4) AS weight FROM q GROUP BY ALL"


@query()
def w2v_sg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed.word2vec_sg(food_tokens(spark, sf_dir), 8, 2)


@query()
def w2v_cbow(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed.negative_sampling(food_tokens(spark, sf_dir), 8, 2, "cbow", epochs=2)[0]


@query()
def d2v_dm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed.negative_sampling(food_tokens(spark, sf_dir), 8, 2, "dm", epochs=2)[1].select("food_key", "vec")


@query()
def d2v_dbow(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed.negative_sampling(food_tokens(spark, sf_dir), 8, 2, "dbow", epochs=2)[1].select("food_key", "vec")


@query()
def d2v_combine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line vectors of a document model beside sums of its word vectors."""
    df = food_tokens(spark, sf_dir)
    words, lines, _ = embed.negative_sampling(df, 8, 2, "dm", epochs=1)
    return lines.select("food_key", F.col("vec").alias("direct")).join(merge.combine_words(df, words, 8, "sum").withColumnRenamed("vec", "sum"), "food_key")


@query()
def glove_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    losses = embed.glove(food_tokens(spark, sf_dir), 8, 2, rounds=2)[1]
    return spark.createDataFrame([(i, float(x)) for i, x in enumerate(losses)], "turn int, loss double")


@query()
def layer_provider(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed.LayerProvider().transform(food_tokens(spark, sf_dir))


_L = "SELECT vec_id, embedding AS e FROM embeddings"


@query(f"WITH l AS ({_L}) SELECT vec_id, round(e[1]::DOUBLE + e[17] + e[33] + e[49], 4) AS first, round(list_sum(list_transform(e, lambda x: x::DOUBLE)), 4) AS total, 16 AS width FROM l")
def layers_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = table(spark, sf_dir, "embeddings").select("vec_id", merge.last_layers(merge.layer_slices(F.col("embedding"))).alias("v"))
    return v.select("vec_id", F.round(F.get("v", F.lit(0)), 4).alias("first"), F.round(F.aggregate("v", F.lit(0.0), lambda a, x: a + x), 4).alias("total"), F.size("v").alias("width"))


@query(f"WITH l AS ({_L}) SELECT vec_id, round(e[1]::DOUBLE, 4) AS first, round(e[64]::DOUBLE, 4) AS last, 64 AS width FROM l")
def layers_concat(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = table(spark, sf_dir, "embeddings").select("vec_id", merge.last_layers(merge.layer_slices(F.col("embedding")), "concat").alias("v"))
    at = lambda i: F.round(F.get("v", F.lit(i)).cast("double"), 4)
    return v.select("vec_id", at(0).alias("first"), at(63).alias("last"), F.size("v").alias("width"))


_D, _W = "(50), (100), (200)", "(2), (3), (5), (10)"
_GRID = f"""(SELECT 'word2vec' AS algorithm, arch AS architecture, d AS dim, w AS window_, c AS combine FROM (VALUES ('cbow'), ('sg')) a(arch), (VALUES {_D}) b(d), (VALUES {_W}) e(w), (VALUES ('sum'), ('avg')) f(c)
UNION ALL SELECT 'glove', '', d, w, c FROM (VALUES {_D}) b(d), (VALUES {_W}) e(w), (VALUES ('sum'), ('avg')) f(c)
UNION ALL SELECT 'doc2vec', arch, d, w, c FROM (VALUES ('dm'), ('dbow')) a(arch), (VALUES {_D}) b(d), (VALUES {_W}) e(w), (VALUES ('sum'), ('avg')) f(c)
UNION ALL SELECT 'bert', '', 0, 0, c FROM (VALUES ('sum'), ('concat')) f(c))"""


_SIZED = "tk AS (SELECT len(string_split(p_name, ' ')) + len(string_split(p_type, ' ')) AS k FROM part), ct AS (SELECT k, count(*) AS m FROM tk GROUP BY k)"


@query(f"WITH {_SIZED} SELECT g.*, (SELECT coalesce(sum(m), 0) FROM ct)::BIGINT AS lines, (SELECT coalesce(sum(m * list_sum(list_transform(range(1, k), lambda d: CASE WHEN d <= window_ THEN 2 * (k - d) ELSE 0 END))), 0) FROM ct)::BIGINT AS pairs FROM {_GRID} g")
def embedding_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every setting with the lines that it trains on and the pairs of words within its window."""
    grid = spark.createDataFrame(embed.embedding_grid(), "algorithm string, architecture string, dim int, window_ int, combine string")
    p = table(spark, sf_dir, "part").select((F.size(F.split("p_name", " ")) + F.size(F.split("p_type", " "))).alias("k")).groupBy("k").agg(F.count("*").alias("m"))
    # a line of k words has 2 (k - d) pairs at distance d
    at = lambda w: F.aggregate(F.sequence(F.lit(1), F.greatest("k", F.lit(1))), F.lit(0).cast("long"), lambda a, d: a + F.when(d <= w, 2 * (F.col("k") - d)).otherwise(0))
    windows = (0, *embed.WINDOWS)
    sizes = p.agg(F.coalesce(F.sum("m"), F.lit(0)).alias("lines"), *(F.coalesce(F.sum(F.col("m") * at(w)), F.lit(0)).alias(f"_{w}") for w in windows))
    sizes = sizes.select("lines", F.explode(F.array(*(F.struct(F.lit(w).alias("window_"), F.col(f"_{w}").alias("pairs")) for w in windows))).alias("_w")).select("lines", "_w.*")
    return grid.join(F.broadcast(sizes), "window_").select("algorithm", "architecture", "dim", "window_", "combine", "lines", "pairs")


_SIX = "(SELECT count(DISTINCT o_orderkey % 6) FROM orders)"


@query(f"SELECT algorithm, count(*) * 5 * {_SIX} AS models FROM {_GRID} GROUP BY algorithm UNION ALL SELECT 'all', count(*) * 5 * {_SIX} FROM {_GRID}")
def registry_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The models of the experiment; the six of the identity are the collections that the recipes belong to."""
    r = spark.createDataFrame(embed.embedding_grid(), "algorithm string, architecture string, dim int, window_ int, combine string")
    r = r.crossJoin(spark.createDataFrame([(t,) for t in TARGETS], "target string")).crossJoin(table(spark, sf_dir, "orders").select(render.corpus(F.col("o_orderkey")).alias("six")).distinct())
    return r.groupBy("algorithm").agg(F.count("*").alias("models")).union(r.agg(F.lit("all"), F.count("*")))


@query("WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings), p AS (SELECT a.vec_id AS query, b.vec_id, round(list_sum(list_transform(list_zip(a.v, b.v), lambda z: z[1] * z[2])) / (sqrt(list_sum(list_transform(a.v, lambda x: x * x))) * sqrt(list_sum(list_transform(b.v, lambda x: x * x)))), 6) AS cosine FROM e a, e b WHERE a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id) SELECT query, vec_id, cosine, rank::INT AS rank FROM (SELECT *, row_number() OVER (PARTITION BY query ORDER BY cosine DESC, vec_id) AS rank FROM p) WHERE rank <= 5")
def cosine_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "embeddings")
    return embed.nearest(e, e.where("vec_id % 50 = 0"), 5)


@query()
def lsh_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Approximate neighbours by random projections, with their recall against the exact ones."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH

    e = table(spark, sf_dir, "embeddings")
    v = embed.as_vectors(spark, e, "embedding")
    model = BucketedRandomProjectionLSH(inputCol="_vector", outputCol="h", bucketLength=2.0, numHashTables=8, seed=1).fit(v)
    near = model.approxSimilarityJoin(v.where("vec_id % 50 = 0"), v, 1.5, "d").select(F.col("datasetA.vec_id").alias("query"), F.col("datasetB.vec_id").alias("vec_id")).distinct()
    exact = embed.nearest(e, e.where("vec_id % 50 = 0"), 5).select("query", "vec_id")
    return exact.join(near.withColumn("found", F.lit(1)), ["query", "vec_id"], "left").groupBy("query").agg(F.avg(F.coalesce("found", F.lit(0))).alias("recall"))


# merges -------------------------------------------------------------------------------------------


def _vec_columns(df: DataFrame, key: str, vec: str = "vec") -> DataFrame:
    at = lambda i: F.round(F.get(F.col(vec), F.lit(i)).cast("double"), 4)
    total = F.round(F.aggregate(F.col(vec), F.lit(0.0), lambda a, x: a + x), 3)
    return df.select(key, at(0).alias("v0"), at(31).alias("v31"), at(63).alias("v63"), total.alias("total"))


def _merge_sql(weight: str, div: str, scale: int = 1) -> str:
    part = lambda x: f"{scale} * sum({weight} * {x}) / {div}"
    s = "list_sum(list_transform(embedding, lambda x: x::DOUBLE))"
    return f"WITH {WEIGHED} SELECT recipe_id, round({part('embedding[1]::DOUBLE')}, 4) AS v0, round({part('embedding[32]::DOUBLE')}, 4) AS v31, round({part('embedding[64]::DOUBLE')}, 4) AS v63, round({part(s)}, 3) AS total FROM g JOIN embeddings ON vec_id = idx GROUP BY recipe_id"


@query(_merge_sql("grams", "sum(grams)"))
def merge_domain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _vec_columns(merge.merge_domain(views.weighed(spark, sf_dir), views.vectors(spark, sf_dir), 64), "recipe_id")


@query(_merge_sql("grams", "sum(grams)", 100))
def merge_domain_100(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _vec_columns(merge.merge_domain(views.weighed(spark, sf_dir), views.vectors(spark, sf_dir), 64, scale="per100"), "recipe_id")


@query(_merge_sql("1", "1"))
def merge_plain_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _vec_columns(merge.merge_plain(views.weighed(spark, sf_dir), views.vectors(spark, sf_dir), 64, "sum"), "recipe_id")


@query(_merge_sql("1", "count(*)"))
def merge_plain_avg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _vec_columns(merge.merge_plain(views.weighed(spark, sf_dir), views.vectors(spark, sf_dir), 64, "avg"), "recipe_id")


def _word_sql(div: str) -> str:
    part = lambda i: f"round(sum(coalesce(embedding[{i}]::DOUBLE, 0)) / {div}, 4)"
    return f"WITH {_TOKENS}, v AS (SELECT word, row_number() OVER (ORDER BY n DESC, word) - 1 AS id FROM (SELECT unnest(w) AS word, count(*) AS n FROM tk GROUP BY 1)), x AS (SELECT DISTINCT p_name || '|' || lower(p_type) AS food_key, string_split(p_name, ' ') || string_split(lower(p_type), ' ') AS w FROM part), y AS (SELECT food_key, unnest(w) AS word FROM x) SELECT food_key, {part(1)} AS v0, {part(64)} AS v63 FROM y LEFT JOIN v USING (word) LEFT JOIN embeddings ON vec_id = id GROUP BY food_key"


def _combined(spark: SparkSession, sf_dir: str, how: str) -> DataFrame:
    df = food_tokens(spark, sf_dir)
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("word_id"), F.col("embedding").alias("vec"))
    words = vocab.vocabulary(df).join(e, "word_id").select("word", "vec")
    at = lambda i: F.round(F.get("vec", F.lit(i)), 4)
    return merge.combine_words(df, words, 64, how).select("food_key", at(0).alias("v0"), at(63).alias("v63"))


Q["words_sum"] = lambda spark, sf_dir: _combined(spark, sf_dir, "sum")
Q["words_avg"] = lambda spark, sf_dir: _combined(spark, sf_dir, "avg")
O["words_sum"], O["words_avg"] = _word_sql("1"), _word_sql("count(*)")
O["words_sum"] = O["words_sum"].replace("tk AS (SELECT DISTINCT p_name,", "tk AS (SELECT DISTINCT p_name, p_type,")
O["words_avg"] = O["words_avg"].replace("tk AS (SELECT DISTINCT p_name,", "tk AS (SELECT DISTINCT p_name, p_type,")


@query(f"WITH {WEIGHED} SELECT corpus, count(*) AS n, count(vec_id) AS known FROM g LEFT JOIN (SELECT vec_id FROM embeddings WHERE vec_id < 60) ON vec_id = idx GROUP BY corpus")
def oov_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    known = render.name_vectors(spark, sf_dir).where("name_idx < 60")
    return views.weighed(spark, sf_dir).select("corpus", "food_key").join(known, "food_key", "left").groupBy("corpus").agg(F.count("*").alias("n"), F.count("vec").alias("known"))


@query(f"WITH {RECIPES} SELECT corpus, count(*) AS recipes FROM r GROUP BY corpus UNION ALL SELECT 'all', count(*) FROM r UNION ALL SELECT 'listed', count(*) FROM orders")
def recipe_corpus_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = views.recipe_features(spark, sf_dir, 4)
    by = f.groupBy("corpus").agg(F.count("*").alias("recipes"))
    return by.union(f.agg(F.lit("all"), F.count("*"))).union(table(spark, sf_dir, "orders").agg(F.lit("listed"), F.count("*")))


# regressions, measures ----------------------------------------------------------------------------


@query(f"WITH {RECIPES} SELECT fold, count(*) AS n FROM r GROUP BY fold")
def fold_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.recipes(spark, sf_dir).groupBy("fold").agg(F.count("*").alias("n"))


_DH4 = f"{RECIPES}, m AS (SELECT recipe_id, " + ", ".join(f"sum(grams * embedding[{i}]::DOUBLE) / sum(grams) AS x{i}" for i in range(1, 5)) + " FROM g JOIN embeddings ON vec_id = idx GROUP BY recipe_id)"
_GRAM = " UNION ALL ".join(f"SELECT fold, {i} AS i, {j} AS j, round(sum({a} * {b}), 3) AS s FROM z GROUP BY fold" for i, a in enumerate(("1", "x1", "x2", "x3", "x4", "fat")) for j, b in enumerate(("1", "x1", "x2", "x3", "x4", "fat")) if i <= j)


@query(f"WITH {_DH4}, z AS (SELECT * FROM r JOIN m USING (recipe_id)) SELECT fold, i, j, s::DOUBLE AS s FROM ({_GRAM})")
def gram_fold(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = regress.gram(views.recipe_features(spark, sf_dir, 4), "dh", 4, ("fat",))
    cell = g.select("fold", F.posexplode("stats").alias("k", "s")).select("fold", F.floor(F.col("k") / 6).cast("int").alias("i"), (F.col("k") % 6).alias("j"), F.round("s", 3).alias("s"))
    return cell.where("i <= j")


@query(f"WITH {WEIGHED}, w AS (SELECT recipe_id, {FOLD} AS fold, food, sum(grams) AS x FROM g GROUP BY ALL), t AS (SELECT recipe_id, sum(x) AS all_ FROM w GROUP BY ALL), s AS (SELECT w.recipe_id, fold, food, x / all_ AS w FROM w JOIN t USING (recipe_id)) SELECT a.fold, count(*) AS n, round(sum(a.w * b.w), 4) AS moment, round(sum(a.w * b.w) FILTER (WHERE a.food = b.food), 4) AS diagonal FROM s a JOIN s b USING (recipe_id) GROUP BY a.fold")
def coshare(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = nutrients.shares(views.weighed(spark, sf_dir)).withColumn("share", F.col("share") / 100).withColumn("fold", bands.fold(F.col("recipe_id")))
    m = regress.coshare_moments(lines)
    n = lines.groupBy("recipe_id", "fold").agg(F.countDistinct("food_key").alias("k")).groupBy("fold").agg(F.sum(F.col("k") * F.col("k")).alias("n"))
    sums = m.groupBy("fold").agg(F.round(F.sum("moment"), 4).alias("moment"), F.round(F.sum(F.when(F.col("food_i") == F.col("food_j"), F.col("moment"))), 4).alias("diagonal"))
    return n.join(sums, "fold")


@query(f"WITH {_DH4}, z AS (SELECT * FROM r JOIN m USING (recipe_id)) SELECT round(regr_slope(fat, x1), 4) AS slope, round(regr_intercept(fat, x1), 4) AS intercept FROM z")
def linear_coef(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = views.recipe_features(spark, sf_dir, 1)
    b0, b = regress.fit_linear(regress.total(regress.collect_stats(regress.gram(f, "dh", 1, ("fat",)), 1)), 0)
    return spark.createDataFrame([(round(float(b[0]), 4), round(b0, 4))], "slope double, intercept double")


_BAND = {
    t: "CASE " + " ".join(f"WHEN {t} {'<' if a is not None else '<='} {end} THEN {a if a is not None else f'abs({t}) * {s}'}" for end, a, s in rows[:-1]) + f" ELSE {rows[-1][1] if rows[-1][1] is not None else f'abs({t}) * {rows[-1][2]}'} END"
    for t, rows in bands.BANDS.items()
}


def _constant_sql(agg: str) -> str:
    guess = ", ".join(f"{agg}(r.{t}) AS h_{t}" for t in TARGETS)
    hits = " UNION ALL ".join(f"SELECT '{t}' AS target, fold, avg(CASE WHEN abs({t} - h_{t}) <= {_BAND[t]} THEN 100.0 ELSE 0 END) AS a FROM z GROUP BY fold" for t in TARGETS)
    return f"WITH {RECIPES}, h AS (SELECT k.fold, {guess} FROM r, (SELECT DISTINCT fold FROM r) k WHERE r.fold <> k.fold GROUP BY k.fold), z AS (SELECT * FROM r JOIN h USING (fold)) SELECT target, round(avg(a), 4) AS accuracy FROM ({hits}) GROUP BY target"


def _constant(spark: SparkSession, sf_dir: str, how: str) -> DataFrame:
    return regress.average_accuracy(regress.with_constant(views.recipes(spark, sf_dir).select("fold", *TARGETS), how, exact=True)).select("target", F.round("accuracy", 4).alias("accuracy"))


Q["accuracy_mean"], O["accuracy_mean"] = lambda spark, sf_dir: _constant(spark, sf_dir, "mean"), _constant_sql("avg")
Q["accuracy_median"], O["accuracy_median"] = lambda spark, sf_dir: _constant(spark, sf_dir, "median"), _constant_sql("median")


def _baseline_sql(agg: str) -> str:
    return f"WITH {RECIPES} SELECT k.fold, {', '.join(f'round({agg}(r.{t}), 4) AS {t}' for t in TARGETS)} FROM r, (SELECT DISTINCT fold FROM r) k WHERE r.fold <> k.fold GROUP BY k.fold"


def _baseline(spark: SparkSession, sf_dir: str, how: str) -> DataFrame:
    return regress.with_constant(views.recipes(spark, sf_dir).select("fold", *TARGETS), how, exact=True).groupBy("fold").agg(*(F.round(F.max(f"hat_{t}"), 4).alias(t) for t in TARGETS))


Q["baseline_mean"], O["baseline_mean"] = lambda spark, sf_dir: _baseline(spark, sf_dir, "mean"), _baseline_sql("avg")
Q["baseline_median"], O["baseline_median"] = lambda spark, sf_dir: _baseline(spark, sf_dir, "median"), _baseline_sql("median")


def _shifted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A known prediction, off by a tenth and a bit: measures can be computed twice."""
    return views.recipes(spark, sf_dir).select("*", *((F.col(t) * 1.1 + 0.3).alias(f"hat_{t}") for t in TARGETS))


_HITS = " UNION ALL ".join(f"SELECT '{t}' AS target, fold, 100 * avg(CASE WHEN abs({t} - ({t} * 1.1 + 0.3)) <= {_BAND[t]} THEN 1.0 ELSE 0 END) AS a FROM r GROUP BY fold" for t in TARGETS)


@query(f"WITH {RECIPES} SELECT target, fold, round(a, 4) AS accuracy FROM ({_HITS})")
def accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = F.explode(F.array(*(F.struct(F.lit(t).alias("target"), bands.hit(t, F.col(t), F.col(f"hat_{t}")).alias("h")) for t in TARGETS)))
    return _shifted(spark, sf_dir).select("fold", rows.alias("e")).groupBy("e.target", "fold").agg(F.round(F.avg("e.h") * 100, 4).alias("accuracy"))


@query(f"WITH {RECIPES} SELECT target, round(avg(a), 4) AS accuracy FROM ({_HITS}) GROUP BY target")
def accuracy_avg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return regress.average_accuracy(_shifted(spark, sf_dir)).select("target", F.round("accuracy", 4).alias("accuracy"))


_ERR = " UNION ALL ".join(f"SELECT '{t}' AS target, round(sqrt(avg(power({t} * 0.1 + 0.3, 2))), 4) AS rmse, round(avg(abs({t} * 0.1 + 0.3)), 4) AS mae, round(1 - sum(power({t} * 0.1 + 0.3, 2)) / var_pop({t}) / count(*), 4) AS r2 FROM r" for t in TARGETS)


@query(f"WITH {RECIPES} {_ERR}")
def errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return regress.errors(_shifted(spark, sf_dir)).select("target", *(F.round(c, 4).alias(c) for c in ("rmse", "mae", "r2")))


@query(f"WITH {RECIPES} SELECT corpus, CASE WHEN round(fat, 6) <= 3 THEN 'low' WHEN round(fat, 6) <= 17.5 THEN 'medium' ELSE 'high' END AS fat_light, CASE WHEN round(2.5 * sodium, 6) <= 0.3 THEN 'low' WHEN round(2.5 * sodium, 6) <= 1.5 THEN 'medium' ELSE 'high' END AS salt_light, count(*) AS n FROM r GROUP BY ALL")
def traffic_light(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = views.recipes(spark, sf_dir)
    return r.groupBy("corpus", bands.traffic_light("fat", F.round("fat", 6)).alias("fat_light"), bands.traffic_light("salt", F.round(bands.salt(F.col("sodium")), 6)).alias("salt_light")).agg(F.count("*").alias("n"))


@query(f"WITH {RECIPES} SELECT (SELECT count(*) FROM orders) AS recipes, (SELECT count(*) FROM r) AS embedded, (SELECT count(*) FROM g) AS lines, (SELECT count(DISTINCT food) FROM g) AS foods, (SELECT count(*) FROM part) AS items, 3660::BIGINT AS models")
def pipeline_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = views.weighed(spark, sf_dir)
    one = lambda df, n: df.agg(F.count("*").alias(n))
    out = one(table(spark, sf_dir, "orders"), "recipes").crossJoin(one(views.recipes(spark, sf_dir), "embedded"))
    out = out.crossJoin(w.agg(F.count("*").alias("lines"), F.countDistinct("food").alias("foods"))).crossJoin(one(table(spark, sf_dir, "part"), "items"))
    return out.withColumn("models", F.lit(len(regress.registry())).cast("long"))
