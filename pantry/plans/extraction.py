"""Queries: sources, preparation, units, quantities, clauses, the normalizer."""

from __future__ import annotations

import re
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pantry.functions import lexicons as lx
from pantry.functions import prep, rules
from pantry.operators import linking
from pantry.operators.normalize import normalize_counted, normalize_lines, recipe_lists, split_structured
from pantry.plans import render, views
from pantry.plans.truth import LINES
from pantry.session import shared_dir, table
from pantry.sources import adapters, formats

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


TRIPLE = ("line_key", "part_no", "qty", "unit", "food")


def _truth(where: str) -> str:
    return f"WITH {LINES} SELECT line_key, part_no, qty, unit, food FROM tw WHERE {where}"


def _by_template(name: str, *templates: int) -> None:
    """A rule's query: the lines whose template needs it, parsed; SQL has the numbers they were made of."""
    Q[name] = lambda spark, sf_dir: views.triples(spark, sf_dir, templates).select(*TRIPLE)
    O[name] = _truth(f"t IN ({', '.join(map(str, templates))})")


for _name, _templates in {
    "unit_dict": (0,), "unit_canonical": (0, 1, 3), "unit_absent": (4, 15), "unit_container": (2, 12), "unit_all": (0, 2, 11, 12, 19),
    "qty_mixed": (1,), "qty_single": (0, 16), "qty_words": (3, 4, 15, 17), "qty_absent": (7,), "qty_percent": (18,),
    "clause_and": (10,), "clause_plus": (6,), "clause_or_one": (8,), "clause_range": (5,), "clause_trigger": (9,),
    "multi_first": (13,), "multi_second": (14,), "food_rest": (0, 1, 4), "food_explained": (7, 16), "prep_article": (3, 15),
}.items():
    _by_template(_name, *_templates)

#: Literal texts for rules that the rendered names cannot reach: {q} is a part's size.
#: rule: [(text, [(quantity in SQL, unit, food)])]
EXT: dict[str, list[tuple[str, list[tuple[str, str | None, str]]]]] = {
    "unit_paired_clove": [("{q} cloves garlic", [("q", "clove", "garlic")])],
    "unit_paired_stick": [("{q} sticks butter", [("q", "stick", "butter")]), ("{q} cinnamon sticks", [("q", "stick", "cinnamon")])],
    "unit_paired_sprig": [("{q} sprigs of thyme", [("q", "sprig", "thyme")])],
    "unit_paired_link": [("{q} links sausage", [("q", "link", "sausage")])],
    "unit_paired_stalk": [("{q} stalks celery", [("q", "stalk", "celery")]), ("{q} stalks spring onion", [("q", "stalk", "spring onion")])],
    "unit_paired_sheet": [("{q} sheets gelatin", [("q", "sheet", "gelatin")]), ("{q} sheets of baking paper", [("q", None, "sheet baking paper")])],
    "unit_paired_cube": [("{q} cubes stock", [("q", "cube", "stock")])],
    "unit_paired_head": [("{q} heads lettuce", [("q", "head", "lettuce")])],
    "unit_kinds": [("{q} g salt", [("q", "g", "salt")]), ("{q} cups milk", [("q", "cup", "milk")]), ("{q} dashes salt", [("q", "dash", "salt")]), ("{q} jars honey", [("q", "jar", "honey")])],
    "qty_product": [("{q} 2 oz bars rice", [("q * 2", "oz", "bar rice")]), ("{q} 1.5 oz bars rice", [("q * 1.5", "oz", "bar rice")]), ("1.5 {q} oz bars rice", [("q * 1.5", "oz", "bar rice")]), ("1/2 {q} oz bars rice", [("q * 0.5", "oz", "bar rice")]), ("1/2 1/4 cup rice", [("0.125", "cup", "rice")]), ("1.5 2.5 cup rice", [("3.75", "cup", "rice")])],
    "qty_triple": [("{q} 8 1/2 oz bars rice", [("q * 8.5", "oz", "bar rice")])],
    "qty_bad": [("{q}/0 cup rice", [("NULL", "cup", "rice")])],
    "clause_and_ignored": [("pepper and oil", [("NULL", None, "pepper oil")]), ("{q} cups bread and butter", [("q", "cup", "bread butter")])],
    "clause_or_unit": [("butter or {q} tbsp oil or lard", [("q", "tbsp", "oil")])],
    "clause_or_first": [("{q} tbsp oil or 2 tsp lard or fat", [("q", "tbsp", "oil")])],
    "clause_or_assigned": [("pinch salt or {q} tsp lard or fat", [("q", "tsp", "lard")])],
    "clause_or_nounit": [("{q} eggs or lard or fat", [("q", None, "egg")])],
    "clause_combo": [("2-3 cups rice or barley plus {q} tbsp oil", [("2", "cup", "rice"), ("q", "tbsp", "oil")])],
    "multi_two_units": [("{q} oz 453 g rice", [("q", "oz", "rice")])],
    "multi_nounit": [("{q}.5 1/2 eggs", [("q + 0.5", None, "egg")])],
    "unit_phrases": [("{q} fl oz cream", [("q", "floz", "cream")]), ("{q} fluid ounces cream", [("q", "floz", "cream")]), ("{q} fl. oz. cream", [("q", "floz", "cream")]), ("{q} table spoons oil", [("q", "tbsp", "oil")]), ("{q} thumb-sized ginger", [("q", "thumb", "ginger")]), ("{q} lbss beef", [("q", "lb", "beef")])],
    "qty_large_words": [("one hundred grams rice", [("100", "g", "rice")]), ("two hundred and fifty g rice", [("250", "g", "rice")]), ("twenty-five oz rice", [("25", "oz", "rice")]), ("a hundred g rice", [("100", "g", "rice")])],
    "unit_container_first": [("1 container (250 grams) cottage cheese", [("250", "g", "cottage cheese")]), ("{q} cans (400 g) beans", [("q * 400", "g", "bean")])],
    "food_lemma": [("{q} cups molasses", [("q", "cup", "molasses")]), ("{q} cups hummus", [("q", "cup", "hummus")])],
    "food_branded": [("{q} cups M&M's candies", [("q", "cup", "m&m's candy")])],
}


def ext_lines(spark: SparkSession, sf_dir: str, rule: str) -> DataFrame:
    texts = F.array(*(F.lit(t) for t, _ in EXT[rule]))
    p = table(spark, sf_dir, "part").select("p_partkey", "p_size", F.posexplode(texts).alias("i", "_t"))
    return p.select("p_partkey", "i", F.replace("_t", F.lit("{q}"), F.col("p_size").cast("string")).alias("text"))


def _ext(rule: str) -> None:
    Q[rule] = lambda spark, sf_dir: normalize_lines(ext_lines(spark, sf_dir, rule)).select("p_partkey", "i", "part_no", "qty", "unit", "food")
    null = lambda v: "NULL" if v is None else "'" + v.replace("'", "''") + "'"
    rows = [f"SELECT p_partkey, {i}::INT AS i, {k}::INT AS part_no, ({x})::DOUBLE AS qty, {null(u)}::VARCHAR AS unit, {null(f)} AS food FROM p" for i, (_, got) in enumerate(EXT[rule]) for k, (x, u, f) in enumerate(got)]
    O[rule] = "WITH p AS (SELECT p_partkey, p_size AS q FROM part) " + " UNION ALL ".join(rows)


for _rule in EXT:
    _ext(_rule)


# sources ------------------------------------------------------------------------------------------


def _header(name: str) -> str:
    """SQL of a collection's recipes: what its adapter's header and lines must hold."""
    has = {c.split()[0] for c in re.split(r", (?=\w+ )", adapters.SCHEMAS[name])}
    given = lambda c, x: x if c in has else "NULL"
    nutrients = render.OWN if "nutrients" in has else {}
    own = lambda n: f"round(({nutrients[n]})::DOUBLE, 4)" if n in nutrients else "NULL::DOUBLE"
    names = {"E": 5 + render.FILLERS, "A": 5, "C": 3}.get(name)
    return f"""WITH {LINES} SELECT recipe_id, '{name}' AS corpus, {given('title', "'Recipe ' || recipe_id")} AS title, {given('url', "'https://recipes.example/' || recipe_id")} AS url,
        {given('instruction', "'Mix ' || count(*) || ' things.'")} AS instruction, {given('calories', 'any_value(o_totalprice)')}::DOUBLE AS calories,
        {own('fat')} AS fat, {own('protein')} AS protein, {own('sodium')} AS sodium, {names or 'NULL'}::INT AS nutrients, count(*) AS n_lines, {'count(qty)' if name == 'A' else '0'}::BIGINT AS n_given
        FROM tr JOIN orders ON o_orderkey = recipe_id WHERE corpus = '{name}' GROUP BY recipe_id"""


def _source(name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """The collection through its files: written as its source would have it, read with the declared schema, harmonized."""
        path = f"{shared_dir(spark)}/pantry-source-{name}-{uuid.uuid4().hex}"
        formats.write(render.collection(spark, sf_dir, name), path, "json")
        df = adapters.read(spark, path, name)
        lines = adapters.harmonize(df, name).groupBy("recipe_id").agg(F.count("*").alias("n_lines"), F.count("qty").alias("n_given"))
        own = lambda n: F.round(F.try_element_at("nutrients", F.lit(n)), 4).alias(n)
        head = adapters.headers(df, name).select("recipe_id", "corpus", "title", "url", "instruction", "calories", own("fat"), own("protein"), own("sodium"), F.when(F.col("nutrients").isNotNull(), F.size("nutrients")).alias("nutrients"))
        return head.join(lines, "recipe_id")

    return run


for _c in "ABCDEF":
    _key = "src_structured" if _c == "A" else f"src_raw_{_c.lower()}"
    Q[_key], O[_key] = _source(_c), _header(_c)


def harmonized(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The six collections in one shape; the structured one brings its columns instead of text."""
    a = views.structured(spark, sf_dir).where("corpus = 'A'").select("recipe_id", "corpus", "pos", "line_key", "qty", "unit", "food")
    return a.unionByName(render.raw_lines(spark, sf_dir), allowMissingColumns=True)


@query(f"WITH {LINES} SELECT corpus, count(*) AS n_lines, count(*) FILTER (WHERE corpus <> 'A') AS n_texts, count(DISTINCT recipe_id) AS n_recipes FROM tr GROUP BY corpus")
def harmonized_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return harmonized(spark, sf_dir).groupBy("corpus").agg(F.count("*").alias("n_lines"), F.count("text").alias("n_texts"), F.countDistinct("recipe_id").alias("n_recipes"))


@query("SELECT conv_id, turn, count(*) AS n_lines, sum(length(line))::BIGINT AS n_chars FROM (SELECT conv_id, turn, unnest(string_split(text, chr(10))) AS line FROM conversations) GROUP BY ALL")
def explode_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn", F.posexplode(F.split("text", "\n")).alias("pos", "line"))
    return c.groupBy("conv_id", "turn").agg(F.count("*").alias("n_lines"), F.sum(F.char_length("line")).alias("n_chars"))


@query(f"WITH {LINES} SELECT line_key, part_no, qty, unit, food FROM tw WHERE corpus IN ('B', 'E')")
def translate_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The two foreign collections, translated, then parsed: the English answer must come out."""
    raw = render.raw_lines(spark, sf_dir).where(F.col("corpus").isin("B", "E"))
    return normalize_lines(raw, translator=views.glossary(spark)).select(*TRIPLE)


@query("SELECT lang, lang <> 'en' AS needs, count(*) AS n FROM documents GROUP BY ALL")
def lang_gate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").groupBy("lang", (F.col("lang") != "en").alias("needs")).agg(F.count("*").alias("n"))


@query(f"WITH {LINES} SELECT array_to_string(list_sort(list_distinct(string_split(food, ' '))), ' ') AS food_key, count(*) AS n FROM tw GROUP BY 1")
def distinct_foods(spark: SparkSession, sf_dir: str) -> DataFrame:
    return normalize_counted(views.text_lines(spark, sf_dir)).groupBy("food_key").agg(F.sum("n").alias("n"))


_PARTS = "SELECT * FROM i WHERE item_id % 2 = 0 UNION ALL SELECT * FROM i WHERE item_id % 3 = 0 UNION ALL SELECT * FROM i"
_ITEM_TEXT = f"""i AS (SELECT p_partkey AS item_id, CASE WHEN n <= 1 THEN upper(noun[1]) || substr(noun, 2) || 's, ' || adj WHEN n <= 3 THEN adj || ' ' || noun || ' ' || p_size WHEN n <= 5 THEN adj || ' ' || noun || ' set' WHEN n = 6 THEN adj || ' fitting' ELSE adj || 'widgt' END AS text
    FROM (SELECT *, split_part(p_name, ' ', 1) AS adj, split_part(p_name, ' ', 2) AS noun, list_position({list(render.NOUN)!r}, split_part(p_name, ' ', 2)) - 1 AS n FROM part))"""


@query(f"WITH {_ITEM_TEXT}, u AS ({_PARTS}) SELECT (SELECT count(*) FROM u) AS n_before, count(*) AS n_after, sum(item_id)::BIGINT AS ids FROM (SELECT text, min(item_id) AS item_id FROM u GROUP BY text)")
def fcdb_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = render.fcdb_parts(spark, sf_dir)
    before = parts[0].select("item_id").union(parts[1].select("item_id")).union(parts[2].select("item_id")).agg(F.count("*").alias("n_before"))
    after = linking.build_fcdb(parts).agg(F.count("*").alias("n_after"), F.sum("item_id").alias("ids"))
    return before.crossJoin(after)


@query(f"WITH {LINES} SELECT recipe_id, count(*) AS n, string_agg(food || '|' || coalesce(unit, '-'), ';' ORDER BY pos, part_no, line_key) AS lines FROM tw WHERE corpus = 'C' GROUP BY recipe_id")
def recipe_lists_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = views.triples(spark, sf_dir).where("corpus = 'C'")
    line = F.struct("pos", "part_no", "line_key", F.concat(F.col("food"), F.lit("|"), F.coalesce("unit", F.lit("-"))).alias("s"))
    # ties of (pos, line_key) between parts are settled by part, as in SQL
    got = df.groupBy("recipe_id").agg(F.count("*").alias("n"), F.array_sort(F.collect_list(line)).alias("l"))
    return got.select("recipe_id", "n", F.array_join(F.transform("l", lambda x: x["s"]), ";").alias("lines"))


Q["recipe_lists"], O["recipe_lists"] = Q.pop("recipe_lists_query"), O.pop("recipe_lists_query")


@query(f"WITH {LINES} SELECT recipe_id, len(l) AS n, l[1].food AS first_food, l[-1].unit AS last_unit, list_sum(list_transform(l, lambda x: x.qty)) AS qty FROM (SELECT recipe_id, list({{'food': food, 'unit': unit, 'qty': qty}} ORDER BY pos, part_no, qty, unit NULLS FIRST, food) AS l FROM tw WHERE t IN (0, 6) GROUP BY recipe_id)")
def recipe_structs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A recipe's aligned list: names and quantities stay together whatever is asked of it."""
    l = recipe_lists(views.triples(spark, sf_dir, (0, 6)))  # noqa: E741
    total = F.aggregate("lines", F.lit(0.0), lambda a, x: a + x["qty"])
    return l.select("recipe_id", F.size("lines").cast("long").alias("n"), F.get("lines", F.lit(0))["food"].alias("first_food"), F.element_at("lines", -1)["unit"].alias("last_unit"), total.alias("qty"))


_PHRASES = {
    "units": [*lx.surfaces(), *lx.CONTAINERS, *lx.PAIRS],
    "conversions": [u for u, *_ in lx.grams_of_units()],
    "brands": list(lx.BRANDS),
    "redundant": [*lx.REDUNDANT, *lx.REDUNDANT_PHRASES, *lx.PROTECTED],
}
_LONGEST = max(len(p.split(" ")) for v in _PHRASES.values() for p in v)


def _lexicon_sql() -> str:
    entry = ", ".join("('{}', '{}')".format(n, p.replace("'", "''")) for n, v in _PHRASES.items() for p in v)
    grams = " UNION ALL ".join(f"SELECT array_to_string(w[i:i + {k - 1}], ' ') AS phrase FROM (SELECT w, unnest(range(1, len(w) - {k - 2})) AS i FROM d)" for k in range(1, _LONGEST + 1))
    return f"WITH e(dictionary, phrase) AS (VALUES {entry}), d AS (SELECT string_split(text, ' ') AS w FROM documents WHERE text IS NOT NULL), c AS (SELECT phrase, count(*) AS uses FROM ({grams}) WHERE phrase IN (SELECT phrase FROM e) GROUP BY phrase) SELECT dictionary, count(*) AS n, coalesce(sum(uses), 0)::BIGINT AS uses FROM e LEFT JOIN c USING (phrase) GROUP BY dictionary"


@query(_lexicon_sql())
def lexicon_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entries of each dictionary, and how often the documents use them."""
    entries = None
    for name, t in lx.as_tables(spark).items():
        e = t.select(F.lit(name).alias("dictionary"), F.col(t.columns[0]).alias("phrase"))
        entries = e if entries is None else entries.union(e)
    known = [r[0] for r in entries.select("phrase").distinct().collect()]  # the dictionaries
    words = table(spark, sf_dir, "documents").select(F.split("text", " ").alias("w"))
    uses = None
    for k in range(1, _LONGEST + 1):
        mine = [p for p in known if len(p.split(" ")) == k]
        phrase = F.transform(F.sequence(F.lit(1), F.size("w") - k + 1), lambda i: F.array_join(F.slice("w", i, k), " ")) if k > 1 else F.col("w")  # noqa: B023
        some = words.where(F.size("w") >= k).select(F.explode(F.filter(phrase, lambda x: x.isin(*mine))).alias("phrase")) if mine else None  # noqa: B023
        uses = some if uses is None else uses.unionByName(some) if some is not None else uses
    uses = uses.groupBy("phrase").agg(F.count("*").alias("uses"))
    return entries.join(uses, "phrase", "left").groupBy("dictionary").agg(F.count("*").alias("n"), F.coalesce(F.sum("uses"), F.lit(0)).alias("uses"))


# preparation --------------------------------------------------------------------------------------

#: rule: (function, [(text, expected)]): own strings around a part's size {q} and name {f}; {f|} is the name by tokens.
GOLDEN: dict[str, tuple] = {
    "prep_tokens": (lambda c: F.array_join(prep.tokens(c), "|"), [("{q}  red {f}", "{q}|red|{f|}"), ("3.5% {f} ", "3.5%|{f|}"), ("{q}", "{q}")]),
    "prep_lemmas": (prep.lemmas, [("berries leaves {f}s boxes cups radish peaches", "berry leaf {f} box cup radish peach"), ("asparagus gas {q} couscous", "asparagus gas {q} couscous"), ("molasses {f} glasses hummus", "molasses {f} glass hummus")]),
    "prep_redundant": (prep.redundant, [("{q} cups of fresh {f}", "{q} cups {f}"), ("{f} to taste", "{f}"), ("the finely cut {f}", "cut {f}")]),
    "prep_branded": (lambda c: prep.restore_brands(prep.ampersand(prep.shield_brands(c))), [("{q} m&m's & {f}", "{q} m&m's  and  {f}")]),
    "prep_special": (lambda c: prep.squeeze(prep.specials(prep.slash(prep.plus_sign(prep.ampersand(prep.percent(prep.ranges(c))))))), [("a% {q}% {f} & c + d 1/{q} e/f {q}-3 g-h i!", "a {q}% {f} and c plus d 1/{q} e f {q} to 3 g h i")]),
    "prep_number_words": (lambda c: prep.number_words(prep.halves(c)), [("two and a half {f}", "2 1/2 {f}"), ("half a {f}", "1/2 {f}"), ("half of eleven {f}", "1/2 11 {f}"), ("twenty five {f} {q}", "25 {f} {q}"), ("two hundred and fifty {f}", "250 {f}"), ("one hundred {q} {f}", "100 {q} {f}"), ("three hundred seven {f}", "307 {f}"), ("20 5 {f}", "20 5 {f}")]),
    "prep_truncate": (lambda c: rules.truncate(rules.tag_quantities(rules.tag_units(c)), c), [("{q} cup {f} , washed . dry", "<{q}> @cup {f}"), ("{q} cup {f} , and oil", "<{q}> @cup {f} , and oil"), ("{q} {f} , beaten", "<{q}> {f} , beaten")]),
    "prep_all": (prep.prepare, [("Two ½ cups (fresh) {f}s & nuts!", "2 1/2 cup {f} and nut"), ("An {f}", "1 {f}"), ("a cup of {f}", "1 cup {f}")]),
}


def _golden(name: str, rule, cases: list[tuple[str, str]]) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        p = table(spark, sf_dir, "part").select("p_partkey", "p_size", "p_name", F.posexplode(F.array(*(F.lit(c[0]) for c in cases))).alias("i", "t"))
        text = F.replace(F.replace("t", F.lit("{q}"), F.col("p_size").cast("string")), F.lit("{f}"), F.col("p_name"))
        return p.select("p_partkey", "i", rule(text).alias("out"))

    quoted = lambda s: "'" + s.replace("'", "''") + "'"
    Q[name] = run
    values = ", ".join(f"({i}, {quoted(c[1])})" for i, c in enumerate(cases))
    O[name] = f"SELECT p_partkey, i::INT AS i, replace(replace(replace(e, '{{q}}', p_size::VARCHAR), '{{f|}}', replace(p_name, ' ', '|')), '{{f}}', p_name) AS out FROM part, (VALUES {values}) AS t(i, e)"


for _name, (_rule, _cases) in GOLDEN.items():
    _golden(_name, _rule, _cases)


def _hashed(rule):
    return lambda spark, sf_dir: table(spark, sf_dir, "documents").select("doc_id", F.md5(rule(F.col("text")).cast("binary")).alias("h"))


def _replaced(c: str, pairs: dict[str, str]) -> str:
    for a, b in pairs.items():
        c = f"replace({c}, '{a}', '{b}')"
    return c


Q["prep_brackets"] = _hashed(prep.brackets)
O["prep_brackets"] = "SELECT doc_id, md5(translate(text, '()[]{}', '')) AS h FROM documents"
Q["prep_vulgar"] = _hashed(prep.vulgar)
O["prep_vulgar"] = f"SELECT doc_id, md5({_replaced('text', {k: ' ' + v for k, v in lx.VULGAR.items()})}) AS h FROM documents"
Q["prep_signs"] = _hashed(lambda c: prep.plus_sign(prep.ampersand(c)))
O["prep_signs"] = f"SELECT doc_id, md5({_replaced('text', {'&': ' and ', '+': ' plus '})}) AS h FROM documents"


# the normalizer -----------------------------------------------------------------------------------


@query(_truth("true"))
def normalize_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.triples(spark, sf_dir).select(*TRIPLE)


@query(f"WITH {LINES} SELECT corpus, count(*) AS n, count(qty) AS with_qty, count(unit) AS with_unit, round(sum(qty), 4) AS sum_qty FROM tw GROUP BY corpus")
def normalize_by_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    has = lambda c: F.sum(F.when(F.col(c).isNotNull(), F.col("n")).otherwise(F.lit(0).cast("long")))
    return normalize_counted(views.text_lines(spark, sf_dir), ("corpus",)).groupBy("corpus").agg(F.sum("n").alias("n"), has("qty").alias("with_qty"), has("unit").alias("with_unit"), F.round(F.sum(F.col("qty") * F.col("n")), 4).alias("sum_qty"))


@query(f"WITH {LINES} SELECT corpus, t, count(*) AS n, 1.0::DOUBLE AS qty_right, 1.0::DOUBLE AS unit_right, 1.0::DOUBLE AS food_right FROM tr GROUP BY corpus, t")
def extract_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of lines whose parts are exactly right, by template and collection."""
    t, f = F.col("t"), F.col("f")
    fused = F.when(f.endswith("widget"), F.replace(f, F.lit(" "), F.lit(""))).otherwise(f)
    food = F.when(t == 17, fused).when(t == 18, F.concat(F.lit("3.5% "), f)).when(t == 19, F.concat(F.lit("clove "), f)).otherwise(f)
    lines = views.answers(render.ingredient_lines(spark, sf_dir)).withColumnsRenamed({"qty": "_q", "unit": "_u"}).withColumn("_f", food)
    got = normalize_lines(lines.select("corpus", "t", "text", "_q", "_u", "_f")).where("part_no = 0")
    right = lambda a, b: F.avg(F.col(a).eqNullSafe(F.col(b)).cast("double"))
    return got.groupBy("corpus", "t").agg(F.count("*").alias("n"), right("qty", "_q").alias("qty_right"), right("unit", "_u").alias("unit_right"), right("food", "_f").alias("food_right"))


@query(f"WITH {LINES}, k AS (SELECT unnest((CASE WHEN t IN (6, 9, 10) THEN ['plus'] ELSE [] END) || (CASE WHEN t = 8 THEN ['or'] ELSE [] END) || (CASE WHEN unit IS NOT NULL THEN ['unit'] ELSE [] END) || (CASE WHEN t IN (13, 14) THEN ['several'] ELSE [] END) || (CASE WHEN t = 16 THEN ['truncated'] ELSE [] END) || (CASE WHEN t IN (2, 11, 12) THEN ['container'] ELSE [] END)) AS rule FROM tw) SELECT rule, count(*) AS n FROM k GROUP BY rule")
def rule_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return normalize_counted(views.text_lines(spark, sf_dir)).select("n", F.explode("rules_fired").alias("rule")).groupBy("rule").agg(F.sum("n").alias("n"))


@query("SELECT p_partkey, i::INT AS i, i = 1 AS is_food FROM part, (VALUES (0), (1)) AS t(i)")
def food_nonfood(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "part").select("p_partkey", F.posexplode(F.array(F.lit("1 sheet of baking paper"), F.lit("2 cups rice"))).alias("i", "text"))
    return normalize_lines(p).select("p_partkey", "i", "is_food")


@query("SELECT p_partkey, i::INT AS pos, (CASE i WHEN 0 THEN p_size ELSE 15 END)::DOUBLE AS qty, CASE i WHEN 0 THEN 'cups' WHEN 1 THEN 'grams' ELSE 'tablespoons' END AS unit, CASE i WHEN 0 THEN 'rice brown' WHEN 1 THEN '3.5% cream' ELSE 'cocoa' END AS food FROM part, (VALUES (0), (1), (2)) AS t(i)")
def split_structured_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "part").select("p_partkey", F.concat(F.col("p_size").cast("string"), F.lit(" cups rice, brown; 15 grams 3.5% cream; 15 tablespoons cocoa.")).alias("text"))
    return split_structured(p).select("p_partkey", "pos", "qty", "unit", "food")


Q["split_structured"], O["split_structured"] = Q.pop("split_structured_text"), O.pop("split_structured_text")


@query()
def prose_robustness(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rules on multilingual prose, junk and turns: nothing fails, no row is lost, quantities are numbers."""
    docs = table(spark, sf_dir, "documents").select(F.explode(F.split("text", "\n")).alias("text"))
    turns = table(spark, sf_dir, "conversations").select(F.explode(F.split("text", "\n")).alias("text"))
    short = table(spark, sf_dir, "benchmark").select("text")
    lines = docs.union(turns).union(short).where("text != ''").distinct()
    return normalize_lines(lines).agg(F.countDistinct("text").alias("texts"), F.count("*").alias("rows"), F.count("qty").alias("quantities"), F.count("unit").alias("units"))

