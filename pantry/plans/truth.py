"""Answers in SQL, from the numbers that the inputs are rendered from: nothing here parses text."""

from __future__ import annotations

from pantry.functions import lexicons as lx
from pantry.plans.render import ADJ, NOUN, SPELT, WORDS


def _list(values) -> str:
    return "[" + ", ".join("'" + v.replace("'", "''") + "'" for v in values) + "]"


NAME = f"({_list(ADJ)}[({{i}} // 8 + 1)::INT] || ' ' || {_list(NOUN)}[({{i}} % 8 + 1)::INT])"

LINES = f"""
b AS (SELECT l_orderkey AS recipe_id, substr('ABCDEF', (l_orderkey % 6 + 1)::INT, 1) AS corpus, l_linenumber AS pos,
        concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey) AS line_key, l_partkey, l_suppkey, l_quantity::INT AS q, p_name AS f, p_size AS s,
        list_position({_list(ADJ)}, split_part(p_name, ' ', 1)) - 1 AS a, list_position({_list(NOUN)}, split_part(p_name, ' ', 2)) - 1 AS n,
        {_list(s[0] for s in SPELT)}[(l_partkey % 8 + 1)::INT] AS u, ((l_orderkey * 31 + l_linenumber * 7 + l_partkey) % 20)::INT AS t
      FROM lineitem JOIN part ON l_partkey = p_partkey),
c AS (SELECT *, {NAME.format(i="((8 * a + n + 1) % 64)")} AS f2 FROM b),
tr AS (SELECT *, 0 AS part_no,
        (CASE WHEN t IN (0, 5, 6, 8, 9, 10, 11, 13, 16, 18, 19) THEN q WHEN t = 1 THEN q + 0.5 WHEN t = 2 THEN 250 * q WHEN t IN (3, 15) THEN 1 WHEN t = 4 THEN 1 + q % 10
              WHEN t = 12 THEN 2 * q WHEN t = 14 THEN 0.25 WHEN t = 17 THEN (CASE WHEN n = 7 THEN q ELSE 0.5 END) END)::DOUBLE AS qty,
        CASE WHEN t IN (0, 1, 3, 5, 6, 8, 9, 10, 13, 14, 16, 18) THEN u WHEN t = 2 THEN 'g' WHEN t = 12 THEN 'oz' WHEN t = 11 THEN 'packet' END AS unit,
        CASE WHEN t = 17 AND n = 7 THEN split_part(f, ' ', 1) || 'widget' WHEN t = 18 THEN '3.5% ' || f WHEN t = 19 THEN 'clove ' || f ELSE f END AS food FROM c),
tw AS (SELECT * FROM tr UNION ALL BY NAME
       SELECT * REPLACE (1 AS part_no, (CASE WHEN t = 10 THEN 3 ELSE 2 END)::DOUBLE AS qty, CASE t WHEN 6 THEN 'tbsp' WHEN 9 THEN 'tsp' ELSE 'oz' END AS unit, f2 AS food) FROM tr WHERE t IN (6, 9, 10))
"""

GENERAL = "CASE unit " + " ".join(f"WHEN '{u.name}' THEN {u.grams}" for u in lx.UNITS) + " " + " ".join(f"WHEN '{c}' THEN {g}" for c, g in lx.CONTAINERS.items()) + " END"

#: Composition items as token lists: nouns, the rest, lemma key.
_ITEMS = f"""
i0 AS (SELECT p_partkey AS item_id, p_size AS s, list_position({_list(ADJ)}, split_part(p_name, ' ', 1)) - 1 AS a, split_part(p_name, ' ', 1) AS adj, split_part(p_name, ' ', 2) AS noun,
        list_position({_list(NOUN)}, split_part(p_name, ' ', 2)) - 1 AS n FROM part),
i1 AS (SELECT item_id, CASE WHEN n <= 3 THEN [noun] WHEN n <= 5 THEN [noun, 'set'] WHEN n = 6 THEN ['fitting'] ELSE [adj || 'widgt'] END AS ns,
        CASE WHEN n <= 1 OR n IN (4, 5, 6) THEN [adj] WHEN n <= 3 THEN [adj] ELSE [] END AS adjs, CASE WHEN n IN (2, 3) THEN [s::VARCHAR] ELSE [] END AS nums FROM i0),
it AS (SELECT min(item_id) AS item_id, list_sort(ns) AS ns, adjs, nums, list_sort(ns || adjs || nums) AS toks FROM i1 GROUP BY ALL),
{{foods}},
pr AS (SELECT array_to_string(fd.toks, ' ') AS key, fd.ns AS fns, fd.adjs AS fadjs, fd.toks AS ftoks, it.*,
        CASE WHEN len(list_distinct(fd.ns || it.ns)) > 0 THEN len(list_intersect(fd.ns, it.ns))::DOUBLE / len(list_distinct(fd.ns || it.ns)) END AS e1,
        (len(list_intersect(fd.adjs, it.adjs || it.nums)) + 1)::DOUBLE / (len(list_distinct(fd.adjs || it.adjs || it.nums)) + 2) AS e2,
        (len(it.adjs) + 1)::DOUBLE / (len(it.adjs || it.nums) + 2) AS e2p,
        levenshtein(array_to_string(fd.toks, ''), array_to_string(it.toks, ''))::INT AS dist, length(array_to_string(fd.toks, '')) AS flen FROM fd, it),
pi AS (SELECT *, e1 * e2 AS idx, list_has_any(ftoks, toks) AS shares, CASE WHEN ftoks = toks THEN 1 WHEN list_sort(fns) = ns AND e1 * e2 > 0 THEN 2 WHEN e1 * e2 > 0 THEN 3 WHEN list_has_any(ftoks, toks) THEN 4 WHEN levenshtein(array_to_string(ftoks, ''), array_to_string(toks, '')) < flen THEN 5 END AS tier FROM pr)
"""

_NAMES = """SELECT DISTINCT [split_part(p_name, ' ', 2)] AS ns, [split_part(p_name, ' ', 1)] AS adjs, list_sort(string_split(p_name, ' ')) AS toks FROM part
       UNION ALL SELECT DISTINCT [split_part(p_name, ' ', 1) || 'widget'], [], [split_part(p_name, ' ', 1) || 'widget'] FROM part WHERE p_name LIKE '%widget'"""
ITEMS = _ITEMS.replace("{foods}", f"fd AS ({_NAMES})")


def linked(where: str = "tier IS NOT NULL", score: str = "CASE WHEN tier <= 3 THEN idx WHEN tier = 4 THEN e2 ELSE 0 END", tier: str = "tier") -> str:
    """Best item a food by tier, score, distance, item."""
    return f"(SELECT key, item_id, {tier} AS tier, idx, dist FROM (SELECT *, row_number() OVER (PARTITION BY key ORDER BY {tier}, -({score}), dist, item_id) AS k FROM pi WHERE {where}) WHERE k = 1)"


#: Foods that lines hold, as token sets: numbers stand with the adjectives, which is where the index counts them.
_FOUND = """SELECT DISTINCT list_sort(list_filter(w, lambda x: list_contains(NOUNS, x) OR x = 'clove' OR x LIKE '%_widget')) AS ns, list_filter(w, lambda x: list_contains(ADJS, x) OR x = '3.5%') AS adjs, list_sort(w) AS toks
       FROM (SELECT DISTINCT string_split(food, ' ') AS w FROM ex)""".replace("NOUNS", _list(NOUN)).replace("ADJS", _list(ADJ))

#: Lines of all collections as they are extracted (the structured one by its columns), linked by all pairs,
#: with the grams and nutrients of the linked item.
WEIGHED = f"""{LINES},
ex AS (SELECT recipe_id, corpus, pos, part_no, line_key, qty, unit, CASE WHEN corpus = 'A' THEN f ELSE food END AS food, (CASE WHEN part_no = 0 THEN 8 * a + n ELSE (8 * a + n + 1) % 64 END)::INT AS idx
       FROM tw WHERE corpus <> 'A' OR part_no = 0),
{_ITEMS.replace("{foods}", f"fd AS ({_FOUND})")},
lk AS {linked()},
nu AS (SELECT p_partkey AS item_id, (8 * p_size)::DOUBLE AS portion_g, (5 * n + a + p_size / 8)::DOUBLE AS fat, (2 * a + n + p_size / 4)::DOUBLE AS protein, (6 * abs(n - a) + p_size / 8)::DOUBLE AS sugar,
        (0.375 * (5 * n + a + p_size / 8))::DOUBLE AS satfat, (n * a / 32 + p_size / 64)::DOUBLE AS sodium
       FROM (SELECT *, list_position({_list(ADJ)}, split_part(p_name, ' ', 1)) - 1 AS a, list_position({_list(NOUN)}, split_part(p_name, ' ', 2)) - 1 AS n FROM part)),
g AS (SELECT recipe_id, corpus, pos, part_no, line_key, qty, unit, food, ex.idx AS idx, lk.item_id, lk.tier, portion_g,
        (CASE WHEN unit IS NULL THEN coalesce(qty, 1) * portion_g ELSE qty * {GENERAL} END)::DOUBLE AS grams, fat, protein, sugar, satfat, sodium
      FROM ex LEFT JOIN lk ON array_to_string(list_sort(string_split(food, ' ')), ' ') = lk.key LEFT JOIN nu ON nu.item_id = lk.item_id)
"""

#: Recipes with targets and folds.
FOLD = "(((recipe_id % 2147483648) * 2654435761 % 4294967296) // 65536 % 5)::INT"
RECIPES = f"""{WEIGHED},
r AS (SELECT recipe_id, corpus, {FOLD} AS fold, sum(grams) AS grams, count(*) AS n_lines,
        {", ".join(f"sum(grams * {t}) / sum(grams) AS {t}" for t in ("fat", "protein", "sugar", "satfat", "sodium"))} FROM g GROUP BY ALL)
"""
