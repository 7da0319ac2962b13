"""Ridge regressions in SQL: sums of products, elimination by a recursive query, predictions and hits.

The counterpart of ``operators.experiment``: it merges, solves and scores for itself from the given tables.
"""

from __future__ import annotations

from pantry.functions.bands import BANDS
from pantry.operators.nutrients import TARGETS
from pantry.plans.truth import RECIPES

_N = len(TARGETS)
_WEIGHT = {"dh": "grams / sum(grams) OVER (PARTITION BY recipe_id)", "avg": "1.0::DOUBLE / count(*) OVER (PARTITION BY recipe_id)"}
_HELD = {"fold": ("'all'", "fold::VARCHAR"), "corpus": ("'all'", "corpus"), "corpus|fold": ("corpus", "fold::VARCHAR"), "none": ("'all'", "'none'")}


def _band(t: str, scale: float) -> str:
    rows = BANDS[t]
    of = lambda a, share: f"{a}" if a is not None else f"abs(y) * {share}"
    whens = " ".join(f"WHEN y {'<' if a is not None else '<='} {end} THEN {of(a, s)}" for end, a, s in rows[:-1])
    return f"{scale} * CASE {whens} ELSE {of(*rows[-1][1:])} END"


def models(kind: str, cell: str, lam: float, dim: int = 64) -> str:
    """CTEs: f (recipes with x and y), bb (grp, held, means and b, a list a feature with a number a target)."""
    d, side = dim, 1 + dim + _N
    grp, held = _HELD[cell]
    apart = "true" if cell == "none" else "gs.held <> q.held"
    return f"""{RECIPES},
    pv AS MATERIALIZED (SELECT recipe_id, {_WEIGHT[kind]} AS w, idx FROM g WHERE grams IS NOT NULL),
    px AS (SELECT recipe_id, w * unnest(embedding[1:{d}])::DOUBLE AS e, unnest(range({d})) AS i FROM pv JOIN embeddings ON vec_id = idx),
    mx AS (SELECT recipe_id, i, sum(e) AS x FROM px GROUP BY ALL),
    f AS MATERIALIZED (SELECT recipe_id, any_value(corpus) AS corpus, any_value({grp}) AS grp, any_value({held}) AS held, list(x ORDER BY i) AS x, any_value([{", ".join(TARGETS)}]) AS y FROM mx JOIN r USING (recipe_id) GROUP BY recipe_id),
    s1 AS (SELECT grp, held, v, unnest(v) AS a, unnest(range(1, {side + 1})) AS i FROM (SELECT grp, held, list_concat([1.0::DOUBLE], x, y) AS v FROM f)),
    s2 AS (SELECT grp, held, i, a, unnest(v) AS b, unnest(range(1, {side + 1})) AS j FROM s1),
    gs AS MATERIALIZED (SELECT grp, held, i, j, sum(a * b) AS s FROM s2 WHERE i <= j GROUP BY ALL),
    tn AS (SELECT gs.grp, q.held, i, j, sum(s) AS s FROM gs JOIN (SELECT DISTINCT grp, held FROM f) q ON gs.grp = q.grp AND {apart} GROUP BY ALL),
    fu AS (SELECT * FROM tn UNION ALL SELECT grp, held, j, i, s FROM tn WHERE i < j),
    nn AS (SELECT grp, held, s AS n FROM tn WHERE i = 1 AND j = 1),
    mu AS (SELECT tn.grp, tn.held, j, s / n AS m FROM tn JOIN nn USING (grp, held) WHERE i = 1),
    ce AS (SELECT fu.grp, fu.held, fu.i, fu.j, s / n - a.m * b.m + CASE WHEN fu.i = fu.j AND fu.i <= {d + 1} THEN {lam} ELSE 0 END AS c FROM fu JOIN nn USING (grp, held)
           JOIN mu a ON a.grp = fu.grp AND a.held = fu.held AND a.j = fu.i JOIN mu b ON b.grp = fu.grp AND b.held = fu.held AND b.j = fu.j WHERE fu.i BETWEEN 2 AND {d + 1} AND fu.j >= 2),
    mt AS (SELECT grp, held, list(row ORDER BY i) AS mat FROM (SELECT grp, held, i, list(c ORDER BY j) AS row FROM ce GROUP BY ALL) GROUP BY ALL),
    gj AS (SELECT grp, held, 1 AS k, mat FROM mt UNION ALL
           SELECT grp, held, k + 1, list_transform(mat, lambda w, i: CASE WHEN i = k THEN piv ELSE list_transform(w, lambda v, j: v - w[k] * piv[j]) END)
           FROM (SELECT *, list_transform(mat[k], lambda v: v / mat[k][k]) AS piv FROM gj WHERE k <= {d})),
    ml AS (SELECT grp, held, list(m ORDER BY j) AS means FROM mu GROUP BY ALL),
    bb AS (SELECT grp, held, means, mat FROM gj JOIN ml USING (grp, held) WHERE k = {d + 1})"""


def _hats(dim: int) -> str:
    """hats: a row a recipe and target with the prediction of the model that did not see it."""
    rows = " UNION ALL ".join(
        f"SELECT recipe_id, corpus, grp, held, '{t}' AS target, y[{i + 1}] AS y, means[{2 + dim + i}] + list_sum(list_transform(range(1, {dim + 1}), lambda k: mat[k][{dim + 1 + i}] * (x[k] - means[k + 1]))) AS hat FROM f JOIN bb USING (grp, held)"
        for i, t in enumerate(TARGETS)
    )
    return f"hats AS ({rows})"


def predictions(kind: str, cell: str, lam: float, dim: int = 64, scale: float = 1.0, errors: bool = False) -> str:
    """(grp, cell, target, a): hit rates in percent; with ``errors`` (recipe_id, target, hat, e)."""
    head = f"WITH RECURSIVE {models(kind, cell, lam, dim)}, {_hats(dim)}"
    if errors:
        return f"{head} SELECT recipe_id, target, hat, y - hat AS e FROM hats"
    hits = " UNION ALL ".join(f"SELECT grp, held AS cell, target, 100 * avg(CASE WHEN abs(y - hat) <= {_band(t, scale)} THEN 1.0 ELSE 0 END) AS a FROM hats WHERE target = '{t}' GROUP BY ALL" for t in TARGETS)
    return f"{head} {hits}"


def fitted(lam: float, dim: int = 64) -> str:
    """(target, i, coefficient) of the models of all recipes."""
    rows = " UNION ALL ".join(
        f"SELECT '{t}' AS target, 0 AS i, round(means[{2 + dim + i}] - list_sum(list_transform(range(1, {dim + 1}), lambda k: mat[k][{dim + 1 + i}] * means[k + 1])), 3) AS coefficient FROM bb"
        f" UNION ALL SELECT '{t}', unnest(range(1, {dim + 1}))::INT, round(unnest(list_transform(mat, lambda w: w[{dim + 1 + i}])), 3) FROM bb"
        for i, t in enumerate(TARGETS)
    )
    return f"WITH RECURSIVE {models('dh', 'none', lam, dim)} {rows}"


def _constant(agg: str) -> str:
    """Hit rates of the mean or median of the other folds of the collection."""
    guess = ", ".join(f"{agg}(r.{t}) AS h_{t}" for t in TARGETS)
    hits = " UNION ALL ".join(f"SELECT corpus, fold, '{t}' AS target, 100 * avg(CASE WHEN abs({t} - h_{t}) <= {_band(t, 1.0).replace('y', t)} THEN 1.0 ELSE 0 END) AS a FROM z GROUP BY ALL" for t in TARGETS)
    cells = "SELECT DISTINCT corpus, fold FROM r"
    return f"WITH {RECIPES}, h AS (SELECT k.corpus, k.fold, {guess} FROM r JOIN ({cells}) k ON r.corpus = k.corpus AND r.fold <> k.fold GROUP BY ALL), z AS (SELECT * FROM r JOIN h USING (corpus, fold)) SELECT corpus, target, avg(a) AS a FROM ({hits}) GROUP BY ALL"


def _average(kind: str) -> str:
    return f"SELECT grp AS corpus, target, avg(a) AS a FROM ({predictions(kind, 'corpus|fold', 1e-4)}) GROUP BY ALL"


#: (corpus, target, dh, mean, median, no_dh) of the ready vectors.
ACCURACY = f"""SELECT corpus, target, round(d.a, 4) AS dh, round(m.a, 4) AS mean, round(e.a, 4) AS median, round(p.a, 4) AS no_dh
    FROM ({_average('dh')}) d JOIN ({_constant('avg')}) m USING (corpus, target) JOIN ({_constant('median')}) e USING (corpus, target) JOIN ({_average('avg')}) p USING (corpus, target)"""
