"""Every query that has SQL gives the rows of that SQL; the others run and have rows."""

from __future__ import annotations

import pytest

from pantry.plans import catalog
from tests.oracle import connect, same

QUERIES, SQL = catalog.queries(), catalog.oracle_sql()


@pytest.fixture(scope="module")
def con(sf_dir):
    return connect(sf_dir)


@pytest.mark.parametrize("name", sorted(SQL))
def test_equals_sql(spark, sf_dir, con, name):
    same(QUERIES[name](spark, sf_dir), con, SQL[name])


#: The rest: iterative ones are covered by their properties elsewhere.
LIGHT = ("agg_approx", "sample", "stream_late", "random_candidates", "layer_provider", "lsh_topk", "quality_from_vectors", "w2v_sg")


@pytest.mark.parametrize("name", LIGHT)
def test_runs(spark, sf_dir, name):
    assert QUERIES[name](spark, sf_dir).count() > 0


def test_prose_loses_no_text(spark, sf_dir):
    r = QUERIES["prose_robustness"](spark, sf_dir).first()
    assert r.rows >= r.texts > 100


def test_stream_link_equals_batch(spark, sf_dir):
    from pantry.operators import linking
    from pantry.plans import views

    links = {r.key: r.tier for r in linking.link_foods(views.foods(spark, sf_dir), views.items(spark, sf_dir)).collect()}
    want: dict = {}
    for r in views.triples(spark, sf_dir, (0,)).collect():
        want[links.get(r.food_key)] = want.get(links.get(r.food_key), 0) + 1
    assert {r.tier: r.n for r in QUERIES["stream_link"](spark, sf_dir).collect()} == want
