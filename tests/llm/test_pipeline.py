"""The pipeline's stages on planted cases, each judged on its own input."""

from __future__ import annotations

import random

import pytest

import corpus_pipeline
from pantry.session import materialize


@pytest.fixture(scope="module")
def planted(spark):
    r = random.Random(2)
    make = lambda n: " ".join(f"word{r.randint(0, 3000)}" for _ in range(n))
    shared = "this notice is repeated in many documents of the collection for no reason"
    clean = [make(120) for _ in range(40)]
    rows = [(i, f"{t}\n{shared}" if i < 8 else t) for i, t in enumerate(clean)]
    rows += [(100 + i, clean[20 + i]) for i in range(3)]  # exact copies
    rows += [(200 + i, clean[30 + i].replace(clean[30 + i].split()[50], "changed", 1)) for i in range(3)]  # near copies
    rows += [(300, "too short"), (301, "buy now today " * 60), (302, "| " * 80)]
    return spark.createDataFrame([(i, t, "en", f"s{i % 3}", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")


def test_stages(spark, planted):
    seen = {}
    docs = planted
    for name, stage in corpus_pipeline.STAGES:
        docs = materialize(stage(spark, docs, ""), "test")
        seen[name] = docs
        if name != "packing":
            assert docs.columns == planted.columns
    ids = lambda n: {r.doc_id for r in seen[n].select("doc_id").collect()}
    assert ids("quality_rules") == {r.doc_id for r in planted.collect()} - {300, 301, 302}
    held = {r.doc_id for r in seen["line_dedup"].where("text like '%this notice%'").collect()}
    assert held == {7}
    assert ids("near_dedup") == ids("quality_rules") - {100, 101, 102, 200, 201, 202}
    assert ids("mixing") <= ids("near_dedup")
    assert ids("packing") == ids("mixing")


def test_run(spark, sf_dir):
    assert corpus_pipeline.run(spark, sf_dir).count() > 0
