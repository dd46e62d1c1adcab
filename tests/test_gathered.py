"""Searches over the saved index: no row for each pair, and the scan's answers, ties and copies included."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecforest.functions.params import ForestParams
from vecforest.operators import ann, gathered
from vecforest.operators.range_query import build_index
from vecforest.operators.views import queries_of
from vecforest.plans import staging

P = ForestParams(K=4, L=3, max_size=16, sample=1.0)


@pytest.fixture(scope="module")
def copies(spark):
    """900 vectors, a third of them one vector."""
    x = np.random.default_rng(5).standard_normal((900, 8)).round(3)
    x[::3] = x[0]
    v = staging.staged(spark.createDataFrame([(i, a.tolist(), i % 10) for i, a in enumerate(x)], "vec_id long, embedding array<float>, label int"), "copies")
    return v, build_index(v, P, keep=("label",))


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_searches_equal_the_scan(copies, monkeypatch):
    v, index = copies
    monkeypatch.setattr(gathered, "PAIRS_AT_ONCE", 5_000)  # several blocks a task
    q = queries_of(v, 50)
    assert rows(ann.ck_ann_index(index, v, q, 5)) == rows(ann.ck_ann(v, q, 5, P).result)
    assert rows(ann.ck_ann_index(index, v, q, 5, workers=8)) == rows(ann.ck_ann(v, q, 5, P).result)
    some = F.col("label") < 5
    assert rows(ann.ck_ann_index(index, v, q, 5, where=some)) == rows(ann.ck_ann(v, q, 5, P, where=some).result)
    assert rows(ann.ck_ann_index(index, v, q, 5, 0.3, rounds=9)) == rows(ann.ck_ann(v, q, 5, P, 0.3, rounds=9).result)
    for r in (0.5, 1.5):
        assert rows(ann.rc_ann_index(index, v, q, r)) == rows(ann.rc_ann(v, q, r, P))


def test_no_table_of_pairs_is_made(copies, monkeypatch):
    v, index = copies
    made = []

    def counted(df, name):
        out = staging.staged(df, name)
        made.append(out.count())
        return out

    monkeypatch.setattr(ann, "staged", counted)
    if hasattr(ann, "gathered"):
        monkeypatch.setattr(gathered, "staged", counted)
    q = queries_of(v, 10)
    assert ann.ck_ann_index(index, v, q, 5).count() == 5 * 90
    assert made and max(made) <= 900
