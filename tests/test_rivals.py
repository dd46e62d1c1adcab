from __future__ import annotations

import numpy as np
import pytest

from vecforest.baselines.layered_graph import layered_graph_ann
from vecforest.baselines.multi_codebook import multi_codebook_ann
from vecforest.baselines.projected import circular_run_ann, longest_circular_run, pivot_rings
from vecforest.functions.params import ForestParams
from vecforest.operators import ann, metrics, views
from vecforest.operators.engine import Spaces
from vecforest.operators.exact import collected, exact_knn
from vecforest.operators.projection import projection_matrix


@pytest.fixture(scope="module")
def data(spark, sf):
    v = views.emb64(spark, sf).select("vec_id", "embedding").cache()
    q = collected(views.queries_of(v))
    return v, q, exact_knn(v, q, 10).cache()


def recall(df, truth):
    return metrics.recall(df, truth, 10).groupBy().avg("recall").first()[0]


def test_graph_and_codebooks(data):
    v, q, truth = data
    assert recall(layered_graph_ann(v, q, 10, M=12, ef_build=60, ef=60), truth) > 0.8
    wide, narrow = (recall(multi_codebook_ann(v, q, 10, n_probe=p, exact=100), truth) for p in (128, 8))
    assert wide > 0.5 and wide >= narrow


def test_circular_runs():
    same = np.array([[True, False, True, True], [False] * 4, [True] * 4, [False, True, True, False]])
    assert longest_circular_run(same).tolist() == [3, 0, 4, 2]


def test_probes_do_not_lose_runs(data):
    v, q, truth = data
    assert recall(circular_run_ann(v, q, 10, n_cand=80, probes=4), truth) >= recall(circular_run_ann(v, q, 10, n_cand=80), truth) - 0.1


def test_pivots_keep_all_that_is_near(data):
    v, q, _ = data
    spaces = Spaces(projection_matrix(64, 15, 1, 15), 15, 1)
    kept = {(r["query_id"], r["vec_id"]) for r in pivot_rings(v, q, spaces, 5, {int(i): 4.0 for i in q.ids}).collect()}
    x = {r["vec_id"]: np.array(r["embedding"], dtype=float) for r in v.collect()}
    for qid, e in zip(q.ids.tolist(), q.vectors, strict=True):
        near = {i for i, p in x.items() if i != qid and np.linalg.norm(spaces.project(p[None]) - spaces.project(e[None])) <= 4.0}
        assert {(qid, i) for i in near} <= kept


def test_recall_rises_with_the_budget(data):
    v, q, truth = data
    got = [recall(ann.ck_ann(v, q, 10, ForestParams(beta=b)).result, truth) for b in (0.02, 0.1, 0.5)]
    assert got[0] <= got[1] + 0.05 <= got[2] + 0.1 and got[2] > 0.8


def test_copies_have_ratio_one(spark):
    v = spark.createDataFrame([(i, [1.0, 2.0]) for i in range(6)], "vec_id long, embedding array<float>")
    q = collected(views.queries_of(v))
    t = exact_knn(v, q, 3)
    assert metrics.overall_ratio(t, t).first()["ratio"] == 1.0
