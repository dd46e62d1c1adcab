from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecforest.operators import views
from vecforest.operators.breakpoints import breakpoints, ranks, select_ranks, selected
from vecforest.operators.encode import by_space, edges_of, encode, packed, region_balance
from vecforest.operators.projection import good_rows, project, projection_matrix
from vecforest.operators.selection import ranked_columns


@pytest.fixture(scope="module")
def projected(spark, sf):
    return project(views.emb64(spark, sf), projection_matrix(64, 4, 2)).select("vec_id", "proj").cache()


def test_native_and_arrow_projection_agree(spark, sf):
    v, m = views.emb64(spark, sf), projection_matrix(64, 2, 2)
    a = {r["vec_id"]: r["proj"] for r in project(v, m).collect()}
    b = {r["vec_id"]: r["proj"] for r in project(v, m, "native").collect()}
    assert all(np.allclose(a[i], b[i], atol=2e-9) for i in a)


def test_exact_methods_give_the_same_edges(projected):
    got = {m: edges_of(breakpoints(projected, 4, 2, 16, m), 4, 2) for m in ("full_sort", "select_rounds", "histogram_rounds")}
    assert got["full_sort"] == got["select_rounds"] == got["histogram_rounds"]


@pytest.mark.parametrize("method", ["percentile", "approx_percentile", "kll"])
def test_engine_quantiles_are_near(projected, method):
    exact, got = edges_of(breakpoints(projected, 4, 2, 16), 4, 2), edges_of(breakpoints(projected, 4, 2, 16, method), 4, 2)
    assert max(abs(a - b) for x, y in zip(exact, got, strict=True) for a, b in zip(x, y, strict=True)) < 0.2


def test_regions_are_balanced_and_hold_their_points(projected):
    edges = edges_of(breakpoints(projected, 4, 2, 16), 4, 2)
    codes = encode(projected, edges)
    for r in region_balance(codes, 4, 16).collect():
        assert r["used"] == 16 and r["most"] - r["least"] <= 2
    for r in codes.collect():
        for x, s, e in zip(r["proj"], r["code"], edges, strict=True):
            assert e[s] <= x <= e[s + 1]


def test_symbol_kernels_agree(projected):
    edges = edges_of(breakpoints(projected, 4, 2, 16), 4, 2)
    rows = [{r["vec_id"]: r["code"] for r in encode(projected, edges, k).collect()} for k in ("arrow", "halving", "count")]
    assert rows[0] == rows[1] == rows[2]


def test_ranks_of_a_line():
    assert ranks(1024, 256)[:2] == [5, 9] and len(ranks(1024, 256)) == 255
    x = np.random.default_rng(1).permutation(np.arange(1, 1025)).astype(float)
    assert select_ranks(x, ranks(1024, 256)) == [float(r) for r in ranks(1024, 256)]


def test_selection_with_ties_and_few_values(spark):
    df = spark.createDataFrame([([float(i % 3), float(i)],) for i in range(5000)], "v array<double>")
    assert ranked_columns(df, "v", [[1, 2500, 5000], [1, 2500, 5000]]) == [[0.0, 1.0, 2.0], [0.0, 2499.0, 4999.0]]
    assert np.isnan(ranked_columns(df, "v", [[9000], [1]])[0][0])


def test_selection_counts_fewer_comparisons_than_a_sort(projected):
    r = selected(projected, 4, 16).agg(F.sum("comparisons"), F.sum("sort_comparisons")).first()
    assert 0 < r[0] < 2 * r[1]


def test_codes_pack_to_bytes(projected):
    codes = encode(projected, edges_of(breakpoints(projected, 4, 2), 4, 2))
    r = by_space(codes, 4, 2).select("code", packed("code").alias("b")).first()
    assert list(r["b"]) == r["code"]


def test_bad_rows_split_off(spark):
    rows = [(1, [1.0, 2.0]), (2, [1.0]), (3, None), (4, [1.0, float("nan")])]
    good, bad = good_rows(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), 2)
    assert [r["vec_id"] for r in good.collect()] == [1] and bad.count() == 3
