from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecforest.functions.params import ForestParams
from vecforest.operators import ann, views
from vecforest.operators.exact import Queries, collected, exact_knn
from vecforest.operators.range_query import ForestIndex, _bounds, build_index, range_query, range_trace
from vecforest.operators.tree import build_forest, build_incremental, choose, grow, shared_bits

P = ForestParams(K=4, L=2, max_size=8, sample=1.0)


@pytest.fixture(scope="module")
def index(spark, sf):
    return build_index(views.emb64(spark, sf).select("vec_id", "embedding"), P)


@pytest.fixture(scope="module")
def asked(spark, sf):
    return collected(views.queries_of(views.emb64(spark, sf)))


def spaced(index):
    return index.points.withColumn("root_key", F.expr("aggregate(transform(code, (s, i) -> shiftright(s, 7) * cast(pow(2, 3 - i) as int)), 0, (a, x) -> a + x)").cast("long"))


def test_bounds_of_a_box():
    lo, hi = np.array([[1.0, 1.0]]), np.array([[2.0, 3.0]])
    for q, lb, ub in (((0.0, 2.0), 1.0, 5**0.5), ((0.0, 0.0), 2**0.5, 13**0.5), ((1.5, 2.0), 0.0, 1.25**0.5), ((2.0, 3.0), 0.0, 5**0.5)):
        a, b = _bounds(lo, hi, np.array(q))
        assert a[0] == pytest.approx(lb, abs=1e-8) and b[0] == pytest.approx(ub, abs=1e-8)


def test_split_choice_and_shared_bits():
    assert choose(10, np.array([1, 1, 2]), np.array([9, 5, 5])) == 1
    assert choose(10, np.array([2, 1, 8]), np.array([5, 5, 5])) == 1
    assert choose(10, np.array([8, 8]), np.array([5, 5])) == -1
    assert shared_bits(np.array([0b10100000]), np.array([0b10111111])).tolist() == [3]


def test_two_bit_drawing():
    codes = np.array([[s, t] for s in range(4) for t in range(4)])
    leaf, nodes = grow(1, "0", codes[(codes < 2).all(1)], np.array([1, 1]), 2, bits=2)
    assert sorted(set(leaf)) == ["0|0:0", "0|0:1"]
    assert {tuple(n[5]) for n in nodes if n[7]} == {(0, 0), (1, 0)}


def test_copies_make_a_saturated_leaf():
    codes = np.vstack([np.full((50, 3), 77), np.random.default_rng(0).integers(0, 256, (24, 3))])
    leaf, nodes = grow(1, "r", codes, np.array([1, 1, 1]), 8)
    assert any(n[8] and n[6] >= 50 for n in nodes) and len(set(leaf[:50])) == 1


def test_invariants(index):
    nodes, points = index.nodes.collect(), index.points.collect()
    leaves = {(n["space"], n["node_id"]): n for n in nodes if n["is_leaf"]}
    held: dict = {}
    for p in points:
        n = leaves[(p["space"], p["leaf_id"])]
        held[(p["space"], p["leaf_id"])] = held.get((p["space"], p["leaf_id"]), 0) + 1
        assert all(c >> (8 - b) == v for c, b, v in zip(p["code"], n["bits"], n["prefix"], strict=True))
        assert all(a <= x <= z for a, x, z in zip(n["lo"], p["proj"], n["hi"], strict=True))
    assert {k: n["n_points"] for k, n in leaves.items()} == held
    assert all(n["n_points"] <= 8 or n["saturated"] for n in leaves.values())
    children: dict = {}
    for n in nodes:
        if n["parent_id"] is not None:
            children.setdefault((n["space"], n["parent_id"]), []).append(n["n_points"])
    inner = [n for n in nodes if not n["is_leaf"]]
    assert all(len(children[(n["space"], n["node_id"])]) == 2 and sum(children[(n["space"], n["node_id"])]) == n["n_points"] for n in inner)


def test_strategies_build_the_same_trees(index):
    got = {}
    for s in ("levels", "subtrees", "hybrid"):
        nodes, points = build_forest(spaced(index).select("vec_id", "space", "code", "proj", "root_key").repartition(3), 4, 8, s, local_rows=20)
        got[s] = ({(n["space"], n["path"], n["n_points"], n["is_leaf"], tuple(n["bits"])) for n in nodes.collect()}, {(p["space"], p["vec_id"], p["path"]) for p in points.collect()})
    assert got["levels"] == got["subtrees"] == got["hybrid"]


def test_arrival_order_fills_leaves(index):
    rows = build_incremental(spaced(index), 4, 8).collect()
    assert len(rows) == index.points.count()
    counts: dict = {}
    for r in rows:
        counts[(r["space"], r["path"])] = counts.get((r["space"], r["path"]), 0) + 1
    assert max(counts.values()) <= 8


def test_range_filters_nest(index, asked):
    sets = {f: {tuple(r) for r in range_query(index, asked, 2.0, f).select("query_id", "space", "vec_id").collect()} for f in ("exact", "cell", "leaf")}
    assert sets["exact"] <= sets["cell"] <= sets["leaf"] and sets["exact"]
    brute = {(q, s + 1, r["vec_id"]) for q, v in zip(asked.ids.tolist(), (asked.vectors @ index.matrix.T).reshape(len(asked), 2, 4), strict=True) for r in index.points.collect() for s in range(2) if r["space"] == s + 1 and r["vec_id"] != q and np.sqrt(((np.array(r["proj"]) - v[s]) ** 2).sum()) <= 2.0}
    assert sets["exact"] == brute
    t = range_trace(index, asked, 2.0).first()
    assert t["leaves"] == t["pruned"] + t["contained"] + t["straddling"]


def test_save_and_load(index, asked, tmp_path, spark):
    index.save(f"file://{tmp_path}/ix")
    other = ForestIndex.load(spark, f"file://{tmp_path}/ix")
    a, b = ({tuple(r) for r in range_query(i, asked, 2.0).select("query_id", "space", "vec_id").collect()} for i in (index, other))
    assert a == b and other.params == index.params


def test_tuned_search_fills_its_budget(index, asked, spark, sf):
    v = views.emb64(spark, sf).select("vec_id", "embedding")
    n = v.count() - 1
    rows = ann.ck_ann_tuned(index, v, asked, 10).collect()
    need = P.need(n, 10)
    assert all(need <= r["pooled"] < need + 8 * 2 for r in rows)
    assert len(rows) == 10 * len(asked)


def test_search_beyond_the_points(spark):
    v = spark.createDataFrame([(i, [float(i), 0.0]) for i in range(1, 6)], "vec_id long, embedding array<float>")
    q = Queries(np.array([1]), np.array([[1.0, 0.0]]))
    assert ann.ck_ann(v, q, 50, ForestParams(K=2, L=2)).result.count() == 4
    assert exact_knn(v, q, 50).count() == 4
    assert exact_knn(v.where("false"), q, 5).count() == 0


def test_box_gap_by_points(spark):
    from pyspark.sql import functions as F

    from vecforest.functions import exprs

    df = spark.createDataFrame([([0.0, 0.0], [1.0, 1.0], [4.0, 5.0], [6.0, 7.0]), ([0.0, 0.0], [3.0, 3.0], [1.0, 2.0], [2.0, 9.0])], "a array<double>, b array<double>, c array<double>, d array<double>")
    got = [r[0] for r in df.select(exprs.box_gap(F.col("a"), F.col("b"), F.col("c"), F.col("d"), 2)).collect()]
    assert got == [5.0, 0.0]


def test_workloads_run(spark, sf):
    from vecforest import workloads
    from vecforest.operators import views

    v = views.emb64(spark, sf)
    rows = workloads.w12_w13_curves(v, 5, (0.05, 0.2))
    recall = {(r[1], r[2]): r[4] for r in rows if r[3] == "recall"}
    assert all(recall[m, "beta=0.05"] <= recall[m, "beta=0.2"] for m in ("forest", "forest_index"))
    assert {r[2] for r in rows if r[0] == "W4"} == {"step=range", "step=select", "step=rerank"}
    scales = {(r[2], r[3]): r[4] for r in workloads.w9b_scales(spark, sf, (1, 4))}
    assert 3.5 < scales["copies=4", "memory_bytes"] / scales["copies=1", "memory_bytes"] < 4.5
    assert scales["copies=4", "file_bytes"] > 2 * scales["copies=1", "file_bytes"]  # files have a fixed share besides
