from __future__ import annotations

import pytest

from vecforest.queries import relational, search

FAST = [n for n in {**search.SQL, **relational.SQL} if not n.startswith("wl_") and n not in ("ck_ann_rounds", "knn_join", "index_roundtrip", "range_query_queues", "range_query_frontier", "range_ring", "split_choice", "code_bytes", "cell_bounds", "breakpoints_full_sort", "time_features")]


@pytest.mark.parametrize("name", FAST)
def test_query_equals_its_sql(spark, sf, duck, same, name):
    q, sql = {**search.Q, **relational.Q}[name], {**search.SQL, **relational.SQL}[name]
    same(q(spark, sf), duck.execute(sql).df())


def test_entry_needs_no_training_data_operators(monkeypatch):
    import __spark_entry__ as entry

    monkeypatch.setattr(entry, "_llm", None)
    assert "ck_ann_strict" in entry.queries() and not any(n.startswith("op1_") for n in entry.queries())
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_scan_is_pruned(spark, sf):
    plan = relational.Q["scan_pruned"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity)" in plan and "ReadSchema: struct<l_orderkey:bigint,l_quantity:double,l_returnflag:string>" in plan


def test_encoding_has_no_exchange(spark, sf):
    from vecforest.operators import views
    from vecforest.operators.encode import encode
    from vecforest.operators.projection import project, projection_matrix

    df = encode(project(views.emb64(spark, sf), projection_matrix(64, 4, 2)), [[0.0, 0.5, 1.0]] * 8)
    assert "Exchange" not in df._jdf.queryExecution().executedPlan().toString()
