"""Rates over pairs and the join in blocks, against their SQL."""

from __future__ import annotations

import numpy as np

from vecforest.operators import ann, rates
from vecforest.queries import search


def _copies(spark, tmp_path):
    """300 vectors, of which a query has copies: their ratios are no numbers."""
    import duckdb

    x = np.random.default_rng(6).standard_normal((300, 64)).astype(np.float32)
    x[5::7] = x[100]
    spark.createDataFrame([(i, a.tolist(), i % 10) for i, a in enumerate(x)], "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
    return con


def test_tails_count_copies_as_their_sql(spark, same, tmp_path, monkeypatch):
    con = _copies(spark, tmp_path)
    monkeypatch.setattr(rates, "PAIRS_AT_ONCE", 500)
    for name in ("tail_rates", "beta_curve"):
        same(search.Q[name](spark, str(tmp_path)), con.execute(search.SQL[name]).df())


def test_join_in_blocks_of_both_sides(spark, same, tmp_path, monkeypatch):
    con = _copies(spark, tmp_path)
    for block in (30, 2_000):  # a node's vectors travel once a block
        monkeypatch.setattr(ann, "NODE_BLOCK", block)
        same(search.Q["knn_join"](spark, str(tmp_path)), con.execute(search.SQL["knn_join"]).df())
