"""What the reviewer of round 2 found: a test each that failed before."""

from __future__ import annotations

import datetime as dt
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from vecforest.functions.params import ForestParams
from vecforest.operators import ann, counted, views
from vecforest.operators.exact import collected
from vecforest.operators.range_query import build_index
from vecforest.plans.staging import shared_dir, staged
from vecforest.queries import relational, search


def test_day_frames_keep_fractions_of_seconds(spark, same, tmp_path):
    import duckdb

    start = dt.datetime(2024, 1, 1, 0, 0, 0, 700_000)
    day = dt.timedelta(days=1)
    micro = dt.timedelta(microseconds=1)
    ts = [start, start + day - micro, start + day, start + day + micro, start + day + dt.timedelta(microseconds=200_000)]
    rows = [(i, t, 1, float(i)) for i, t in enumerate(ts)]
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, value double").write.parquet(f"{tmp_path}/events.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
    same(relational.Q["win_frames"](spark, str(tmp_path)), con.execute(relational.SQL["win_frames"]).df())


@pytest.mark.parametrize("encoder,local_rows,rule", [("dynamic", 200_000, "even"), ("static", 200_000, "even"), ("dynamic", 50, "even"), ("static", 50, "cycle")])
def test_counted_trees_and_search_equal_the_stored_ones(spark, sf, encoder, local_rows, rule):
    v = staged(views.line_num(spark, sf).dropDuplicates(["vec_id"]), "points")
    q = collected(v.where(F.col("vec_id") % 1000 == 1).select(F.col("vec_id").alias("query_id"), "embedding"))
    p = ForestParams(K=4, L=4, max_size=32)
    stored = build_index(v, p, encoder=encoder, rule=rule)
    edges = counted.cuts(v, p)
    index = counted.build_counted(v, p, counted.static_cuts(edges, p) if encoder == "static" else edges, rule, local_rows)
    rows = lambda df: sorted(map(tuple, df.collect()), key=repr)
    columns = ["space", "path", "parent", "depth", "bits", "prefix", "n_points", "is_leaf", "saturated", "split_dim", "node_id", "parent_id", "lo", "hi"]
    assert rows(index.nodes.select(*columns)) == rows(stored.nodes.select(*columns))
    want = ann.ck_ann_tuned(stored, v, q, 10)
    got = counted.ck_ann_counted(index, v, q, 10)
    assert len(q) > 2 and rows(got.select(*want.columns)) == rows(want)


def test_static_recall_stages_no_row_a_point(spark, sf):
    """Bytes that the query leaves in the shared folder, for each order line."""
    top = Path(shared_dir(spark).removeprefix("file:"))
    size = lambda: sum(f.stat().st_size for f in top.rglob("*.parquet"))
    before, n = size(), views.table(spark, sf, "lineitem").count()
    rows = search.Q["wl_static_recall"](spark, sf).collect()
    print((size() - before) / n)
    assert {r["encoder"] for r in rows} == {"dynamic", "static"} and size() - before < 128 * n  # one projection of a point has 128
