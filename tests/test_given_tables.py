"""Queries that made their data up, or took the vectors' length for granted, follow the given tables."""

from __future__ import annotations

import datetime as dt

import numpy as np
import pytest

from vecforest.queries import relational, search

BOTH = {**search.Q, **relational.Q}, {**search.SQL, **relational.SQL}


def _folder(spark, path, n, d):
    x = np.random.default_rng(n).standard_normal((n, d))
    spark.createDataFrame([(i, a.tolist(), i % 10) for i, a in enumerate(x)], "vec_id long, embedding array<float>, label int").write.parquet(f"{path}/embeddings.parquet")
    spark.createDataFrame([(7 * i * n,) for i in range(1, 4)], "o_orderkey long").write.parquet(f"{path}/orders.parquet")
    spark.createDataFrame([(i, dt.datetime(2024, 1, 1) + dt.timedelta(hours=n * i)) for i in range(50)], "event_id long, ts timestamp_ntz").write.parquet(f"{path}/events.parquet")


@pytest.mark.parametrize("name,d", [("beta_curve", 64), ("radius_schedule", 64), ("range_ids", 64), ("measure_cumulative", 64), ("cost_model", 12), ("measure_memory", 12)])
def test_follows_its_table(spark, same, tmp_path, name, d):
    import duckdb

    seen = []
    for n in (150, 220):
        path = f"{tmp_path}/{n}"
        _folder(spark, path, n, d)
        con = duckdb.connect()
        for t in ("embeddings", "orders", "events"):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path}/{t}.parquet/*.parquet'")
        got = BOTH[0][name](spark, path)
        same(got, con.execute(BOTH[1][name]).df())
        seen.append(sorted(map(tuple, got.collect())))
    assert seen[0] != seen[1]
