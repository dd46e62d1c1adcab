from __future__ import annotations

import datetime

from pyspark.sql import functions as F

from vecforest.operators import views
from vecforest.operators.breakpoints import breakpoints
from vecforest.operators.exact import collected, exact_knn
from vecforest.operators.encode import by_space, edges_of, encode, with_root_key
from vecforest.operators.projection import project, projection_matrix
from vecforest.sources.vectors import parse, read_vectors, record
from vecforest.streaming import streams


def test_stream_encodes_like_a_batch(spark, sf, tmp_path):
    v = views.emb64(spark, sf)
    v.repartition(3).write.parquet(f"file://{tmp_path}/in")
    m = projection_matrix(64, 4, 2)
    pr = project(v.select("vec_id", "embedding"), m)
    edges = edges_of(breakpoints(pr, 4, 2), 4, 2)
    q = streams.append_encoded(streams.encoded_stream(streams.vector_stream(spark, f"{tmp_path}/in"), m, edges, 4, 2), f"{tmp_path}/out", f"{tmp_path}/cp")
    q.awaitTermination()
    rows = lambda df: sorted((r["vec_id"], r["space"], tuple(r["code"]), r["root_key"]) for r in df.collect())
    assert rows(spark.read.parquet(f"{tmp_path}/out")) == rows(with_root_key(by_space(encode(pr, edges), 4, 2), 4))
    d = streams.drift(by_space(encode(pr, edges), 4, 2), 4).collect()
    assert all(r["drift"] < 2 for r in d)


def test_stream_insertion_keeps_every_point(spark, sf, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    v = views.emb64(spark, sf)
    v.repartition(2).write.parquet(f"file://{tmp_path}/in")
    m = projection_matrix(64, 4, 1)
    edges = edges_of(breakpoints(project(v.select("vec_id", "embedding"), m), 4, 1), 4, 1)
    stream = streams.encoded_stream(streams.vector_stream(spark, f"{tmp_path}/in", 1), m, edges, 4, 1).select("space", "root_key", "vec_id", "code")
    seen: dict = {}

    def put(batch, _):
        for r in batch.collect():
            seen[(r["space"], r["path"])] = r["n"]
            parent = r["path"].rpartition("|")[0]
            if parent:
                seen.pop((r["space"], parent), None)

    streams.inserted(stream, 4, 16).writeStream.foreachBatch(put).outputMode("update").option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start().awaitTermination()
    assert max(seen.values()) <= 16


def test_windows_and_sessions_on_batches(spark, sf):
    e = spark.read.parquet(f"{sf}/events.parquet")
    n = e.count()
    assert streams.user_windows(e).agg(F.sum("n")).first()[0] == n
    assert streams.user_sessions(e).agg(F.sum("n")).first()[0] == n
    assert streams.user_windows(e, slide="12 hours").agg(F.sum("n")).first()[0] == 2 * n


def test_vector_files(spark, tmp_path):
    rows = [[1.0, 2.5], [3.0, -4.0]]
    (tmp_path / "a.fvecs").write_bytes(b"".join(record(r) for r in rows))
    assert [v for _, v in parse((tmp_path / "a.fvecs").read_bytes())] == rows
    got = read_vectors(spark, f"file://{tmp_path}/a.fvecs").orderBy("place").collect()
    assert [list(r["embedding"]) for r in got] == rows


def _two_files(spark, folder, first, second, schema):
    for i, rows in enumerate((first, second)):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"file://{folder}/{i}")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").option("latestFirst", "false").parquet(f"{folder}")


EVENT = "event_id long, ts timestamp, user_id long, value double"


def _at(minute):
    return datetime.datetime(2024, 1, 1) + datetime.timedelta(minutes=minute)


def test_late_rows_are_counted(spark, tmp_path):
    stream = _two_files(spark, tmp_path / "in", [(1, _at(0), 1, 1.0), (2, _at(300), 1, 1.0)], [(3, _at(10), 1, 1.0), (4, _at(250), 1, 1.0), (5, _at(400), 1, 1.0)], EVENT)
    streams.late_counted(stream, f"{tmp_path}/out", f"{tmp_path}/cp").awaitTermination()
    got = [(r["n"], r["late"]) for r in spark.read.parquet(f"{tmp_path}/out").orderBy("batch").collect()]
    assert sorted(got) in ([(2, 0), (3, 1)], [(2, 2), (3, 0)])  # by which file comes first


def _gathered(query_of, tmp_path, mode="append"):
    rows: list = []
    query_of.writeStream.foreachBatch(lambda b, _: rows.extend(map(tuple, b.collect()))).outputMode(mode).option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start().awaitTermination()
    return rows


def test_repeated_events_go(spark, tmp_path):
    stream = _two_files(spark, tmp_path / "in", [(1, _at(0), 1, 1.0), (1, _at(1), 1, 1.0), (2, _at(5), 1, 1.0)], [(2, _at(6), 1, 1.0), (3, _at(7), 1, 1.0)], EVENT)
    assert sorted(r[0] for r in _gathered(streams.deduplicated(stream), tmp_path)) == [1, 2, 3]


def test_follow_ups_of_two_streams(spark, tmp_path):
    a = _two_files(spark, tmp_path / "a", [(1, _at(0), 1, 1.0)], [(2, _at(100), 2, 1.0)], EVENT)
    b = _two_files(spark, tmp_path / "b", [(11, _at(30), 1, 1.0), (12, _at(90), 1, 1.0)], [(13, _at(130), 2, 1.0), (14, _at(130), 3, 1.0)], EVENT)
    assert sorted(_gathered(streams.follow_ups(a, b), tmp_path)) == [(1, 11), (2, 13)]


def test_queries_over_a_stream(spark, sf, tmp_path):
    v = views.emb64(spark, sf)
    v.repartition(2).write.parquet(f"file://{tmp_path}/in")
    q = collected(views.queries_of(v))
    rows = _gathered(streams.query_stream(streams.vector_stream(spark, f"{tmp_path}/in"), q, 5), tmp_path)
    exact = {(r["query_id"], r["vec_id"]) for r in exact_knn(v, q, 5).collect()}
    assert exact <= {(r[0], r[1]) for r in rows}
