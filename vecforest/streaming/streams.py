"""Streams over vectors and events. Batch and stream give the same rows where both exist."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery

from ..operators.encode import Edges, by_space, encode, with_root_key
from ..operators.exact import Queries, distances, framed, smallest
from ..operators.projection import project, stacked
from ..operators.tree import BITS, choose


def vector_stream(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema("vec_id long, embedding array<float>, label int").option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def encoded_stream(stream: DataFrame, matrix: np.ndarray, edges: Edges, K: int, L: int, bits: int = BITS) -> DataFrame:
    """(vec_id, space, code, proj, root_key) with frozen cut points: what a late vector lacks no shuffle finds."""
    return with_root_key(by_space(encode(project(stream.select("vec_id", "embedding"), matrix), edges), K, L), K, bits)


def append_encoded(stream: DataFrame, path: str, checkpoint: str) -> StreamingQuery:
    """Appends batches to the encoded table; a batch that is run again replaces itself."""

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


class Inserter(StatefulProcessor):
    """Arrival-order insertion into the subtree of one first-layer node; a full leaf splits before it takes a point.

    State: one entry a leaf (path -> bits used, codes and ids), and the splits.
    """

    K, max_size, bits = 16, 64, BITS

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.leaves = handle.getMapState("leaves", "path string", "used array<int>, ids array<long>, codes array<array<int>>")
        self.splits = handle.getMapState("splits", "path string", "dim int, used int")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        space, root = key
        for batch in rows:
            touched: set[str] = set()
            for vec, code in zip(batch["vec_id"].tolist(), batch["code"], strict=True):
                touched |= self._insert(str(root), int(vec), np.asarray(code, dtype=np.int64))
            out = []
            for path in sorted(touched):
                if self.leaves.containsKey((path,)):
                    used, ids, _ = self.leaves.getValue((path,))
                    out.append((space, root, path, len(ids)))
            yield pd.DataFrame(out, columns=["space", "root_key", "path", "n"])

    def _insert(self, path: str, vec: int, code: np.ndarray) -> set[str]:
        if not self.leaves.containsKey((path,)) and not self.splits.containsKey((path,)):
            self.leaves.updateValue((path,), ([1] * self.K, [], []))
        while True:
            while self.splits.containsKey((path,)):
                dim, used = self.splits.getValue((path,))
                path = f"{path}|{dim}:{(int(code[dim]) >> (self.bits - 1 - used)) & 1}"
            used, ids, codes = self.leaves.getValue((path,))
            u = np.asarray(used, dtype=np.int64)
            if len(ids) < self.max_size or (u >= self.bits).all():
                self.leaves.updateValue((path,), (list(used), [*ids, vec], [*codes, code.tolist()]))
                return {path}
            c = np.asarray([list(x) for x in codes], dtype=np.int64)
            dim = choose(len(c), u, ((c >> np.maximum(self.bits - 1 - u, 0)) & 1).sum(0), self.bits)
            up = (c[:, dim] >> (self.bits - 1 - u[dim])) & 1
            below = u.copy()
            below[dim] += 1
            for bit in (0, 1):
                part = np.flatnonzero(up == bit).tolist()
                self.leaves.updateValue((f"{path}|{dim}:{bit}",), (below.tolist(), [ids[i] for i in part], [list(codes[i]) for i in part]))
            self.splits.updateValue((path,), (int(dim), int(u[dim])))
            self.leaves.removeKey((path,))

    def close(self) -> None:
        return


def inserted(stream: DataFrame, K: int, max_size: int = 64, bits: int = BITS) -> DataFrame:
    """(space, root_key, path, n): leaves that a batch touched, after it. Needs the RocksDB state store."""
    kind = type("Inserter", (Inserter,), {"K": K, "max_size": max_size, "bits": bits})
    return stream.groupBy("space", "root_key").transformWithStateInPandas(statefulProcessor=kind(), outputStructType="space int, root_key long, path string, n int", outputMode="Update", timeMode="None")


def query_stream(stream: DataFrame, q: Queries, k: int) -> DataFrame:
    """(query_id, vec_id, dist): per batch the k nearest new vectors of a bounded query set."""

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            if len(batch):
                x, ids = stacked(batch["embedding"]), batch["vec_id"].to_numpy()
                for qid, v in zip(q.ids.tolist(), q.vectors, strict=True):
                    d = distances(x, v)
                    at = smallest(d, ids, k)
                    out.append(pd.DataFrame({"query_id": qid, "vec_id": ids[at], "dist": d[at]}))
            yield framed(out, ["query_id", "vec_id", "dist"])

    return stream.select("vec_id", "embedding").mapInPandas(scan, "query_id long, vec_id long, dist double")


def user_windows(events: DataFrame, late: str = "1 hour", length: str = "1 day", slide: str | None = None) -> DataFrame:
    """(user_id, start, end, n, mean): tumbling or sliding windows behind a watermark."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("mean")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "mean")


def user_sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def follow_ups(first: DataFrame, second: DataFrame, minutes: int = 60, late: str = "2 hours") -> DataFrame:
    """(first, second): second events of the same user within so many minutes of the first; an interval join of two streams."""
    a = first.withWatermark("ts", late).select(F.col("user_id").alias("u1"), F.col("ts").alias("t1"), F.col("event_id").alias("first"))
    b = second.withWatermark("ts", late).select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"), F.col("event_id").alias("second"))
    return a.join(b, F.expr(f"u1 = u2 AND t2 > t1 AND t2 <= t1 + INTERVAL {minutes} MINUTES")).select("first", "second")


def drift(encoded: DataFrame, K: int, regions: int = 256) -> DataFrame:
    """(space, chi2 over its degrees of freedom): how far symbol counts are from equal; about 1 while the cut points fit, more calls for a rebuild."""
    long = encoded.select("space", F.posexplode("code").alias("dim", "s")).groupBy("space", "dim", "s").agg(F.count(F.lit(1)).alias("n"))
    col = long.groupBy("space", "dim").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("sq"))
    return col.groupBy("space").agg((F.avg(F.col("sq") * regions / F.col("n") - F.col("n")) / (regions - 1)).alias("drift"))


def late_counted(events: DataFrame, path: str, checkpoint: str, late_seconds: int = 3600) -> StreamingQuery:
    """Counts by batch, as rows (batch, n, late, newest) under path: late rows are older than the newest row of the batches before by more than late_seconds.

    That is what a watermark of the same delay drops from windows. A batch that
    is run again replaces its row.
    """

    def put(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        known = [r[0] for r in spark.read.parquet(path).where(F.col("batch") < number).agg(F.max("newest")).collect()] if number else [None]
        limit = F.lit(known[0]) - F.expr(f"INTERVAL {late_seconds} SECONDS") if known[0] is not None else None
        late = F.count_if(F.col("ts") < limit) if limit is not None else F.lit(0)
        row = batch.agg(F.count(F.lit(1)).alias("n"), late.cast("long").alias("late"), F.greatest(F.max("ts"), F.lit(known[0]).cast("timestamp")).alias("newest"))
        row.coalesce(1).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return events.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
