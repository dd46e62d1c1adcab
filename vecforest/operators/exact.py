"""Exact nearest neighbours, and checks of approximate answers against them."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .projection import DECIMALS, stacked

MOST_QUERIES = 20_000  # a query set travels to every task


@dataclass
class Queries:
    """A bounded query set on the driver: ids and vectors."""

    ids: np.ndarray
    vectors: np.ndarray

    def __len__(self) -> int:
        return len(self.ids)


def collected(queries: DataFrame, most: int = MOST_QUERIES) -> Queries:
    """Brings a query set (query_id, embedding) to the driver; refuses more than `most`, which are for knn_join()."""
    rows = queries.select("query_id", F.col("embedding").cast("array<double>").alias("e")).limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"more than {most} queries; use knn_join()")
    rows.sort(key=lambda r: r["query_id"])
    return Queries(np.array([r["query_id"] for r in rows], dtype=np.int64), np.array([r["e"] for r in rows], dtype=float).reshape(len(rows), -1))


def framed(parts: list[pd.DataFrame], columns: list[str]) -> pd.DataFrame:
    """The parts in one frame; only non-empty ones, so that 64-bit ids stay integers."""
    some = [p for p in parts if len(p)]
    return pd.concat(some) if some else pd.DataFrame({c: [] for c in columns})


def distances(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    return np.round(np.sqrt(((x - q) ** 2).sum(1)), DECIMALS)


def smallest(dist: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k least (distance, id)."""
    if len(dist) > k:
        cut = np.partition(dist, k - 1)[k - 1]
        some = np.flatnonzero(dist <= cut)
        return some[np.lexsort((ids[some], dist[some]))[:k]]
    return np.lexsort((ids, dist))


def ranked(found: DataFrame, k: int) -> DataFrame:
    """(query_id, rank, vec_id, dist): the k least by distance and id; tasks hand on k rows a query."""
    w = Window.partitionBy("query_id").orderBy("dist", "vec_id")
    return found.withColumn("rank", F.row_number().over(w).cast("long")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "dist")


def exact_knn(points: DataFrame, queries: DataFrame | Queries, k: int = 1) -> DataFrame:
    """(query_id, rank, vec_id, dist) of the k nearest other points, by scanning all points once.

    A query is not its own neighbour (vec_id <> query_id). Ties go to the lower
    id. Fewer than k points give fewer rows.
    """
    q = queries if isinstance(queries, Queries) else collected(queries)

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            x, ids = stacked(batch["embedding"]), batch["vec_id"].to_numpy()
            out = []
            for qid, v in zip(q.ids, q.vectors, strict=True):
                if not len(ids):
                    continue
                dist = distances(x, v)
                dist[ids == qid] = np.inf
                at = smallest(dist, ids, k)
                at = at[np.isfinite(dist[at])]
                out.append(pd.DataFrame({"query_id": qid, "vec_id": ids[at], "dist": dist[at]}))
            yield framed(out, ["query_id", "vec_id", "dist"])

    return ranked(points.select("vec_id", "embedding").mapInPandas(scan, "query_id long, vec_id long, dist double"), k)


def check_c_k_ann(result: DataFrame, truth: DataFrame, c: float) -> DataFrame:
    """Rank by rank: whether the distance is at most c times the exact one; ranks without an answer are not valid."""
    t = truth.select("query_id", "rank", F.col("dist").alias("exact"))
    r = result.select("query_id", "rank", "dist")
    return t.join(r, ["query_id", "rank"], "left").select("query_id", "rank", F.coalesce(F.col("dist") <= F.round(F.col("exact") * c, 9), F.lit(False)).alias("valid"))


def check_c_ann(result: DataFrame, truth: DataFrame, c: float) -> DataFrame:
    return check_c_k_ann(result.where("rank = 1"), truth.where("rank = 1"), c)


def check_rc_ann(result: DataFrame, truth: DataFrame, r: float, c: float) -> DataFrame:
    """By query: must (a point within r: an answer within c * r is due), empty (none within c * r: no answer) or free; and whether the answer obeys."""
    t = truth.where("rank = 1").select("query_id", F.col("dist").alias("nearest"))
    a = result.select("query_id", F.col("dist").alias("got"))
    case = F.when(F.col("nearest") <= r, "must").when(F.col("nearest") > c * r, "empty").otherwise("free")
    ok = F.when(case == "must", F.coalesce(F.col("got") <= c * r, F.lit(False))).when(case == "empty", F.col("got").isNull() | (F.col("got") > c * r)).otherwise(F.col("got").isNull() | (F.col("got") <= c * r))
    return t.join(a, "query_id", "left").select("query_id", case.alias("case"), ok.alias("valid"))
