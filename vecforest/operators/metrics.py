"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.params import ForestParams


def recall(result: DataFrame, truth: DataFrame, k: int, tie_aware: bool = False) -> DataFrame:
    """(query_id, recall): share of the k exact neighbours among the answers; tie_aware counts any answer as near as the k-th."""
    asked = truth.select("query_id").distinct()
    if tie_aware:
        last = truth.groupBy("query_id").agg(F.max("dist").alias("kth"))
        hits = result.join(last, "query_id").where(F.col("dist") <= F.col("kth")).groupBy("query_id").agg(F.count(F.lit(1)).alias("hits"))
    else:
        hits = result.select("query_id", "vec_id").join(truth.where(F.col("rank") <= k).select("query_id", "vec_id"), ["query_id", "vec_id"]).groupBy("query_id").agg(F.count(F.lit(1)).alias("hits"))
    return asked.join(hits, "query_id", "left").select("query_id", (F.coalesce("hits", F.lit(0)) / k).alias("recall"))


def overall_ratio(result: DataFrame, truth: DataFrame) -> DataFrame:
    """(query_id, ratio, n_returned): mean over ranks of the distance over the exact one; 0 over 0 is 1; missing ranks are left out."""
    t = truth.select("query_id", "rank", F.col("dist").alias("exact"))
    both = t.join(result.select("query_id", "rank", "dist"), ["query_id", "rank"])
    one = F.when((F.col("exact") == 0) & (F.col("dist") == 0), 1.0).when(F.col("exact") > 0, F.col("dist") / F.col("exact"))
    return both.groupBy("query_id").agg(F.avg(one).alias("ratio"), F.count(F.lit(1)).alias("n_returned"))


def index_size(n: int, params: ForestParams, nodes: int = 0) -> dict[str, int]:
    """Bytes: one a symbol, eight an id in each space, 2K + 40 a node."""
    return {"codes": n * params.K * params.L, "ids": 8 * n * params.L, "nodes": nodes * (2 * params.K + 40)}


def memory(n: int, d: int, params: ForestParams, nodes: int = 0, pooled: int = 0) -> dict[str, int]:
    """Bytes while a query runs: raw vectors (four a number), the index, and the pool."""
    return {"raw": 4 * n * d, **index_size(n, params, nodes), "pool": 16 * pooled}


def predicted_ops(n: int, d: int, p: ForestParams, workers: int = 1, k: int = 50) -> dict[str, float]:
    """Operation counts of the parts: projecting, looking symbols up, building, pruning and re-ranking."""
    log_r = float(p.bits)
    return {
        "project": p.L * p.K * n * d / workers,
        "encode": p.L * p.K * n * log_r / workers,
        "build": p.L * n * p.K * log_r / workers,
        "range": p.L * (p.K * p.K * log_r * n / p.max_size + p.K * n) / workers,
        "rerank": p.need(n, k) * float(d) / workers,
    }


def timed(df: DataFrame) -> float:
    """Seconds to compute a plan without keeping its rows."""
    start = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def stage_times(stages: dict[str, Callable[[], DataFrame]]) -> dict[str, float]:
    return {name: timed(make()) for name, make in stages.items()}


def speedup(t1: float, tp: float) -> float:
    return t1 / tp if tp else float("inf")


def cumulative_cost(log: DataFrame, name: str, t_index: float, t_query: float) -> DataFrame:
    """(method, day, queries, seconds): indexing, then the queries of a log (day, queries) up to each day."""
    return log.select(F.lit(name).alias("method"), "day", "queries", (F.lit(float(t_index)) + F.col("queries") * float(t_query)).alias("seconds"))


def break_even(ours: tuple[float, float], rival: tuple[float, float]) -> int:
    """Queries that we answer before the rival's index is ready: (index seconds, query seconds) of either."""
    return max(0, int((rival[0] - ours[0]) // ours[1])) if ours[1] > 0 else 0


def tidy(spark: SparkSession, rows: list[tuple[str, str, str, str, float]]) -> DataFrame:
    return spark.createDataFrame(rows, "workload string, method string, params string, measure string, value double")
