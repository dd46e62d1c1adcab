"""Rivals that pool projected neighbours: they differ from the forest in spaces, proximity and stops only."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.params import chi2_upper
from ..operators import engine
from ..operators.exact import Queries, collected, distances, framed, ranked, smallest
from ..operators.projection import dimension, projection_matrix, stacked


def _need(beta: float, k: int):
    return lambda n: math.ceil(round(beta * n + k, 9))


def query_box_ann(points: DataFrame, queries: DataFrame | Queries, k: int = 50, L: int = 5, K: int = 12, w: float | None = None, beta: float = 0.1, c: float = 1.5, seed: int = 7) -> engine.Search:
    """Query-centred boxes of side w * r in L spaces of K dimensions; r grows by c; budget beta * n + k."""
    q = queries if isinstance(queries, Queries) else collected(queries)
    spaces = engine.Spaces(projection_matrix(dimension(points), K, L, seed), K, L, "linf", w or 4 * c * c)
    return engine.search(points, q, spaces, k, c, 1.0, _need(beta, k))


def pivot_metric_ann(points: DataFrame, queries: DataFrame | Queries, k: int = 50, m: int = 15, s: int = 5, beta: float = 0.1, c: float = 1.5, seed: int = 15) -> engine.Search:
    """One space of m dimensions, range queries of radius t * r with t from a chi-squared quantile; s pivots can prune (pivot_rings)."""
    q = queries if isinstance(queries, Queries) else collected(queries)
    spaces = engine.Spaces(projection_matrix(dimension(points), m, 1, seed), m, 1)
    return engine.search(points, q, spaces, k, c, math.sqrt(chi2_upper(1 / math.e, m)), _need(beta, k))


def pivot_rings(points: DataFrame, q: Queries, spaces: engine.Spaces, s: int, radius: dict[int, float]) -> DataFrame:
    """(query_id, vec_id): points that no pivot rules out: |d(o, pivot) - d(q, pivot)| <= radius for each; pivots chosen far apart in a sample."""
    sample = spaces.project(stacked(points.select("vec_id", "embedding").orderBy("vec_id").limit(1000).toPandas()["embedding"]))
    pivots = [sample[0]]
    while len(pivots) < s:
        pivots.append(sample[np.argmax(np.min([np.linalg.norm(sample - p, axis=1) for p in pivots], axis=0))])
    at = np.stack(pivots)
    qd = np.linalg.norm(spaces.project(q.vectors)[:, None] - at[None], axis=2)

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            if len(batch):
                pd_ = np.linalg.norm(spaces.project(stacked(batch["embedding"]))[:, None] - at[None], axis=2)
                for a, qid in enumerate(q.ids.tolist()):
                    ok = (np.abs(pd_ - qd[a]) <= radius[qid] + 1e-9).all(1) & (batch["vec_id"].to_numpy() != qid)
                    out.append(pd.DataFrame({"query_id": qid, "vec_id": batch["vec_id"].to_numpy()[ok]}))
            yield framed(out, ["query_id", "vec_id"])

    return points.select("vec_id", "embedding").mapInPandas(rows, "query_id long, vec_id long")


def collision_count_ann(points: DataFrame, queries: DataFrame | Queries, k: int = 50, m: int = 32, threshold: int | None = None, beta: float = 0.1, c: float = 1.5, seed: int = 23) -> engine.Search:
    """m single hashes with intervals round the query; a candidate agrees in `threshold` of them (0.6 m by default); widths grow by c."""
    q = queries if isinstance(queries, Queries) else collected(queries)
    spaces = engine.Spaces(projection_matrix(dimension(points), m, 1, seed), m, 1, "kth", order=threshold or math.ceil(0.6 * m))
    return engine.search(points, q, spaces, k, c, 1.0, _need(beta, k))


def metric_order_ann(points: DataFrame, queries: DataFrame | Queries, k: int = 50, m: int = 8, beta: float = 0.1, seed: int = 31) -> engine.Search:
    """One space of m dimensions, points in the order of projected distance up to the budget beta * n + k."""
    q = queries if isinstance(queries, Queries) else collected(queries)
    spaces = engine.Spaces(projection_matrix(dimension(points), m, 1, seed), m, 1)
    return engine.search(points, q, spaces, k, 1e9, 1e-30, _need(beta, k))


def static_bucket_ann(points: DataFrame, queries: DataFrame | Queries, k: int = 50, K: int = 3, L: int = 6, w: float = 2.0, seed: int = 5) -> DataFrame:
    """Fixed grid: candidates share all K buckets with the query in one of L tables."""
    q = queries if isinstance(queries, Queries) else collected(queries)
    matrix = projection_matrix(dimension(points), K, L, seed)
    qb = np.floor(np.round(q.vectors @ matrix.T, 9) / w).reshape(len(q), L, K)

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            if len(batch):
                x, ids = stacked(batch["embedding"]), batch["vec_id"].to_numpy()
                b = np.floor(np.round(x @ matrix.T, 9) / w).reshape(len(x), L, K)
                for a, qid in enumerate(q.ids.tolist()):
                    at = np.flatnonzero((b == qb[a]).all(2).any(1) & (ids != qid))
                    d = distances(x[at], q.vectors[a])
                    best = smallest(d, ids[at], k)
                    out.append(pd.DataFrame({"query_id": qid, "vec_id": ids[at][best], "dist": d[best]}))
            yield framed(out, ["query_id", "vec_id", "dist"])

    return ranked(points.select("vec_id", "embedding").mapInPandas(rows, "query_id long, vec_id long, dist double"), k)


def longest_circular_run(same: np.ndarray) -> np.ndarray:
    """Longest run of true along each row, the end joined to the start."""
    n, m = same.shape
    doubled = np.concatenate([same, same], 1)
    run, best = np.zeros(n, dtype=np.int64), np.zeros(n, dtype=np.int64)
    for j in range(2 * m):
        run = np.where(doubled[:, j], run + 1, 0)
        best = np.maximum(best, run)
    return np.minimum(best, m)


def circular_run_ann(points: DataFrame, queries: DataFrame | Queries, k: int = 50, m: int = 64, w: float = 2.0, n_cand: int = 200, seed: int = 64, probes: int = 0) -> DataFrame:
    """m bucket hashes as a circular string: the n_cand points with the longest run of equal positions, then true distances.

    With probes, each query also tries its string with one position moved to a
    neighbouring bucket, for the `probes` positions nearest to a border.
    """
    q = queries if isinstance(queries, Queries) else collected(queries)
    matrix = projection_matrix(dimension(points), m, 1, seed)
    qp = np.round(q.vectors @ matrix.T, 9) / w
    qb = np.floor(qp)
    strings = []
    for a in range(len(q)):
        mine = [qb[a]]
        inside = qp[a] - qb[a]
        for j in np.argsort(np.minimum(inside, 1 - inside))[:probes]:
            moved = qb[a].copy()
            moved[j] += 1 if inside[j] > 0.5 else -1
            mine.append(moved)
        strings.append(mine)

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            if len(batch):
                x, ids = stacked(batch["embedding"]), batch["vec_id"].to_numpy()
                b = np.floor(np.round(x @ matrix.T, 9) / w)
                for a, qid in enumerate(q.ids.tolist()):
                    run = np.max([longest_circular_run(b == s) for s in strings[a]], axis=0)
                    run[ids == qid] = -1
                    best = smallest(-run.astype(float), ids, n_cand)
                    best = best[run[best] >= 0]
                    out.append(pd.DataFrame({"query_id": qid, "vec_id": ids[best], "run": run[best], "dist": distances(x[best], q.vectors[a])}))
            yield framed(out, ["query_id", "vec_id", "run", "dist"])

    found = points.select("vec_id", "embedding").mapInPandas(rows, "query_id long, vec_id long, run long, dist double")
    w_ = Window.partitionBy("query_id").orderBy(F.desc("run"), "vec_id")
    return ranked(found.withColumn("at", F.row_number().over(w_)).where(F.col("at") <= n_cand).select("query_id", "vec_id", "dist"), k)


def box_tiles(projected: DataFrame, leaf_size: int = 64) -> DataFrame:
    """(tile, n, lo, hi): sort-tile boxes over the first two projected coordinates, by range partitions: the data-oriented tree's leaf level."""
    n = projected.count()
    strips = max(1, round(math.sqrt(max(n, 1) / leaf_size)))
    x, y = F.get("proj", F.lit(0)), F.get("proj", F.lit(1))
    from ..operators.selection import ranked_columns

    cuts = ranked_columns(projected.select(F.array(x).alias("x")), "x", [[min(n, i * n // strips + 1) for i in range(1, strips)]])[0] if strips > 1 else []
    at = F.size(F.filter(F.array(*[F.lit(c) for c in cuts]), lambda c: c <= x)) if cuts else F.lit(0)
    one = projected.select(x.alias("x"), y.alias("y"), at.alias("strip"))
    sizes = {r["strip"]: r["n"] for r in one.groupBy("strip").agg(F.count(F.lit(1)).alias("n")).collect()}
    wide = one.select("strip", F.array(*[F.when(F.col("strip") == s, F.col("y")) .otherwise(F.lit(1.7e308)) for s in range(strips)]).alias("ys"))
    inner = ranked_columns(wide, "ys", [[min(sizes.get(s, 0), i * sizes.get(s, 0) // strips + 1) for i in range(1, strips)] if sizes.get(s) else [] for s in range(strips)]) if strips > 1 else [[]]
    lists = F.array(*[F.array(*[F.lit(float(c)) for c in cs]) if cs else F.array().cast("array<double>") for cs in inner])
    tiled = one.withColumn("row", F.size(F.filter(F.get(lists, F.col("strip")), lambda c: c <= F.col("y"))))
    return tiled.groupBy("strip", "row").agg(F.count(F.lit(1)).alias("n"), F.min("x").alias("x_lo"), F.max("x").alias("x_hi"), F.min("y").alias("y_lo"), F.max("y").alias("y_hi"))
