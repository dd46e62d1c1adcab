"""Persisted forests and range queries on their trees."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.params import ForestParams
from ..plans.staging import staged
from .breakpoints import breakpoints, sampled, static_breakpoints
from .encode import Edges, by_space, edges_of, encode, packed, with_root_key
from .exact import Queries, framed
from .projection import dimension, project, projection_matrix
from .tree import build_forest, forest_stats, with_cells

LEAF_BROADCAST = 200_000  # rows of a leaf list that go to every task; a longer list is joined by a shuffle


@dataclass
class ForestIndex:
    """L trees: node table with cells, and the points by leaf (space, leaf_id, vec_id, code, proj)."""

    params: ForestParams
    d: int
    matrix: np.ndarray
    edges: Edges
    nodes: DataFrame
    points: DataFrame

    @property
    def leaves(self) -> DataFrame:
        return self.nodes.where("is_leaf")

    def stats(self) -> DataFrame:
        return forest_stats(self.nodes)

    def save(self, path: str) -> None:
        """Points by space, clustered by leaf, so that row groups carry narrow leaf ranges; the model beside them."""
        spark = self.points.sparkSession
        self.points.repartitionByRange("space", "leaf_id").sortWithinPartitions("leaf_id").write.mode("overwrite").partitionBy("space").parquet(f"{path}/points")
        self.nodes.write.mode("overwrite").parquet(f"{path}/nodes")
        p = self.params
        model = {"params": {k: getattr(p, k) for k in p.__dataclass_fields__}, "d": self.d, "edges": self.edges, "matrix": self.matrix.tolist()}
        spark.createDataFrame([(json.dumps(model),)], "model string").coalesce(1).write.mode("overwrite").text(f"{path}/model")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> ForestIndex:
        model = json.loads(spark.read.text(f"{path}/model").first()[0])
        return cls(ForestParams(**model["params"]), model["d"], np.array(model["matrix"]), model["edges"], spark.read.parquet(f"{path}/nodes"), spark.read.parquet(f"{path}/points"))


def build_index(points: DataFrame, params: ForestParams, strategy: str = "hybrid", method: str = "histogram_rounds", encoder: str = "dynamic", keep: tuple[str, ...] = (), rule: str = "even", matrix: np.ndarray | None = None) -> ForestIndex:
    """Projects (by the params' own matrix unless one is given), cuts, encodes and builds by a split rule (even, cycle, first); raw vectors are read in narrow stages only, codes and projected coordinates are shuffled."""
    d = dimension(points)
    matrix = projection_matrix(d, params.K, params.L, params.seed) if matrix is None else matrix
    projected = staged(project(points.select("vec_id", "embedding", *keep), matrix).drop("embedding"), "projected")
    part = sampled(projected, params.sample, regions=params.regions)
    table = breakpoints(projected, params.K, params.L, params.regions, method, part)
    edges = edges_of(table, params.K, params.L)
    if encoder == "static":
        inner = static_breakpoints(params.regions)
        edges = [[min(e[0], inner[0]), *inner, max(e[-1], inner[-1])] for e in edges]
    spaced = with_root_key(by_space(encode(projected, edges), params.K, params.L, keep=keep), params.K, params.bits)
    nodes, placed = build_forest(spaced, params.K, params.max_size, strategy, params.bits, rule)
    nodes = staged(with_cells(nodes, edges, params.K, params.bits), "cells")
    return ForestIndex(params, d, matrix, edges, nodes, staged(placed.select("space", "leaf_id", "vec_id", "code", "proj", *keep), "leaves"))


def _bounds(lo: np.ndarray, hi: np.ndarray, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bounds of the distances of boxes (rows) to a point, rounded outwards."""
    gap = np.maximum(np.maximum(lo - q, q - hi), 0)
    far = np.maximum(np.abs(q - lo), np.abs(q - hi))
    return np.floor(np.sqrt((gap**2).sum(1)) * 1e9) / 1e9, np.ceil(np.sqrt((far**2).sum(1)) * 1e9) / 1e9


def leaves_for(index: ForestIndex, q: Queries, radius: dict[int, float], beyond: dict[int, float] | None = None, nodes: DataFrame | None = None) -> DataFrame:
    """(query_id, space, leaf_id, lb, ub, n_points, q, radius): leaves whose lower bound is at most the query's radius (and above `beyond`)."""
    K, L = index.params.K, index.params.L
    pq = np.round(q.vectors @ index.matrix.T, 9).reshape(len(q), L, K)

    def judge(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for space, part in batch.groupby("space"):
                lo, hi = np.stack(part["lo"].tolist()), np.stack(part["hi"].tolist())
                for a, qid in enumerate(q.ids.tolist()):
                    lb, ub = _bounds(lo, hi, pq[a, space - 1])
                    ok = lb <= radius[qid]
                    if beyond is not None:
                        ok &= lb > beyond[qid]
                    n = int(ok.sum())
                    out.append(pd.DataFrame({"query_id": qid, "space": space, "leaf_id": part["node_id"].to_numpy()[ok], "lb": lb[ok], "ub": ub[ok], "n_points": part["n_points"].to_numpy()[ok], "q": [pq[a, space - 1]] * n, "radius": float(radius[qid])}))
            yield framed(out, ["query_id", "space", "leaf_id", "lb", "ub", "n_points", "q", "radius"])

    source = (index.leaves if nodes is None else nodes).select("space", "node_id", "lo", "hi", "n_points")
    return source.mapInPandas(judge, "query_id long, space int, leaf_id long, lb double, ub double, n_points long, q array<double>, radius double")


def frontier(index: ForestIndex, q: Queries, radius: dict[int, float]) -> tuple[DataFrame, DataFrame]:
    """The leaves as in leaves_for(), found by walking down from the roots; and counters by query and space.

    Each step evaluates the children of the nodes that survived: for node
    tables too large to be read whole.
    """
    level = leaves_for(index, q, radius, nodes=index.nodes.where("parent_id is null"))
    found, counts = [], []
    for _ in range(8 * index.params.K + 1):
        level = staged(level, "frontier")
        if level.isEmpty():
            break
        kinds = level.join(index.nodes.select("space", F.col("node_id").alias("leaf_id"), "is_leaf"), ["space", "leaf_id"])
        found.append(kinds.where("is_leaf").drop("is_leaf"))
        counts.append(kinds.select("query_id", "space", "is_leaf"))
        children = index.nodes.select("space", F.col("parent_id").alias("leaf_id"), "node_id", "lo", "hi", F.col("n_points").alias("np")).join(kinds.where("not is_leaf").select("query_id", "space", "leaf_id", "q", "radius"), ["space", "leaf_id"])
        level = _judged(children)
    out, c = found[0], counts[0]
    for x, y in zip(found[1:], counts[1:], strict=True):
        out, c = out.unionByName(x), c.unionByName(y)
    return out.select("query_id", "space", "leaf_id", "lb", "ub", "n_points", "q", "radius"), c.groupBy("query_id", "space").agg(F.count(F.lit(1)).alias("nodes_kept"), F.count_if("is_leaf").alias("leaves_kept"))


def _judged(children: DataFrame) -> DataFrame:
    def judge(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            if not len(batch):
                continue
            lo, hi, q = (np.stack(batch[c].tolist()) for c in ("lo", "hi", "q"))
            lb, ub = _bounds(lo, hi, q)
            ok = lb <= batch["radius"].to_numpy()
            yield batch.assign(lb=lb, ub=ub)[ok][["query_id", "space", "node_id", "lb", "ub", "np", "q", "radius"]].rename(columns={"node_id": "leaf_id", "np": "n_points"})

    return children.mapInPandas(judge, "query_id long, space int, leaf_id long, lb double, ub double, n_points long, q array<double>, radius double")


def points_of(index: ForestIndex, leaves: DataFrame, leaf_filter: str = "exact", n_leaves: int | None = None, where: Column | None = None) -> DataFrame:
    """(query_id, space, vec_id, p, lb, leaf_id) of the leaves' points that pass: exact projected distance, bound of the point's own cell, or all.

    Points of a leaf that lies inside the radius pass untested (its upper bound
    is within). A query's own row is left out. where restricts the points by
    columns that the index keeps.
    """
    K = index.params.K
    listed = leaves.select("query_id", "space", "leaf_id", "lb", "ub", "q", "radius")
    if n_leaves is not None and n_leaves <= LEAF_BROADCAST:
        listed = F.broadcast(listed)
    some = index.points if where is None else index.points.where(where)
    rows = some.join(listed, ["space", "leaf_id"]).where(F.col("vec_id") != F.col("query_id"))
    terms = sum(((F.element_at("proj", j) - F.element_at("q", j)) * (F.element_at("proj", j) - F.element_at("q", j)) for j in range(2, K + 1)), (F.element_at("proj", 1) - F.element_at("q", 1)) * (F.element_at("proj", 1) - F.element_at("q", 1)))
    rows = rows.withColumn("p", F.round(F.sqrt(terms), 9))
    limit = F.col("radius")
    if leaf_filter == "exact":
        rows = rows.where((F.col("ub") <= limit) | (F.col("p") <= limit))
    elif leaf_filter == "cell":
        rows = rows.where((F.col("ub") <= limit) | (_cell_bound(index)("space", "code", "q") <= limit))
    elif leaf_filter != "leaf":
        raise ValueError(leaf_filter)
    return rows.select("query_id", "space", "vec_id", "p", "lb", "leaf_id")


def _cell_bound(index: ForestIndex):
    """Lower bound of a point's own cell, by one look-up of all edges of a batch."""
    edges, K = np.array(index.edges, dtype=float), index.params.K

    def bound(space: pd.Series, code: pd.Series, q: pd.Series) -> pd.Series:
        if not len(space):
            return pd.Series([], dtype=float)
        c = np.stack([np.asarray(x, dtype=np.int64) for x in code])
        row = (space.to_numpy(dtype=np.int64)[:, None] - 1) * K + np.arange(K)
        return pd.Series(_bounds(edges[row, c], edges[row, c + 1], np.stack(q.tolist()))[0])

    return F.pandas_udf(bound, "double")


def range_query(index: ForestIndex, q: Queries, radius: float | dict[int, float], leaf_filter: str = "exact", walk: str = "flat", n_workers: int = 1, n_queues: int = 1) -> DataFrame:
    """(query_id, space, vec_id, p, lb, leaf_id): points within a projected radius in each tree.

    With workers and queues the leaf list is dealt by first-layer node and a
    queue number; the answer does not depend on either.
    """
    r = radius if isinstance(radius, dict) else {int(i): float(radius) for i in q.ids}
    leaves = leaves_for(index, q, r) if walk == "flat" else frontier(index, q, r)[0]
    if n_workers > 1 or n_queues > 1:
        leaves = leaves.withColumn("queue", F.pmod(F.xxhash64("leaf_id"), F.lit(max(n_queues, 1)))).repartition(n_workers, "space", "leaf_id", "queue").drop("queue")
    leaves = staged(leaves, "leaf-list")
    return points_of(index, leaves, leaf_filter, leaves.count())


def range_ring(index: ForestIndex, q: Queries, inner: dict[int, float] | float, outer: dict[int, float] | float, leaf_filter: str = "exact") -> DataFrame:
    """Points whose projected distance lies in (inner, outer]: what a grown radius adds."""
    as_map = lambda r: r if isinstance(r, dict) else {int(i): float(r) for i in q.ids}
    lo = as_map(inner)
    limit = F.element_at(F.create_map(*[x for i, r in lo.items() for x in (F.lit(i).cast("long"), F.lit(float(r)))]), F.col("query_id"))
    return range_query(index, q, as_map(outer), leaf_filter).where(F.col("p") > limit)


def range_trace(index: ForestIndex, q: Queries, radius: float) -> DataFrame:
    """By query and space: leaves seen, pruned, contained and straddling, and points tested."""
    r = {int(i): float(radius) for i in q.ids}
    everything = leaves_for(index, q, {i: float("inf") for i in r})
    lb, ub, n = F.col("lb"), F.col("ub"), F.col("n_points")
    inside = lb <= radius
    return everything.groupBy("query_id", "space").agg(
        F.count(F.lit(1)).alias("leaves"), F.count_if(~inside).alias("pruned"), F.count_if(ub <= radius).alias("contained"), F.count_if(inside & (ub > radius)).alias("straddling"),
        F.coalesce(F.sum(F.when(inside & (ub > radius), n)), F.lit(0)).alias("points_tested"), F.coalesce(F.sum(F.when(ub <= radius, n)), F.lit(0)).alias("points_taken"),
    )


def code_bytes(index: ForestIndex) -> DataFrame:
    """Points with their codes packed, one byte a symbol."""
    return index.points.select("space", "leaf_id", packed("code").alias("code"), "vec_id")
