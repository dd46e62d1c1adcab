"""Searches over a saved forest without a row for each pair of a query and a point.

The trees' entries of a point are gathered once into one row beside its vector,
clustered by the leaves of the first tree. Each pass hands all queries to the
tasks, which skip the queries that no space of a block of points reaches, and
sends on counts by query, or k answers a query. Proximities come from a matrix
product; those too close to a limit to be told apart are computed again as the
scan does, so every comparison is the scan's.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.staging import staged
from .exact import Queries, ranked
from .projection import DECIMALS, stacked
from .range_query import ForestIndex

BINS = 256  # of a query's proximities, to find its radius
PAIRS_AT_ONCE = 2_000_000  # proximities in memory
ROWS_A_PART = 10_000
SLACK = 2e-6  # a share of the norms: more than a product's rounding adds to a distance


def gathered(index: ForestIndex, points: DataFrame, where: Column | None = None, workers: int = 1) -> DataFrame:
    """(vec_id, embedding, proj): one row a point of the index, space after space; neighbours by the first tree's leaves."""
    some = index.points if where is None else index.points.where(where)
    rows = some.groupBy("vec_id").agg(F.sort_array(F.collect_list(F.struct("space", "leaf_id", "proj"))).alias("at"))
    rows = rows.select("vec_id", F.element_at("at.leaf_id", 1).alias("leaf"), F.flatten("at.proj").alias("proj")).join(points.select("vec_id", "embedding"), "vec_id")
    spark = points.sparkSession
    parts = max(workers, 2 * spark.sparkContext.defaultParallelism, points.count() // ROWS_A_PART)
    # by the id too, so that a leaf of many equal points is no part of its own
    return staged(rows.repartitionByRange(parts, "leaf", "vec_id").sortWithinPartitions("leaf").select("vec_id", "embedding", "proj"), "gathered")


class Block:
    """Some points and the queries that may reach them: proximities (space, query, point), exact where a limit is close."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, px: np.ndarray, q: Queries, pq: np.ndarray, asked: np.ndarray):
        self.ids, self.vectors, self.px, self.q, self.pq, self.asked = ids, vectors, px, q, pq[asked], asked
        self.p = product_distances(self.pq.transpose(1, 0, 2), px.transpose(1, 0, 2))
        self.close = SLACK * (1e-3 + np.sqrt((px**2).sum(2).max()) + np.sqrt((self.pq**2).sum(2)).max(1))
        at = np.minimum(np.searchsorted(q.ids, ids), len(q) - 1)
        place = np.full(len(q), -1)
        place[asked] = np.arange(len(asked))
        own = np.flatnonzero((q.ids[at] == ids) & (place[at] >= 0))
        self.p[:, place[at[own]], own] = np.inf  # a query's own row is never its answer

    def exact(self, a: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Proximities (pair, space) as the scan computes them."""
        out = np.round(np.sqrt(((self.px[j] - self.pq[a]) ** 2).sum(2)), DECIMALS)
        out[self.ids[j] == self.q.ids[self.asked[a]]] = np.inf
        return out

    def sharpened(self, *limits: np.ndarray) -> None:
        """Makes the proximities near a limit (by query) exact."""
        near = np.zeros(self.p.shape[1:], dtype=bool)
        for limit in limits:
            near |= (np.abs(self.p - limit[self.asked][None, :, None]) <= self.close[None, :, None]).any(0)
        a, j = np.nonzero(near)
        if len(a):
            self.p[:, a, j] = self.exact(a, j).T

    def bins(self, width: np.ndarray) -> np.ndarray:
        """Bin of each point's least proximity (query, point); BINS beyond the last one."""
        least, w = self.p.min(0), width[self.asked][:, None]
        share = least / w
        ok = np.isfinite(share)
        a, j = np.nonzero(ok & (np.abs(share - np.rint(np.where(ok, share, 0))) * w <= self.close[:, None]))
        if len(a):
            share[a, j] = self.exact(a, j).min(1) / width[self.asked][a]
        return np.minimum(np.floor(np.where(np.isfinite(share), share, BINS)), BINS).astype(np.int64)

    def entry(self, inner: np.ndarray, outer: np.ndarray) -> np.ndarray:
        """First space (from 1) that admits each point at the outer radius; 0 where one admits it at the inner one, L + 1 where none does."""
        self.sharpened(inner, outer)
        inside = self.p <= outer[self.asked][None, :, None]
        e = np.where(inside.any(0), inside.argmax(0) + 1, len(self.p) + 1)
        e[(self.p <= inner[self.asked][None, :, None]).any(0)] = 0
        return e

    def distances(self) -> tuple[np.ndarray, np.ndarray]:
        """Distances (query, point) by a product, and by query what they may be off by."""
        v = self.q.vectors[self.asked]
        off = SLACK * (1e-3 + np.sqrt((self.vectors**2).sum(1).max()) + np.sqrt((v**2).sum(1)))
        return product_distances(v[None], self.vectors[None])[0], off

    def exact_distances(self, a: np.ndarray, j: np.ndarray) -> np.ndarray:
        return np.round(np.sqrt(((self.vectors[j] - self.q.vectors[self.asked[a]]) ** 2).sum(1)), DECIMALS)


def product_distances(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Distances (space, query, point) of (space, query, dim) to (space, point, dim)."""
    out = q @ x.transpose(0, 2, 1)
    out *= -2
    out += (q**2).sum(2)[:, :, None]
    out += (x**2).sum(2)[:, None, :]
    return np.sqrt(np.maximum(out, 0, out=out), out=out)


def blocks(batches: Iterator[pd.DataFrame], index: tuple[np.ndarray, int, int], q: Queries, radius: np.ndarray | None) -> Iterator[Block]:
    """The points in blocks, each with the queries for which some space's box of it lies within the radius."""
    matrix, K, L = index
    pq = np.round(q.vectors @ matrix.T, DECIMALS).reshape(len(q), L, K)
    size = max(16, PAIRS_AT_ONCE // (L * max(len(q), 1)))
    for batch in batches:
        for at in range(0, len(batch), size):
            part = batch.iloc[at : at + size]
            px = stacked(part["proj"]).reshape(len(part), L, K)
            asked = np.arange(len(q))
            if radius is not None:
                gap = np.maximum(np.maximum(px.min(0) - pq, pq - px.max(0)), 0)
                asked = np.flatnonzero((np.sqrt((gap**2).sum(2)) - 1e-6 <= radius[:, None]).any(1))
            if len(asked):
                yield Block(part["vec_id"].to_numpy(), stacked(part["embedding"]), px, q, pq, asked)


def _of(index: ForestIndex) -> tuple[np.ndarray, int, int]:
    return index.matrix, index.params.K, index.params.L


def _added(rows: DataFrame, q: Queries, width: int) -> np.ndarray:
    """Sums (query, place) of the tasks' rows (a, counts): a row a query on the driver."""
    sums = rows.groupBy("a").agg(F.array(*[F.sum(F.element_at("counts", i + 1)) for i in range(width)]).alias("counts")).collect()
    out = np.zeros((len(q), width), dtype=np.int64)
    for r in sums:
        out[r["a"]] = r["counts"]
    return out


def _picked(rows: DataFrame, q: Queries, need: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """By query: the first of its BINS after which `need` are counted (-1 if none), and the count before it; from rows (a, counts as bytes)."""

    def pick(pdf: pd.DataFrame) -> pd.DataFrame:
        a = int(pdf["a"].iloc[0])
        upto = np.cumsum(np.sum([np.frombuffer(c, dtype=np.int64) for c in pdf["counts"]], axis=0))
        at = int(np.searchsorted(upto, need[a]))
        return pd.DataFrame({"a": [a], "bin": [at if at < BINS else -1], "before": [int(upto[at - 1]) if 0 < at < BINS else 0]})

    bins, before = np.full(len(q), -1), np.zeros(len(q), dtype=np.int64)
    for r in rows.groupBy("a").applyInPandas(pick, "a int, bin int, before long").collect():
        bins[r["a"]], before[r["a"]] = r["bin"], r["before"]
    return bins, before


def _packed(counts: np.ndarray) -> pd.DataFrame:
    held = np.flatnonzero(counts.any(1))
    return pd.DataFrame({"a": held.astype(np.int32), "counts": pd.Series([counts[a].tobytes() for a in held], dtype=object)})


def reach(index: ForestIndex, q: Queries, need: np.ndarray, where: Column | None) -> np.ndarray:
    """By query: a projected radius within which the first tree holds `need` points and one more, from its leaves' upper bounds."""
    K, L = index.params.K, index.params.L
    pq = np.round(q.vectors @ index.matrix.T, DECIMALS).reshape(len(q), L, K)[:, 0]
    ends = np.array([[e[0], e[-1]] for e in index.edges[:K]], dtype=float)
    width = (np.sqrt((np.maximum(np.abs(pq - ends[:, 0]), np.abs(pq - ends[:, 1])) ** 2).sum(1)) * (1 + 1e-6) + 1e-6) / BINS
    leaves = index.leaves.where("space = 1").select("node_id", "lo", "hi", "n_points")
    if where is not None:
        held = index.points.where(where).where("space = 1").groupBy(F.col("leaf_id").alias("node_id")).agg(F.count(F.lit(1)).alias("n_points"))
        leaves = leaves.drop("n_points").join(held, "node_id")

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        counts = np.zeros((len(q), BINS), dtype=np.int64)
        for batch in batches:
            if not len(batch):
                continue
            lo, hi, n = stacked(batch["lo"]), stacked(batch["hi"]), batch["n_points"].to_numpy()
            for a in range(len(q)):
                ub = np.sqrt((np.maximum(np.abs(pq[a] - lo), np.abs(pq[a] - hi)) ** 2).sum(1))
                counts[a] += np.bincount(np.minimum((ub / width[a]).astype(np.int64), BINS - 1), weights=n, minlength=BINS).astype(np.int64)
        yield _packed(counts)

    bins, _ = _picked(leaves.mapInPandas(count, "a int, counts binary"), q, need + 1)
    return np.where(bins < 0, BINS, bins + 1) * width


def filling(index: ForestIndex, rows: DataFrame, q: Queries, need: np.ndarray, most: np.ndarray) -> np.ndarray:
    """By query: the need-th least proximity to another point, none of them beyond `most`; -1 where there are fewer points."""
    width, shape = (most * (1 + 1e-6) + 1e-6) / BINS, _of(index)

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        counts = np.zeros((len(q), BINS + 1), dtype=np.int64)
        for b in blocks(batches, shape, q, most):
            at = b.bins(width) + (np.arange(len(b.asked)) * (BINS + 1))[:, None]
            counts[b.asked] += np.bincount(at.ravel(), minlength=len(b.asked) * (BINS + 1)).reshape(-1, BINS + 1)
        yield _packed(counts[:, :BINS])

    bins, before = _picked(rows.mapInPandas(count, "a int, counts binary"), q, need)

    def values(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in blocks(batches, shape, q, most):
            a, j = np.nonzero(b.bins(width) == bins[b.asked][:, None])
            met = pd.DataFrame({"a": b.asked[a].astype(np.int32), "p": b.exact(a, j).min(1) if len(a) else np.zeros(0)})
            yield met.groupby(["a", "p"]).size().reset_index(name="n")

    def nth(pdf: pd.DataFrame) -> pd.DataFrame:
        a, some = int(pdf["a"].iloc[0]), pdf.sort_values("p")
        at = int(np.searchsorted(before[a] + some["n"].cumsum().to_numpy(), need[a]))
        return pd.DataFrame({"a": [a], "r": [float(some["p"].iloc[at])]})

    out = np.full(len(q), -1.0)
    for r in rows.mapInPandas(values, "a int, p double, n long").groupBy("a").applyInPandas(nth, "a int, r double").collect():
        out[r["a"]] = r["r"]
    return out


def entering(index: ForestIndex, rows: DataFrame, q: Queries, inner: np.ndarray, outer: np.ndarray, near: np.ndarray | None = None) -> np.ndarray:
    """By query: points that enter beyond the inner radius, by space; and last, points within the outer one whose distance is at most `near`."""
    shape, L = _of(index), index.params.L

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        counts = np.zeros((len(q), L + 2), dtype=np.int64)
        for b in blocks(batches, shape, q, outer):
            e = b.entry(inner, outer)
            at = e + (np.arange(len(b.asked)) * (L + 2))[:, None]
            added = np.bincount(at.ravel(), minlength=len(b.asked) * (L + 2)).reshape(-1, L + 2)
            counts[b.asked, :L] += added[:, 1 : L + 1]
            if near is not None:
                d, off = b.distances()
                limit, off = near[b.asked][:, None], off[:, None]
                inside = e <= L
                ok = inside & (d <= limit)
                a, j = np.nonzero(inside & (np.abs(d - limit) <= off))
                ok[a, j] = b.exact_distances(a, j) <= near[b.asked][a]
                counts[b.asked, L] += ok.sum(1)
        held = np.flatnonzero(counts.any(1))
        yield pd.DataFrame({"a": held.astype(np.int32), "counts": pd.Series(list(counts[held, : L + 1]), dtype=object)})

    return _added(rows.mapInPandas(count, "a int, counts array<long>"), q, L + 1)


def nearest(index: ForestIndex, rows: DataFrame, q: Queries, inner: np.ndarray, outer: np.ndarray, last: np.ndarray, k: int) -> DataFrame:
    """(query_id, rank, vec_id, dist): the k nearest of the points within the inner radius, or the outer one in the spaces up to `last`; each task hands on k rows a query."""
    shape = _of(index)

    def rows_of(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        who, dist, ids = np.zeros(0, dtype=np.int64), np.zeros(0), np.zeros(0, dtype=np.int64)
        bound = np.full(len(q), np.inf)  # the k-th distance so far
        for b in blocks(batches, shape, q, np.maximum(inner, outer)):
            d, off = b.distances()
            d[b.entry(inner, outer) > last[b.asked][:, None]] = np.inf
            limit = bound[b.asked]
            if d.shape[1] > k:
                limit = np.minimum(limit, np.partition(d, k - 1, axis=1)[:, k - 1] + off)
            a, j = np.nonzero((d <= (limit + off)[:, None]) & np.isfinite(d))
            who, dist, ids = np.r_[who, b.asked[a]], np.r_[dist, b.exact_distances(a, j)], np.r_[ids, b.ids[j]]
            by = np.lexsort((ids, dist, who))
            who, dist, ids = who[by], dist[by], ids[by]
            place = np.arange(len(who)) - np.searchsorted(who, who)
            bound[who[place == k - 1]] = dist[place == k - 1]
            who, dist, ids = who[place < k], dist[place < k], ids[place < k]
        yield pd.DataFrame({"query_id": q.ids[who], "vec_id": ids, "dist": dist})

    return ranked(rows.mapInPandas(rows_of, "query_id long, vec_id long, dist double"), k)
