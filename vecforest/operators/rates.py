"""Rates over all pairs of a bounded query set with all points, in blocks: each task sends on its counts."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .exact import Queries, collected
from .projection import DECIMALS, stacked

PAIRS_AT_ONCE = 2_000_000  # squared projected distances in memory
SLACK = 1e-9  # a share of the squared norms: more than a product's rounding adds


class Pairs:
    """Queries against a block of points: squared distances s2 (query, point) and squared projected ones p2 (space, query, point), by products."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, q: Queries, matrix: np.ndarray, K: int):
        self.x, self.q, L = x, q, len(matrix) // K
        self.px = np.round(x @ matrix.T, DECIMALS).reshape(len(x), L, K)
        self.pq = np.round(q.vectors @ matrix.T, DECIMALS).reshape(len(q), L, K)
        self.other = q.ids[:, None] != ids[None, :]
        self.s2 = self._squared(q.vectors[None], x[None])[0]
        self.p2 = self._squared(self.pq.transpose(1, 0, 2), self.px.transpose(1, 0, 2))
        self.off = SLACK * ((self.px**2).sum(2).max() + (self.pq**2).sum(2).max() + (x**2).sum(1).max() + (q.vectors**2).sum(1).max())

    @staticmethod
    def _squared(q: np.ndarray, x: np.ndarray) -> np.ndarray:
        out = q @ x.transpose(0, 2, 1)
        out *= -2
        out += (q**2).sum(2)[:, :, None]
        out += (x**2).sum(2)[:, None, :]
        return out

    def exact(self, a: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Squared distances (pair) and squared projected ones (pair, space), by differences."""
        return ((self.x[j] - self.q.vectors[a]) ** 2).sum(1), ((self.px[j] - self.pq[a]) ** 2).sum(2)


def _blocks(batches: Iterator[pd.DataFrame], q: Queries, matrix: np.ndarray, K: int) -> Iterator[Pairs]:
    size = max(16, PAIRS_AT_ONCE // (max(len(q), 1) * (len(matrix) // K)))
    for batch in batches:
        for at in range(0, len(batch) if len(q) else 0, size):
            part = batch.iloc[at : at + size]
            yield Pairs(part["vec_id"].to_numpy(), stacked(part["embedding"]), q, matrix, K)


def tail_check(points: DataFrame, queries: DataFrame | Queries, matrix: np.ndarray, K: int, tails: list[tuple[float, float]]) -> DataFrame:
    """By (alpha, quantile): the share of projected distances above s * sqrt(quantile); about alpha. Pairs at distance 0 count as above, as a ratio that is no number is greatest."""
    q = queries if isinstance(queries, Queries) else collected(queries)
    L = len(matrix) // K

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        over, pairs = [0] * len(tails), 0
        for b in _blocks(batches, q, matrix, K):
            pairs += int(b.other.sum()) * L
            for i, (_, x) in enumerate(tails):
                limit = x * b.s2
                above = b.p2 > limit
                above &= b.other
                a, j = np.nonzero((np.abs(b.p2 - limit) <= (1 + x) * b.off).any(0) & b.other)
                s2, p2 = b.exact(a, j)
                s2 = np.sqrt(s2) ** 2
                above[:, a, j] = ((p2 / np.where(s2 > 0, s2, 1.0)[:, None] > x) | (s2 == 0)[:, None]).T
                over[i] += int(above.sum())
        yield pd.DataFrame({"alpha": [a for a, _ in tails], "over": over, "pairs": pairs})

    rows = points.select("vec_id", "embedding").mapInPandas(count, "alpha double, over long, pairs long")
    return rows.groupBy("alpha").agg((F.sum("over") / F.sum("pairs")).alias("rate"))


def admitted(points: DataFrame, queries: DataFrame | Queries, matrix: np.ndarray, K: int, reach: list[float]) -> DataFrame:
    """(L, share): of the pairs, those of which one of the first L spaces shrinks the distance to reach[L - 1] of it or less; pairs at distance 0 are left out."""
    q = queries if isinstance(queries, Queries) else collected(queries)

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        met, pairs = np.zeros(len(reach), dtype=np.int64), 0
        for b in _blocks(batches, q, matrix, K):
            ok = b.other.copy()
            a, j = np.nonzero(ok & (b.s2 <= b.off))
            ok[a, j] = np.round(np.sqrt(b.exact(a, j)[0]), DECIMALS) > 0
            pairs += int(ok.sum())
            least = np.minimum.accumulate(b.p2, axis=0)
            for i, r in enumerate(reach):
                limit = r * r * b.s2
                inside = (least[i] <= limit) & ok
                # rounded to DECIMALS, either distance may move by as much again
                a, j = np.nonzero(ok & (np.abs(least[i] - limit) <= (1 + r * r) * b.off + 1e-7))
                s2, p2 = b.exact(a, j)
                inside[a, j] = np.round(np.sqrt(p2), DECIMALS)[:, : i + 1].min(1, initial=np.inf) / np.round(np.sqrt(s2), DECIMALS) <= r
                met[i] += int(inside.sum())
        yield pd.DataFrame({"L": np.arange(1, len(reach) + 1), "met": met, "pairs": pairs})

    rows = points.select("vec_id", "embedding").mapInPandas(count, "L long, met long, pairs long")
    return rows.groupBy("L").agg((F.sum("met") / F.sum("pairs")).alias("share"))
