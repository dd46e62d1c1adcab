"""Layered proximity graphs, one per shard: greedy descent, then best-first search. No guarantee."""

from __future__ import annotations

import heapq
import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.exact import Queries, collected, framed, ranked
from ..operators.projection import DECIMALS, stacked

SHARD_ROWS = 20_000


class Graph:
    """A graph of levels over the rows of one shard, built point by point."""

    def __init__(self, x: np.ndarray, M: int = 25, ef: int = 200, seed: int = 1):
        self.x, self.M, self.ef = x, M, ef
        rng = np.random.Generator(np.random.PCG64(seed))
        self.level = np.floor(-np.log(1 - rng.random(len(x))) / math.log(max(M, 2))).astype(int)
        self.links: list[list[list[int]]] = [[[] for _ in range(h + 1)] for h in self.level]
        self.entry = -1
        for i in range(len(x)):
            self._add(i)

    def _far(self, v: np.ndarray, ids: list[int]) -> np.ndarray:
        return np.sqrt(((self.x[ids] - v) ** 2).sum(1))

    def _beam(self, v: np.ndarray, start: list[int], ef: int, level: int) -> list[tuple[float, int]]:
        """The ef nearest points that a best-first walk on one level meets, nearest first."""
        first = self._far(v, start)
        seen = set(start)
        todo = list(zip(first.tolist(), start, strict=True))
        heapq.heapify(todo)
        best = [(-d, i) for d, i in todo]
        heapq.heapify(best)
        while todo:
            d, i = heapq.heappop(todo)
            if len(best) >= ef and d > -best[0][0]:
                break
            new = [j for j in self.links[i][level] if j not in seen]
            if not new:
                continue
            seen.update(new)
            for dj, j in zip(self._far(v, new).tolist(), new, strict=True):
                if len(best) < ef or dj < -best[0][0]:
                    heapq.heappush(todo, (dj, j))
                    heapq.heappush(best, (-dj, j))
                    if len(best) > ef:
                        heapq.heappop(best)
        return sorted((-d, i) for d, i in best)

    def _diverse(self, found: list[tuple[float, int]], most: int) -> list[int]:
        """Near points, each nearer to the centre than to any one already taken; filled up by the nearest."""
        taken: list[int] = []
        for d, i in found:
            if len(taken) == most:
                break
            if not taken or d <= self._far(self.x[i], taken).min():
                taken.append(i)
        rest = [i for _, i in found if i not in set(taken)]
        return taken + rest[: most - len(taken)]

    def _add(self, i: int) -> None:
        if self.entry < 0:
            self.entry = i
            return
        at, v = [self.entry], self.x[i]
        top = self.level[self.entry]
        for h in range(top, self.level[i], -1):
            at = [self._beam(v, at, 1, h)[0][1]]
        for h in range(min(top, self.level[i]), -1, -1):
            found = self._beam(v, at, self.ef, h)
            most = self.M if h else 2 * self.M
            for j in self._diverse(found, self.M):
                self.links[i][h].append(j)
                self.links[j][h].append(i)
                if len(self.links[j][h]) > most:
                    near = self.links[j][h]
                    order = sorted(zip(self._far(self.x[j], near).tolist(), near, strict=True))
                    self.links[j][h] = self._diverse(order, most)
            at = [j for _, j in found]
        if self.level[i] > top:
            self.entry = i

    def nearest(self, v: np.ndarray, k: int, ef: int) -> list[tuple[float, int]]:
        if self.entry < 0:
            return []
        at = [self.entry]
        for h in range(self.level[self.entry], 0, -1):
            at = [self._beam(v, at, 1, h)[0][1]]
        return self._beam(v, at, max(ef, k), 0)[:k]


def layered_graph_ann(points: DataFrame, queries: DataFrame | Queries, k: int = 50, M: int = 25, ef_build: int = 200, ef: int = 100, shards: int | None = None) -> DataFrame:
    """(query_id, rank, vec_id, dist): a graph per shard of SHARD_ROWS points at most, the queries asked of each, the best merged."""
    q = queries if isinstance(queries, Queries) else collected(queries)
    shards = shards or max(1, math.ceil(points.count() / SHARD_ROWS))

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("vec_id")
        ids = pdf["vec_id"].to_numpy()
        graph, out = Graph(stacked(pdf["embedding"]), M, ef_build), []
        for qid, v in zip(q.ids.tolist(), q.vectors, strict=True):
            got = [(d, ids[i]) for d, i in graph.nearest(v, k + 1, ef) if ids[i] != qid][:k]
            out.append(pd.DataFrame({"query_id": qid, "vec_id": [i for _, i in got], "dist": [round(d, DECIMALS) for d, _ in got]}))
        return framed(out, ["query_id", "vec_id", "dist"])

    shard = F.pmod(F.xxhash64("vec_id"), F.lit(shards)).cast("int").alias("shard")
    found = points.select("vec_id", "embedding", shard).groupBy("shard").applyInPandas(one, "query_id long, vec_id long, dist double")
    return ranked(found, k)
