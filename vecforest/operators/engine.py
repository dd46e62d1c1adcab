"""One search engine for all methods that pool projected neighbours under growing radii.

A method differs from the others in its projected proximity: the Euclidean
norm, the greatest coordinate difference, or the l-th smallest one. A point
enters a query's pool at one step, round * L + space; the loop over rounds and
spaces stops at the first step where the budget is full or enough points are
near enough. So a search is: find the first radius (order statistic), count
points by step, take the stop, and read the answers of the steps up to it.
Each part is one pass over the points; vectors are never shuffled.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .exact import Queries, distances, framed, ranked, smallest
from .projection import DECIMALS, stacked
from .selection import ranked_columns


SELF = 1.7e308  # proximity of a query to its own row: beyond all others
TINY = 1e-9


@dataclass
class Spaces:
    """L projected spaces of K dimensions and the proximity that is measured in them."""

    matrix: np.ndarray
    K: int
    L: int
    kind: str = "l2"  # l2, linf (twice the greatest difference over w), kth (the order-th smallest difference)
    w: float = 1.0
    order: int = 1

    def project(self, x: np.ndarray) -> np.ndarray:
        return np.round(x @ self.matrix.T, DECIMALS) if len(x) else np.zeros((0, self.K * self.L))

    def proximity(self, px: np.ndarray, pq: np.ndarray) -> np.ndarray:
        """Proximity of each point (row) to one query in each space (column)."""
        delta = np.abs(px - pq).reshape(len(px), self.L, self.K)
        if self.kind == "l2":
            out = np.sqrt((delta**2).sum(2))
        elif self.kind == "linf":
            out = 2 * delta.max(2) / self.w
        elif self.kind == "kth":
            out = np.partition(delta, self.order - 1, axis=2)[:, :, self.order - 1] if self.K else delta.sum(2)
        else:
            raise ValueError(self.kind)
        return np.round(out, DECIMALS)


@dataclass
class Radii:
    """Projected radii by query: first * c ** round; the true radius is the projected one over eps."""

    first: dict[int, float]
    c: float
    eps: float
    rounds: int = 1

    def projected(self, query: int) -> np.ndarray:
        return self.first[query] * np.power(self.c, np.arange(self.rounds))

    def near(self, query: int) -> np.ndarray:
        """c times the true radius, by round."""
        return self.c * (self.projected(query) / self.eps)


@dataclass
class Stops:
    """Last admitted step of each query, its pool's size, and how it stopped."""

    step: dict[int, int] = field(default_factory=dict)
    pooled: dict[int, int] = field(default_factory=dict)
    why: dict[int, str] = field(default_factory=dict)
    n: dict[int, int] = field(default_factory=dict)


def steps(p: np.ndarray, radii: np.ndarray, L: int) -> np.ndarray:
    """Entry step of each point: least over spaces of round * L + space (from 1); 0 beyond the last round."""
    t = np.searchsorted(radii, p, side="left")
    e = np.where(t < len(radii), t * L + np.arange(1, L + 1), np.iinfo(np.int64).max)
    e = e.min(1)
    return np.where(e == np.iinfo(np.int64).max, 0, e)


def first_radius(points: DataFrame, q: Queries, spaces: Spaces, need: dict[int, int]) -> dict[int, float]:
    """By query: the need-th smallest proximity to another point, the least radius that fills the budget."""

    def nearest(v: pd.Series, ids: pd.Series) -> pd.Series:
        px, i = spaces.project(stacked(v)), ids.to_numpy()
        pairs = zip(q.ids, spaces.project(q.vectors), strict=True)
        return pd.Series(list(np.stack([np.where(i == qid, SELF, spaces.proximity(px, pq).min(1)) for qid, pq in pairs], 1)) if len(v) else [], dtype=object)

    near = points.select(F.pandas_udf(nearest, "array<double>")("embedding", "vec_id").alias("m"))
    got = ranked_columns(near, "m", [[need[i]] for i in q.ids.tolist()])
    return {qid: max(r, TINY) if r < SELF else TINY for qid, (r,) in zip(q.ids.tolist(), got, strict=True)}


def tally(points: DataFrame, q: Queries, spaces: Spaces, radii: Radii) -> dict[int, tuple[int, np.ndarray, np.ndarray]]:
    """By query: other points, points by entry step, and near points by the round in which both tests first hold. One pass; tasks add up."""
    pq = spaces.project(q.vectors)

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            if not len(batch):
                continue
            x, ids = stacked(batch["embedding"]), batch["vec_id"].to_numpy()
            px, out = spaces.project(x), []
            for a, qid in enumerate(q.ids.tolist()):
                other = ids != qid
                e = steps(spaces.proximity(px[other], pq[a]), radii.projected(qid), spaces.L)
                d = distances(x[other][e > 0], q.vectors[a])
                e_in = e[e > 0]
                both = np.maximum((e_in - 1) // spaces.L, np.searchsorted(radii.near(qid), d, side="left"))
                both = both[both < radii.rounds]
                out.append(pd.DataFrame({"a": a, "kind": 0, "at": 0, "n": [int(other.sum())]}))
                for kind, values in ((1, e_in), (2, both)):
                    v, n = np.unique(values, return_counts=True)
                    out.append(pd.DataFrame({"a": a, "kind": kind, "at": v, "n": n}))
            yield pd.concat(out)

    rows = points.select("vec_id", "embedding").mapInPandas(count, "a int, kind int, at long, n long").groupBy("a", "kind", "at").agg(F.sum("n").alias("n")).collect()
    total = np.zeros(len(q), dtype=np.int64)
    entered = np.zeros((len(q), radii.rounds * spaces.L + 1), dtype=np.int64)
    near = np.zeros((len(q), radii.rounds), dtype=np.int64)
    for r in rows:
        if r["kind"] == 0:
            total[r["a"]] = r["n"]
        elif r["kind"] == 1:
            entered[r["a"], r["at"]] = r["n"]
        else:
            near[r["a"], r["at"]] = r["n"]
    return {qid: (int(total[a]), entered[a], near[a]) for a, qid in enumerate(q.ids.tolist())}


def stop(counts: dict[int, tuple[int, np.ndarray, np.ndarray]], L: int, k: int, need_of, every: str = "tree") -> Stops:
    """First step where the pool holds need_of(n) points, or where a round ends with k near points, or where no point is left."""
    out = Stops()
    for qid, (n, entered, near) in counts.items():
        pool, close = np.cumsum(entered), np.cumsum(near)
        last = len(entered) - 1
        options = []
        full = np.flatnonzero(pool >= min(need_of(n), max(n, 1)))
        if len(full):
            s = int(full[0]) if every == "tree" else math.ceil(full[0] / L) * L
            options.append((max(s, 1), "budget" if need_of(n) <= n else "exhausted"))
        done = np.flatnonzero(close >= k)
        if len(done):
            options.append(((int(done[0]) + 1) * L, "near"))
        s, why = min(options) if options else (last, "rounds")
        out.step[qid], out.why[qid], out.pooled[qid], out.n[qid] = s, why, int(pool[min(s, last)]), n
    return out


def pool(points: DataFrame, q: Queries, spaces: Spaces, radii: Radii, stops: Stops | None = None) -> DataFrame:
    """(query_id, vec_id, entry_step, dist) of the pooled points."""
    pq = spaces.project(q.vectors)

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            x, ids = stacked(batch["embedding"]), batch["vec_id"].to_numpy()
            px = spaces.project(x)
            for a, qid in enumerate(q.ids.tolist() if len(ids) else []):
                e = steps(spaces.proximity(px, pq[a]), radii.projected(qid), spaces.L)
                ok = (e > 0) & (ids != qid) & (e <= (stops.step[qid] if stops else 1 << 60))
                out.append(pd.DataFrame({"query_id": qid, "vec_id": ids[ok], "entry_step": e[ok], "dist": distances(x[ok], q.vectors[a])}))
            yield framed(out, ["query_id", "vec_id", "entry_step", "dist"])

    return points.select("vec_id", "embedding").mapInPandas(rows, "query_id long, vec_id long, entry_step int, dist double")


def answers(points: DataFrame, q: Queries, spaces: Spaces, radii: Radii, stops: Stops, k: int) -> DataFrame:
    """(query_id, rank, vec_id, dist): the k nearest of the pool; each task hands on k rows a query and batch."""
    pq = spaces.project(q.vectors)

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            x, ids = stacked(batch["embedding"]), batch["vec_id"].to_numpy()
            px = spaces.project(x)
            for a, qid in enumerate(q.ids.tolist() if len(ids) else []):
                e = steps(spaces.proximity(px, pq[a]), radii.projected(qid), spaces.L)
                at = np.flatnonzero((e > 0) & (ids != qid) & (e <= stops.step[qid]))
                d = distances(x[at], q.vectors[a])
                best = smallest(d, ids[at], k)
                out.append(pd.DataFrame({"query_id": qid, "vec_id": ids[at][best], "dist": d[best]}))
            yield framed(out, ["query_id", "vec_id", "dist"])

    return ranked(points.select("vec_id", "embedding").mapInPandas(rows, "query_id long, vec_id long, dist double"), k)


@dataclass
class Search:
    """A finished search: the answers, and how each query went."""

    result: DataFrame
    stops: Stops
    radii: Radii
    guaranteed: bool = False  # by its parameters: budget and first radius


def search(points: DataFrame, q: Queries, spaces: Spaces, k: int, c: float, eps: float, need_of, r_min: str | float | dict = "budget", rounds: int | None = None, every: str = "tree", n: int | None = None) -> Search:
    """Runs the passes. r_min: 'budget', one true radius, or radii by query."""
    if r_min == "budget":
        n = points.count() if n is None else n
        own = {r[0] for r in points.where(F.col("vec_id").isin([int(i) for i in q.ids])).select("vec_id").collect()}
        others = {i: n - (i in own) for i in q.ids.tolist()}
        first = first_radius(points, q, spaces, {i: min(need_of(m), max(m, 1)) for i, m in others.items()})
        radii = Radii(first, c, eps, rounds or 1)
    else:
        first = {int(i): eps * (r_min[int(i)] if isinstance(r_min, dict) else float(r_min)) for i in q.ids}
        radii = Radii(first, c, eps, rounds or 40)
    stops = stop(tally(points, q, spaces, radii), spaces.L, k, need_of, every)
    return Search(answers(points, q, spaces, radii, stops, k), stops, radii)
