"""Inverted multi-index with rotated product codes: cells from two coarse codebooks, distances from lookup tables. No guarantee."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.exact import Queries, collected, distances, framed, ranked, smallest
from ..operators.projection import stacked

TRAIN_ROWS = 20_000  # vectors that a training sees at most


def kmeans(x: np.ndarray, k: int, rounds: int = 12, seed: int = 1) -> np.ndarray:
    rng = np.random.Generator(np.random.PCG64(seed))
    centres = x[rng.choice(len(x), k, replace=False)].copy()
    for _ in range(rounds):
        near = nearest(x, centres)
        for j in range(k):
            if (near == j).any():
                centres[j] = x[near == j].mean(0)
    return centres


def nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return ((x**2).sum(1)[:, None] - 2 * x @ centres.T + (centres**2).sum(1)[None]).argmin(1)


@dataclass
class Codebooks:
    rotation: np.ndarray
    coarse: list[np.ndarray]
    fine: list[np.ndarray]

    def halves(self, x: np.ndarray) -> list[np.ndarray]:
        return np.array_split(x @ self.rotation, len(self.coarse), axis=1)

    def encode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Coarse cells and fine codes, one column a part."""
        parts = self.halves(x)
        cells = [nearest(p, c) for p, c in zip(parts, self.coarse, strict=True)]
        rest = [p - c[a] for p, c, a in zip(parts, self.coarse, cells, strict=True)]
        return np.stack(cells, 1), np.stack([nearest(r, f) for r, f in zip(rest, self.fine, strict=True)], 1)


def learn(x: np.ndarray, M: int = 2, k_coarse: int = 16, k_fine: int = 64, rounds: int = 4, seed: int = 1) -> Codebooks:
    """Codebooks and rotation in turn: k-means in each part, then the rotation that brings the vectors nearest to their codes."""
    books = Codebooks(np.eye(x.shape[1]), [], [])
    for _ in range(rounds):
        parts = np.array_split(x @ books.rotation, M, axis=1)
        books.coarse = [kmeans(p, min(k_coarse, len(x)), seed=seed) for p in parts]
        rest = [p - c[nearest(p, c)] for p, c in zip(parts, books.coarse, strict=True)]
        books.fine = [kmeans(r, min(k_fine, len(x)), seed=seed) for r in rest]
        cells, codes = books.encode(x)
        y = np.concatenate([c[a] + f[b] for c, f, a, b in zip(books.coarse, books.fine, cells.T, codes.T, strict=True)], 1)
        u, _, vt = np.linalg.svd(x.T @ y)
        books.rotation = u @ vt
    parts = np.array_split(x @ books.rotation, M, axis=1)
    books.coarse = [kmeans(p, min(k_coarse, len(x)), seed=seed) for p in parts]
    books.fine = [kmeans(p - c[nearest(p, c)], min(k_fine, len(x)), seed=seed) for p, c in zip(parts, books.coarse, strict=True)]
    return books


def multi_codebook_ann(points: DataFrame, queries: DataFrame | Queries, k: int = 50, M: int = 2, k_coarse: int = 16, k_fine: int = 64, n_probe: int = 32, exact: int = 0, seed: int = 1) -> DataFrame:
    """(query_id, rank, vec_id, dist): the n_probe cells nearest to a query, points ranked by table distances; with `exact`, so many of them by true distance.

    Training sees a sample of TRAIN_ROWS vectors chosen by a hash; every vector is encoded.
    """
    q = queries if isinstance(queries, Queries) else collected(queries)
    n = points.count()
    share = min(1.0, TRAIN_ROWS / max(n, 1))
    sample = points.where(F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.lit(1 << 32)) < int(share * (1 << 32))).select("vec_id", "embedding").toPandas().sort_values("vec_id")
    books = learn(stacked(sample["embedding"]), M, k_coarse, k_fine, seed=seed)
    asked = []
    for v in q.vectors:
        parts = [p[0] for p in books.halves(v[None])]
        half = [((c - p) ** 2).sum(1) for c, p in zip(books.coarse, parts, strict=True)]
        cost = half[0][:, None] + half[1][None] if M == 2 else half[0][:, None]
        probe = np.zeros(cost.shape, dtype=bool)
        probe.flat[np.argsort(cost, axis=None, kind="stable")[:n_probe]] = True
        asked.append((parts, probe))
    keep = max(k, exact)

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            if len(batch):
                x, ids = stacked(batch["embedding"]), batch["vec_id"].to_numpy()
                cells, codes = books.encode(x)
                for (parts, probe), qid, v in zip(asked, q.ids.tolist(), q.vectors, strict=True):
                    at = np.flatnonzero(probe[tuple(cells.T)] if M == 2 else probe[cells[:, 0], 0])
                    at = at[ids[at] != qid]
                    near = sum((((c[cells[at, m]] + f[codes[at, m]]) - p) ** 2).sum(1) for m, (c, f, p) in enumerate(zip(books.coarse, books.fine, parts, strict=True)))
                    table = np.round(np.sqrt(near), 9) if len(at) else np.zeros(0)
                    best = at[smallest(table, ids[at], keep)]
                    d = distances(x[best], v) if exact else np.sort(table)[:keep]
                    out.append(pd.DataFrame({"query_id": qid, "vec_id": ids[best], "dist": d}))
            yield framed(out, ["query_id", "vec_id", "dist"])

    return ranked(points.select("vec_id", "embedding").mapInPandas(rows, "query_id long, vec_id long, dist double"), k)
