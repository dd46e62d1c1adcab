"""Exact order statistics of many columns at once, without sorting or gathering them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PARTS = 64
SMALL = 2_000


def ranked_columns(df: DataFrame, column: str, ranks: list[list[int]]) -> list[list[float]]:
    """Values at 1-based ranks of each position of an array column.

    Each round counts, by position, how many values fall into the parts of the
    ranges that still hold a wanted rank, with their least and greatest value;
    tasks add up before they send. A range is settled when its values are equal,
    and the last few values of narrow ranges come to the driver (SMALL a range
    at most). The driver holds one range per wanted rank. Ranks beyond the
    number of values give NaN.
    """
    many = len(ranks)
    wanted = [sorted(set(r)) for r in ranks]
    got: list[dict[int, float]] = [{} for _ in range(many)]
    # (low, high, values below low, count, ranks inside); both ends belong to the range
    open_: list[list[tuple[float, float, int, int, list[int]]]] = []
    first = df.select(column).mapInPandas(lambda it: _ends(it, column, many), "g int, n long, lo double, hi double")
    ends = {r["g"]: r for r in first.groupBy("g").agg(F.sum("n").alias("n"), F.min("lo").alias("lo"), F.max("hi").alias("hi")).collect()}
    for g in range(many):
        e = ends.get(g)
        inside = [r for r in wanted[g] if e is not None and 1 <= r <= e["n"]]
        for r in wanted[g]:
            if r not in inside:
                got[g][r] = float("nan")
        open_.append([(e["lo"], e["hi"], 0, e["n"], inside)] if inside else [])
    while any(open_):
        gather: list[tuple[int, float, float, int, list[int]]] = []
        edges: list[np.ndarray] = []
        for g in range(many):
            cuts, rest = [], []
            for lo, hi, below, n, inside in open_[g]:
                if lo == hi:
                    got[g] |= {r: lo for r in inside}
                elif n <= SMALL:
                    gather.append((g, lo, hi, below, inside))
                else:
                    cuts.append(np.linspace(lo, hi, PARTS + 1)[:-1])
                    cuts.append(np.array([np.nextafter(hi, np.inf)]))
                    rest.append((lo, hi, below, n, inside))
            open_[g] = rest
            edges.append(np.unique(np.concatenate(cuts)) if cuts else np.array([]))
        if gather:
            _gathered(df, column, gather, got)
        if not any(open_):
            break
        counted = df.select(column).mapInPandas(lambda it, e=edges: _counts(it, column, e), "g int, bin int, n long, lo double, hi double")
        rows = counted.groupBy("g", "bin").agg(F.sum("n").alias("n"), F.min("lo").alias("lo"), F.max("hi").alias("hi")).collect()
        bins: dict[int, list] = {}
        for r in rows:
            bins.setdefault(r["g"], []).append(r)
        for g in range(many):
            new = []
            for lo, hi, below, _, inside in open_[g]:
                at = below
                for r in sorted((r for r in bins.get(g, []) if r["lo"] >= lo and r["hi"] <= hi), key=lambda r: r["bin"]):
                    here = [x for x in inside if at < x <= at + r["n"]]
                    if here:
                        new.append((r["lo"], r["hi"], at, r["n"], here))
                    at += r["n"]
            open_[g] = new
    return [[got[g][r] for r in ranks[g]] for g in range(many)]


def _matrix(batch: pd.DataFrame, column: str) -> np.ndarray:
    return np.stack([np.asarray(v, dtype=np.float64) for v in batch[column]])


def _ends(batches: Iterator[pd.DataFrame], column: str, many: int) -> Iterator[pd.DataFrame]:
    for batch in batches:
        if len(batch):
            x = _matrix(batch, column)
            yield pd.DataFrame({"g": np.arange(many), "n": len(x), "lo": x.min(0), "hi": x.max(0)})


def _counts(batches: Iterator[pd.DataFrame], column: str, edges: list[np.ndarray]) -> Iterator[pd.DataFrame]:
    for batch in batches:
        if not len(batch):
            continue
        x, out = _matrix(batch, column), []
        for g, e in enumerate(edges):
            if not len(e):
                continue
            at = np.searchsorted(e, x[:, g], side="right")
            order = np.argsort(at, kind="stable")
            v = x[order, g]
            bins, first, n = np.unique(at[order], return_index=True, return_counts=True)
            out.append(pd.DataFrame({"g": g, "bin": bins, "n": n, "lo": np.minimum.reduceat(v, first), "hi": np.maximum.reduceat(v, first)}))
        if out:
            yield pd.concat(out)


def _gathered(df: DataFrame, column: str, ranges: list[tuple[int, float, float, int, list[int]]], got: list[dict[int, float]]) -> None:
    """Settles ranges of SMALL values at most by bringing the values."""

    def some(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            if len(batch):
                x = _matrix(batch, column)
                out = []
                for i, (g, lo, hi, _, _) in enumerate(ranges):
                    v = x[:, g]
                    v = v[(v >= lo) & (v <= hi)]
                    if len(v):
                        u, n = np.unique(v, return_counts=True)
                        out.append(pd.DataFrame({"i": i, "v": u, "n": n}))
                if out:
                    yield pd.concat(out)

    rows = df.select(column).mapInPandas(some, "i int, v double, n long").groupBy("i", "v").agg(F.sum("n").alias("n")).toPandas()
    for i, (g, _, _, below, inside) in enumerate(ranges):
        part = rows[rows["i"] == i].sort_values("v")
        upto = below + part["n"].cumsum().to_numpy()
        for r in inside:
            got[g][r] = float(part["v"].iloc[int(np.searchsorted(upto, r))])
