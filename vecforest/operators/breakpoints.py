"""Cut points of projected coordinates into regions of equal count."""

from __future__ import annotations

from statistics import NormalDist

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .projection import DECIMALS, long_form
from .selection import ranked_columns

SCHEMA = "space int, dim int, edges array<double>"


def ranks(m: int, regions: int, rule: str = "first") -> list[int]:
    """1-based ranks of the inner edges among m values: where each region but the first begins."""
    if rule == "floor":
        return [max(1, (z - 1) * (m // regions)) for z in range(2, regions + 1)]
    return [min(m, (z - 1) * m // regions + 1) for z in range(2, regions + 1)]


def sampled(df: DataFrame, share: float, id_column: str = "vec_id", regions: int = 256, n: int | None = None) -> DataFrame:
    """Rows chosen by a linear mix of their id, alike in every engine; all of them if there would be too few."""
    n = df.count() if n is None else n
    if n * share < min(n, 64 * regions):
        share = min(1.0, 64 * regions / max(n, 1))
    return df if share >= 1 else df.where(F.pmod(F.col(id_column) * 48271 + 11, F.lit(2147483647)) < int(2147483647 * share))


def breakpoints(projected: DataFrame, K: int, L: int, regions: int = 256, method: str = "histogram_rounds", sample: DataFrame | None = None, rule: str = "first") -> DataFrame:
    """(space, dim, edges of regions + 1): inner edges from the sample (all rows by default), outer ones the least and greatest of all rows.

    full_sort ranks each column by a window; select_rounds selects within one
    task per column; histogram_rounds narrows all columns at once by counting
    and moves no column; percentile and approx_percentile use the engine's
    aggregates.
    """
    spark = projected.sparkSession
    part = projected if sample is None else sample
    G = K * L
    m = part.count()
    if not m:
        return spark.createDataFrame([], SCHEMA)
    at = ranks(m, regions, rule)
    outer = projected.select(*[F.min(F.get("proj", F.lit(g))).alias(f"a{g}") for g in range(G)], *[F.max(F.get("proj", F.lit(g))).alias(f"b{g}") for g in range(G)]).first()
    if method == "histogram_rounds":
        inner = ranked_columns(part, "proj", [at] * G)
    elif method == "full_sort":
        w = Window.partitionBy("space", "dim").orderBy("x")
        wanted = sorted(set(at))
        rows = long_form(part, K).withColumn("r", F.row_number().over(w)).where(F.col("r").isin(wanted)).collect()
        by = {(r["space"], r["dim"], r["r"]): r["x"] for r in rows}
        inner = [[by[g // K + 1, g % K + 1, r] for r in at] for g in range(G)]
    elif method == "select_rounds":
        rows = selected(part, K, regions, rule).collect()
        by = {(r["space"], r["dim"]): r["inner"] for r in rows}
        inner = [list(by[g // K + 1, g % K + 1]) for g in range(G)]
    elif method in ("percentile", "approx_percentile"):
        shares = F.array(*[F.lit((r - 0.5) / m) for r in at])
        agg = (lambda g: F.percentile_approx(F.get("proj", F.lit(g)), shares, 100_000)) if method == "approx_percentile" else (lambda g: F.percentile(F.get("proj", F.lit(g)), shares))
        row = part.agg(*[agg(g).alias(f"p{g}") for g in range(G)]).first()
        inner = [list(row[g]) for g in range(G)]
    elif method == "kll":
        row = part.agg(*[F.expr(f"kll_sketch_agg_double(proj[{g}], 2000)").alias(f"s{g}") for g in range(G)])
        shares = "array(" + ",".join(f"{(r - 0.5) / m}D" for r in at) + ")"
        got = row.select(*[F.expr(f"kll_sketch_get_quantile_double(s{g}, {shares})").alias(f"q{g}") for g in range(G)]).first()
        inner = [list(got[g]) for g in range(G)]
    else:
        raise ValueError(method)
    rows = [(g // K + 1, g % K + 1, [float(outer[g]), *map(float, inner[g]), float(outer[G + g])]) for g in range(G)]
    return spark.createDataFrame(rows, SCHEMA)


def select_ranks(x: np.ndarray, at: list[int], count: list[int] | None = None) -> list[float]:
    """Values at ranks by halving: each round partitions the pieces of the round before at their middle wanted rank."""
    x = x.copy()
    out: dict[int, float] = {}
    pieces = [(0, len(x), sorted({r - 1 for r in at}))]
    while pieces:
        new = []
        for lo, hi, inside in pieces:
            if not inside:
                continue
            mid = inside[len(inside) // 2]
            x[lo:hi] = np.partition(x[lo:hi], mid - lo)
            if count is not None:
                count[0] += 2 * (hi - lo)  # a selection looks at each value about twice
            out[mid] = float(x[mid])
            new += [(lo, mid, [r for r in inside if r < mid]), (mid + 1, hi, [r for r in inside if r > mid])]
        pieces = new
    return [out[r - 1] for r in at]


def selected(projected: DataFrame, K: int, regions: int = 256, rule: str = "first") -> DataFrame:
    """(space, dim, inner, comparisons, sort_comparisons): selection by halving, one task per column of a bounded sample."""

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        x, n = pdf["x"].to_numpy(), [0]
        inner = select_ranks(x, ranks(len(x), regions, rule), n)
        full = int(len(x) * np.log2(max(len(x), 2)))
        return pd.DataFrame({"space": pdf["space"].iloc[:1], "dim": pdf["dim"].iloc[:1], "inner": [inner], "comparisons": [n[0]], "sort_comparisons": [full]})

    return long_form(projected, K).groupBy("space", "dim").applyInPandas(one, "space int, dim int, inner array<double>, comparisons long, sort_comparisons long")


def static_breakpoints(regions: int = 256) -> list[float]:
    """Inner edges of equal mass under N(0, 1), the same for all data; rounded like projections."""
    return [round(NormalDist().inv_cdf(z / regions), DECIMALS) for z in range(1, regions)]
