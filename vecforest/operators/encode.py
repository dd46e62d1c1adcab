"""Symbols of projected points, one byte a coordinate."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import exprs
from .projection import stacked

Edges = list[list[float]]


def edges_of(table: DataFrame, K: int, L: int) -> Edges:
    """K * L edge lists on the driver, space after space."""
    by = {(r["space"], r["dim"]): list(r["edges"]) for r in table.collect()}
    return [by[g // K + 1, g % K + 1] for g in range(K * L)] if by else []


def encode(projected: DataFrame, edges: Edges, kernel: str = "arrow") -> DataFrame:
    """Adds `code`: the symbol of each coordinate, the number of inner edges that are at most it; no shuffle.

    Regions are closed below and open above; the outer ones take whatever lies
    beyond. kernel: arrow (binary search by numpy), halving or count (built-in
    functions; the first needs 2 ** b regions).
    """
    inner = [e[1:-1] for e in edges]
    if kernel == "arrow":
        arrays = [np.array(e) for e in inner]

        def symbols(v: pd.Series) -> pd.Series:
            x = stacked(v)
            return pd.Series(list(np.stack([np.searchsorted(e, x[:, g], side="right") for g, e in enumerate(arrays)], 1).astype(np.int32))) if len(v) else pd.Series([], dtype=object)

        return projected.withColumn("code", F.pandas_udf(symbols, "array<int>")(F.col("proj")))
    out = []
    for g, e in enumerate(inner):
        lit, x = F.array(*[F.lit(float(v)) for v in e]), F.get("proj", F.lit(g))
        out.append(exprs.symbol_halving(x, lit, (len(e) + 1).bit_length() - 1) if kernel == "halving" else exprs.symbol_native(x, lit))
    return projected.withColumn("code", F.array(*out))


def encode_by_scopes(projected: DataFrame, edges: Edges, K: int, L: int, workers: int, n: int | None = None) -> DataFrame:
    """(vec_id, code): as encode(), by workers that hold a range of dimensions of all spaces each, as work_scopes() deals them.

    Coordinates move to the worker of their dimension and back, so encode(),
    which leaves rows where they are, is the form for large tables; this one
    suits few rows with many dimensions.
    """
    spark = projected.sparkSession
    scopes = F.broadcast(work_scopes(spark, K, projected.count() if n is None else n, workers).select("wid", "first_dim", "end_dim"))
    inner = [np.array(e[1:-1]) for e in edges]

    def symbols(g: pd.Series, x: pd.Series) -> pd.Series:
        at, v, out = g.to_numpy(), x.to_numpy(), np.zeros(len(g), dtype=np.int32)
        for column in np.unique(at):
            mine = at == column
            out[mine] = np.searchsorted(inner[column], v[mine], side="right")
        return pd.Series(out)

    long = projected.select("vec_id", F.posexplode("proj").alias("g", "x"))
    dim = F.col("g") % K
    dealt = long.join(scopes, (dim >= F.col("first_dim")) & (dim < F.col("end_dim"))).repartitionById(workers, F.col("wid").cast("int"))
    coded = dealt.withColumn("s", F.pandas_udf(symbols, "int")("g", "x"))
    return coded.groupBy("vec_id").agg(F.array_sort(F.collect_list(F.struct("g", "s"))).alias("at")).select("vec_id", F.col("at.s").alias("code"))


def packed(code: str = "code"):
    """A code of symbols below 256 as binary, one byte each."""
    return F.unhex(F.array_join(F.transform(code, lambda s: F.lpad(F.hex(s.cast("long")), 2, "0")), ""))


def by_space(encoded: DataFrame, K: int, L: int, id_column: str = "vec_id", keep: tuple[str, ...] = ()) -> DataFrame:
    """(vec_id, space, code of K symbols, root_key): one row per point and space."""
    spaces = F.posexplode(F.array(*[F.struct(F.slice("code", i * K + 1, K).alias("code"), F.slice("proj", i * K + 1, K).alias("proj")) for i in range(L)])).alias("i", "s")
    return encoded.select(id_column, *keep, spaces).select(id_column, *keep, (F.col("i") + 1).alias("space"), F.col("s.code").alias("code"), F.col("s.proj").alias("proj"))


def with_root_key(spaced: DataFrame, K: int, bits: int = 8) -> DataFrame:
    return spaced.withColumn("root_key", exprs.root_key(F.col("code"), K, bits))


def region_balance(encoded: DataFrame, K: int, regions: int = 256) -> DataFrame:
    """By column: rows, used regions, least and most of a used region, and chi-squared against equal counts."""
    long = encoded.select(F.posexplode("code").alias("i", "s")).groupBy("i", "s").agg(F.count(F.lit(1)).alias("n"))
    n, sq = F.sum("n"), F.sum(F.col("n") * F.col("n"))
    return long.groupBy("i").agg(n.alias("n"), F.count(F.lit(1)).alias("used"), F.min("n").alias("least"), F.max("n").alias("most"), F.round(sq * regions / n - n, 6).alias("chi2")).select((F.floor(F.col("i") / K) + 1).cast("int").alias("space"), (F.col("i") % K + 1).cast("int").alias("dim"), "n", "used", "least", "most", "chi2")


def work_scopes(spark: SparkSession, K: int, n: int, workers: int) -> DataFrame:
    """(wid, first_dim, end_dim, first_point, end_point): even shares by floor division, the last worker takes the remainder."""
    w = F.col("wid")
    last = w == workers - 1
    return spark.range(workers).select(
        F.col("id").alias("wid"),
    ).select(
        "wid",
        (w * (K // workers)).alias("first_dim"),
        F.when(last, F.lit(K).cast("long")).otherwise((w + 1) * (K // workers)).alias("end_dim"),
        (w * (n // workers)).alias("first_point"),
        F.when(last, F.lit(n).cast("long")).otherwise((w + 1) * (n // workers)).alias("end_point"),
    )
