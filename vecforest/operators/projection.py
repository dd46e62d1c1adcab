"""Gaussian projections of vectors into several low-dimensional spaces."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DECIMALS = 9


def projection_matrix(d: int, K: int, L: int, seed: int = 42) -> np.ndarray:
    """K * L coefficient vectors of d standard normals, space after space, rounded to six decimals so that SQL can hold them."""
    return np.round(np.random.Generator(np.random.PCG64(seed)).standard_normal((K * L, d)), 6)


def coefficients(spark: SparkSession, matrix: np.ndarray, K: int) -> DataFrame:
    rows = [(i // K + 1, i % K + 1, p + 1, float(a)) for i, row in enumerate(matrix) for p, a in enumerate(row)]
    return spark.createDataFrame(rows, "space int, dim int, pos int, a double")


def dimension(points: DataFrame, column: str = "embedding") -> int:
    """Length of the vectors; all rows must agree."""
    least, most = points.agg(F.min(F.size(column)), F.max(F.size(column))).first()
    if least is not None and least != most:
        raise ValueError(f"vectors of {least} to {most} dimensions; split them off with good_rows()")
    return least or 0


def good_rows(points: DataFrame, d: int, column: str = "embedding") -> tuple[DataFrame, DataFrame]:
    """Rows whose vector has d finite numbers, and the others."""
    ok = F.coalesce((F.size(column) == d) & ~F.exists(column, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf")))), F.lit(False))
    return points.where(ok), points.where(~ok)


def stacked(vectors: pd.Series) -> np.ndarray:
    return np.stack([np.asarray(v, dtype=np.float64) for v in vectors]) if len(vectors) else np.zeros((0, 0))


def project(points: DataFrame, matrix: np.ndarray, kernel: str = "arrow", column: str = "embedding", out: str = "proj") -> DataFrame:
    """Adds the K * L projected coordinates as one array, space after space; no shuffle."""
    if kernel == "native":
        rows = F.array(*[F.array(*[F.lit(float(a)) for a in row]) for row in matrix])
        one = lambda r: F.round(F.aggregate(F.zip_with(r, F.col(column).cast("array<double>"), lambda a, x: a * x), F.lit(0.0), lambda m, x: m + x), DECIMALS)
        return points.withColumn(out, F.transform(rows, one))

    def kernel_(v: pd.Series) -> pd.Series:
        return pd.Series(list(np.round(stacked(v) @ matrix.T, DECIMALS))) if len(v) else pd.Series([], dtype=object)

    return points.withColumn(out, F.pandas_udf(kernel_, "array<double>")(F.col(column)))


def long_form(projected: DataFrame, K: int, id_column: str = "vec_id") -> DataFrame:
    """(vec_id, space, dim, x), one row per coordinate."""
    return projected.select(id_column, F.posexplode("proj").alias("i", "x")).select(id_column, (F.floor(F.col("i") / K) + 1).cast("int").alias("space"), (F.col("i") % K + 1).cast("int").alias("dim"), "x")


def bucket_hash(projected: DataFrame, w: float, offset: float = 0.0) -> DataFrame:
    """Adds the bucket form of every hash: floor((x + offset) / w)."""
    return projected.withColumn("buckets", F.transform("proj", lambda x: F.floor((x + F.lit(offset)) / F.lit(w)).cast("long")))


def pair_differences(points: DataFrame, queries: DataFrame, matrix: np.ndarray, K: int) -> DataFrame:
    """(query_id, vec_id, s, delta array): true distance and projected differences of the pairs of a bounded query set with all points."""
    q = project(queries, matrix).select(F.col("query_id"), F.col("embedding").alias("qe"), F.col("proj").alias("qp"))
    p = project(points, matrix).select("vec_id", F.col("embedding").alias("pe"), "proj")
    pairs = p.join(F.broadcast(q), F.col("vec_id") != F.col("query_id"))
    e = lambda c: F.col(c).cast("array<double>")
    s = F.sqrt(F.aggregate(F.zip_with(e("pe"), e("qe"), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda m, x: m + x))
    return pairs.select("query_id", "vec_id", s.alias("s"), F.zip_with("proj", "qp", lambda a, b: a - b).alias("delta"))


def chi2_check(points: DataFrame, queries: DataFrame, matrix: np.ndarray, K: int) -> DataFrame:
    """Moments of the squared projected over the squared true distance, by space: about K and 2K."""
    pairs = pair_differences(points, queries, matrix, K)
    L = len(matrix) // K
    ratios = pairs.select(F.posexplode(F.array(*[F.try_divide(F.aggregate(F.slice("delta", i * K + 1, K), F.lit(0.0), lambda m, x: m + x * x), F.col("s") * F.col("s")) for i in range(L)])).alias("i", "ratio"))
    return ratios.groupBy((F.col("i") + 1).alias("space")).agg(F.count(F.lit(1)).alias("pairs"), F.avg("ratio").alias("mean"), F.var_samp("ratio").alias("variance"))


def stability_check(points: DataFrame, queries: DataFrame, matrix: np.ndarray, K: int) -> DataFrame:
    """Moments of single differences over the true distance: about those of N(0, 1)."""
    one = pair_differences(points, queries, matrix, K).select(F.explode(F.transform("delta", lambda x: F.try_divide(x, F.col("s")))).alias("z"))
    return one.agg(F.count(F.lit(1)).alias("n"), F.avg("z").alias("mean"), F.var_samp("z").alias("variance"), F.skewness("z").alias("skewness"), F.kurtosis("z").alias("kurtosis"))


def collision_curve(points: DataFrame, queries: DataFrame, matrix: np.ndarray, K: int, w: float) -> DataFrame:
    """Share of equal buckets by true distance (in tenths): falls with distance."""
    q = bucket_hash(project(queries, matrix), w).select("query_id", F.col("embedding").alias("qe"), F.col("buckets").alias("qb"))
    p = bucket_hash(project(points, matrix), w).select("vec_id", F.col("embedding").alias("pe"), "buckets")
    e = lambda c: F.col(c).cast("array<double>")
    s = F.sqrt(F.aggregate(F.zip_with(e("pe"), e("qe"), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda m, x: m + x))
    same = F.aggregate(F.zip_with("buckets", "qb", lambda a, b: F.when(a == b, 1).otherwise(0)), F.lit(0), lambda m, x: m + x)
    pairs = p.join(F.broadcast(q), F.col("vec_id") != F.col("query_id")).select(F.floor(F.round(s, DECIMALS) * 10).cast("long").alias("tenth"), same.cast("long").alias("same"))
    return pairs.groupBy("tenth").agg(F.count(F.lit(1)).alias("pairs"), F.sum("same").alias("same"), (F.sum("same") / (F.count(F.lit(1)) * len(matrix))).alias("rate"))
