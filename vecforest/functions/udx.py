"""Python functions for SQL: Arrow scalars, aggregates, table functions and a small front end."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, StructType

from ..operators.exact import Queries, exact_knn
from . import exprs
from .params import ForestParams


class RadiusSchedule:
    """Table function radius_schedule(r_min, c, rounds): (t, r)."""

    def eval(self, r_min: float, c: float, rounds: int):
        for t in range(rounds):
            yield t, float(r_min) * float(c) ** t


def register(spark: SparkSession) -> None:
    """vf_dot, vf_l2, vf_l2sq (built-in), vf_l2_batch (Arrow), vf_sum (aggregate), radius_schedule (table function)."""
    exprs.register(spark)

    def l2_batch(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([float(np.linalg.norm(np.asarray(x, float) - np.asarray(y, float))) for x, y in zip(a, b, strict=True)], dtype=float)

    def total(v: pd.Series) -> list[float]:
        return np.sum(np.stack(v.tolist()), axis=0).tolist() if len(v) else []

    spark.udf.register("vf_l2_batch", F.pandas_udf(l2_batch, DoubleType()))
    spark.udf.register("vf_sum", F.pandas_udf(total, ArrayType(DoubleType()), F.PandasUDFType.GROUPED_AGG))
    spark.udtf.register("radius_schedule", F.udtf(RadiusSchedule, returnType=StructType().add("t", IntegerType()).add("r", DoubleType())))


class Engine:
    """A session's front end: tables of vectors by name, searches from SQL or from Python."""

    def __init__(self, spark: SparkSession, params: ForestParams | None = None):
        self.spark, self.params = spark, params or ForestParams()
        self.tables: dict[str, DataFrame] = {}
        register(spark)

    def add(self, name: str, points: DataFrame) -> None:
        self.tables[name] = points
        points.createOrReplaceTempView(name)

    def sql(self, text: str, **args) -> DataFrame:
        return self.spark.sql(text, args=args or None)

    def knn(self, name: str, vector, k: int = 10) -> DataFrame:
        """Exact neighbours of one vector."""
        return exact_knn(self.tables[name], Queries(np.array([-1], dtype=np.int64), np.asarray([vector], dtype=float)), k)

    def ann(self, name: str, vector, k: int = 10) -> DataFrame:
        from ..operators.ann import ck_ann

        return ck_ann(self.tables[name], Queries(np.array([-1], dtype=np.int64), np.asarray([vector], dtype=float)), k, self.params).result


