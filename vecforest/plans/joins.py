"""Joins that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def interval_join(left: DataFrame, right: DataFrame, keys: list[str], ts: str, seconds: int) -> DataFrame:
    """Pairs with equal keys and left.ts < right.ts <= left.ts + seconds.

    Time is cut into buckets of that length, so that a right row can only match
    left rows of its own bucket and of the one before: an equi-join on the keys
    and the bucket, then the exact test. Rows with a null time match nothing.
    """
    bucket = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / (seconds * 1_000_000))
    lf = left.withColumnRenamed(ts, "__l").withColumn("__b", F.explode(F.array(bucket("__l"), bucket("__l") + 1)))
    r = right.withColumnRenamed(ts, "__r").withColumn("__b", bucket("__r"))
    inside = (F.col("__r") > F.col("__l")) & (F.col("__r") <= F.col("__l") + F.make_interval(secs=F.lit(seconds)))
    return lf.join(r, [*keys, "__b"]).where(inside).drop("__b", "__l", "__r")


def asof_join(left: DataFrame, right: DataFrame, keys: list[str], ts: str, values: list[str]) -> DataFrame:
    """Each left row with the values of the latest right row of its keys at or before it; nulls if there is none.

    Both sides go into one stream by key and time; the last right row so far is
    a running window, so nothing is paired. Of right rows at one time the
    greatest values win.
    """
    packed = F.struct(*values)
    r = right.groupBy(*keys, ts).agg(F.max(packed).alias("__v")).withColumn("__side", F.lit(0))
    cols = [c for c in left.columns if c not in (*keys, ts)]
    lf = left.select(*keys, ts, F.struct(*cols).alias("__row")).withColumn("__side", F.lit(1))
    both = lf.unionByName(r, allowMissingColumns=True)
    w = Window.partitionBy(*keys).orderBy(ts, "__side").rowsBetween(Window.unboundedPreceding, 0)
    out = both.withColumn("__last", F.last("__v", ignorenulls=True).over(w)).where("__side = 1")
    return out.select(*keys, ts, *[F.col(f"__row.{c}").alias(c) for c in cols], *[F.col(f"__last.{v}").alias(v) for v in values])


def salted_join(large: DataFrame, small: DataFrame, keys: list[str], salts: int, how: str = "inner") -> DataFrame:
    """Equi-join whose large side deals each key to `salts` tasks; the small side is repeated so often."""
    if how not in ("inner", "left"):
        raise ValueError(how)
    dealt = large.withColumn("__salt", F.pmod(F.xxhash64(*large.columns), F.lit(salts)).cast("int"))
    copies = small.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return dealt.join(copies, [*keys, "__salt"], how).drop("__salt")
