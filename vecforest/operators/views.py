"""Vector views over the tables, and query sets."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def emb64(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label")


def emb64_scaled(spark: SparkSession, sf_dir: str, copies: int, sigma: float = 0.05) -> DataFrame:
    """Each vector `copies` times with small seeded shifts: planted neighbours, and the axis of size."""
    v = emb64(spark, sf_dir).withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    # two uniform parts of a hash: the sum is near enough to a bell
    noise = lambda i: ((F.pmod(F.xxhash64("vec_id", "copy", i), F.lit(100003)) + F.pmod(F.xxhash64(i, "copy", "vec_id"), F.lit(100003))) / 100003.0 - 1.0) * (sigma * 2.449)
    return v.select((F.col("vec_id") * copies + F.col("copy")).alias("vec_id"), F.transform("embedding", lambda x, i: x + F.when(F.col("copy") == 0, F.lit(0.0)).otherwise(noise(i))).alias("embedding"), "label")


def gram_vectors(df: DataFrame, id_column: Column, text: Column, d: int, keep: tuple[str, ...] = ()) -> DataFrame:
    """(vec_id, embedding): counts of character trigrams by code-point arithmetic modulo d, scaled to length 1; zeros for texts under three characters."""
    def kernel(texts: pd.Series) -> pd.Series:
        out = []
        for t in texts:
            c = np.frombuffer((t or "").encode("utf-32-le"), dtype=np.uint32).astype(np.int64)
            v = np.bincount(((c[:-2] * 31 + c[1:-1]) * 31 + c[2:]) % d, minlength=d).astype(float) if len(c) > 2 else np.zeros(d)
            n = np.sqrt((v * v).sum())
            out.append(v / n if n else v)
        return pd.Series(out)

    return df.select(id_column.cast("long").alias("vec_id"), *keep, F.pandas_udf(kernel, "array<double>")(text).alias("embedding"))


def doc_grams(spark: SparkSession, sf_dir: str, d: int = 100) -> DataFrame:
    return gram_vectors(table(spark, sf_dir, "documents"), F.col("doc_id"), F.col("text"), d, ("lang",))


def conv_grams(spark: SparkSession, sf_dir: str, d: int = 100) -> DataFrame:
    c = table(spark, sf_dir, "conversations")
    return gram_vectors(c, F.col("conv_id") * 1000 + F.col("turn"), F.col("text"), d, ("conv_id", "turn", "role"))


def page_grams(spark: SparkSession, sf_dir: str, d: int = 96) -> DataFrame:
    return gram_vectors(table(spark, sf_dir, "pages"), F.col("page_id"), F.regexp_replace("html", "<[^>]*>", " "), d)


def line_num(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Twelve standardised numbers of each order line; ties and skew."""
    t = table(spark, sf_dir, "lineitem")
    days = F.datediff("l_shipdate", F.lit("1992-01-01").cast("date")).cast("double")
    raw = [F.col("l_quantity"), F.col("l_extendedprice"), F.col("l_discount"), F.col("l_tax"), days, F.col("l_linenumber").cast("double"), F.log1p("l_extendedprice"), F.col("l_extendedprice") * (1 - F.col("l_discount"))]
    flags = [(F.col("l_returnflag") == x).cast("double") for x in ("A", "N", "R")] + [(F.col("l_linestatus") == "O").cast("double")]
    cols = [c.cast("double") for c in raw + flags]
    stats = t.agg(*[F.struct(F.avg(c).alias("m"), F.stddev_pop(c).alias("s")).alias(f"c{i}") for i, c in enumerate(cols)]).first()
    z = [(c - (stats[i]["m"] or 0.0)) / (stats[i]["s"] or 1.0) for i, c in enumerate(cols)]
    return t.select((F.col("l_orderkey") * 10 + F.col("l_linenumber")).cast("long").alias("vec_id"), F.array(*z).alias("embedding"))


def user_series(spark: SparkSession, sf_dir: str) -> DataFrame:
    """By user: count and mean value by hour and event type (24 x 5 x 2), standardised within the user."""
    e = table(spark, sf_dir, "events")
    kinds = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").limit(5).collect()]
    cell = F.hour("ts") * 5 + F.array_position(F.array(*[F.lit(k) for k in kinds]), F.col("event_type")) - 1
    per = e.withColumn("cell", cell.cast("int")).groupBy("user_id", "cell").agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("v"))
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("cell", F.struct(F.col("n").cast("double").alias("n"), "v")))).alias("m"))
    got = lambda f: F.transform(F.sequence(F.lit(0), F.lit(119)), lambda i: F.coalesce(F.try_element_at("m", i.cast("int"))[f], F.lit(0.0)))
    return m.select(F.col("user_id").alias("vec_id"), F.concat(got("n"), got("v")).alias("embedding"))


def cust_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """By customer: orders by priority, spending, discounts, segment and region, from four joins and a pivot."""
    c, o, li, n = (table(spark, sf_dir, t) for t in ("customer", "orders", "lineitem", "nation"))
    lines = li.groupBy("l_orderkey").agg(F.sum("l_quantity").alias("q"), F.avg("l_discount").alias("d"), F.count(F.lit(1)).alias("n"))
    per = o.join(lines, o.o_orderkey == lines.l_orderkey, "left")
    priorities = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
    agg = per.groupBy("o_custkey").agg(*[F.count_if(F.col("o_orderpriority") == p).cast("double").alias(f"p{i}") for i, p in enumerate(priorities)], F.sum("o_totalprice").alias("spent"), F.sum("q").alias("q"), F.avg("d").alias("d"))
    segments = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
    full = c.join(agg, c.c_custkey == agg.o_custkey, "left").join(F.broadcast(n), c.c_nationkey == n.n_nationkey, "left")
    cols = [F.coalesce(F.col(x), F.lit(0.0)) for x in ("p0", "p1", "p2", "p3", "p4")] + [F.log1p(F.coalesce("spent", F.lit(0.0))), F.coalesce("q", F.lit(0.0)) / 100, F.coalesce("d", F.lit(0.0)) * 10, F.col("c_acctbal") / 1000]
    cols += [(F.col("c_mktsegment") == s).cast("double") for s in segments] + [(F.col("n_regionkey") == r).cast("double") for r in range(5)]
    return full.select(F.col("c_custkey").cast("long").alias("vec_id"), F.array(*[x.cast("double") for x in cols]).alias("embedding"))


VIEWS = {"emb64": emb64, "doc_grams": doc_grams, "conv_grams": conv_grams, "page_grams": page_grams, "line_num": line_num, "user_series": user_series, "cust_profile": cust_profile}


def queries_of(points: DataFrame, every: int = 100) -> DataFrame:
    """(query_id, embedding): the rows whose id is a multiple of `every`; searches leave a query's own row out."""
    return points.where(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("query_id"), "embedding")


def holdout_split(points: DataFrame, n_q: int = 100, seed: int = 42) -> DataFrame:
    """(vec_id, is_query): n_q rows drawn by a linear mix of their ids become queries, the others stay points."""
    mix = F.pmod(F.col("vec_id") * 48271 + seed * 7919, F.lit(2147483647))
    chosen = points.select("vec_id", mix.alias("mix")).orderBy("mix", "vec_id").limit(n_q).select("vec_id", F.lit(True).alias("is_query"))
    return points.select("vec_id").join(F.broadcast(chosen), "vec_id", "left").select("vec_id", F.coalesce("is_query", F.lit(False)).alias("is_query"))


def held_out(points: DataFrame, n_q: int = 100, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """Points without the drawn queries (anti-join), and the queries."""
    split = holdout_split(points, n_q, seed).where("is_query").select("vec_id")
    return points.join(F.broadcast(split), "vec_id", "left_anti"), points.join(F.broadcast(split), "vec_id", "left_semi").select(F.col("vec_id").alias("query_id"), "embedding")


