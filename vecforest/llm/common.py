"""What the operators share: tables, staged intermediate tables, n-gram hashes of arrays."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()
NO_ID = -(1 << 63)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one in local mode where none is set."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if where:
        return where.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that the whole cluster shares")
    where = tempfile.mkdtemp(prefix="vecforest-")
    spark.sparkContext.setCheckpointDir(where)
    return spark.sparkContext.getCheckpointDir()


def staged(df: DataFrame, name: str) -> DataFrame:
    """Write df as a table in the shared folder and read it again.

    Cuts the lineage at files that outlive any executor, and gives the planner
    true sizes. The table is removed when the driver ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/staged-{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    atexit.register(_remove, spark, path)
    return spark.read.schema(df.schema).parquet(path)


def _remove(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session has ended before the interpreter
        return


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only."""
    return F.translate(text, UPPER, LOWER)


def text_key(text: Column) -> Column:
    """64-bit key of a text; with doc_id it names a row up to equal rows."""
    return F.xxhash64(F.coalesce(text, F.lit("")), F.length(F.coalesce(text, F.lit(""))))


def id_key(doc_id: Column) -> Column:
    return F.coalesce(doc_id.cast("long"), F.lit(NO_ID))


def row_key(doc_id: Column, text: Column) -> Column:
    """64-bit key of a row by id and text; null ids are told apart by their texts."""
    return F.xxhash64(id_key(doc_id), F.coalesce(text, F.lit("")), F.length(F.coalesce(text, F.lit(""))))


def shifted(array: Column, by: int) -> Column:
    return F.slice(array, by + 1, 1 << 30)


def with_grams(df: DataFrame, hashes: str, n: int, out: str) -> DataFrame:
    """Adds column out: hashes of all runs of n elements of the long array `hashes`, in order.

    Runs are put together from runs of 1, 2, 4, ... elements, so each step is one
    zip over the array. A shorter array has none.
    """
    runs, at, cur, length, bits, made = None, 0, hashes, 1, n, []
    while bits:
        if bits & 1:
            if runs is None:
                runs, at = cur, length
            else:
                name = f"__r{len(made)}"
                df = df.withColumn(name, F.zip_with(runs, shifted(F.col(cur), at), lambda a, b: F.xxhash64(a, b)))
                made.append(name)
                runs, at = name, at + length
        bits >>= 1
        if bits:
            name = f"__r{len(made)}"
            df = df.withColumn(name, F.zip_with(cur, shifted(F.col(cur), length), lambda a, b: F.xxhash64(a, b)))
            made.append(name)
            cur, length = name, 2 * length
    many = F.greatest(F.size(hashes) - (n - 1), F.lit(0))
    return df.withColumn(out, F.slice(F.col(runs), F.lit(1), many)).drop(*made)


def with_window_minima(df: DataFrame, values: str, width: int, out: str) -> DataFrame:
    """Adds column out: the least of each `width` neighbouring elements; a window over the end holds what is left."""
    runs, at, cur, length, bits, made = None, 0, values, 1, width, []
    while bits:
        if bits & 1:
            if runs is None:
                runs, at = cur, length
            else:
                name = f"__m{len(made)}"
                df = df.withColumn(name, F.zip_with(runs, shifted(F.col(cur), at), lambda a, b: F.least(a, b)))
                made.append(name)
                runs, at = name, at + length
        bits >>= 1
        if bits:
            name = f"__m{len(made)}"
            df = df.withColumn(name, F.zip_with(cur, shifted(F.col(cur), length), lambda a, b: F.least(a, b)))
            made.append(name)
            cur, length = name, 2 * length
    return df.withColumn(out, F.array_distinct(F.col(runs))).drop(*made)


SALTS = 16


def joined_by_salt(rows: DataFrame, one_each: DataFrame, key: str, spread_by: str) -> DataFrame:
    """rows joined with a table of one row a key, each of whose rows goes to SALTS tasks: a key that most rows hold is no task of its own."""
    salt = F.pmod(F.xxhash64(spread_by, F.lit(3)), F.lit(SALTS)).cast("int").alias("__salt")
    every = one_each.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return rows.select("*", salt).join(every, [key, "__salt"]).drop("__salt")


def joined_with_hot(rows: DataFrame, one_each: DataFrame, key: str, *spread_by: str, share: int = 1000, salted: bool = False, counted: DataFrame | None = None) -> DataFrame:
    """rows joined with a table of one row a key; a key that holds more than one row in `share` goes to a task for each such part of it.

    There are `share` such keys at most, so they go to all workers. rows should be a staged table, as it is read for them too;
    else counted is one that holds each key as often.
    salted keeps column __salt, the number of the task of such a key.
    """
    counted = rows if counted is None else counted
    most = max(1000, counted.count() // share)
    hot = counted.groupBy(key).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > most)
    hot = F.broadcast(staged(hot.select(key, F.ceil(F.col("n") / most).cast("int").alias("__many")), "hot"))
    salt = F.coalesce(F.pmod(F.xxhash64(*spread_by, F.lit(3)), F.col("__many")), F.lit(0)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.coalesce("__many", F.lit(1)) - 1))
    left = rows.join(hot, key, "left").withColumn("__salt", salt).drop("__many")
    right = one_each.join(hot, key, "left").withColumn("__salt", every).drop("__many")
    out = left.join(right, [key, "__salt"])
    return out if salted else out.drop("__salt")
