"""Benchmark decontamination by winnowing (DataFrame functions only).

Both sides keep the least hash of k-word grams in each window of w neighbouring
grams. Two texts that share k + w - 1 words share such a window, hence a kept
hash, so joining kept hashes finds every document that shares `span` words with
an item (k + w - 1 = span). The hits of those documents are then extended to
all windows of the item that occur, word by word.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower, id_key, row_key, staged, table, text_key, with_grams, with_window_minima

#: Fixed values of the contract: what parts words after lower-casing A-Z, and before. Splitting is far faster than extracting here.
BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
BETWEEN_ANY_CASE = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def words(text: Column) -> Column:
    return F.array_remove(F.split(ascii_lower(F.coalesce(text, F.lit(""))), BETWEEN), "")


def n_words(text: Column) -> Column:
    return F.size(F.array_remove(F.split(F.coalesce(text, F.lit("")), BETWEEN_ANY_CASE), "")).cast("long")


def _hashed(df: DataFrame, text: str) -> DataFrame:
    return df.withColumn("h", F.transform(words(F.col(text)), lambda w: F.xxhash64(w)))


def _winnowed(df: DataFrame, k: int, span: int, short: list[int]) -> DataFrame:
    """Column fps: hashes kept by winnowing, and all grams of the lengths in short."""
    df = with_window_minima(with_grams(df, "h", k, "g"), "g", span - k + 1, "fps")
    parts = ["fps"]
    for m in short:
        df = with_grams(df, "h", m, f"s{m}")
        parts.append(f"s{m}")
    return df.withColumn("fps", F.concat(*parts)) if short else df


def decontaminate(docs: DataFrame, items: DataFrame, k: int = 5, span: int = 13, ratio: int = 20) -> DataFrame:
    """One row per document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated.

    docs needs doc_id and text, items needs item_id and text; other columns are
    ignored. A null or empty text has no words and is never hit; a null item
    has no windows; a null doc_id or item_id is kept as null (null items count
    under the name ''). Equal rows each give a row. No items: nothing is hit.
    """
    keyed = docs.select("doc_id", "text").withColumn("rid", id_key(F.col("doc_id"))).withColumn("rt", text_key(F.col("text")))
    bench = _hashed(items.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item"), "text"), "text").where(F.size("h") > 0).select("item", "h").dropDuplicates()
    n = F.size("h")
    short = sorted(r[0] for r in bench.where(n < span).select(n).distinct().collect())  # at most span - 1 numbers
    long_fps = _winnowed(bench.where(n >= span), k, span, []).select(F.explode_outer("fps").alias("fp"))
    windows = with_grams(bench.where(n >= span), "h", span, "g").select("item", F.explode_outer(F.array_distinct("g")).alias("g"), F.lit(span).alias("m"))
    for m in short:
        of_m = with_grams(bench.where(n == m), "h", m, "g").select("item", F.explode_outer("g").alias("g"), F.lit(m).alias("m"))
        windows = windows.unionByName(of_m)
        long_fps = long_fps.unionByName(of_m.select(F.col("g").alias("fp")))
    windows, fps = staged(windows.distinct(), "windows"), staged(long_fps.distinct(), "prints")

    seeds = _winnowed(_hashed(keyed, "text"), k, span, short).select("rid", "rt", F.explode_outer("fps").alias("fp"))
    near = staged(seeds.join(fps, "fp", "left_semi").select("rid", "rt").distinct(), "hits")

    hit = _hashed(keyed.join(near, ["rid", "rt"], "left_semi"), "text").select("rid", "rt", "h")
    grams = None
    for m in [*short, span]:
        of_m = with_grams(hit, "h", m, "g").select("rid", "rt", F.posexplode_outer("g").alias("pos", "g"), F.lit(m).alias("m"))
        grams = of_m if grams is None else grams.unionByName(of_m)
    found = grams.join(windows, ["g", "m"])
    # a document's words and the items that it holds bound what these arrays gather
    spans = found.groupBy("rid", "rt").agg(F.array_sort(F.collect_set(F.struct("pos", (F.col("pos") + F.col("m")).alias("end")))).alias("spans"), F.sort_array(F.collect_set("item")).alias("its"))
    start = F.struct(F.lit(0).alias("n"), F.lit(0).alias("upto"))
    covered = F.aggregate(
        "spans",
        start,
        lambda acc, s: F.struct(
            (acc["n"] + F.greatest(F.lit(0), s["end"] - F.greatest(acc["upto"], s["pos"]))).alias("n"),
            F.greatest(acc["upto"], s["end"]).alias("upto"),
        ),
        lambda acc: acc["n"],
    )
    per_doc = staged(spans.select("rid", "rt", covered.cast("long").alias("n_hit"), F.size("its").cast("long").alias("n_items"), F.sha2(F.array_join("its", ","), 256).alias("items_sha256")), "found")
    base = keyed.select("doc_id", "rid", "rt", n_words(F.col("text")).alias("n_words"))
    out = base.join(per_doc, ["rid", "rt"], "left").select(
        "doc_id",
        "n_words",
        F.coalesce("n_hit", F.lit(0).cast("long")).alias("n_hit"),
        F.coalesce("n_items", F.lit(0).cast("long")).alias("n_items"),
        F.coalesce("items_sha256", F.sha2(F.lit(""), 256)).alias("items_sha256"),
    )
    return out.withColumn("contaminated", (F.col("n_hit") > 0) & (F.col("n_hit") * ratio >= F.col("n_words")))


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents that are not contaminated, all their columns; rows with a null doc_id are judged by their text alone."""
    keyed = docs.withColumn("__row", row_key(F.col("doc_id"), F.col("text")))
    bad = decontaminate(keyed.select(F.col("__row").alias("doc_id"), "text"), table(spark, sf_dir, "benchmark")).where("contaminated").select(F.col("doc_id").alias("__row")).distinct()
    return keyed.join(bad, "__row", "left_anti").select(*docs.columns)


OP8_SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
i AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
im AS (SELECT item_id, w, least(13, len(w)) AS m FROM i WHERE len(w) > 0),
iw AS (SELECT DISTINCT item_id, m, array_to_string(list_slice(w, p, p + m - 1), ' ') AS g FROM (SELECT item_id, w, m, unnest(range(1, len(w) - m + 2)) AS p FROM im)),
ms AS (SELECT DISTINCT m FROM iw),
dw AS (SELECT doc_id, m, p, array_to_string(list_slice(w, p, p + m - 1), ' ') AS g FROM (SELECT doc_id, w, m, unnest(range(1, len(w) - m + 2)) AS p FROM d, ms WHERE len(w) >= m)),
f AS (SELECT dw.doc_id, dw.p, dw.m, iw.item_id FROM dw JOIN iw ON dw.m = iw.m AND dw.g = iw.g),
hit AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT DISTINCT doc_id, unnest(range(p, p + m)) AS p FROM f) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS ids FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM f) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN hit USING (doc_id) LEFT JOIN its USING (doc_id)
"""
