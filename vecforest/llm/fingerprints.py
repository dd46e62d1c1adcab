"""Threshold-scaled sketches of documents (DataFrame functions only).

A fingerprint keeps every shingle hash below a fixed fraction of the hash
range. Fingerprints of parts merge by union, and the share of one that lies in
another estimates containment whatever the two lengths.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import NO_ID, id_key, table, text_key, with_grams

SHINGLE = 5
FRACTION = 4  # one hash of so many stays
ROWS_A_BUCKET = 4096
MOST_BUCKETS = 1 << 14  # bounds that a plan holds; beyond them buckets grow, and the window over one spills
CHUNK = 256


def with_fingerprint(df: DataFrame, text: str, out: str, size: int = SHINGLE, fraction: int = FRACTION) -> DataFrame:
    """Adds column out: the sorted kept hashes of the runs of `size` words of a text.

    Words are runs of non-blank characters, in lower case. A text of fewer
    words has one shingle, all its words; one without words has none. Where no
    hash is below the threshold the least one stays, so that only texts without
    words have empty fingerprints.
    """
    limit = limit_of(fraction)
    words = F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"\s+"), lambda w: w != "")
    df = with_grams(df.withColumn("__h", F.transform(words, lambda w: F.xxhash64(w))), "__h", size, "__g")
    df = df.withColumn("__g", F.when((F.size("__h") > 0) & (F.size("__h") < size), F.array(F.xxhash64("__h"))).otherwise(F.col("__g")))
    df = df.withColumn("__k", F.filter("__g", lambda x: x < limit))
    least = F.when(F.size("__g") > 0, F.array(F.array_min("__g"))).otherwise(F.array().cast("array<bigint>"))
    return df.withColumn(out, F.when(F.size("__k") > 0, F.array_sort(F.array_distinct("__k"))).otherwise(least)).drop("__h", "__g", "__k")


def limit_of(fraction: int) -> int:
    """Hashes below stay."""
    return min(-(1 << 63) + (1 << 64) // fraction, (1 << 63) - 1)


def merged(a: Column, b: Column, fraction: int = FRACTION) -> Column:
    """The fingerprint of the shingles of two texts together, exactly: a least hash that stood in for none goes once there are others."""
    both = F.array_sort(F.array_union(a, b))
    kept = F.filter(both, lambda x: x < limit_of(fraction))
    return F.when(F.size(kept) > 0, kept).otherwise(F.slice(both, 1, 1))


def containment(a: Column, b: Column) -> Column:
    """Share of the smaller fingerprint that lies in the other; 1 for two empty ones, 0 for one.

    Estimates the share of the shingles of the text with fewer that the other
    holds, as each shingle is kept with the same chance.
    """
    less = F.least(F.size(a), F.size(b))
    return F.when(less > 0, F.size(F.array_intersect(a, b)) / less).when(F.size(a) == F.size(b), F.lit(1.0)).otherwise(F.lit(0.0))


def jaccard(a: Column, b: Column) -> Column:
    """Likeness by union: shared hashes over all; 1 for two empty ones."""
    both = F.size(F.array_intersect(a, b))
    return F.when(F.size(a) + F.size(b) > 0, both / (F.size(a) + F.size(b) - both)).otherwise(F.lit(1.0))


def as_text(fp: Column) -> Column:
    return F.array_join(F.transform(fp, lambda h: F.lpad(F.lower(F.hex(h)), 16, "0")), "")


def _bounds(keys: DataFrame) -> list[int]:
    """Least ids of the buckets, ascending; ids that occur. Their number is bounded by MOST_BUCKETS."""
    n, least = keys.agg(F.count(F.lit(1)), F.min("key")).first()
    many = min(max(1, n // ROWS_A_BUCKET), MOST_BUCKETS)
    if many == 1:
        return [least if n else NO_ID]
    at = F.array(*[F.lit(i / many) for i in range(1, many)])
    cuts = keys.agg(F.percentile_approx("key", at, 20 * many)).first()[0]
    return sorted({least, *cuts})


def _bucket(key: Column, bounds: list[int]) -> Column:
    """Place (from 1) of the last bound that is at most key, by a list of chunks and then one chunk."""
    chunks = [bounds[i : i + CHUNK] for i in range(0, len(bounds), CHUNK)]
    longs = lambda xs: F.array(*[F.lit(x).cast("long") for x in xs])
    chunk = F.size(F.filter(longs([c[0] for c in chunks]), lambda b: b <= key))
    inside = F.size(F.filter(F.element_at(F.array(*[longs(c) for c in chunks]), F.greatest(chunk, F.lit(1))), lambda b: b <= key))
    return (F.greatest(chunk, F.lit(1)) - 1) * CHUNK + inside


def fingerprint(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next.

    The edited text has its last floor(n_chars / 2) code points replaced by the
    first as many (or all) of the next document by ascending doc_id; after the
    last comes the first. Null texts count as empty; null ids come first; rows
    with equal ids follow each other in the order of a hash of their texts.
    near_edited and near_next are containment(): the share of the smaller
    fingerprint that lies in the other.
    """
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("key", id_key(F.col("doc_id")))
    bounds = _bounds(rows.select("key"))
    longs = F.array(*[F.lit(b).cast("long") for b in bounds])
    own = F.struct(_bucket(F.col("key"), bounds).alias("bucket"), F.lit(0).alias("turn"))
    # the first row of a bucket also ends the bucket before it; the first of all ends the last
    starts = F.when(F.array_contains(longs, F.col("key")), _bucket(F.col("key"), bounds))
    ghost = F.when(starts == 1, F.struct(F.lit(len(bounds)).alias("bucket"), F.lit(2).alias("turn"))).when(starts > 1, F.struct((starts - 1).alias("bucket"), F.lit(1).alias("turn")))
    dealt = rows.withColumn("at", F.explode(F.array_compact(F.array(own, ghost)))).select("doc_id", "text", "key", "at.*")
    dealt = with_fingerprint(dealt, "text", "fp").withColumn("tk", text_key(F.col("text")))
    w = Window.partitionBy("bucket").orderBy("turn", "key", "tk")
    near = dealt.withColumn("next", F.lead("text").over(w)).withColumn("next_fp", F.lead("fp").over(w)).where("turn = 0")
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substr("text", F.lit(1), n - half), F.substr("next", F.lit(1), half))
    near = with_fingerprint(near.withColumn("edited", edited), "edited", "edited_fp")
    return near.select(
        "doc_id",
        n.cast("long").alias("n_chars"),
        F.sha2("edited", 256).alias("edited_sha256"),
        as_text(F.col("fp")).alias("fingerprint"),
        as_text(F.col("edited_fp")).alias("edited_fingerprint"),
        containment(F.col("fp"), F.col("edited_fp")).alias("near_edited"),
        containment(F.col("fp"), F.col("next_fp")).alias("near_next"),
    )


def op3_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint(table(spark, sf_dir, "documents"))
