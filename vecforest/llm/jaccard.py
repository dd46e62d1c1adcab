"""Word n-gram Jaccard join with Bayesian pruning of candidates.

Banded MinHash proposes groups, a walk over MinHash values drops the pairs
whose chance to reach the threshold has become negligible, and the rest is
verified exactly. Equal texts are joined once, by one of them.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import NO_ID, id_key, joined_by_salt, row_key, staged, table
from .components import components

SHINGLE, THRESHOLD = 5, 0.8
ROWS, BANDS = 4, 32  # a pair at the threshold shares no band once in 20 million times
HASHES = ROWS * BANDS
TOLERANCE = 1e-6
STEP = 16
BLOCK = 512  # members of a block; a task compares two blocks at most
LARGE = 8192  # candidate groups above are dealt out by band; links are the same either way
HOT = 1000  # texts with more copies than one row in so many are joined by a broadcast
KEPT_WORDS = 300_000
SIEVE_BITS = 1 << 28  # of the filter that goes to all workers
SIEVE_PARTS = 64
_GOLD = np.uint64(0x9E3779B97F4A7C15)


class Words(dict):
    """Hashes of words; keeps those met first, the frequent ones among them."""

    def __missing__(self, word: str) -> int:
        h = xxhash.xxh3_64_intdigest(word.encode("utf-8", "surrogatepass"))
        if len(self) < KEPT_WORDS:
            self[word] = h
        return h


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingles(text: str, words: Words, size: int = SHINGLE) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the runs of `size` words (in lower case, between blanks); all words if there are fewer."""
    h = np.array(list(map(words.__getitem__, text.lower().split())), dtype=np.uint64)
    if not len(h):
        return h
    return np.unique(runs(h, min(size, len(h))))


def runs(h: np.ndarray, size: int) -> np.ndarray:
    """Hashes of all runs of `size` values, put together from runs of 1, 2, 4, ... values."""
    out, at, length = None, 0, 1
    while True:
        if size & length:
            if out is None:
                out = h
            else:
                n = min(len(out), len(h) - at)
                out = mixed(out[:n] * _GOLD + h[at : at + n] + np.uint64(length))
            at += length
        if at == size:
            return out
        h = mixed(h[:-length] * _GOLD + h[length:] + np.uint64(size))
        length *= 2


def _factors() -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.Generator(np.random.PCG64(4))
    return rng.integers(1, 1 << 63, HASHES, dtype=np.uint64) | np.uint64(1), rng.integers(0, 1 << 63, HASHES, dtype=np.uint64)


def signature(sh: np.ndarray) -> np.ndarray:
    """MinHash values, 32 bits each."""
    a, b = _factors()
    out = np.full(HASHES, np.uint64(0xFFFFFFFFFFFFFFFF))
    for at in range(0, len(sh), 4096):
        part = (sh[at : at + 4096, None] * a + b) >> np.uint64(32)
        out = np.minimum(out, part.min(0))
    return out.astype(np.uint32)


def band_keys(sig: np.ndarray) -> np.ndarray:
    """One 64-bit key per band; the band's number is part of it."""
    rows = sig.reshape(BANDS, ROWS).astype(np.uint64)
    out = np.arange(1, BANDS + 1, dtype=np.uint64) * _GOLD
    for j in range(ROWS):
        out = mixed(out + _GOLD + rows[:, j])
    return out.astype(np.int64)


def least_matches(threshold: float = THRESHOLD, tolerance: float = TOLERANCE) -> list[int]:
    """By number n of compared values: the fewest matches m with P(similarity >= threshold | m of n) >= tolerance.

    Under a uniform prior the posterior is Beta(m + 1, n - m + 1); its tail is a
    binomial sum.
    """
    out = [0]
    for n in range(1, HASHES + 1):
        for m in range(n + 1):
            # P(Beta(m + 1, n - m + 1) >= t) = P(Binomial(n + 1, t) <= m)
            tail = sum(math.comb(n + 1, i) * threshold**i * (1 - threshold) ** (n + 1 - i) for i in range(m + 1))
            if tail >= tolerance:
                break
        out.append(m)
    return out


def verified_pairs(sets: list[np.ndarray], sigs: np.ndarray, left: np.ndarray, right: np.ndarray, same: bool, threshold: float, floors: list[int]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (places) of left x right, or of left alone, whose Jaccard similarity reaches the threshold."""
    sizes = np.array([len(s) for s in sets])
    i, j = (np.triu_indices(len(left), 1) if same else np.divmod(np.arange(len(left) * len(right)), max(len(right), 1)))
    i, j = left[i], (left if same else right)[j]
    ok = np.minimum(sizes[i], sizes[j]) >= threshold * np.maximum(sizes[i], sizes[j])
    i, j = i[ok], j[ok]
    matches = np.zeros(len(i), dtype=np.int32)
    for at in range(0, HASHES, STEP):
        if not len(i):
            return
        for h in range(at, at + STEP):
            column = sigs[:, h]
            matches += column[i] == column[j]
        ok = matches >= floors[at + STEP]
        i, j, matches = i[ok], j[ok], matches[ok]
    if not len(i):
        return
    shared = _shared(sets, i, j)
    # shared / (a + b - shared) >= t, in integers as far as it goes
    ok = shared >= threshold * (sizes[i] + sizes[j] - shared) - 1e-9
    yield i[ok], j[ok]


def _shared(sets: list[np.ndarray], i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Sizes of the intersections; by pairs if they are few, else by products of slices of the membership matrix."""
    used = np.unique(np.concatenate([i, j]))
    if len(i) < 2 * len(used):
        return np.array([len(np.intersect1d(sets[a], sets[b], assume_unique=True)) for a, b in zip(i, j, strict=True)], dtype=np.int64)
    place = np.full(len(sets), -1)
    place[used] = np.arange(len(used))
    flat = np.concatenate([sets[u] for u in used])
    owner = np.repeat(np.arange(len(used)), [len(sets[u]) for u in used])
    values, column, many = np.unique(flat, return_inverse=True, return_counts=True)
    keep = many[column] > 1
    owner, column = owner[keep], column[keep]
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    shared = np.zeros((len(used), len(used)), dtype=np.float32)
    cols = np.unique(column)
    for at in range(0, len(cols), 4096):
        lo, hi = np.searchsorted(column, cols[at]), np.searchsorted(column, cols[min(at + 4096, len(cols)) - 1], side="right")
        m = np.zeros((len(used), 4096), dtype=np.float32)
        m[owner[lo:hi], np.searchsorted(cols[at : at + 4096], column[lo:hi])] = 1
        shared += m @ m.T
    return shared[place[i], place[j]].astype(np.int64)


def _root(parent: np.ndarray, x: int) -> int:
    while parent[x] != x:
        parent[x] = parent[parent[x]]
        x = parent[x]
    return x


def _compared(key, pdf: pd.DataFrame, threshold: float, floors: list[int]) -> pd.DataFrame:
    """All pairs of one cell that share a band: for each member its links here (copies counted) and the least member that it hangs with."""
    pdf = pdf.drop_duplicates("rep")  # equal rows of the source
    sets = [np.frombuffer(s, dtype=np.uint64) for s in pdf["shingles"]]
    sigs = np.stack([signature(s) for s in sets])
    block = pdf["block"].to_numpy()
    first, second, band = int(key[1]), int(key[2]), int(key[3])
    left, right = np.flatnonzero(block == first), np.flatnonzero(block == second)
    copies, reps = pdf["copies"].to_numpy(), pdf["rep"].to_numpy()
    links = np.zeros(len(pdf), dtype=np.int64)
    parent = np.arange(len(pdf))
    order = np.argsort(np.argsort(reps))
    keys = np.stack([band_keys(s) for s in sigs])
    for i, j in verified_pairs(sets, sigs, left, right, first == second, threshold, floors):
        same = keys[i] == keys[j]
        ok = same.any(1)
        if band >= 0:  # a pair counts in the first band that it shares
            ok &= same.argmax(1) == band
        i, j = i[ok], j[ok]
        np.add.at(links, i, copies[j])
        np.add.at(links, j, copies[i])
        for a, b in zip(i.tolist(), j.tolist(), strict=True):
            a, b = _root(parent, a), _root(parent, b)
            if a != b:
                parent[a if order[a] > order[b] else b] = b if order[a] > order[b] else a
    hang = np.array([_root(parent, x) for x in range(len(pdf))], dtype=int)
    out = pd.DataFrame({"rep": reps, "links": links, "hang": reps[hang]})
    return out[links > 0]


def join(docs: DataFrame, threshold: float = THRESHOLD, size: int = SHINGLE) -> DataFrame:
    """One row per document: doc_id, class_id, n_links, n_copies.

    n_links counts the other documents whose word shingles are as similar as
    the threshold, copies included; n_copies those with the same text.
    class_id is the least doc_id that is linked over any number of links, the
    document's own if there is none. Texts without words (and null texts) link
    with none. Null ids are told apart by nothing and count as one id, null.
    Equal rows are copies of each other. Texts are told apart by 64 bits of
    hash. Pairs that share no band are not compared, in groups of any size.
    """
    keyed = docs.select(id_key(F.col("doc_id")).alias("id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("t", F.xxhash64("text", F.length("text")))

    def signed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        words = Words()
        for batch in batches:
            for at in range(0, len(batch), 512):
                part = batch.iloc[at : at + 512]
                rows = []
                for i, t, text in zip(part["id"], part["t"], part["text"], strict=True):
                    sh = shingles(text, words, size)
                    rows.append((i, t, len(sh), band_keys(signature(sh)).tolist() if len(sh) else []))
                yield pd.DataFrame(rows, columns=["id", "t", "n", "bands"])

    signs = staged(keyed.mapInPandas(signed, "id long, t long, n int, bands array<long>"), "signs")
    texts = staged(signs.where("n > 0").groupBy("t").agg(F.min("id").alias("least_id"), F.count(F.lit(1)).alias("copies")), "texts")

    # groups of different texts that share a band; each member is tied to the group's least
    banded = signs.where("n > 0").select("t", F.posexplode_outer("bands").alias("band", "key"))
    groups = staged(banded.groupBy("key").agg(F.min("t").alias("least"), F.max("t").alias("most")).where("least <> most").select("key", "least"), "groups")
    of_groups = broadcast_sieve(groups.select(F.col("key").alias("k")))

    def in_groups(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        bits = of_groups.value
        for batch in batches:
            some = batch[batch["n"] > 0]
            if not len(some):
                continue
            keys = np.stack([np.asarray(b, dtype=np.int64) for b in some["bands"]])
            at, band = np.nonzero(sieved(keys.reshape(-1), bits).reshape(keys.shape))
            yield pd.DataFrame({"t": some["t"].to_numpy()[at], "band": band, "key": keys[at, band]})

    # copies meet before the join, and a key that many texts hold goes to several tasks
    near = signs.select("t", "n", "bands").mapInPandas(in_groups, "t long, band int, key long").distinct()
    member_of = staged(joined_by_salt(near, groups, "key", "t").select("t", "band", "key", "least"), "members")
    ties = member_of.where("t <> least").select(F.col("t").alias("u"), F.col("least").alias("v"))
    member = staged(components(ties), "candidates")
    weight = staged(member.groupBy("root").agg(F.count(F.lit(1)).alias("n")), "weights")
    dealt = joined_by_salt(member, weight, "root", "node").select(F.col("node").alias("t"), "root", "n")
    spread = lambda n: F.greatest(F.lit(1), F.ceil(n / BLOCK)).cast("int")
    whole = dealt.where(F.col("n") <= LARGE).select("t", F.col("root").alias("cell"), F.lit(-1).alias("band"), spread(F.col("n")).alias("blocks"))
    in_bands = member_of.join(dealt.where(F.col("n") > LARGE).select("t"), "t").select("t", "band", "key")
    counts = staged(in_bands.groupBy("key").agg(F.count(F.lit(1)).alias("n")), "band-counts")
    in_bands = joined_by_salt(in_bands, counts, "key", "t").select("t", F.col("key").alias("cell"), "band", spread(F.col("n")).alias("blocks"))
    cells = whole.unionByName(in_bands).withColumn("block", F.pmod(F.xxhash64("t", "cell"), F.col("blocks")).cast("int"))
    cells = staged(cells, "cells")

    # shingles of the members, from the source once more; a filter of bounded size keeps most other texts out of the shuffle
    wanted = staged(cells.select("t").distinct().join(texts, "t").select("t", "least_id", "copies"), "wanted")
    sieve = broadcast_sieve(wanted.select(F.col("t").bitwiseXOR(F.col("least_id")).alias("k")))

    def as_shingles(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        words, bits = Words(), sieve.value
        for batch in batches:
            some = batch[sieved(batch["t"].to_numpy() ^ batch["id"].to_numpy(), bits)]
            yield pd.DataFrame({"id": some["id"], "t": some["t"], "shingles": [shingles(t, words, size).tobytes() for t in some["text"]]})

    found_texts = keyed.mapInPandas(as_shingles, "id long, t long, shingles binary")
    pairs = cells.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    pairs = pairs.join(wanted, "t").select("t", "least_id", "copies", "cell", "band", "block", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"))
    pairs = found_texts.join(staged(pairs, "pairs"), "t").where("id = least_id").select(F.col("t").alias("rep"), "copies", "shingles", "cell", "band", "block", "lo", "hi")
    floors = least_matches(threshold)
    found = pairs.groupBy("cell", "lo", "hi", "band").applyInPandas(lambda key, pdf: _compared(key, pdf, threshold, floors), "rep long, links long, hang long")
    found = staged(found, "links")

    tied = staged(components(found.where("rep <> hang").select(F.col("rep").alias("u"), F.col("hang").alias("v"))), "tied")
    ids = tied.join(texts, tied["node"] == texts["t"]).groupBy("root").agg(F.min("least_id").alias("class"))
    tally = found.groupBy("rep").agg(F.sum("links").alias("links")).join(tied, F.col("rep") == F.col("node"))
    linked = staged(joined_by_salt(tally, ids, "root", "rep").select(F.col("rep").alias("t"), "links", "class"), "linked")
    per_text = texts.where("copies > 1").select("t", "copies", "least_id").join(linked, "t", "full").select("t", F.coalesce("copies", F.lit(1)).alias("copies"), F.coalesce("class", "least_id").alias("class"), F.coalesce("links", F.lit(0)).alias("links"))
    per_text = staged(per_text, "per-text")
    often = F.col("copies") > max(HOT, signs.count() / HOT)  # of HOT texts at most
    hot = F.broadcast(per_text.where(often))
    out = signs.select("id", "t")
    out = out.join(hot, "t").unionByName(out.join(hot.select("t"), "t", "left_anti").join(per_text.where(~often), "t", "left"))
    back = lambda c: F.when(c != NO_ID, c)
    return out.select(
        back(F.col("id")).alias("doc_id"),
        back(F.coalesce("class", "id")).alias("class_id"),
        (F.coalesce("links", F.lit(0)) + F.coalesce(F.col("copies") - 1, F.lit(0))).cast("long").alias("n_links"),
        F.coalesce(F.col("copies") - 1, F.lit(0)).cast("long").alias("n_copies"),
    )


def broadcast_sieve(keys: DataFrame, most_bits: int = SIEVE_BITS):
    """Broadcast bitmap of the hashed keys (k long): 16 bits a row as long as that stays below most_bits; more rows let more others through.

    It only keeps most of the other rows out of a shuffle; a join decides.
    """
    n = keys.count()
    size = 1 << max(10, min(most_bits.bit_length() - 1, (16 * max(n, 1)).bit_length()))
    span = size // SIEVE_PARTS

    def slots(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            at = np.unique(_slot(batch["k"].to_numpy(), size))
            yield pd.DataFrame({"part": at // span, "at": at % span})

    def mark(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        made: dict[int, np.ndarray] = {}
        for batch in batches:
            for part, some in batch.groupby("part"):
                made.setdefault(int(part), np.zeros(span, dtype=bool))[some["at"].to_numpy()] = True
        for part, bits in made.items():
            yield pd.DataFrame({"part": [part], "bits": [np.packbits(bits).tobytes()]})

    every = np.zeros(size // 8, dtype=np.uint8)
    for row in keys.mapInPandas(slots, "part long, at long").repartition("part").mapInPandas(mark, "part long, bits binary").collect():
        every[row["part"] * span // 8 : (row["part"] + 1) * span // 8] |= np.frombuffer(bytes(row["bits"]), dtype=np.uint8)
    return keys.sparkSession.sparkContext.broadcast(every)


def _slot(keys: np.ndarray, size: int) -> np.ndarray:
    return (mixed(keys.astype(np.int64).view(np.uint64)) % np.uint64(size)).astype(np.int64)


def sieved(keys: np.ndarray, bits: np.ndarray) -> np.ndarray:
    at = _slot(keys, 8 * len(bits))
    return ((bits[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1).astype(bool)


def op4_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join(table(spark, sf_dir, "documents"))


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: of each class one document stays, that with the least doc_id (null last), of equal ids the one with the least hash of id and text. Rows are told apart by id and text."""
    keyed = docs.withColumn("__row", row_key(F.col("doc_id"), F.col("text")))
    classes = staged(join(keyed.select(F.col("__row").alias("doc_id"), "text")).select(F.col("doc_id").alias("__row"), F.col("class_id").alias("__class")).distinct(), "classes")
    order = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").cast("long").alias("id"), F.col("__row").alias("row"))
    least = keyed.select("doc_id", "__row").join(classes, "__row").groupBy("__class").agg(F.min(order).alias("first")).select(F.col("first.row").alias("__row"))
    return keyed.join(least, "__row", "left_semi").dropDuplicates(["__row"]).select(*docs.columns)


OP4_SQL = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '\s+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(list_slice(w, p, p + 4), ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS p FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE k >= 0.8 * (a.n + b.n - k) - 1e-9),
e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r AS (WITH RECURSIVE c(doc_id, reach) AS (SELECT x, y FROM e UNION SELECT c.doc_id, e.y FROM c JOIN e ON e.x = c.reach) SELECT doc_id, min(reach) AS least FROM c GROUP BY doc_id),
k AS (SELECT x AS doc_id, count(*) AS n FROM e GROUP BY x),
c AS (SELECT coalesce(text, '') AS t, count(*) AS n FROM documents GROUP BY ALL)
SELECT d.doc_id, least(coalesce(r.least, d.doc_id), d.doc_id) AS class_id, coalesce(k.n, 0) AS n_links, CASE WHEN len(d.w) > 0 THEN c.n - 1 ELSE 0 END AS n_copies
FROM d JOIN documents o USING (doc_id) JOIN c ON c.t = coalesce(o.text, '') LEFT JOIN r USING (doc_id) LEFT JOIN k USING (doc_id)
"""
