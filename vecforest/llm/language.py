"""Language identification by Bayesian fusion of evidence.

A model of hashed letter trigrams per language, of any script, gives the likelihood of a text. Grouped
aggregation of what the texts say gives the likelihood of a declared language
and of an address suffix, and a prior by host that falls back on its domain,
its top-level domain and the whole table. The posterior is their product.
"""

from __future__ import annotations

import math
import re
import unicodedata
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import staged, table

SLOTS = 1 << 16  # of hashed trigrams and of hashed pairs; a language takes 256 KiB in the model
MOST_LANGUAGES = 1024  # that bound the model; labels with fewer rows than the first so many are no languages of the model
TRUST, CHANCE = 5.0, 60.0  # an unseen trigram counts as TRUST of its pair over CHANCE letters
AT_ONCE = 1 << 14  # trigrams of a text that are looked up together
TELLING = 100.0  # letters after which more of the same text says nothing new
BACK_OFF = 10.0  # pages that a wider prior counts as
FEW = 0.5

_DROP = re.compile(r"<(script|style)\b.*?</\1\s*>|<!--.*?-->|<[^>]*>", re.S | re.I)
_ENTITY = re.compile(r"&[#\w]+;")


def visible(html: str) -> str:
    """The text between the tags; scripts, styles and comments go."""
    return _ENTITY.sub(" ", _DROP.sub(" ", html))


def letter_table() -> np.ndarray:
    """The lower-case code of each UTF-16 unit that is a letter or a mark of some script; 0 for all else."""
    out = np.zeros(0x10000, dtype=np.uint32)
    for code in range(0x10000):
        c = chr(code)
        if unicodedata.category(c)[0] in "LM":
            low = c.lower()
            out[code] = ord(low) if len(low) == 1 else code
    return out


def trigrams(text: str, letters: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Slots of the letter trigrams of a text whose last or middle place is a letter, and of the pairs that they begin with."""
    x = letters[np.frombuffer(f"  {text} ".encode("utf-16-le", "surrogatepass"), dtype=np.uint16)]
    a, b, c = x[:-2], x[1:-1], x[2:]
    ok = (b > 0) | (c > 0)
    pair = a[ok] * np.uint32(0x9E3779B1) + b[ok] * np.uint32(0x85EBCA77)
    three = (pair ^ (pair >> np.uint32(15))) * np.uint32(0xC2B2AE3D) + c[ok] * np.uint32(0x27D4EB2F)
    slot = lambda h: ((h ^ (h >> np.uint32(13))) * np.uint32(0x165667B1)) >> np.uint32(16)
    return slot(three).astype(np.int64), slot(pair).astype(np.int64)


def train(docs: DataFrame, lang: str = "lang") -> tuple[list[str], np.ndarray]:
    """Languages, and tables (2 x SLOTS x language) of ln(count + smoothing) of trigrams and of pairs; from all rows with a language.

    ln P(third | first two letters) is the difference of the two entries. Each
    task adds its rows up in tables of fixed size before they move.
    """

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        letters, totals = letter_table(), {}
        for batch in batches:
            for name, part in batch.groupby("lang"):
                total = totals.setdefault(name, np.zeros(2 * SLOTS, dtype=np.int64))
                for start in range(0, len(part), 256):
                    three, two = trigrams("  ".join(part["text"].iloc[start : start + 256]), letters)
                    total[:SLOTS] += np.bincount(three, minlength=SLOTS)
                    total[SLOTS:] += np.bincount(two, minlength=SLOTS)
            if len(totals) > 64:  # tables of that many languages leave the task
                yield from rows_of(totals)
                totals = {}
        yield from rows_of(totals)

    def rows_of(totals: dict[str, np.ndarray]) -> Iterator[pd.DataFrame]:
        for name, total in totals.items():
            some = np.flatnonzero(total)
            yield pd.DataFrame({"lang": name, "at": some, "n": total[some]})

    def packed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for name, part in batch.groupby("lang"):
                yield pd.DataFrame({"lang": [name], "at": [part["at"].to_numpy(dtype=np.int64).tobytes()], "n": [part["n"].to_numpy(dtype=np.int64).tobytes()]})

    rows = docs.select(F.col(lang).cast("string").alias("lang"), F.coalesce("text", F.lit("")).alias("text")).where("lang is not null")
    names = sorted(r["lang"] for r in rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "lang").limit(MOST_LANGUAGES).collect())
    some = rows.mapInPandas(count, "lang string, at long, n long").groupBy("lang", "at").agg(F.sum("n").alias("n"))
    out = np.zeros((2, SLOTS, len(names)), dtype=np.float32)
    place = {name: j for j, name in enumerate(names)}
    for r in some.mapInPandas(packed, "lang string, at binary, n binary").toLocalIterator():
        if r["lang"] in place:
            at = np.frombuffer(bytes(r["at"]), dtype=np.int64)
            out[at // SLOTS, at % SLOTS, place[r["lang"]]] = np.frombuffer(bytes(r["n"]), dtype=np.int64)
    out[0] += TRUST / CHANCE
    out[1] += TRUST
    return names, np.log(out, out=out)


def domain_of(host: Column) -> Column:
    """Last two labels of a host name."""
    return F.regexp_extract(host, r"([^.]+\.[^.]+)$", 1)


def top_of(host: Column) -> Column:
    return F.regexp_extract(host, r"\.([^.]+)$", 1)


def identify(rows: DataFrame, names: list[str], table_: np.ndarray, html: bool = False) -> DataFrame:
    """Fuses the evidence of rows (id, text, declared, suffix, host): id, lang, probability, text_lang, n_letters, rejected.

    Null text, declared, suffix or host is no evidence. Letters are those of any
    script. rejected: no letters, letters less likely than by chance under each language, or no language with
    probability 0.5. Without languages all rows are rejected and lang is null.
    """
    many = len(names)
    if not many:
        return rows.select("id", F.lit(None).cast("string").alias("lang"), F.lit(0.0).alias("probability"), F.lit(None).cast("string").alias("text_lang"), F.lit(0).cast("long").alias("n_letters"), F.lit(True).alias("rejected"))
    shared = rows.sparkSession.sparkContext.broadcast(table_)  # 2 x SLOTS x MOST_LANGUAGES at most

    def likelihoods(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        letters, logs = letter_table(), shared.value
        for batch in batches:
            sizes, means = [], []
            for text in batch:
                three, two = trigrams(visible(text) if html else text, letters)
                total = np.zeros(many)
                for at in range(0, len(three), AT_ONCE):
                    total += (logs[0, three[at : at + AT_ONCE]] - logs[1, two[at : at + AT_ONCE]]).sum(0, dtype=np.float64)
                sizes.append(len(three))
                means.append((total / max(len(three), 1)).tolist())
            yield pd.DataFrame({"n": np.array(sizes, dtype=np.int64), "mean": means})

    of = F.pandas_udf(likelihoods, "n long, mean array<double>")
    seen = rows.withColumn("t", of(F.coalesce("text", F.lit("")))).select("id", "declared", "suffix", F.coalesce("host", F.lit("")).alias("host"), F.col("t.n").alias("n"), F.col("t.mean").alias("mean"))
    ll = F.transform("mean", lambda x: x * F.least(F.col("n").cast("double"), F.lit(TELLING)))
    seen = staged(seen.withColumn("ll", ll).drop("mean").withColumn("post", _normal(F.col("ll"))), "likelihoods")

    # what the texts say about each declared language, suffix, host, domain and top-level domain, in one aggregation
    marks = F.array(*[F.struct(F.lit(kind).alias("kind"), value.alias("value")) for kind, value in (
        ("declared", F.col("declared")), ("suffix", F.col("suffix")), ("host", F.col("host")), ("domain", domain_of(F.col("host"))), ("top", top_of(F.col("host"))), ("all", F.lit("")))])
    sums = [F.sum(F.get("post", F.lit(j))).alias(f"s{j}") for j in range(many)]
    told = seen.select(F.explode(marks).alias("m"), "post").select("m.kind", "m.value", "post").where("value is not null").groupBy("kind", "value").agg(*sums)
    told = staged(told.select("kind", "value", F.array(*[f"s{j}" for j in range(many)]).alias("s")), "evidence")
    whole = told.where("kind = 'all'").first()
    total = [x + FEW for x in whole["s"]] if whole else [1.0] * many
    lits = lambda xs: F.array(*[F.lit(float(x)) for x in xs])
    top_prior = lits([x / sum(total) for x in total])

    def under(s: Column, wider: Column) -> Column:
        n = F.aggregate(F.coalesce(s, F.array()), F.lit(0.0), lambda a, x: a + x)
        return F.when(s.isNull(), wider).otherwise(F.zip_with(s, wider, lambda x, w: (x + BACK_OFF * w) / (n + BACK_OFF)))

    of_kind = lambda kind, key, name: told.where(F.col("kind") == kind).select(F.col("value").alias(key), F.col("s").alias(name))
    hosts = of_kind("host", "host", "hs").withColumn("domain", domain_of(F.col("host"))).withColumn("top", top_of(F.col("host")))
    hosts = hosts.join(of_kind("domain", "domain", "ds"), "domain", "left").join(of_kind("top", "top", "ts"), "top", "left")
    hosts = hosts.withColumn("p", under(F.col("ts"), top_prior)).withColumn("p", under(F.col("ds"), F.col("p"))).withColumn("prior", under(F.col("hs"), F.col("p"))).select("host", "prior")

    def given(kind: str, name: str) -> DataFrame:
        """ln P(value | language), smoothed by one row for each value."""
        mine = told.where(F.col("kind") == kind)
        values = mine.count()
        all_of = mine.agg(*[F.sum(F.get("s", F.lit(j))) for j in range(many)]).first()
        below = lits([(x or 0.0) + FEW * max(values, 1) for x in all_of])
        return mine.select(F.col("value").alias(kind), F.zip_with("s", below, lambda x, b: F.log((x + FEW) / b)).alias(name))

    none = lits([0.0] * many)
    fused = seen.join(hosts, "host", "left").join(given("declared", "dl"), "declared", "left").join(given("suffix", "sl"), "suffix", "left")
    add = lambda a, b: F.zip_with(a, b, lambda x, y: x + y)
    logs = add(add(F.col("ll"), F.transform(F.coalesce("prior", top_prior), lambda x: F.log(x))), add(F.coalesce("dl", none), F.coalesce("sl", none)))
    fused = fused.withColumn("logs", logs).withColumn("fused", _normal(F.col("logs")))
    labels = F.array(*[F.lit(x) for x in names])
    best = F.array_max("fused")
    chance = F.array_max("ll") < F.least(F.col("n").cast("double"), F.lit(TELLING)) * -math.log(CHANCE)
    return fused.select(
        "id",
        F.get(labels, F.array_position("fused", best).cast("int") - 1).alias("lang"),
        F.round(best, 9).alias("probability"),
        F.when(F.col("n") > 0, F.get(labels, F.array_position("post", F.array_max("post")).cast("int") - 1)).alias("text_lang"),
        F.col("n").alias("n_letters"),
        ((F.col("n") == 0) | chance | (best < 0.5)).alias("rejected"),
    )


def _normal(logs: Column) -> Column:
    """Probabilities of an array of logarithms."""
    parts = F.transform(logs, lambda x: F.exp(x - F.array_max(logs)))
    return F.transform(parts, lambda x: x / F.aggregate(parts, F.lit(0.0), lambda a, y: a + y))


def of_pages(pages: DataFrame, docs: DataFrame) -> DataFrame:
    """One row per page: page_id, lang, probability, text_lang, declared, n_letters, rejected; the models come from docs (text, lang).

    declared is the lang attribute of the html element; the suffix is a
    two-letter first step of the path, else the top-level domain. Null urls and
    html are no evidence; equal rows each give a row.
    """
    html, url = F.col("html"), F.col("url")
    host = F.lower(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1))
    step = F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://[^/?#]*/([a-zA-Z]{2})(?:[/?#]|$)", 1)
    declared = F.lower(F.regexp_extract(html, r"(?i)<html\b[^>]*?\blang\s*=\s*[\"']?([a-zA-Z]+)", 1))
    rows = pages.select(
        F.struct(F.col("page_id").alias("page_id"), F.nullif(declared, F.lit("")).alias("declared")).alias("id"),
        html.alias("text"),
        F.nullif(declared, F.lit("")).alias("declared"),
        F.coalesce(F.nullif(F.lower(step), F.lit("")), F.nullif(top_of(host), F.lit(""))).alias("suffix"),
        F.nullif(host, F.lit("")).alias("host"),
    )
    names, logs = train(docs)
    return identify(rows, names, logs, html=True).select("id.page_id", "lang", "probability", "text_lang", "id.declared", "n_letters", "rejected")


def op5_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return of_pages(table(spark, sf_dir, "pages"), table(spark, sf_dir, "documents"))


def keep_known_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents whose language is identified; lang is the declared language and source the host.

    The model comes from the stage's own input. Rows go if their text is null or
    has no letters, or is in no language of the input; letters of all scripts
    count. Rows are judged by their own text, whatever their ids; equal rows
    stay or go together.
    """
    names, logs = train(docs)
    rows = docs.select(F.struct(*[F.col(c) for c in docs.columns]).alias("row")).select(
        "row", F.col("row.text").alias("text"), F.col("row.lang").cast("string").alias("declared"), F.lit(None).cast("string").alias("suffix"), F.col("row.source").cast("string").alias("host")
    )
    keyed = rows.select(F.struct(F.col("row.doc_id").alias("doc_id"), F.xxhash64("text").alias("tk")).alias("id"), "text", "declared", "suffix", "host")
    bad = identify(keyed, names, logs).where("rejected").select(F.col("id.doc_id").alias("__id"), F.col("id.tk").alias("__tk")).distinct()
    on = F.col("__id").eqNullSafe(F.col("doc_id")) & (F.col("__tk") == F.xxhash64("text"))
    return docs.join(bad, on, "left_anti").select(*docs.columns)
