"""Secret scans: fixed patterns, and sliding-window entropy over candidate strings (DataFrame functions only)."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table


def _either_case(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


#: Fixed values of the contract: the base patterns, in the order of the kinds.
_NAMES = "|".join(_either_case(w) for w in ("password", "passwd", "secret", "token", "api_?key"))
ASSIGN = rf"({_NAMES})[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)"
ACCESS = "AKIA[A-Z0-9]{12,}"
HEX = "[0-9a-f]{32,}"
KINDS = ("assign", "access", "hex", "entropy")

#: Candidate strings and their characters, the window, and bits of entropy a character that a window of a class must reach.
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_-"
CANDIDATE = "[A-Za-z0-9+/_-]{20,}"
WINDOW = 20
CLASSES = (("hex", "^([0-9a-f]+|[0-9A-F]+)$", 3.0), ("one_case", "^([0-9a-z+/_-]+|[0-9A-Z+/_-]+)$", 3.6), ("mixed", "", 3.7))
#: Whole candidates of these shapes are no secrets: UUIDs, and paths or names of words and numbers between separators.
_SEGMENT = "([A-Za-z][a-z]{0,14}[0-9]{0,4}|[A-Z]{2,15}[0-9]{0,4}|[0-9]{1,8})"
ALLOWED = "|".join(("^[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}$", f"^[/_+-]*{_SEGMENT}([/_+-]+{_SEGMENT})+[/_+-]*$"))
#: Windows that touch one of these are not looked at: marks of examples, filling, runs of an alphabet.
MARKS = "EXAMPLE|example|sample|placeholder|xxxx|XXXX|0000|0123456789|abcdefghij|ABCDEFGHIJ"
COUNTS_A_LONG, BITS_A_COUNT = 12, 5  # a count of up to WINDOW takes 5 bits
SCALE = 1_000_000


def _bits(n: int) -> int:
    return round(SCALE * n * math.log2(n)) if n else 0


#: n * log2 n in millionths, by n up to the window: entropies are then sums of integers, equal in every engine.
N_LOG_N = [_bits(n) for n in range(WINDOW + 2)]


def most_for(threshold: float, window: int = WINDOW) -> int:
    """A window reaches the threshold when its sum of n log n is at most this."""
    return _bits(window) - round(SCALE * threshold * window)


def _placed(kind: str, pieces: Column, found: Column, kept: Column) -> Column:
    """Spans of the matches: text between them comes from pieces, their own from found; kept: array of booleans."""
    none = F.array().cast("array<struct<start:int,rank:int,end:int>>")
    state = F.struct(F.lit(0).alias("at"), none.alias("spans"))

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.length(x["piece"])
        end = start + F.length(x["hit"])
        span = F.struct(start.alias("start"), F.lit(KINDS.index(kind)).alias("rank"), end.alias("end"))
        return F.struct(end.alias("at"), F.when(x["keep"], F.concat(acc["spans"], F.array(span))).otherwise(acc["spans"]).alias("spans"))

    parts = F.arrays_zip(F.slice(pieces, F.lit(1), F.size(found)).alias("piece"), found.alias("hit"), kept.alias("keep"))
    return F.aggregate(parts, state, step, lambda acc: acc["spans"])


def peak_sum(text: Column, window: int = WINDOW) -> Column:
    """Least sum of n log n over the windows of a text of ALPHABET; the largest integer if it is shorter than a window.

    The state carries the count of each character in the window, packed in
    longs. A window moves by one character: the count of the one that comes in
    and of the one that goes out change by one, and the sum by two table
    differences each.
    """
    logs = F.array(*[F.lit(x) for x in N_LOG_N])
    slots = -(-len(ALPHABET) // COUNTS_A_LONG)
    slot = lambda code: F.floor((code - 1) / COUNTS_A_LONG).cast("int")
    shift = lambda code: (F.lit(BITS_A_COUNT) * ((code - 1) % COUNTS_A_LONG)).cast("int")
    unit = lambda code: F.call_function("shiftleft", F.lit(1).cast("long"), shift(code))
    count = lambda counts, code: F.call_function("shiftright", F.get(counts, slot(code)), shift(code)).bitwiseAND((1 << BITS_A_COUNT) - 1).cast("int")
    codes = F.transform(F.split(text, ""), lambda c: F.instr(F.lit(ALPHABET), c))
    zeros = F.array_repeat(F.lit(0), window)
    moves = F.element_at(F.transform(F.array(codes), lambda cs: F.zip_with(cs, F.concat(zeros, F.slice(cs, F.lit(1), F.greatest(F.size(cs) - window, F.lit(0)))), lambda a, b: F.struct(a.alias("come"), b.alias("gone")))), 1)

    def step(acc: Column, m: Column) -> Column:
        come, gone = m["come"], m["gone"]
        before = count(acc["counts"], come)
        total = acc["total"] + F.get(logs, before + 1) - F.get(logs, before)
        held = count(acc["counts"], gone) + F.when(gone == come, 1).otherwise(0)
        full = gone > 0
        moved = F.when(full, total - F.get(logs, held) + F.get(logs, held - 1)).otherwise(total)
        counts = F.transform(acc["counts"], lambda x, i: x + F.when(i == slot(come), unit(come)).otherwise(0) - F.when(full & (i == slot(gone)), unit(gone)).otherwise(0))
        n = acc["n"] + 1
        return F.struct(counts.alias("counts"), moved.alias("total"), n.alias("n"), F.when(n >= window, F.least(acc["best"], moved)).otherwise(acc["best"]).alias("best"))

    start = F.struct(F.array_repeat(F.lit(0).cast("long"), slots).alias("counts"), F.lit(0).alias("total"), F.lit(0).alias("n"), F.lit((1 << 31) - 1).alias("best"))
    return F.aggregate(moves, start, step, lambda acc: acc["best"])


def suspicious(text: Column) -> Column:
    """Whether a candidate string looks random: digits and letters, of no allowed shape, a window off the marks with enough entropy for its class."""
    most = F.lit(most_for(CLASSES[-1][2]))
    for _, shape, threshold in reversed(CLASSES[:-1]):
        most = F.when(text.rlike(shape), most_for(threshold)).otherwise(most)
    parts = F.filter(F.split(text, MARKS), lambda x: F.length(x) >= WINDOW)
    shaped = text.rlike("[0-9]") & text.rlike("[A-Za-z]") & ~text.rlike(ALLOWED)
    return F.when(shaped, F.exists(parts, lambda x: peak_sum(x) <= most)).otherwise(False)


def outside(span: Column, spans: str) -> Column:
    """The parts of a span that none of the spans (sorted by start) covers."""
    part = lambda a, b: F.array(F.struct(a.alias("start"), span["rank"].alias("rank"), b.alias("end")))
    none = F.array().cast("array<struct<start:int,rank:int,end:int>>")
    state = F.struct(span["start"].alias("at"), none.alias("out"))

    def step(acc: Column, b: Column) -> Column:
        meets = (b["start"] < span["end"]) & (b["end"] > acc["at"])
        more = F.when(meets & (b["start"] > acc["at"]), F.concat(acc["out"], part(acc["at"], b["start"]))).otherwise(acc["out"])
        return F.struct(F.when(meets, b["end"]).otherwise(acc["at"]).alias("at"), more.alias("out"))

    return F.aggregate(spans, state, step, lambda acc: F.when(acc["at"] < span["end"], F.concat(acc["out"], part(acc["at"], span["end"]))).otherwise(acc["out"]))


def with_spans(docs: DataFrame, text: str = "text") -> DataFrame:
    """Adds columns __base and __spans: arrays of (start, rank, end) in order; rank is the place of the kind in KINDS.

    Offsets are code points, the end is exclusive. Null and empty texts have none.
    """
    t = F.coalesce(F.col(text), F.lit(""))
    none = F.array().cast("array<struct<start:int,rank:int,end:int>>")

    def of(kind: str, pattern: str, may: Column, kept) -> Column:
        found = F.regexp_extract_all(t, F.lit(pattern), F.lit(0))
        return F.when(may, _placed(kind, F.split(t, pattern, -1), found, kept(found))).otherwise(none)

    long_enough = F.transform(F.regexp_extract_all(t, F.lit(ASSIGN), F.lit(2)), lambda x: F.length(x) >= 8)
    everyone = lambda found: F.transform(found, lambda _: F.lit(True))
    assigns = of("assign", ASSIGN, t.contains("=") | t.contains(":"), lambda _: long_enough)
    access = of("access", ACCESS, t.contains("AKIA"), everyone)
    hexes = of("hex", HEX, t.rlike(HEX), everyone)
    random = of("entropy", CANDIDATE, t.rlike(CANDIDATE), lambda found: F.transform(found, suspicious))
    out = docs.withColumn("__base", F.array_sort(F.concat(assigns, access, hexes))).withColumn("__random", random)
    new = F.flatten(F.transform("__random", lambda r: outside(r, "__base")))
    return out.withColumn("__spans", F.when(F.size("__random") == 0, F.col("__base")).otherwise(F.array_sort(F.concat("__base", new)))).drop("__random")


def named(spans: str) -> Column:
    """kind:start:end of each span, joined by commas."""
    kinds = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(kinds, s["rank"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def scan(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, n_assign, n_access, n_hex, base_sha256, spans.

    Null and empty texts give zeros and ''. Equal rows each give a row; other
    columns are ignored. The method adds spans of kind entropy: candidates that
    look random, but for their parts in base spans.
    """
    found = with_spans(docs.select("doc_id", "text"))
    count = lambda kind: F.size(F.filter("__base", lambda s: s["rank"] == KINDS.index(kind))).cast("long")
    return found.select("doc_id", *[count(k).alias(f"n_{k}") for k in KINDS[:3]], F.sha2(named("__base"), 256).alias("base_sha256"), named("__spans").alias("spans"))


def op7_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))


MASK = "[SECRET]"


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: each run of overlapping spans in a text gives way to MASK; n_chars follows. Texts without spans stay as they are."""
    found = with_spans(docs)
    t = F.col("text")
    state = F.struct(F.lit("").alias("out"), F.lit(0).alias("at"))

    def step(acc: Column, s: Column) -> Column:
        between = F.when(s["start"] >= acc["at"], F.concat(F.substr(t, acc["at"] + 1, s["start"] - acc["at"]), F.lit(MASK))).otherwise(F.lit(""))
        return F.struct(F.concat(acc["out"], between).alias("out"), F.greatest(acc["at"], s["end"]).alias("at"))

    masked = F.aggregate("__spans", state, step, lambda acc: F.concat(acc["out"], F.substr(t, acc["at"] + 1, F.length(t))))
    cut = found.withColumn("text", F.when(F.size("__spans") > 0, masked).otherwise(t))
    if "n_chars" in docs.columns:
        cut = cut.withColumn("n_chars", F.when(F.size("__spans") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars")))
    return cut.select(*docs.columns)


def _placed_sql(kind: str, pattern: str, keep: str = "true") -> str:
    quoted = pattern.replace("'", "''")
    return f"""
{kind}_m AS (SELECT doc_id, regexp_extract_all(t, '{quoted}', 0) AS f, regexp_extract_all(t, '{quoted}', {2 if kind == "assign" else 0}) AS g, string_split_regex(t, '{quoted}') AS p FROM d WHERE regexp_matches(t, '{quoted}')),
{kind}_i AS (SELECT doc_id, unnest(range(1, len(f) + 1)) AS i, unnest(f) AS f, unnest(g) AS g, unnest(p[1:len(f)]) AS p FROM {kind}_m),
{kind}_s AS (SELECT doc_id, g, i, sum(length(p) + length(f)) OVER (PARTITION BY doc_id ORDER BY i) - length(f) AS s, sum(length(p) + length(f)) OVER (PARTITION BY doc_id ORDER BY i) AS e FROM {kind}_i),
{kind}_k AS (SELECT doc_id, {KINDS.index(kind)} AS k, '{kind}' AS n, CAST(s AS BIGINT) AS s, CAST(e AS BIGINT) AS e FROM {kind}_s WHERE {keep})"""


_MOST_SQL = "CASE " + " ".join(f"WHEN regexp_matches(g, '{shape}') THEN {most_for(threshold)}" for _, shape, threshold in CLASSES[:-1]) + f" ELSE {most_for(CLASSES[-1][2])} END"

OP7_SQL = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
{_placed_sql("assign", ASSIGN, "length(g) >= 8")},
{_placed_sql("access", ACCESS)},
{_placed_sql("hex", HEX)},
cand AS (SELECT DISTINCT unnest(regexp_extract_all(t, '{CANDIDATE}')) AS g FROM d WHERE regexp_matches(t, '{CANDIDATE}')),
shaped AS (SELECT g, part, {_MOST_SQL} AS most FROM (SELECT g, unnest(string_split_regex(g, '{MARKS}')) AS part FROM cand WHERE regexp_matches(g, '[0-9]') AND regexp_matches(g, '[A-Za-z]') AND NOT regexp_matches(g, '{ALLOWED}'))),
win AS (SELECT DISTINCT g, most, part, p, substr(part, p, {WINDOW}) AS w FROM (SELECT g, most, part, unnest(range(1, length(part) - {WINDOW} + 2)) AS p FROM shaped WHERE length(part) >= {WINDOW})),
ch AS (SELECT g, most, part, p, c, count(*) AS n FROM (SELECT g, most, part, p, unnest(string_split(w, '')) AS c FROM win) GROUP BY ALL),
sums AS (SELECT g, most, part, p, sum(list_extract([{", ".join(map(str, N_LOG_N))}], CAST(n AS INTEGER) + 1)) AS total FROM ch GROUP BY ALL),
rnd AS (SELECT DISTINCT g FROM sums WHERE total <= most),
{_placed_sql("entropy", CANDIDATE, "g IN (SELECT g FROM rnd)")},
base AS (SELECT * FROM assign_k UNION ALL SELECT * FROM access_k UNION ALL SELECT * FROM hex_k),
meets AS (SELECT r.doc_id, r.s AS rs, r.e AS re, b.s AS bs, b.e AS be FROM entropy_k r LEFT JOIN base b ON b.doc_id = r.doc_id AND b.s < r.e AND r.s < b.e),
gaps AS (SELECT doc_id, greatest(rs, coalesce(max(be) OVER (PARTITION BY doc_id, rs ORDER BY bs, be ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), rs)) AS s, bs AS e FROM meets WHERE bs IS NOT NULL
  UNION ALL SELECT doc_id, greatest(rs, coalesce(max(be), rs)) AS s, re AS e FROM meets GROUP BY doc_id, rs, re),
every AS (SELECT * FROM base UNION ALL SELECT doc_id, 3 AS k, 'entropy' AS n, s, e FROM gaps WHERE s < e),
b AS (SELECT doc_id, count(*) FILTER (k = 0) AS a0, count(*) FILTER (k = 1) AS a1, count(*) FILTER (k = 2) AS a2, string_agg(n || ':' || s || ':' || e, ',' ORDER BY s, k, e) AS j FROM base GROUP BY doc_id),
v AS (SELECT doc_id, string_agg(n || ':' || s || ':' || e, ',' ORDER BY s, k, e) AS j FROM every GROUP BY doc_id)
SELECT d.doc_id, coalesce(a0, 0) AS n_assign, coalesce(a1, 0) AS n_access, coalesce(a2, 0) AS n_hex, sha256(coalesce(b.j, '')) AS base_sha256, coalesce(v.j, '') AS spans
FROM d LEFT JOIN b USING (doc_id) LEFT JOIN v USING (doc_id)
"""
