"""Toxicity after noisy-channel deobfuscation.

What is odd about a text (signs among letters, letters spaced out, letters
repeated) becomes a lattice of what could have been meant; Viterbi decoding
under a character model of the whole corpus picks a path. The restored text is
scored by word and word-start evidence learnt from labelled documents.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import staged, table
from .quality import held_out, sampled_labels

SAMPLE = 20_000
LEXICON = 2_000  # most features that a round of learning adds
KEPT = 200_000
FEWEST = 3  # documents that a piece of evidence needs
USUAL = 1000.0  # pieces of evidence of a document that counts fully

#: Letters that a sign may stand for, in natural order of the signs.
STANDS_FOR = {"!": "il", "$": "s", "(": "c", "+": "t", "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g", "@": "a", "|": "il", "€": "e"}
KEEP_SIGN, SWAP, DROP_REPEAT, DROP_ONE, DROP_GAP = 6.0, 1.0, 0.7, 6.0, 0.3  # costs, natural logarithms
LETTERS = "abcdefghijklmnopqrstuvwxyzßàáâäçèéêíîïñóôöùúûü"
CODE = {c: i + 1 for i, c in enumerate(LETTERS)}  # 0: a word's border and all else
BASE = len(LETTERS) + 1

_SIGNS = "".join(re.escape(c) for c in STANDS_FOR)
_ONE = r"[^\W\d_]"
#: What makes a word odd: a sign beside a letter, or a letter three times in a row.
ODD = re.compile(rf"{_ONE}[{_SIGNS}]|[{_SIGNS}]{_ONE}|({_ONE})\1\1")
#: A word of single characters with gap signs between each two.
GAPS = " ._*-"
GAPPED = re.compile(rf"[\w{_SIGNS}](?:[._*-]+[\w{_SIGNS}]){{2,}}")
OPENING, CLOSING = "\"'([{<", "!.,;:?\"')]}>"
WORD = re.compile(r"[^\W\d_]+")


def code_table() -> np.ndarray:
    out = np.zeros(0x10000, dtype=np.int64)
    for c, i in CODE.items():
        out[ord(c)] = out[ord(c.upper()) if len(c.upper()) == 1 else ord(c)] = i
    return out


def trigram_counts(texts: DataFrame) -> np.ndarray:
    """Counts of letter trigrams over all texts; each task adds its own up, and the table's size is fixed."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        codes, total = code_table(), np.zeros(BASE**3, dtype=np.int64)
        for batch in batches:
            for at in range(0, len(batch), 256):
                joined = "  ".join(batch["text"].iloc[at : at + 256])
                points = np.frombuffer(joined.encode("utf-16-le", "surrogatepass"), dtype=np.uint16)
                x = codes[points]
                if len(x) > 2:
                    total += np.bincount((x[:-2] * BASE + x[1:-1]) * BASE + x[2:], minlength=BASE**3)
        some = np.flatnonzero(total)
        yield pd.DataFrame({"at": some, "n": total[some]})

    got = texts.mapInPandas(count, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).toPandas()
    out = np.zeros(BASE**3)
    out[got["at"].to_numpy(dtype=int)] = got["n"]
    return out.reshape(BASE, BASE, BASE)


def character_costs(counts: np.ndarray) -> np.ndarray:
    """-ln P(c | a, b) of a trigram model that falls back on bigrams and letters."""
    uni = (counts.sum((0, 1)) + 1) / (counts.sum() + BASE)
    two = counts.sum(0)
    bi = (two + 5 * uni) / (two.sum(1, keepdims=True) + 5)
    return -np.log((counts + 5 * bi[None]) / (counts.sum(2, keepdims=True) + 5))


class Restorer:
    """Restores texts word by word; a clean word has a lattice of one path and stays as it is."""

    def __init__(self, costs: np.ndarray):
        self.costs = costs.tolist()

    def tokens(self, text: str) -> list[str]:
        """Words of the text in lower case; three or more single characters in a row are one word, with blanks inside; quotes before the first and signs after the last may hang on."""
        found = text.lower().split()
        lengths = list(map(len, found))
        if lengths.count(1) < 2:
            return found
        out, run = [], []
        for word, n in zip(found, lengths, strict=True):
            if n == 1 or not run and n == 2 and word[0] in OPENING:
                run.append(word)
                continue
            if run and n <= 3 and not word[1:].strip(CLOSING):
                run.append(word)
                word = None
            out += [" ".join(run)] if len(run) > 2 else run
            run = []
            if word is not None:
                out.append(word)
        return out + ([" ".join(run)] if len(run) > 2 else run)

    def text(self, text: str) -> str:
        """The restored text in lower case, with one blank between words."""
        return " ".join(map(self.word, self.tokens(text)))

    def word(self, word: str) -> str:
        """The word restored; quotes before it and signs of the sentence after it stay as they are."""
        core = word.lstrip(OPENING).rstrip(CLOSING)
        gapped = " " in core or GAPPED.fullmatch(core) is not None
        if not core or not gapped and not ODD.search(core):
            return word
        at = word.index(core)
        return word[:at] + self.decode(core, gapped) + word[at + len(core) :]

    def decode(self, word: str, gapped: bool = False) -> str:
        """Cheapest path: states are the last two letters; an edge keeps, swaps or drops a character. A letter that stands twice may be dropped at a high cost, as doubling is plain spelling."""
        paths: dict[tuple[int, int], tuple[float, tuple]] = {(0, 0): (0.0, ())}
        for i, c in enumerate(word):
            if c in STANDS_FOR:
                options = [(x, SWAP) for x in STANDS_FOR[c]] + [(c, KEEP_SIGN)]
            else:
                options = [(c, 0.0)]
            if gapped and c in GAPS:
                options = [("", DROP_GAP), (c, KEEP_SIGN)]
            elif i and c == word[i - 1]:
                long = word[max(0, i - 2) : i] == c + c or word[i - 1 : i + 2] == c + c + c
                options.append(("", DROP_REPEAT if long else DROP_ONE))
            new: dict[tuple[int, int], tuple[float, tuple]] = {}
            for (a, b), (cost, made) in paths.items():
                row = self.costs[a][b]
                for x, extra in options:
                    if x:
                        code = CODE.get(x, 0)
                        state, total, out = (b, code), cost + extra + row[code], (made, x)
                    else:
                        state, total, out = (a, b), cost + extra, made
                    if state not in new or total < new[state][0]:
                        new[state] = (total, out)
            paths = new
        best = min(((cost + self.costs[a][b][0], made) for (a, b), (cost, made) in paths.items()), key=lambda x: x[0])[1]
        chars = []
        while best:
            best, x = best
            chars.append(x)
        return "".join(reversed(chars))


def evidence(restored: str) -> set[str]:
    """Words of a restored text, and starts of longer words (marked by a star)."""
    words = set(WORD.findall(restored))
    return words | {w[:k] + "*" for w in words for k in (4, 5) if len(w) > k}


class Evidence(dict):
    """Evidence by word as met, of the features in `only` if given; forgets all when full."""

    def __init__(self, restorer: Restorer, only: dict[str, float] | None = None):
        super().__init__()
        self.restorer, self.only = restorer, only

    def __missing__(self, word: str) -> tuple[str, ...]:
        if len(self) >= KEPT:
            self.clear()
        found = evidence(self.restorer.word(word))
        out = self[word] = tuple(found if self.only is None else (x for x in found if x in self.only))
        return out

    def of(self, text: str) -> set[str]:
        out: set[str] = set()
        for word in set(self.restorer.tokens(text)):
            if some := self[word]:
                out.update(some)
        return out


class Lexicon:
    """Weights of evidence for toxicity, and the logistic of their sum."""

    def __init__(self, weights: dict[str, float], slope: float, start: float):
        self.weights, self.slope, self.start = weights, slope, start

    def sum(self, found: set[str]) -> float:
        """Sum of the eight strongest pieces of evidence."""
        return math.fsum(sorted((self.weights[x] for x in found if x in self.weights), reverse=True)[:8])

    def score(self, found: set[str]) -> float:
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, self.start + self.slope * self.sum(found)))))


def _logistic(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and start of a one-variable logistic curve, by damped Newton steps."""
    w = np.array([0.0, math.log((y.sum() + 0.5) / (len(y) - y.sum() + 0.5))])
    a = np.stack([x, np.ones(len(x))], 1)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        h = (a * (p * (1 - p))[:, None]).T @ a + np.diag([1e-2, 1e-3])
        step = np.linalg.solve(h, a.T @ (y - p) - np.array([1e-2, 1e-3]) * w)
        w += np.clip(step, -2, 2)
    return float(max(w[0], 0.0)), float(w[1])


def train(docs: DataFrame, labels: DataFrame, costs: np.ndarray, most: int = SAMPLE) -> Lexicon:
    """Learns the lexicon from a bounded sample of labelled rows (SAMPLE), of LEXICON features at most."""
    chosen = sampled_labels(labels, "toxic", most)
    joined = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id")
    shared = docs.sparkSession.sparkContext.broadcast(costs)

    def found(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known = Evidence(Restorer(shared.value))
        for batch in batches:
            for at in range(0, len(batch), 64):
                part = batch.iloc[at : at + 64]
                yield pd.DataFrame({"doc_id": part["doc_id"], "y": part["y"], "e": [sorted(known.of(t)) for t in part["text"]]})

    rows = staged(joined.mapInPandas(found, "doc_id long, y int, e array<string>"), "evidence")
    # near copies count once: their least hashes agree
    least = lambda seed: F.array_min(F.transform("e", lambda x: F.xxhash64(x, F.lit(seed))))
    unique = rows.withColumn("k1", least(1)).withColumn("k2", least(2)).dropDuplicates(["y", "k1", "k2"])
    # a long document holds many words of no meaning: it counts for less
    unique = unique.select("y", "e", F.least(F.lit(1.0), USUAL / F.size("e")).alias("weight")).where(F.size("e") > 0)
    totals = {r["y"]: r["n"] for r in unique.groupBy("y").agg(F.sum("weight").alias("n")).collect()}
    bad, good = totals.get(1, 0), totals.get(0, 0)
    if not bad or not good:
        return Lexicon({}, 0.0, math.log((bad + 0.5) / (good + 0.5)))
    weights: dict[str, float] = {}
    left, n_left = unique, bad
    for share in (0.01, 0.1):  # then what the first evidence leaves unexplained
        counts = left.select("y", "weight", F.explode_outer("e").alias("x")).groupBy("x").agg(F.sum(F.col("y") * F.col("weight")).alias("a"), F.sum("y").alias("docs"), F.sum(1 - F.col("y")).alias("b"))
        odds = F.log((F.col("a") + 0.5) / (n_left + 1)) - F.log((F.col("b") + 0.5) / (good + 1))
        enough = max(1.0, share * n_left)
        kept = counts.withColumn("w", odds).where((F.col("docs") >= FEWEST) & (F.col("a") >= enough) & (F.col("b") <= 0.05 * F.col("docs")) & (F.col("w") > 2.5)).orderBy(F.desc(F.col("a") * F.col("w")), "x").limit(LEXICON).collect()
        weights |= {r["x"]: r["w"] for r in kept}
        if not kept:
            break
        words = F.array(*[F.lit(x) for x in weights])
        left = left.where((F.col("y") == 0) | ~F.arrays_overlap("e", words))
        n_left = left.where("y = 1").agg(F.sum("weight")).first()[0] or 0.0
        if n_left < 1:
            break
    lexicon = Lexicon(weights, 1.0, 0.0)

    def summed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            yield pd.DataFrame({"doc_id": batch["doc_id"], "y": batch["y"], "s": [lexicon.sum(set(e)) for e in batch["e"]]})

    sums = rows.mapInPandas(summed, "doc_id long, y int, s double").toPandas().sort_values("doc_id", kind="stable")
    lexicon.slope, lexicon.start = _logistic(sums["s"].to_numpy(), sums["y"].to_numpy(dtype=float))
    return lexicon


def score(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, most: int = SAMPLE) -> DataFrame:
    """One row per document: doc_id, held_out, score, predicted.

    Null texts score as empty ones; equal rows each give a row; a null id is
    neither trained on nor held out; without both labels every score is their
    smoothed share. Only the text enters a score.
    """
    texts = docs.select(F.coalesce("text", F.lit("")).alias("text"))
    costs = character_costs(trigram_counts(texts))
    lexicon = train(docs, labels, costs, most)
    shared = docs.sparkSession.sparkContext.broadcast((costs, lexicon.weights, lexicon.slope, lexicon.start))

    def scored(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        costs, *learnt = shared.value
        lexicon = Lexicon(*learnt)
        known = Evidence(Restorer(costs), lexicon.weights)
        for batch in batches:
            yield pd.Series([lexicon.score(known.of(t)) for t in batch], dtype=float)

    of = F.pandas_udf(scored, "double")
    out = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), of(F.coalesce("text", F.lit(""))).alias("score"))
    return out.withColumn("predicted", F.when(F.col("score") >= threshold, 1).otherwise(0))


def restored(docs: DataFrame) -> DataFrame:
    """doc_id, text and restored: each text after decoding, null for null."""
    costs = character_costs(trigram_counts(docs.select(F.coalesce("text", F.lit("")).alias("text"))))
    shared = docs.sparkSession.sparkContext.broadcast(costs)

    def decoded(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        restorer = Restorer(shared.value)
        for batch in batches:
            yield batch.map(lambda t: None if t is None else restorer.text(t))

    return docs.select("doc_id", "text", F.pandas_udf(decoded, "string")(F.col("text")).alias("restored"))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


