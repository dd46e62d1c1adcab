"""Quality classifier: an additive model with pairwise interactions.

Each feature has a lookup table over quantile bins, learnt by boosting shallow
trees that visit the features in turn; the pairs that explain most of what is
left get two-way tables. A score is the logistic of a sum of table entries.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

FOLD = (4, 2)
SAMPLE = 20_000  # labelled rows that a fit sees at most, give or take chance
BINS = 32
ROUNDS, PAIR_ROUNDS, PAIRS, RATE = 150, 60, 8, 0.2

FEATURES = (
    "log_chars", "log_words", "mean_word", "upper", "digit", "punct", "odd_punct", "bang", "blank", "lines_a_word", "stop_a_word",
    "repeat_next", "distinct", "top_word", "distinct_line", "top_line", "pair_repeat", "trail_punct", "short_line", "bar", "angle", "letter_entropy", "upper_words",
)
_WORD = re.compile(r"\S+")
_PLAIN = str.maketrans("", "", ".,;:!?\"'()-")


def features(text: str) -> list[float]:
    """Numbers about a text, by FEATURES; an empty text has zeros."""
    n = len(text)
    words = text.split()
    if not words:
        return [0.0] * len(FEATURES)
    m = len(words)
    letters = sum(map(str.isalpha, text)) or 1
    chars = Counter(text)
    upper = sum(k for c, k in chars.items() if c.isupper())
    digit = sum(k for c, k in chars.items() if c.isdigit())
    blank = sum(k for c, k in chars.items() if c.isspace())
    odd = sum(k for c, k in chars.items() if c in "#$%&*@^~|\\<>{}[]_=+")
    lines = [x for x in text.split("\n") if x.strip()] or [""]
    counts = Counter(words)
    pairs = Counter(zip(words, words[1:]))
    by_line = Counter(lines)
    share = np.fromiter(chars.values(), dtype=float) / n
    return [
        np.log1p(n),
        np.log1p(m),
        (n - blank) / m,
        upper / letters,
        digit / n,
        (n - letters - digit - blank) / n,
        odd / n,
        chars.get("!", 0) / m,
        blank / n,
        len(lines) / m,
        chars.get(".", 0) / m,
        sum(a == b for a, b in zip(words, words[1:])) / m,
        len(counts) / m,
        max(counts.values()) / m,
        len(by_line) / len(lines),
        sum(len(x) * k for x, k in by_line.items() if k > 1) / n,
        sum(k for k in pairs.values() if k > 1) / m,
        sum(not w[-1].isalnum() for w in words) / m,
        sum(len(x) < 30 for x in lines) / len(lines),
        chars.get("|", 0) / m,
        (chars.get("<", 0) + chars.get("{", 0)) / m,
        float(-(share * np.log2(share)).sum()),
        sum(w.isupper() and len(w) > 1 for w in words) / m,
    ]


def _leaf_sums(bins: np.ndarray, g: np.ndarray, h: np.ndarray, many: int) -> tuple[np.ndarray, np.ndarray]:
    return np.bincount(bins, g, many), np.bincount(bins, h, many)


def _best_cut(G: np.ndarray, H: np.ndarray) -> tuple[float, int]:
    """Gain and place of the best cut of a run of bins."""
    g, h = np.cumsum(G)[:-1], np.cumsum(H)[:-1]
    if not len(g):
        return 0.0, 0
    lam = 1.0
    tg, th = G.sum(), H.sum()
    gain = g**2 / (h + lam) + (tg - g) ** 2 / (th - h + lam) - tg**2 / (th + lam)
    gain[(h < 1e-3) | (th - h < 1e-3)] = 0
    at = int(gain.argmax())
    return float(gain[at]), at + 1


def shallow_tree(G: np.ndarray, H: np.ndarray, leaves: int = 4) -> np.ndarray:
    """Values by bin of a tree over one feature with few leaves, from the sums of gradients and curvatures."""
    parts = [(0, len(G))]
    while len(parts) < leaves:
        options = [(*_best_cut(G[a:b], H[a:b]), i) for i, (a, b) in enumerate(parts)]
        gain, at, i = max(options)
        if gain <= 1e-9:
            break
        a, b = parts[i]
        parts[i : i + 1] = [(a, a + at), (a + at, b)]
    out = np.zeros(len(G))
    for a, b in parts:
        out[a:b] = -G[a:b].sum() / (H[a:b].sum() + 1.0)
    return out


def pair_tree(G: np.ndarray, H: np.ndarray) -> tuple[np.ndarray, float]:
    """Values by two bins: one cut of one feature, then a cut of the other on either side; the better order. And its gain."""
    best, gain = np.zeros_like(G), 0.0
    for flip in (False, True):
        g, h = (G.T, H.T) if flip else (G, H)
        cg, ch = np.cumsum(g, 0), np.cumsum(h, 0)
        for a in range(1, g.shape[0], max(1, g.shape[0] // 16)):
            out, total = np.zeros_like(g), 0.0
            for lo, hi, sg, sh in ((0, a, cg[a - 1], ch[a - 1]), (a, g.shape[0], cg[-1] - cg[a - 1], ch[-1] - ch[a - 1])):
                more, at = _best_cut(sg, sh)
                for c, d in ((0, at), (at, len(sg))) if at else ((0, len(sg)),):
                    s, t = sg[c:d].sum(), sh[c:d].sum() + 1.0
                    out[lo:hi, c:d] = -s / t
                    total += s * s / t
            if total > gain:
                best, gain = (out.T if flip else out), total
    return best, gain


class AdditiveModel:
    """Tables by feature and by pair of features over quantile bins."""

    def __init__(self, edges: list[np.ndarray], start: float):
        self.edges, self.start = edges, start
        self.tables = [np.zeros(len(e) + 1) for e in edges]
        self.pairs: list[tuple[int, int, np.ndarray]] = []

    def binned(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(self.edges)], 1)

    def margin(self, b: np.ndarray) -> np.ndarray:
        out = np.full(len(b), self.start)
        for j, t in enumerate(self.tables):
            out += t[b[:, j]]
        for i, j, t in self.pairs:
            out += t[b[:, i], b[:, j]]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(self.binned(x)), -30, 30)))


def fit(x: np.ndarray, y: np.ndarray, bins: int = BINS, rounds: int = ROUNDS, pair_rounds: int = PAIR_ROUNDS, pairs: int = PAIRS, rate: float = RATE) -> AdditiveModel:
    """Fits the tables in turn. Without both labels the model is the smoothed share of label 1 everywhere."""
    p = (y.sum() + 0.5) / (len(y) + 1)
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) if len(x) else np.array([]) for j in range(x.shape[1])]
    model = AdditiveModel(edges, float(np.log(p / (1 - p))))
    if len(np.unique(y)) < 2:
        return model
    b = model.binned(x)
    f = np.full(len(y), model.start)

    def slopes() -> tuple[np.ndarray, np.ndarray]:
        q = 1 / (1 + np.exp(-f))
        return q - y, q * (1 - q)

    for _ in range(rounds):
        for j, t in enumerate(model.tables):
            g, h = slopes()
            step = rate * shallow_tree(*_leaf_sums(b[:, j], g, h, len(t)))
            t += step
            f += step[b[:, j]]
    g, h = slopes()
    ranked = []
    sizes = [len(t) for t in model.tables]

    def sums(i: int, j: int, g: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = b[:, i] * sizes[j] + b[:, j]
        return tuple(s.reshape(sizes[i], sizes[j]) for s in _leaf_sums(at, g, h, sizes[i] * sizes[j]))

    for i in range(len(sizes)):
        for j in range(i):
            ranked.append((pair_tree(*sums(i, j, g, h))[1], i, j))
    chosen = [(i, j) for _, i, j in sorted(ranked, reverse=True)[:pairs]]
    model.pairs = [(i, j, np.zeros((sizes[i], sizes[j]))) for i, j in chosen]
    for _ in range(pair_rounds):
        for i, j, t in model.pairs:
            step = rate * pair_tree(*sums(i, j, *slopes()))[0]
            t += step
            f += step[b[:, i], b[:, j]]
    return model


def held_out(doc_id: Column, fold: tuple[int, int] = FOLD) -> Column:
    """Whether crc32 of the id as text has the fold's remainder; false for a null id."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % fold[0] == fold[1], F.lit(False))


def sampled_labels(labels: DataFrame, label: str, most: int) -> DataFrame:
    """(doc_id, y) of labelled training rows, about `most` at most, chosen by a hash of the id."""
    rows = labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & ~held_out(F.col("doc_id"))).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).groupBy("doc_id").agg(F.max("y").alias("y"))
    n = rows.count()
    if n > most:
        cut = int((1 << 32) * most / n)
        rows = rows.where(F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(1 << 32)) < cut)
    return rows


def train(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> AdditiveModel:
    """Fits the model on a bounded sample of labelled rows (SAMPLE); their features alone come to the driver."""
    chosen = sampled_labels(labels, "quality", most)
    joined = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id")

    def measured(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            yield pd.DataFrame({"doc_id": batch["doc_id"], "y": batch["y"], "x": [features(t) for t in batch["text"]]})

    got = joined.mapInPandas(measured, "doc_id long, y int, x array<double>").toPandas().sort_values("doc_id", kind="stable")
    x = np.array(got["x"].tolist(), dtype=float).reshape(-1, len(FEATURES))
    return fit(x, got["y"].to_numpy(dtype=float))


def score(docs: DataFrame, labels: DataFrame, threshold: float = 0.7, most: int = SAMPLE) -> DataFrame:
    """One row per document: doc_id, held_out, score, predicted.

    Null texts score as empty ones; equal rows each give a row; a null id is
    neither trained on nor held out; without labels every score is 0.5. Only
    the text enters a score.
    """
    model = train(docs, labels, most)

    def scored(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            x = np.array([features(t) for t in batch], dtype=float).reshape(-1, len(FEATURES))
            yield pd.Series(model.score(x))

    of = F.pandas_udf(scored, "double")
    out = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), of(F.coalesce("text", F.lit(""))).alias("score"))
    return out.withColumn("predicted", F.when(F.col("score") >= threshold, 1).otherwise(0))


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
