"""Language-model scores from a log-frequency Bloom filter.

Tasks count the words and word pairs of many texts at a time and send them on
as sorted lists, one for each block of a hash. Each block adds up its lists and
writes the quantised counts of its n-grams into a Bloom filter of its own: an
n-gram of level q is entered q times, as (n-gram, 1) to (n-gram, q), and is read
back by probing level after level until one is missing. The filter of words goes
to all workers, that of pairs too while it is no larger than one broadcast.
Beyond that the pairs of the texts are sent to the blocks instead, which send
sums back, so all pairs are scored in one pass over the texts at any size; the
most frequent pairs of each block are known to all workers. Levels of words that
the words' broadcast does not hold are joined to the texts that have them.
"""

from __future__ import annotations

import math
import struct
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import NO_ID, id_key, staged, table, text_key

HELD_OUT = (7, 2)
HASHES = 4
BITS_A_LEVEL = 10
MOST_BITS = 1 << 30  # of a filter that goes to all workers: one of words, one of pairs
HEAD = 1 << 20  # words whose exact counts go with it
PAIR_HEAD = 1 << 20  # pairs, the most frequent of each block, whose levels go with it where the others are sent to their blocks
PARTS = 4  # tasks that a broadcast's worth of pairs is dealt to
PLACE_BITS = 40  # of a pair within its block; one not seen equals one of a million there once in a million times
PAIR_WEIGHT, PAIR_TRUST = 0.5, 30.0
TOKENS_A_BLOCK = 1_000_000
TOKENS_A_RUN = 1_500_000  # that a task adds up before it sends their counts on
LEAST_BLOCKS = 64
TEXTS_AT_ONCE, CHARACTERS_AT_ONCE, ROWS_AT_ONCE = 512, 2_000_000, 200_000
KEPT_WORDS = 300_000
END = np.uint64(0x9E3779B97F4A7C15)
NO_RARE = (np.array([], dtype=np.uint64), np.array([], dtype=np.int64))
_MIX = np.uint64(0xBF58476D1CE4E5B9)
_MIX2 = np.uint64(0x94D049BB133111EB)


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: close values part."""
    x = (x ^ (x >> np.uint64(30))) * _MIX
    x = (x ^ (x >> np.uint64(27))) * _MIX2
    return x ^ (x >> np.uint64(31))


def pair_keys(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    return mixed(first * np.uint64(0x9E3779B97F4A7C15) + second + np.uint64(1))


class Words(dict):
    """Hashes of words; keeps those met first, the frequent ones among them."""

    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh3_64_intdigest(word)
        if len(self) < KEPT_WORDS:
            self[word] = h
        return h


def tokens(texts: list[str], words: Words) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the tokens of all texts in a row, and how many each text has (the end included).

    bytes.lower and bytes.split know A-Z and the blanks 0x20, 0x09-0x0D only, as asked.
    """
    get, end = words.__getitem__, int(END)
    flat: list[int] = []
    sizes = []
    for text in texts:
        found = text.encode("utf-8", "surrogatepass").lower().split()
        flat.extend(map(get, found))
        flat.append(end)
        sizes.append(len(found) + 1)
    return np.array(flat, dtype=np.uint64), np.array(sizes, dtype=np.int64)


def chunks(batch: pd.DataFrame) -> Iterator[pd.DataFrame]:
    """A batch in parts of so many texts and characters; a longer text is a part of its own."""
    ends = batch["text"].str.len().to_numpy(dtype=np.int64).cumsum()
    at = 0
    while at < len(batch):
        before = ends[at - 1] if at else 0
        upto = int(np.searchsorted(ends, before + CHARACTERS_AT_ONCE, side="right"))
        upto = max(at + 1, min(upto, at + TEXTS_AT_ONCE))
        yield batch.iloc[at:upto]
        at = upto


def level(count: np.ndarray) -> np.ndarray:
    """Quantised count: 1 + floor(2 log2 count), half an octave a level."""
    return 1 + np.floor(2 * np.log2(count) + 1e-9).astype(np.int64)


def level_of(count: Column) -> Column:
    """level() as a column."""
    return (F.lit(1) + F.floor(2 * F.log2(count) + F.lit(1e-9))).cast("int")


class Filter:
    """Blocks first to end - 1 of a Bloom filter of `many`; bits is their size, or one for each of them, in whole bytes."""

    def __init__(self, data: np.ndarray, many: int, bits: int | np.ndarray, first: int = 0, end: int | None = None):
        self.data, self.many, self.bits, self.first, self.end = data, many, bits, first, many if end is None else end
        sizes = np.broadcast_to(np.asarray(bits, dtype=np.int64), (self.end - first,))
        self.starts = np.cumsum(sizes) - sizes
        self.sizes = np.uint32(bits) if np.ndim(bits) == 0 else sizes.astype(np.uint32)

    def covers(self, keys: np.ndarray) -> np.ndarray:
        """Whether the keys' blocks are among the ones here."""
        block = (keys % np.uint64(self.many)).astype(np.int64)
        return (block >= self.first) & (block < self.end)

    @staticmethod
    def places(keys: np.ndarray, at: int, bits: int) -> Iterator[np.ndarray]:
        """HASHES places of the keys at a level: the halves of one mix, then of the next."""
        h = mixed(keys + np.uint64(0x632BE59BD9B4E019 * (at + 1) % (1 << 64)))
        for i in range(HASHES):
            if i and i % 2 == 0:
                h = mixed(h)
            half = (h >> np.uint64(32) if i % 2 else h).astype(np.uint32)
            yield (half % np.uint32(bits)).astype(np.int64)

    @classmethod
    def mark(cls, data: np.ndarray, keys: np.ndarray, levels: np.ndarray) -> None:
        """Enters keys in a block, one boolean a bit."""
        for at in range(1, int(levels.max(initial=0)) + 1):
            for p in cls.places(keys[levels >= at], at, len(data)):
                data[p] = True

    def levels(self, keys: np.ndarray, most: int = 64) -> np.ndarray:
        """Level of each key: how often probing finds it, one level after the other."""
        out = np.zeros(len(keys), dtype=np.int64)
        block = (keys % np.uint64(self.many)).astype(np.int64) - self.first
        bases, sizes = self.starts[block], self.sizes if self.sizes.ndim == 0 else self.sizes[block]
        left = np.arange(len(keys))
        for at in range(1, most + 1):
            h = mixed(keys[left] + np.uint64(0x632BE59BD9B4E019 * (at + 1) % (1 << 64)))
            base, size = bases[left], sizes if sizes.ndim == 0 else sizes[left]
            for i in range(HASHES):  # as places() has them; keys that miss a place are not asked for the next
                if i and i % 2 == 0:
                    h = mixed(h)
                p = ((h >> np.uint64(32) if i % 2 else h).astype(np.uint32) % size).astype(np.int64)
                p += base
                ok = np.flatnonzero((self.data[p >> 3] >> (p & 7).astype(np.uint8)) & 1)
                if len(ok) < len(left):
                    left, h, base, size = left[ok], h[ok], base[ok], size if size.ndim == 0 else size[ok]
            if not len(left):
                break
            out[left] = at
        return out


def folded(keys: np.ndarray, many: int) -> np.ndarray:
    """Keys of pairs with PLACE_BITS bits within their block of `many`, in the same block."""
    return (keys // np.uint64(many) & np.uint64((1 << PLACE_BITS) - 1)) * np.uint64(many) + keys % np.uint64(many)


def planes(x: np.ndarray, width: int) -> bytes:
    """The low `width` bytes of numbers, all the first bytes, then all the second ones and so on."""
    return np.ascontiguousarray(x.astype(np.uint64, copy=False).view(np.uint8).reshape(-1, 8)[:, :width].T).tobytes()


def from_planes(data: bytes, many: int, width: int, at: int = 0) -> np.ndarray:
    out = np.zeros((many, 8), dtype=np.uint8)
    out[:, :width] = np.frombuffer(data, dtype=np.uint8, count=many * width, offset=at).reshape(width, many).T
    return out.reshape(-1).view(np.uint64)


def packed(places: np.ndarray, n: np.ndarray) -> bytes:
    """Rising places as differences, and their counts: a byte each, those of 255 and above once more behind."""
    if not len(places):
        return b""
    steps = np.diff(places, prepend=np.uint64(0))
    width = max(1, (int(steps.max()).bit_length() + 7) // 8)
    return b"".join((struct.pack("<IB", len(places), width), planes(steps, width), np.minimum(n, 255).astype(np.uint8).tobytes(), n[n >= 255].astype(np.int64).tobytes()))


def unpacked(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    if not data:
        return np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
    many, width = struct.unpack_from("<IB", data)
    n = np.frombuffer(data, dtype=np.uint8, count=many, offset=5 + many * width).astype(np.int64)
    n[n == 255] = np.frombuffer(data, dtype=np.int64, offset=5 + many * width + many)
    return np.cumsum(from_planes(data, many, width, 5), dtype=np.uint64), n


def joined(parts: list[np.ndarray]) -> np.ndarray:
    out = np.concatenate(parts)
    parts.clear()
    return out


def tallied(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted keys, each once, and how often they are there; sorts in place, as tasks count at the limit of their memory."""
    keys.sort()
    new = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    return keys[new], np.diff(new, append=len(keys))


def added(lists: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Places of all lists, rising, and the sums of their counts."""
    parts = [unpacked(x) for x in lists]
    places, n = (np.concatenate(x) for x in zip(*parts, strict=True))
    by = np.argsort(places, kind="stable")
    places, n = places[by], n[by]
    new = np.flatnonzero(np.r_[True, places[1:] != places[:-1]][: len(places)])
    return places[new], np.add.reduceat(n, new) if len(new) else n


NGRAMS = "block long, words binary, word_counts binary, bits binary, size int, head binary, head_levels binary, word_rows array<long>, word_total array<long>, pair_rows array<long>, pair_total array<long>"


def _counted(texts: DataFrame, blocks: int) -> DataFrame:
    """One row for each block, as NGRAMS: its words and their exact counts, the filter of its pairs and the filter's size in bits,
    the most frequent pairs and their levels as the filter reads them, and by level how many words and pairs there are and what they count in total."""
    many = np.uint64(blocks)

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        words = Words()
        held: list[list[np.ndarray]] = [[], []]

        def summed() -> Iterator[pd.DataFrame]:
            if not held[0]:
                return
            keys, n = tallied(joined(held[0]))
            block = (keys % many).astype(np.int64)
            by = np.argsort(block, kind="stable")  # places rise with keys
            places, n, cuts = (keys // many)[by], n[by], np.searchsorted(block[by], np.arange(blocks + 1))
            pairs = joined(held[1])
            whose = pairs % many
            whose <<= np.uint64(PLACE_BITS)
            pairs //= many
            pairs &= np.uint64((1 << PLACE_BITS) - 1)
            pairs |= whose
            del whose
            pairs, m = tallied(pairs)
            pair_cuts = np.searchsorted(pairs, np.arange(blocks + 1, dtype=np.uint64) << np.uint64(PLACE_BITS))
            pairs &= np.uint64((1 << PLACE_BITS) - 1)
            some = np.flatnonzero((np.diff(cuts) > 0) | (np.diff(pair_cuts) > 0)).tolist()
            of = lambda a, b, cut: [packed(a[cut[x] : cut[x + 1]], b[cut[x] : cut[x + 1]]) for x in some]
            yield pd.DataFrame({"block": some, "words": of(places, n, cuts), "pairs": of(pairs, m, pair_cuts)})

        size = 0
        for batch in batches:
            for part in chunks(batch):
                flat, sizes = tokens(part["text"].tolist(), words)
                before = np.empty_like(flat)
                before[1:] = flat[:-1]
                before[:1] = END  # each text ends with an end, so the next one starts after it
                held[0].append(flat)
                held[1].append(pair_keys(before, flat))
                size += len(flat)
                if size >= TOKENS_A_RUN:
                    yield from summed()
                    size = 0
        yield from summed()

    def block_of(at: int, word_lists: list[bytes], pair_lists: list[bytes]) -> pd.DataFrame:
        words, n = added(word_lists)
        pairs, m = added(pair_lists)
        keys, lv, word_lv = pairs * many + np.uint64(at), level(m), level(n)
        data = np.zeros(_bits(lv.sum()), dtype=bool)
        Filter.mark(data, keys, lv)
        bits = np.packbits(data, bitorder="little")
        head = np.sort(keys[np.argsort(-lv, kind="stable")[: max(1, PAIR_HEAD // blocks)]])
        read = Filter(bits, blocks, len(data), at, at + 1).levels(head)
        by_level = lambda levels, weights=None: np.bincount(levels, weights).astype(np.int64)
        row = (at, (words * many + np.uint64(at)).tobytes(), n.tobytes(), bits.tobytes(), len(data), head.tobytes(), read.astype(np.uint8).tobytes(), by_level(word_lv), by_level(word_lv, n), by_level(lv), by_level(lv, m))
        return pd.DataFrame([row], columns=[c.split()[0] for c in NGRAMS.split(", ")])

    def merge(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        at, words, pairs = None, [], []
        for batch in batches:
            for block, w, p in zip(batch["block"].tolist(), batch["words"], batch["pairs"], strict=True):
                if block != at:
                    if at is not None:
                        yield block_of(at, words, pairs)
                    at, words, pairs = block, [], []
                words.append(w)
                pairs.append(p)
        if at is not None:
            yield block_of(at, words, pairs)

    rows = texts.mapInPandas(count, "block long, words binary, pairs binary")
    dealt = rows.repartition("block") if blocks <= LEAST_BLOCKS else rows.repartition(blocks, "block")
    return staged(dealt.sortWithinPartitions("block").mapInPandas(merge, NGRAMS), "ngrams")


def _bits(levels: float) -> int:
    """Bits, in whole bytes, of a block whose n-grams have so many levels in all."""
    return int(math.ceil(max(512, float(levels) * BITS_A_LEVEL * 1.02) / 8)) * 8


def _word_rows(ngrams: DataFrame) -> DataFrame:
    """(key, n, lv) of each word."""

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for keys, n in zip(batch["words"], batch["word_counts"], strict=True):
                keys, n = np.frombuffer(keys, dtype=np.int64), np.frombuffer(n, dtype=np.int64)
                for at in range(0, len(keys), ROWS_AT_ONCE):
                    some = slice(at, at + ROWS_AT_ONCE)
                    yield pd.DataFrame({"key": keys[some], "n": n[some], "lv": level(n[some])})

    return ngrams.select("words", "word_counts").mapInPandas(rows, "key long, n long, lv int")


def _word_blocks(ngrams: DataFrame, bits: int, least: int) -> DataFrame:
    """(block, bits): the filter of each block's words of level `least` and above; one block in memory."""

    def build(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for block, keys, n in zip(batch["block"].tolist(), batch["words"], batch["word_counts"], strict=True):
                data, lv = np.zeros(bits, dtype=bool), level(np.frombuffer(n, dtype=np.int64))
                Filter.mark(data, np.frombuffer(keys, dtype=np.uint64)[lv >= least], lv[lv >= least])
                yield pd.DataFrame({"block": [block], "bits": [np.packbits(data, bitorder="little").tobytes()]})

    return staged(ngrams.select("block", "words", "word_counts").mapInPandas(build, "block long, bits binary"), "filter")


def _filter(built: DataFrame, many: int, bits: int | np.ndarray) -> Filter:
    """All blocks on the driver, whose bits the callers bound."""
    out = Filter(None, many, bits)
    sizes = np.broadcast_to(np.asarray(bits, dtype=np.int64), (many,))
    out.data = np.zeros(int(sizes.sum()) // 8, dtype=np.uint8)
    for row in built.toLocalIterator():
        at = int(out.starts[row["block"]]) // 8
        out.data[at : at + int(sizes[row["block"]]) // 8] = np.frombuffer(bytes(row["bits"]), dtype=np.uint8)
    return out


def _head(ngrams: DataFrame, cut: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted keys of the words of level `cut` and above and their counts, on the driver; the caller bounds them.

    One step in Python, as two in a row hold twice as many workers, which stay and load all that is broadcast later.
    """

    def frequent(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for keys, n in zip(batch["words"], batch["word_counts"], strict=True):
                keys, n = np.frombuffer(keys, dtype=np.int64), np.frombuffer(n, dtype=np.int64)
                some = level(n) >= cut
                yield pd.DataFrame({"keys": [keys[some].tobytes()], "counts": [n[some].tobytes()]})

    got = ngrams.select("words", "word_counts").mapInPandas(frequent, "keys binary, counts binary").collect()
    keys, n = np.frombuffer(b"".join(bytes(r[0]) for r in got), dtype=np.uint64), np.frombuffer(b"".join(bytes(r[1]) for r in got), dtype=np.int64)
    by = np.argsort(keys)
    return keys[by], n[by]


#: Places of tokens, and for each its pair's key and the levels of the pair's words.
Asked = tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]
NONE_ASKED: Asked = (np.array([], dtype=np.int64), np.array([], dtype=np.uint64), np.array([], dtype=np.uint8), np.array([], dtype=np.uint8))


class Model:
    """What scoring needs: the words' filter, that of pairs or the sorted most frequent pairs with their levels, mean counts by level, the most frequent words with exact counts, and the totals."""

    def __init__(self, words, pairs, word_means: np.ndarray, pair_means: np.ndarray, head_keys: np.ndarray, head_counts: np.ndarray, total: int, distinct: int, least: int = 1):
        self.least = least  # level of a word from which the filter holds it
        self.words, self.pairs, self.word_means, self.pair_means = words, pairs, word_means, pair_means
        self.head_keys, self.head_counts = head_keys, head_counts
        self.total, self.distinct = total, distinct

    def exact(self, keys: np.ndarray) -> np.ndarray:
        """Exact counts of words among the most frequent; -1 elsewhere."""
        if not len(self.head_keys):
            return np.full(len(keys), -1, dtype=np.int64)
        at = np.minimum(np.searchsorted(self.head_keys, keys), len(self.head_keys) - 1)
        return np.where(self.head_keys[at] == keys, self.head_counts[at], -1)

    def word_levels(self, keys: np.ndarray, rare: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
        """Levels of words: from the filter, or from the sorted rare keys and their levels where it holds level `least` and above only."""
        out = self.words.levels(keys)
        if self.least > 1:
            out[out < self.least] = 0  # what was entered has that level at least
            if len(rare[0]):
                at = np.minimum(np.searchsorted(rare[0], keys), len(rare[0]) - 1)
                out = np.where((out == 0) & (rare[0][at] == keys), rare[1][at], out)
        return out

    def mixed_logs(self, first: np.ndarray, second: np.ndarray, pair: np.ndarray) -> np.ndarray:
        """log10 P of pairs by the levels of their words and their own.

        Mixes the pair's relative frequency with the word's add-one estimate;
        the pair weighs the more the oftener the word before was seen. A level
        reads as the mean of the counts that it holds, so the add-one estimates
        sum to one but for false positives.
        """
        of = lambda means, lv: means[np.minimum(lv, len(means) - 1)]
        c, c2 = of(self.word_means, first), of(self.word_means, second)
        both = np.minimum(of(self.pair_means, pair), c2)
        weight = PAIR_WEIGHT * c / (c + PAIR_TRUST)
        share = np.minimum(1.0, both / np.maximum(c, 1.0))
        return np.log10(weight * share + (1 - weight) * (c2 + 1) / (self.total + self.distinct + 1))

    def looked_up(self, flat: np.ndarray, rare: tuple[np.ndarray, np.ndarray] = NO_RARE) -> tuple[np.ndarray, np.ndarray, Asked]:
        """log10 P of each token given the one before (a text starts after an end), its exact count or -1, and the pairs whose level is not known here and taken for 0."""
        if not len(flat):
            return np.zeros(0), np.zeros(0, dtype=np.int64), NONE_ASKED
        uniq, back = np.unique(flat, return_inverse=True)
        lv = self.word_levels(uniq, rare)
        before = np.empty_like(back)
        before[1:] = back[:-1]
        before[0] = np.searchsorted(uniq, END)
        pairs, pair_back = np.unique(before * np.int64(len(uniq)) + back, return_inverse=True)
        first, second = pairs // len(uniq), pairs % len(uniq)
        keys = folded(pair_keys(uniq[first], uniq[second]), self.words.many)
        probed = (lv[first] > 0) & (lv[second] > 0)
        levels, asked = np.zeros(len(pairs), dtype=np.int64), NONE_ASKED
        if isinstance(self.pairs, Filter):
            levels[probed] = self.pairs.levels(keys[probed])
        else:
            known, known_lv = self.pairs
            at = np.minimum(np.searchsorted(known, keys), max(len(known) - 1, 0))
            here = probed & (known[at] == keys) if len(known) else np.zeros(len(keys), dtype=bool)
            levels[here] = known_lv[at[here]]
            where = np.flatnonzero((probed & ~here)[pair_back])
            pair = pair_back[where]
            asked = where, keys[pair], lv[first[pair]].astype(np.uint8), lv[second[pair]].astype(np.uint8)
        return self.mixed_logs(lv[first], lv[second], levels)[pair_back], self.exact(uniq)[back], asked


class Trained:
    """The staged counts and filter blocks, and the small numbers about them."""

    def __init__(self, texts: DataFrame, most_bits: int, head: int):
        tokens_about = texts.agg(F.sum(F.length("text") / 6 + 1)).first()[0] or 1
        self.many = int(max(LEAST_BLOCKS, tokens_about // TOKENS_A_BLOCK + 1))
        self.ngrams = _counted(texts, self.many)
        # a few numbers for each block
        small = self.ngrams.select("block", "size", "word_rows", "word_total", "pair_rows", "pair_total").collect()
        words, pairs = (self._levels(small, kind) for kind in ("word", "pair"))
        self.total, self.distinct = int(words["total"].sum()), int(words["many"].sum())
        self.least = 1
        while self._word_bits(words, self.least) * self.many > most_bits:
            self.least += 1
        self.word_bits, self.pair_bits = self._word_bits(words, self.least), np.full(self.many, 512, dtype=np.int64)
        for row in small:
            self.pair_bits[row["block"]] = row["size"]
        self.shares = max(1, min(self.many, math.ceil(int(self.pair_bits.sum()) / most_bits)))
        self.word_means, self.pair_means = self._means(words), self._means(pairs)
        above = words.sort_values("lv", ascending=False)
        fits = above[above["many"].cumsum() <= head]
        cut = int(fits["lv"].min()) if len(fits) else 1 << 20
        self.counts = _word_rows(self.ngrams)
        self.head = _head(self.ngrams, cut)
        self.complete = len(self.head[0]) == self.distinct
        self.words = _filter(_word_blocks(self.ngrams, self.word_bits, self.least), self.many, self.word_bits)

    @staticmethod
    def _levels(small: list, kind: str) -> pd.DataFrame:
        """By level (lv): how many n-grams there are, and what they count in total."""
        longest = max((len(r[f"{kind}_rows"]) for r in small), default=0)
        sums = np.zeros((2, longest), dtype=np.int64)
        for r in small:
            for i, values in enumerate((r[f"{kind}_rows"], r[f"{kind}_total"])):
                sums[i, : len(values)] += values
        lv = np.flatnonzero(sums[0])
        return pd.DataFrame({"lv": lv, "many": sums[0, lv], "total": sums[1, lv]})

    def _word_bits(self, levels: pd.DataFrame, least: int) -> int:
        """Bits of a block of words."""
        some = levels[levels["lv"] >= least]
        return _bits((some["lv"] * some["many"]).sum() / self.many)

    @staticmethod
    def _means(levels: pd.DataFrame) -> np.ndarray:
        out = np.zeros(int(levels["lv"].max() if len(levels) else 0) + 1)
        out[levels["lv"].to_numpy(dtype=int)] = levels["total"].to_numpy(dtype=float) / levels["many"].to_numpy(dtype=float)
        return out

    def with_rare(self, keyed: DataFrame) -> DataFrame:
        """keyed (rid, rt, text) with arrays rare, rare_lv: the words of each text that the filter of words leaves out, and their levels."""
        if self.least == 1:
            return keyed.withColumns({"rare": F.lit(None).cast("array<long>"), "rare_lv": F.lit(None).cast("array<int>")})
        f, least = self.words, self.least
        shared = keyed.sparkSession.sparkContext.broadcast((f.data, f.many, f.bits))

        def unheld(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            held, words = Filter(*shared.value), Words()
            for batch in batches:
                for part in chunks(batch):
                    flat, sizes = tokens(part["text"].tolist(), words)
                    uniq, back = np.unique(flat, return_inverse=True)
                    out = (held.levels(uniq, least) < least)[back]
                    pair = np.unique(np.repeat(np.arange(len(part)), sizes)[out] * len(uniq) + back[out])
                    who = pair // len(uniq)
                    yield pd.DataFrame({"rid": part["rid"].to_numpy()[who], "rt": part["rt"].to_numpy()[who], "key": uniq[pair % len(uniq)].view(np.int64)})

        asked = keyed.dropDuplicates(["rid", "rt"]).mapInPandas(unheld, "rid long, rt long, key long")
        known = self.counts.where(F.col("lv") < least).select("key", "lv")
        got = asked.join(known, "key").groupBy("rid", "rt").agg(F.collect_list(F.struct("key", "lv")).alias("at"))
        return keyed.join(staged(got.select("rid", "rt", F.col("at.key").alias("rare"), F.col("at.lv").alias("rare_lv")), "rare"), ["rid", "rt"], "left")

    def all_pairs(self) -> Filter:
        """The filter of all pairs, on the driver."""
        return _filter(self.ngrams.select("block", "bits"), self.many, self.pair_bits)

    def frequent_pairs(self) -> tuple[np.ndarray, np.ndarray]:
        """Sorted keys of the most frequent pairs of each block, and their levels; PAIR_HEAD or few more."""
        got = self.ngrams.select("head", "head_levels").collect()
        keys, lv = np.frombuffer(b"".join(bytes(r[0]) for r in got), dtype=np.uint64), np.frombuffer(b"".join(bytes(r[1]) for r in got), dtype=np.uint8)
        by = np.argsort(keys)
        return keys[by], lv[by].astype(np.int64)

    def shared(self, pairs) -> tuple:
        """What Model takes, in parts that travel."""
        f = self.words
        return (f.data, f.many, f.bits), pairs, self.word_means, self.pair_means, *self.head, self.total, self.distinct, self.least


def _rare_of(part: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """The rare words of some texts, sorted, and their levels."""
    some = [(k, lv) for k, lv in zip(part["rare"], part["rare_lv"], strict=True) if k is not None]
    if not some:
        return NO_RARE
    keys, first = np.unique(np.concatenate([np.asarray(k, dtype=np.int64) for k, _ in some]).view(np.uint64), return_index=True)
    return keys, np.concatenate([np.asarray(lv, dtype=np.int64) for _, lv in some])[first]


def held_out(doc_id: Column, fold: tuple[int, int] = HELD_OUT) -> Column:
    """Whether crc32 of the id as text has the fold's remainder; a null id is no training row and not held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % fold[0] == fold[1], F.lit(False))


def _parts(part: pd.DataFrame, model: Model, words: Words) -> tuple[pd.DataFrame, np.ndarray, Asked]:
    """A row for each text: n_tokens, n_known, logs, score and the words (rest) whose exact counts are not here; how many tokens each has; and what looked_up() could not answer."""
    flat, sizes = tokens(part["text"].tolist(), words)
    log_p, c, asked = model.looked_up(flat, _rare_of(part) if model.least > 1 else NO_RARE)
    starts = np.r_[0, np.cumsum(sizes)[:-1]]
    logs = np.where(c > 0, np.log10(np.maximum(c, 0) + 1.0), 0.0)
    rest = [np.array([], dtype=np.int64)] * len(part)
    if (out := c < 0).any():
        who, what = np.repeat(np.arange(len(part)), sizes)[out], flat[out].astype(np.int64)
        cuts = np.searchsorted(who, np.arange(len(part) + 1))
        rest = [what[s:e] for s, e in zip(cuts[:-1], cuts[1:], strict=True)]
    known = np.add.reduceat((c > 0).astype(np.int64), starts)
    frame = {"held_out": part["held_out"].to_numpy(), "rid": part["rid"].to_numpy(), "rt": part["rt"].to_numpy(), "n_tokens": sizes, "n_known": known, "logs": np.add.reduceat(logs, starts), "score": np.add.reduceat(log_p, starts), "rest": rest}
    return pd.DataFrame(frame), sizes, asked


SCORED = "held_out boolean, rid long, rt long, n_tokens long, n_known long, logs double, score double, rest array<long>"


def _scored(keyed: DataFrame, trained: Trained) -> DataFrame:
    """Rows as SCORED and doc_id, by a filter of all pairs at each worker."""
    f = trained.all_pairs()
    shared = keyed.sparkSession.sparkContext.broadcast(trained.shared((f.data, f.many, f.bits)))

    def local(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        in_words, in_pairs, *others = shared.value
        model, words = Model(Filter(*in_words), Filter(*in_pairs), *others), Words()
        for batch in batches:
            for part in chunks(batch):
                yield _parts(part, model, words)[0]

    return staged(_named(keyed.mapInPandas(local, SCORED)), "scored")


def _named(found: DataFrame) -> DataFrame:
    return found.withColumn("doc_id", F.when(F.col("rid") != NO_ID, F.col("rid")))


def _scored_by_blocks(keyed: DataFrame, trained: Trained) -> DataFrame:
    """Rows as in _scored(). Pairs that are not among the most frequent go to the tasks that hold their blocks, which send back a sum for each text.

    A portion is what a task sends at once: some texts, by their number in it.
    Rows of kind 0 hold a block's filter, rows of kind 1 the pairs of a portion
    or the sums of its texts, rows of kind 2 a text.
    """
    spark, many, sizes = keyed.sparkSession, trained.many, trained.pair_bits
    groups = min(many, PARTS * trained.shares)
    firsts = np.array([many * x // groups for x in range(groups + 1)])
    width = (PLACE_BITS + int(np.diff(firsts).max() - 1).bit_length() + 7) // 8
    shared = spark.sparkContext.broadcast(trained.shared(trained.frequent_pairs()))
    dealt = "group int, kind int, portion long, number int, data binary"
    blank = {"held_out": False, "rid": 0, "rt": 0, "n_tokens": 0, "n_known": 0, "logs": 0.0, "score": 0.0}

    def rows(group, kind: int, portion: int, data: list[bytes]) -> pd.DataFrame:
        return pd.DataFrame({"group": group, "kind": kind, "portion": portion, "number": 0, "data": data, **blank, "rest": [[] for _ in data]})

    def ask(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model, words = Model(Filter(*shared.value[0]), *shared.value[1:]), Words()
        portion, texts, size, held = TaskContext.get().partitionId() << 32, 0, 0, []

        def sent() -> Iterator[pd.DataFrame]:
            if not held:
                return
            whose, keys, first, second = (np.concatenate(x) for x in zip(*held, strict=True))
            held.clear()
            block = (keys % np.uint64(many)).astype(np.int64)
            group = np.searchsorted(firsts, block, side="right") - 1
            by = np.argsort(group.astype(np.int32), kind="stable")
            place = (block - firsts[group]).astype(np.uint64) << np.uint64(PLACE_BITS) | keys // np.uint64(many)
            cuts = np.searchsorted(group[by], np.arange(groups + 1))
            for g in np.flatnonzero(np.diff(cuts)).tolist():
                some = by[cuts[g] : cuts[g + 1]]
                counts = np.bincount(whose[some], minlength=texts).astype(np.uint32)
                yield rows([g], 1, portion, [b"".join((struct.pack("<II", texts, len(some)), counts.tobytes(), first[some].tobytes(), second[some].tobytes(), planes(place[some], width)))])

        for batch in batches:
            for part in chunks(batch):
                frame, tokens_of, (where, *asked) = _parts(part, model, words)
                owner = np.repeat(np.arange(len(part)), tokens_of)[where]
                held.append((texts + owner, *asked))
                number = texts + np.arange(len(part))
                yield frame.assign(group=portion % groups, kind=2, portion=portion, number=number, data=[b""] * len(part))
                texts, size = texts + len(part), size + int(tokens_of.sum())
                if size >= TOKENS_A_RUN:
                    yield from sent()
                    portion, texts, size = portion + 1, 0, 0
        yield from sent()

    def answer(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        scorer = Model(None, None, *shared.value[2:])
        at, bits, held = None, {}, None
        for batch in batches:
            texts = batch["kind"] == 2
            for group, kind, portion, data in zip(*(batch.loc[~texts, c].tolist() for c in ("group", "kind", "portion", "data")), strict=True):
                if group != at:
                    at, bits, held = group, {}, None
                if kind == 0:
                    bits[portion] = data
                    continue
                first, end = int(firsts[group]), int(firsts[group + 1])
                if held is None:
                    of = sizes[first:end]
                    whole = np.frombuffer(b"".join(bits.get(x, bytes(int(n) // 8)) for x, n in zip(range(first, end), of, strict=True)), dtype=np.uint8)
                    held, bits = Filter(whole, many, of, first, end), {}
                n_texts, n = struct.unpack_from("<II", data)
                counts = np.frombuffer(data, dtype=np.uint32, count=n_texts, offset=8)
                words = np.frombuffer(data, dtype=np.uint8, count=2 * n, offset=8 + 4 * n_texts).astype(np.int64)
                place = from_planes(data, n, width, 8 + 4 * n_texts + 2 * n)
                keys = (place & np.uint64((1 << PLACE_BITS) - 1)) * np.uint64(many) + (place >> np.uint64(PLACE_BITS)) + np.uint64(first)
                lv = held.levels(keys)
                seen = np.flatnonzero(lv)
                one, two = words[seen], words[n + seen]
                more = scorer.mixed_logs(one, two, lv[seen]) - scorer.mixed_logs(one, two, np.zeros(len(seen), dtype=np.int64))
                yield rows(group, 1, portion, [np.bincount(np.repeat(np.arange(n_texts), counts)[seen], more, minlength=n_texts).tobytes()])
            if texts.any():
                yield batch[texts]

    def add(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        at, sums = None, None
        for batch in batches:
            for portion, part in batch.groupby("portion", sort=False):
                if portion != at:
                    at, sums = portion, None
                texts = part["kind"] == 2
                for data in part.loc[~texts, "data"]:
                    more = np.frombuffer(data, dtype=np.float64)
                    sums = more if sums is None else sums + more
                if texts.any():
                    part = part[texts]
                    yield part if sums is None else part.assign(score=part["score"].to_numpy() + sums[part["number"].to_numpy()])

    known = F.udf(lambda block: int(np.searchsorted(firsts, block, side="right") - 1), "int")
    empty = [F.lit(v).cast(kind).alias(name) for name, kind, v in (("held_out", "boolean", False), *((c, "long", 0) for c in ("rid", "rt", "n_tokens", "n_known")), ("logs", "double", 0.0), ("score", "double", 0.0))]
    blocks = trained.ngrams.select(known("block").alias("group"), F.lit(0).alias("kind"), F.col("block").alias("portion"), F.lit(0).alias("number"), F.col("bits").alias("data"), *empty, F.array().cast("array<long>").alias("rest"))
    asked = keyed.mapInPandas(ask, f"{dealt}, {SCORED}").unionByName(blocks)
    answered = asked.repartitionById(groups, F.col("group")).sortWithinPartitions("group", "kind").mapInPandas(answer, f"{dealt}, {SCORED}")
    summed = answered.repartition("portion").sortWithinPartitions("portion", "kind", "group").mapInPandas(add, f"{dealt}, {SCORED}")
    return staged(_named(summed.select(*[c.split()[0] for c in SCORED.split(", ")])), "scored")


def score(docs: DataFrame, most_bits: int = MOST_BITS, head: int = HEAD) -> DataFrame:
    """One row per document: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score.

    Null texts count as empty: their one token is the end. Rows with a null id
    train the model and are not held out; equal rows each give a row. Without
    training rows N and V are 0 and no token is known. base_score comes from
    exact counts: of the most frequent words at each worker, of the others by a
    join on the word's 64-bit hash. most_bits bounds each broadcast. All pairs
    count at every size: where one broadcast does not hold them, those of the
    texts go to the blocks that do. Of words, the filter leaves out the least frequent
    levels where it would be larger; these are joined to the texts that hold them.
    """
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("held_out", held_out(F.col("doc_id")))
    trained = Trained(rows.where(~F.col("held_out")).select("text"), most_bits, head)
    total, distinct = trained.total, trained.distinct
    keyed = rows.select(F.col("doc_id").cast("long").alias("doc_id"), "held_out", id_key(F.col("doc_id")).alias("rid"), text_key(F.col("text")).alias("rt"), "text")
    keyed = trained.with_rare(keyed)

    found = _scored(keyed, trained) if trained.shares == 1 else _scored_by_blocks(keyed, trained)
    n = F.col("n_tokens")
    if trained.complete:
        out = found.withColumns({"more": F.lit(0), "more_logs": F.lit(0.0)})
    else:
        # rare words: counted in their document first, then joined on the word
        rare = found.where(F.size("rest") > 0).select("rid", "rt", "rest").dropDuplicates(["rid", "rt"]).select("rid", "rt", F.explode("rest").alias("key")).groupBy("rid", "rt", "key").agg(F.count(F.lit(1)).alias("tf"))
        added = rare.join(trained.counts.select("key", "n"), "key").groupBy("rid", "rt").agg(F.sum("tf").alias("more"), F.sum(F.col("tf") * F.log10(F.col("n") + 1.0)).alias("more_logs"))
        out = found.drop("rest").join(added, ["rid", "rt"], "left")
    return out.select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("n_known") + F.coalesce("more", F.lit(0))).cast("long").alias("n_known"),
        F.lit(total).cast("long").alias("train_tokens"),
        (F.col("logs") + F.coalesce("more_logs", F.lit(0.0)) - n * math.log10(total + distinct + 1)).alias("base_score"),
        "score",
    )


def op6_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(table(spark, sf_dir, "documents"))
