"""Packing, Jaccard join, repeated passages and the pipeline against brute force."""

from __future__ import annotations

import random
import zlib
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from vecforest.llm import components, jaccard, packing, passages
from vecforest.llm.common import staged, table

from .cases import documents, odd_rows, sentence


def test_packing_round_trip(spark):
    rows = packing.pack(documents(spark), with_ids=True).collect()
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(packing.byte_bpe_path())
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in rows:
        assert r["length"] == len(r["ids"]) <= 2048 and r["ids_crc32"] == zlib.crc32(np.array(r["ids"], dtype="<u4").tobytes())
        by_doc[r["doc_id"]].append(r)
        by_seq[r["sequence_id"]].append((r["offset"], r["length"]))
    for i, text in odd_rows():
        if i is None or i == 2:
            continue
        parts = sorted(by_doc[i], key=lambda r: r["piece"])
        assert [x for p in parts for x in p["ids"]] == [*t.encode(text or "", add_special_tokens=False).ids, 0]
        assert [p["start"] for p in parts] == list(np.cumsum([0, *[p["length"] for p in parts]])[:-1]) and all(p["length"] == 2048 for p in parts[1:])
    for places in by_seq.values():
        at = 0
        for o, n in sorted(places):
            assert o == at
            at += n
        assert at <= 2048
    total = sum(r["length"] for r in rows)
    assert len(by_seq) <= total / 2048 * 1.05 + 1 and len(by_doc[2]) == 2
    assert packing.pack(documents(spark, [])).count() == 0


def test_open_bins():
    b = packing.OpenBins(10, 2)
    assert [b.place(n) for n in (6, 7, 3, 4, 9, 1)] == [(0, 0), (1, 0), (1, 7), (0, 6), (2, 0), (2, 9)]
    b = packing.OpenBins(10, 2)
    assert [b.place(n) for n in (5, 7, 8, 3, 2)] == [(0, 0), (1, 0), (2, 0), (0, 5), (0, 8)]  # the third piece closes the fuller one of two
    b = packing.OpenBins(10, 1)
    assert [b.place(n) for n in (6, 7, 4)] == [(0, 0), (1, 0), (2, 0)]


def test_packing_is_best_fit_in_order(spark, monkeypatch):
    """Streams against a plain list of open bins, in the order of the hash."""
    rows = [(i, sentence(i, 20 + 13 * i % 90)) for i in range(300)]
    monkeypatch.setattr(packing, "DOCS_A_STREAM", 100)
    mix = F.xxhash64(F.col("doc_id"), "piece", "ids_crc32")
    got = packing.pack(documents(spark, rows), length=256, open_bins=5).withColumn("mix", mix).withColumn("part", F.shiftright("sequence_id", 40)).collect()
    parts = {r["part"] for r in got}
    assert len(parts) == 4
    for p in parts:
        bins, made, want = {}, 0, []
        for r in sorted((r for r in got if r["part"] == p), key=lambda r: r["mix"]):
            fits = sorted((free, -b) for b, free in bins.items() if free >= r["length"])
            if fits:
                at = -fits[0][1]
            else:
                if len(bins) == 5:
                    del bins[max(b for b, free in bins.items() if free == min(bins.values()))]
                at, made = made, made + 1
                bins[at] = 256
            want.append((r["doc_id"], 256 - bins[at]))
            bins[at] -= r["length"]
            if not bins[at]:
                del bins[at]
        assert made == len({r["sequence_id"] for r in got if r["part"] == p})
        assert sum(x[1] == 0 for x in want) == made


@pytest.mark.parametrize("text", ["", " ", "a" * 5000, "<|endoftext|> x", "é" * 3000, "\n" * 3000, "hi  there   \n\n x", "日本語 😀😀", "don't I'll 12345 6789 \t x"])
def test_encoder_equals_the_library(text):
    e = packing.Encoder(packing.byte_bpe_path())
    assert e.ids(text).tolist() == e.library.encode(text, add_special_tokens=False).ids == e.fast.encode(text, allowed_special=e.special)


def brute_links(rows):
    sets = []
    for _, t in rows:
        w = (t or "").lower().split()
        sets.append({tuple(w[p : p + 5]) for p in range(max(1, len(w) - 4))} if w else set())
    links = defaultdict(set)
    for a in range(len(rows)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if both and both >= 0.8 * (len(sets[a]) + len(sets[b]) - both) - 1e-9:
                links[a].add(b)
                links[b].add(a)
    return links


def near_copies(seed: int, n: int, words: int = 150):
    base = sentence(seed, words).split()
    out = []
    for i in range(n):
        w = list(base)
        w[(i * 7) % words] = f"edit{i}"
        out.append(" ".join(w))
    return out


@pytest.mark.parametrize("large,block", [(8192, 256), (4, 4), (8192, 3)])
def test_join_by_brute_force(spark, monkeypatch, large, block):
    monkeypatch.setattr(jaccard, "LARGE", large)
    monkeypatch.setattr(jaccard, "BLOCK", block)
    rows = [(i, t) for i, t in odd_rows() if i is not None and i != 2] + [(2, odd_rows()[1][1])]
    rows += [(200 + i, t) for i, t in enumerate(near_copies(70, 9))] + [(300, near_copies(70, 9)[3])]
    links = brute_links(rows)
    got = {r["doc_id"]: r for r in jaccard.join(documents(spark, rows)).collect()}
    assert len(got) == len(rows)
    parent = list(range(len(rows)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, bs in links.items():
        for b in bs:
            parent[root(a)] = root(b)
    for a, (i, _) in enumerate(rows):
        assert got[i]["n_links"] == len(links[a]), i
        assert got[i]["class_id"] == min(j for b, (j, _) in enumerate(rows) if root(b) == root(a))


def test_join_of_odd_and_empty_tables(spark):
    got = jaccard.join(documents(spark)).collect()
    assert len(got) == len(odd_rows())
    assert {r["class_id"] for r in got if r["doc_id"] in (1, 2, 3)} == {None} and all(r["n_links"] == 0 for r in got if r["doc_id"] in (4, 5, 6))
    assert jaccard.join(documents(spark, [])).count() == 0
    assert jaccard.join(documents(spark, [(1, None), (2, "")])).count() == 2


def test_pruning_keeps_pairs_at_the_threshold():
    floors = jaccard.least_matches()
    assert floors[0] == 0 and all(a <= b for a, b in zip(floors, floors[1:], strict=False))
    assert floors[jaccard.HASHES] < 0.8 * jaccard.HASHES and floors[jaccard.HASHES] > 0.5 * jaccard.HASHES


def test_components(spark):
    links = [(i, i + 1) for i in range(0, 60)] + [(100, 101), (102, 101), (7, 7)]
    got = {r["node"]: r["root"] for r in components.components(spark.createDataFrame(links, "u long, v long")).collect()}
    assert {got[i] for i in range(61)} == {0} and {got[i] for i in (100, 101, 102)} == {100}
    assert components.components(spark.createDataFrame([], "u long, v long")).count() == 0


def test_passages(spark):
    shared = sentence(80, 90).split()
    fuzzy = list(shared)
    fuzzy[45] = "other"
    rows = [(i, sentence(400 + i, 100) + " " + " ".join(shared if i % 2 else fuzzy) + " " + sentence(500 + i, 60)) for i in range(8)]
    rows += [(50 + i, sentence(600 + i, 200)) for i in range(6)] + [(90, None), (91, ""), (92, "few words")]
    got = passages.repeated_passages(documents(spark, rows)).collect()
    assert {r["doc_id"] for r in got} == set(range(8))
    for r in got:
        assert r["end_word"] - r["start_word"] > 50 and r["identity"] >= 0.8 and r["other_id"] != r["doc_id"]
        if r["other_id"] in (0, 7):  # the first and the last holder meet all others
            assert r["start_word"] <= 101 and r["end_word"] >= 189
    assert passages.repeated_passages(documents(spark, [])).count() == 0
    assert passages.repeated_passages(documents(spark)).count() > 0  # ids occur twice there


@pytest.mark.parametrize("few", [64, 2])
def test_passage_of_parts_that_others_hold(spark, monkeypatch, few):
    monkeypatch.setattr(passages, "FEW_HOLDERS", few, raising=False)
    a, b = sentence(700, 40), sentence(701, 40)
    held = {1: a, 20: a, 2: b, 19: b, 5: f"{a} {b}", 10: f"{a} {b}", 15: f"{a} {b}"}
    rows = [(i, f"{sentence(710 + i, 70)} {t} {sentence(740 + i, 70)}") for i, t in held.items()]
    got = passages.repeated_passages(documents(spark, rows)).collect()
    assert {r["doc_id"] for r in got} == {5, 10, 15}
    assert all(r["start_word"] <= 71 and r["end_word"] >= 149 for r in got)


@pytest.mark.parametrize("few", [64, 2])
def test_changed_passage_of_parts_that_others_hold(spark, monkeypatch, few):
    monkeypatch.setattr(passages, "FEW_HOLDERS", few, raising=False)
    a, b = sentence(700, 40), sentence(701, 40)
    held = {1: a, 20: a, 2: b, 19: b, 5: f"{a} five {b}", 10: f"{a} ten {b}", 15: f"{a} fifteen {b}"}  # no run of 51 equal words
    rows = [(i, f"{sentence(710 + i, 70)} {t} {sentence(740 + i, 70)}") for i, t in held.items()]
    got = passages.repeated_passages(documents(spark, rows)).collect()
    assert {(r["doc_id"], r["other_id"]) for r in got} == {(x, y) for x in (5, 10, 15) for y in (5, 10, 15) if x != y}


def longest_shared(texts):
    """By pair of rows: the longest run of words that both hold."""
    out = {}
    words = [t.lower().split() for t in texts]
    for a in range(len(texts)):
        for b in range(a):
            row, best = [0] * (len(words[b]) + 1), 0
            for x in words[a]:
                row = [0] + [row[j] + 1 if x == y else 0 for j, y in enumerate(words[b])]
                best = max(best, *row)
            out[b, a] = best
    return out


@pytest.mark.parametrize("whole,part", [(56, 24), (60, 30), (70, 35), (80, 40)])
def test_passage_whose_start_others_hold(spark, whole, part):
    p = sentence(820, whole).split()
    held = {1: p[:part], 9: p[:part], 3: p, 7: p}
    rows = [(i, f"{sentence(830 + i, 70)} x{i} {' '.join(t)} y{i} {sentence(850 + i, 70)}") for i, t in held.items()]
    got = {(r["doc_id"], r["other_id"]): r for r in passages.repeated_passages(documents(spark, rows)).collect()}
    assert set(got) == {(3, 7), (7, 3)}
    assert all((r["start_word"], r["end_word"]) == (71, 71 + whole) for r in got.values())


def test_planted_passages_by_brute_force(spark):
    """Each document with a run of over 50 words of another is found, and no document without one."""
    rng = random.Random(5)
    pool = [sentence(1000 + i, rng.randint(45, 120)).split() for i in range(25)]
    rows = []
    for i in range(90):
        parts = [sentence(2000 + i, rng.randint(10, 90))]
        for _ in range(rng.randint(0, 2)):
            p = rng.choice(pool)
            cut = rng.randint(0, max(0, len(p) - 40))
            parts += [f"z{i}", " ".join(p[cut : cut + rng.randint(30, 120)]), f"w{i}", sentence(3000 + 7 * i + len(parts), rng.randint(5, 60))]
        rows.append((i, " ".join(parts)))
    runs = longest_shared([t for _, t in rows])
    want = {x for pair, n in runs.items() if n > 50 for x in pair}
    got = passages.repeated_passages(documents(spark, rows)).collect()
    found = {r["doc_id"] for r in got}
    assert len(want) > 30 and want <= found and len(found - want) <= 0.05 * len(want)
    for r in got:
        a, b = (rows[r[c]][1].lower().split() for c in ("doc_id", "other_id"))
        x, y = a[r["start_word"] : r["end_word"]], b[r["other_start"] : r["other_end"]]
        assert min(len(x), len(y)) > 50 and passages.aligned(x, y) >= 0.8 * max(len(x), len(y))


@pytest.mark.parametrize("words,share,least", [(100, 0.03, 0.95), (100, 0.08, 0.6), (200, 0.08, 0.8)])
def test_recall_of_changed_passages(spark, words, share, least):
    """Share of pairs found whose common passage has a share of its words changed at random in one copy."""
    rng = random.Random(9)
    rows = []
    for i in range(40):
        p = sentence(4000 + i, words).split()
        q = [f"c{i}n{k}" if rng.random() < share else w for k, w in enumerate(p)]
        rows += [(2 * i, f"{sentence(5000 + i, 40)} {' '.join(p)} {sentence(6000 + i, 40)}"), (2 * i + 1, f"{sentence(7000 + i, 40)} {' '.join(q)} {sentence(8000 + i, 40)}")]
    got = {(r["doc_id"], r["other_id"]) for r in passages.repeated_passages(documents(spark, rows)).collect()}
    assert sum((2 * i, 2 * i + 1) in got for i in range(40)) >= least * 40, sum((2 * i, 2 * i + 1) in got for i in range(40))


def test_passages_of_rows_without_ids(spark):
    """Repeated and null ids keep their texts."""
    p = sentence(860, 80)
    rows = [(None, f"{sentence(861, 60)} {p}"), (None, sentence(862, 90)), (5, f"{sentence(863, 60)} {p}"), (5, sentence(864, 90)), (6, f"{p} {sentence(865, 60)}"), (6, f"{p} {sentence(865, 60)}")]
    got = passages.repeated_passages(documents(spark, rows)).collect()
    assert {(r["doc_id"], r["other_id"]) for r in got} == {(a, b) for a in (None, 5, 6) for b in (None, 5, 6) if a != b}
    assert all(r["end_word"] - r["start_word"] == 80 for r in got)


def test_chains():
    a = np.array([0, 4, 9, 200, 204, 208, 212])
    got = sorted(passages.chains(a, a + 7))
    assert [g[:4] for g in got] == [(0, 17, 7, 24), (200, 220, 207, 227)]
    assert passages.aligned("a b c d".split(), "a x c d".split()) == 3


def test_alignment_by_table():
    rng = random.Random(6)
    for _ in range(60):
        x, y = ([rng.choice("abcdef") for _ in range(rng.randint(0, 90))] for _ in range(2))
        row = [0] * (len(y) + 1)
        for w in x:
            new = [0]
            for j, v in enumerate(y):
                new.append(row[j] + 1 if v == w else max(row[j + 1], new[j]))
            row = new
        assert passages.aligned(x, y) == row[-1]


def test_winnowing_by_windows():
    rng = np.random.default_rng(4)
    for n, w in ((3, 8), (8, 8), (9, 8), (200, 8), (200, 12), (57, 5)):
        g = rng.integers(1, 50 if n < 100 else 1 << 60, n).astype(np.uint64)
        want = {i for a in range(max(1, n - w + 1)) for i in range(a, min(n, a + w)) if g[i] == g[a : a + w].min()}
        assert passages.winnowed(g, w).tolist() == sorted(want)


def test_pipeline_by_stages(spark, sf):
    docs = table(spark, sf, "documents")
    name, f = corpus_pipeline.STAGES[0]
    one = staged(f(spark, docs, sf), name)
    assert one.columns == docs.columns and one.count() == docs.count()
    two = staged(corpus_pipeline.STAGES[1][1](spark, one, sf), "two")
    rows = [(r["doc_id"], r["text"]) for r in one.collect()]
    links = brute_links(rows)
    kept = {r["doc_id"] for r in two.collect()}
    seen, want = set(), set()
    for a in range(len(rows)):
        if a in seen:
            continue
        group, todo = {a}, [a]
        while todo:
            for b in links[todo.pop()]:
                if b not in group:
                    group.add(b)
                    todo.append(b)
        seen |= group
        want.add(min(rows[b][0] for b in group))
    assert kept == want
    three = staged(corpus_pipeline.STAGES[2][1](spark, two, sf), "three")
    assert three.columns == docs.columns and 0 < three.count() <= two.count()
    four = staged(corpus_pipeline.STAGES[3][1](spark, three, sf), "four")
    assert four.count() == three.count() and four.columns == docs.columns
    packed = corpus_pipeline.STAGES[4][1](spark, four, sf)
    assert {r[0] for r in packed.select("doc_id").distinct().collect()} == {r["doc_id"] for r in four.collect()}


def test_pipeline_of_odd_rows(spark, sf):
    docs = documents(spark)
    for name, f in corpus_pipeline.STAGES:
        docs = staged(f(spark, docs, sf), name)
    assert docs.count() > 0


def test_pipeline_keeps_each_clean_row(spark, tmp_path):
    """By stage the exact rows that stay: null and repeated ids, other scripts, copies, benchmark text, secrets."""
    item = sentence(870, 40)
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    russian, chinese = "река текла под старым каменным мостом " * 6, "河水在古老的石桥下流过人们看着船只 " * 6
    texts = {"a": sentence(871, 80), "b": sentence(872, 80), "c": sentence(873, 80), "d": sentence(874, 80), "e": sentence(875, 80), "item": item, "secret": f"{sentence(876, 80)} password=hunter2hunter2", "ru": russian, "zh": chinese}
    rows = [(None, "a"), (None, "b"), (4, "c"), (4, "d"), (5, "e"), (6, "e"), (None, "item"), (4, "item"), (7, "secret"), (8, "ru"), (9, "zh")]
    langs = {"ru": "ru", "zh": "zh"}
    docs = spark.createDataFrame([(i, texts[t], langs.get(t, "en"), "s", len(texts[t])) for i, t in rows] + [(10, None, "en", "s", 0), (11, "", "en", "s", 0), (12, "123 --- 456", "en", "s", 11)], "doc_id long, text string, lang string, source string, n_chars long")
    names = {t: n for n, t in texts.items()}

    def kept(df):
        return sorted((str(r["doc_id"]), names.get(r["text"], r["text"])) for r in df.collect())

    every = sorted((str(i), t) for i, t in rows)
    steps = {
        "language": every,
        "near_copies": [x for x in every if x != ("6", "e") and x != ("None", "item")],
        "decontamination": [x for x in every if x != ("6", "e") and x[1] != "item"],
        "secrets": sorted((x[0], texts["secret"].replace("password=hunter2hunter2", "[SECRET]")) if x[1] == "secret" else x for x in every if x != ("6", "e") and x[1] != "item"),
    }
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = staged(stage(spark, docs, str(tmp_path)), name)
        assert kept(docs) == steps[name], name
    assert corpus_pipeline.STAGES[-1][1](spark, docs, str(tmp_path)).count() == len(steps["secrets"])


@pytest.mark.parametrize("least", [0, 50])
def test_seeds_of_many_texts(least):
    """Words, runs that are the least of a window, and none over the end of a text, against the definition."""
    rng = np.random.default_rng(3)
    texts = ["", " \t", "One  two\x1cTHREE fouré", "a " * 70, *(" ".join(rng.choice(list("abcdefg"), n)) for n in (7, 8, 14, 39, 50, 51, 52, 130)), "ßİ " * 60]
    powers = passages.Powers()
    hashes, sizes = passages.hashed_words(texts, powers)
    assert sizes.tolist() == [len(t.lower().split()) for t in texts]
    by_word = {}
    assert all(by_word.setdefault(w, h) == h for w, h in zip([w for t in texts for w in t.lower().split()], hashes.tolist(), strict=True))
    assert len(set(by_word.values())) == len(by_word)
    keys, places, whose = passages.seeds(texts, powers, least)
    up, _ = powers.upto(passages.ANCHOR)
    for i, text in enumerate(texts):
        h = hashes[sizes[:i].sum() : sizes[: i + 1].sum()]
        wanted = set()
        for odd, (size, window) in enumerate(((passages.K, passages.WINDOW), (passages.ANCHOR, passages.STRIDE))):
            g = [int(passages.mixed((h[j : j + size] * up[:size]).sum(keepdims=True))[0]) for j in range(len(h) - size + 1)] if len(h) > least else []
            for s in range(max(1, len(g) - window + 1)):
                part = g[s : s + window]
                wanted |= {(np.uint64(part[j] & ~1 | odd).astype(np.int64), s + j) for j in range(len(part)) if part[j] == min(part)}
        mine = whose == i
        assert sorted(wanted) == sorted(zip(keys[mine], places[mine], strict=True))


def test_chains_near_a_diagonal(monkeypatch):
    """The short way of matches near one diagonal gives what the tree gives."""
    rng = np.random.default_rng(5)
    for _ in range(200):
        n = int(rng.integers(1, 40))
        a = np.cumsum(rng.integers(1, 60, n))
        b = a + 9 + np.cumsum(rng.integers(-1, 2, n)) * int(rng.integers(0, 2))
        short = passages.chains(a, b)
        with monkeypatch.context() as m:
            m.setattr(passages.np, "diff", lambda x: -np.ones(max(len(x) - 1, 0)) if len(x) > 1 else np.array([-1.0]))
            slow = passages.chains(a, b)
        assert sorted(short) == sorted(slow)
