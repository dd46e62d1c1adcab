"""What the reviewer of round 2 found in the training-data operators: a test each that failed before."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from vecforest.llm import lm_scores, passages
from vecforest.llm.common import table

from .cases import documents, sentence


def test_words_beyond_the_filter_score_as_within(spark, sf):
    """A filter too small for rare words changes no score but by levels that either filter misreads (one word in eighty)."""
    docs = table(spark, sf, "documents").where("doc_id < 60")
    texts = docs.where(~lm_scores.held_out(F.col("doc_id"))).select(F.coalesce("text", F.lit("")).alias("text"))
    assert lm_scores.Trained(texts, 100_000, 64).least > 1
    whole = {r["doc_id"]: r for r in lm_scores.score(docs).collect()}
    small = {r["doc_id"]: r for r in lm_scores.score(docs, 100_000, 64).collect()}
    assert whole.keys() == small.keys()
    gaps = [abs(whole[i]["score"] - small[i]["score"]) / whole[i]["n_tokens"] for i in whole]
    assert sum(gaps) / len(gaps) < 0.2  # rare words that score as unseen make 0.89
    assert all(small[i]["n_known"] == whole[i]["n_known"] and small[i]["base_score"] == pytest.approx(whole[i]["base_score"]) for i in whole)


def test_passes_do_not_grow_with_the_pairs(spark, sf, monkeypatch):
    """Pairs that fill five broadcasts take no more passes over the texts than those of one, and score alike."""
    docs = table(spark, sf, "documents").where("doc_id < 200")
    made, read = lm_scores.Trained.__init__, []
    for shares in (1, 5):
        seen = spark.sparkContext.accumulator(0)

        def counted(text, seen=seen):
            seen.add(1)
            return text

        def in_shares(self, *args, shares=shares):
            made(self, *args)
            self.shares = shares

        monkeypatch.setattr(lm_scores.Trained, "__init__", in_shares)
        text = F.udf(counted, "string").asNondeterministic()("text")
        rows = lm_scores.score(docs.select("doc_id", text.alias("text"))).collect()
        read.append((seen.value, {r["doc_id"]: (r["n_known"], round(r["base_score"], 6), round(r["score"], 6)) for r in rows}))
    assert read[0] == read[1]


def test_run_whose_anchors_others_crowd(spark):
    """Two documents share 51 words, of which many others hold the first or the last 45: first, last and neighbouring holders of each anchor."""
    p = sentence(900, 51).split()
    held = {i: p[:45] if i % 2 else p[6:] for i in range(60)} | {20: p, 40: p}
    rows = [(i, f"{sentence(1000 + i, 60)} x{i} {' '.join(t)} y{i} {sentence(1100 + i, 60)}") for i, t in held.items()]
    got = {(r["doc_id"], r["other_id"]): (r["start_word"], r["end_word"]) for r in passages.repeated_passages(documents(spark, rows)).collect()}
    assert got == {(20, 40): (61, 112), (40, 20): (61, 112)}


def test_runs_meet_round_crowded_anchors(spark):
    """Each document of those that share a run of 51 words with others is tied to the first one that holds the run."""
    p = sentence(901, 120).split()
    held = {i: p[7 * (i % 10) : 7 * (i % 10) + 54] for i in range(40)}
    rows = [(i, f"{sentence(1200 + i, 60)} x{i} {' '.join(t)} y{i} {sentence(1300 + i, 60)}") for i, t in held.items()]
    got = {(r["doc_id"], r["other_id"]) for r in passages.repeated_passages(documents(spark, rows)).collect()}
    assert {(i, i % 10) for i in range(10, 40)} <= got
