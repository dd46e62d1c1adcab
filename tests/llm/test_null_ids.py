"""Rows without ids, and rows of equal ids, in the pipeline's stages."""

from __future__ import annotations

from vecforest.llm import decontamination, jaccard

from .cases import documents, sentence


def test_near_copies_without_ids(spark):
    rows = [(None, sentence(801, 80)), (None, sentence(802, 80)), (None, sentence(803, 80)), (1, sentence(803, 80)), (2, sentence(803, 80)), (3, sentence(804, 80)), (3, sentence(805, 80)), (3, sentence(805, 80))]
    got = jaccard.keep_one_of_each(spark, documents(spark, rows), "").collect()
    want = [(None, 801), (None, 802), (1, 803), (3, 804), (3, 805)]
    assert sorted(str((r["doc_id"], r["text"])) for r in got) == sorted(str((i, sentence(n, 80))) for i, n in want)


def test_contaminated_without_ids(spark, tmp_path):
    item = sentence(810, 40)
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    rows = [(None, item), (None, sentence(811, 80)), (4, item), (4, sentence(812, 80))]
    got = decontamination.drop_contaminated(spark, documents(spark, rows), str(tmp_path)).collect()
    assert sorted((str(r["doc_id"]), r["text"]) for r in got) == [("4", sentence(812, 80)), ("None", sentence(811, 80))]
