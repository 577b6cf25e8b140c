"""The pipeline's stages against what each should keep, and on awkward tables."""

import pandas as pd
from pyspark.sql import functions as F

import corpus_pipeline as pipeline
from weftgraph.llm import langid

from .test_nearcopies import brute_components
from .test_operators import AWKWARD, brute_windows

SMALL = "/root/testdata/sf0.01"


def test_stages(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    labels = pd.read_parquet(f"{SMALL}/labels.parquet")
    before = docs.toPandas()
    for name, stage in pipeline.STAGES:
        docs = pipeline.stored(stage(spark, docs, SMALL))
        after = docs.toPandas()
        if name in ("language", "quality"):
            gone = before[~before["doc_id"].isin(after["doc_id"])].merge(labels, on="doc_id")
            clean = before.merge(labels, on="doc_id").query("quality == 1")
            assert (gone["quality"] == 1).sum() <= 0.01 * len(clean)
            if name == "quality":
                assert len(gone) >= 0.9 * (before.merge(labels, on="doc_id")["quality"] == 0).sum()
        elif name == "near_duplicates":
            # the stage has no contract of its own, so five words and a similarity of 0.8 hold
            roots = brute_components(list(zip(before["doc_id"].tolist(), before["text"], strict=True)))
            assert sorted(after["doc_id"]) == sorted(set(roots.values()))
        elif name == "repeated_windows":
            gone = {d: n for d, _, n, _ in brute_windows(list(zip(before["doc_id"], before["text"], strict=True)), 20)}
            words = dict(zip(before["doc_id"], before["text"].str.encode("utf-8").map(lambda b: len(b.split())), strict=True))
            assert len(after) == len(before)
            for r in after.itertuples():
                assert len(r.text.encode().split()) == words[r.doc_id] - gone[r.doc_id] and r.n_chars == len(r.text)
        else:
            assert after.groupby("bin_id")["n_words"].sum().max() <= 2048 and set(after["doc_id"]) == set(before["doc_id"])
        if name != "packing":
            assert list(after.columns) == ["doc_id", "text", "lang", "source", "n_chars"]
        before = after


def test_awkward_rows_and_empty_tables(spark, tmp_path):
    rows = spark.createDataFrame([(d, t, "en", None, 0, "x", 1.0) for d, t in AWKWARD], "doc_id long, text string, lang string, source string, n_chars long, _all string, score double")
    spark.createDataFrame([(6, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    for docs in (rows, rows.where("false")):
        for name, stage in pipeline.STAGES:
            docs = pipeline.stored(stage(spark, docs, str(tmp_path)))
            if name == "language":
                assert docs.where(F.col("text").isNull()).count() == 0
        docs.count()
    assert langid.UNKNOWN == "und"
