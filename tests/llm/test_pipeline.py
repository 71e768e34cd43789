import corpus_pipeline
import numpy as np
from relstrata.llm import decontaminate, mixing, quality, simhash, token_output
from relstrata.llm.common import load

from .test_native import brute_overlaps
from .test_near_copies import brute_classes
from .test_tokens import reference


def test_run_against_brute_force(spark, sf):
    docs = {r["doc_id"]: r for r in load(spark, sf, "documents").collect()}
    judged = quality.judge_quality(load(spark, sf, "documents"), load(spark, sf, "labels"), min_words=0).collect()
    keep = sorted(r["doc_id"] for r in judged if r["kept"])
    rows = [(d, docs[d]["text"]) for d in keep]
    keep = [d for d, c in zip(keep, brute_classes(rows), strict=True) if c == d]
    items = [(r["item_id"], r["text"]) for r in load(spark, sf, "benchmark").collect()]
    bad = {d for d, _ in brute_overlaps([(d, docs[d]["text"]) for d in keep], items)}
    keep = [d for d in keep if d not in bad]
    left = spark.createDataFrame([tuple(docs[d]) for d in keep], load(spark, sf, "documents").schema)
    copies = sorted((r["doc_id"], r["text"]) for r in mixing.replicate(left).collect())
    got = sorted(map(tuple, corpus_pipeline.run(spark, sf).collect()), key=lambda r: r[1])
    assert got == reference(copies)


def test_clean_documents_stay(spark):
    """Of the rows labelled good at most two in a hundred go by the quality rules, and no other stage sees labels."""
    docs, lab = load(spark, "/root/testdata/sf0.01", "documents"), load(spark, "/root/testdata/sf0.01", "labels")
    kept = {r["doc_id"] for r in corpus_pipeline.quality_rules(spark, docs, "/root/testdata/sf0.01").collect()}
    good = {r["doc_id"] for r in lab.where("quality = 1").collect()}
    bad = {r["doc_id"] for r in lab.where("quality = 0").collect()}
    assert len(good & kept) >= 0.98 * len(good) and len(bad & kept) <= 0.1 * len(bad)


def test_rows_without_ids_and_rows_that_share_one(spark, sf, corpus):
    """Each row is judged by its own text: a clean row stays beside a bad one of the same id."""
    item = load(spark, sf, "benchmark").first()["text"]
    junk = " ".join(f"wo{k}$$$ r{k}###" for k in range(80))
    texts = [(None, corpus[0]), (None, junk), (None, item), (-7, corpus[1]), (-7, junk), (-7, item), (-8, None), (-9, ""), (-9, "")]
    df = spark.createDataFrame([(d, t, None, None, None) for d, t in texts], load(spark, sf, "documents").schema)
    given = "/root/testdata/sf0.01"  # the limit needs labelled rows of both kinds
    others = load(spark, given, "documents")
    got = corpus_pipeline.quality_rules(spark, others.unionByName(df), given).collect()
    left = {(r["doc_id"], r["text"]) for r in got}
    assert {(None, corpus[0]), (-7, corpus[1]), (None, item), (-7, item)} <= left and (None, junk) not in left and (-7, junk) not in left
    left = {(r["doc_id"], r["text"]) for r in corpus_pipeline.benchmark_decontamination(spark, df, sf).collect()}
    assert left == {(d, t) for d, t in texts if t != item}
    assert corpus_pipeline.near_dedup(spark, df, sf).where("doc_id is null").count() == 3
    for _, stage in corpus_pipeline.STAGES[-2:]:
        assert stage(spark, df, sf).columns


def test_stages_return_the_columns_of_documents(spark, sf):
    docs = load(spark, sf, "documents")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, sf).columns == corpus_pipeline.COLUMNS, name
    assert np.all([len(s) == 2 for s in corpus_pipeline.STAGES]) and decontaminate and simhash and token_output


def test_empty_documents(spark, sf):
    docs = load(spark, sf, "documents").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, sf).count() == 0
