"""The pipeline's stages keep their promises on whole tables."""

import re

import corpus_pipeline
from evalengine.llm._common import checkpointed


def test_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    columns, seen = docs.columns, [docs]
    for name, stage in corpus_pipeline.STAGES:
        seen.append(checkpointed(stage(spark, seen[-1], small)))
        if name != "packing":
            assert seen[-1].columns == columns
    counts = [d.count() for d in seen]
    assert counts[0] >= counts[1] > counts[2] > counts[3] == counts[4]
    assert not any(re.search(r'token = "[0-9a-f]{40}"', r.text) for r in seen[4].collect())
    assert {r.doc_id for r in seen[5].collect()} == {r.doc_id for r in seen[4].collect()}


def test_near_duplicates_of_null_and_repeated_ids(spark, small):
    long = " ".join(f"word{i}" for i in range(60))
    rows = [(None, "lost id"), (3, "a b c d e"), (3, "a b c d e"), (4, "one text of its own"), (4, "another text of the same id"), (7, long), (None, long), (6, long + " end"), (None, "lost id"), (8, None)]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    got = sorted(((r.doc_id, r.text) for r in corpus_pipeline.near_duplicates(spark, docs, small).collect()), key=str)
    want = [(None, "lost id"), (3, "a b c d e"), (4, "one text of its own"), (4, "another text of the same id"), (6, long + " end"), (8, None)]
    assert got == sorted(want, key=str)


def test_entry_registers_all(spark):
    import __spark_entry__

    names = __spark_entry__.queries()
    assert "pipeline" in names and all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11))
