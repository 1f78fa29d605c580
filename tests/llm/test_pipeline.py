"""Each stage of the corpus pipeline against brute force, on its own input."""

import corpus_pipeline as C
from pyspark.sql import functions as F

from postpool.llm import decontaminate as D

from .hostile import documents, empty
from .test_text_ops import brute_classes, check_packing, naive, texts_of

SF = "/root/testdata/sf0.001"


def test_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    names = [n for n, _ in C.STAGES]
    assert names == ["language_id", "near_duplicates", "decontamination", "packing"] and C.ORACLE_SQL is None
    for name, stage in C.STAGES[:-1]:
        before = texts_of(docs)
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns
        out.write.parquet(f"{tmp_path}/{name}")
        docs = spark.read.parquet(f"{tmp_path}/{name}")
        after = sorted(texts_of(docs))
        if name == "language_id":
            assert set(after) <= set(before) and len(after) >= 0.98 * len(before)
        elif name == "near_duplicates":
            classes = brute_classes(before)
            assert after == sorted((d, t) for d, t in before if classes[d] == d)
        else:
            items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
            clean = {d for d, n, hit, _ in naive(before, items) if not (hit and 20 * hit >= n)}
            assert after == sorted((d, t) for d, t in before if d in clean) and len(after) < len(before)
    packed = C.STAGES[-1][1](spark, docs, SF)
    check_packing(packed.collect(), texts_of(docs))
    whole = C.run(spark, SF)
    assert whole.agg(F.sum("length")).first() == packed.agg(F.sum("length")).first()


def test_stages_bear_hostile_and_empty_tables(spark):
    for make in (documents, empty):
        docs = make(spark)
        for _, stage in C.STAGES:
            stage(spark, docs, SF).collect()


def test_contamination_rule(spark):
    assert D.SHARE == 20 and D.WINDOW == 13
