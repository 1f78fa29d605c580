"""Tables that grow with the input are never collected and hashed on the driver."""

import pytest

from postpool.llm import near_dup


@pytest.mark.parametrize("run", [near_dup.near_duplicates, near_dup.keep_one])
def test_no_join_is_broadcast(spark, sf, monkeypatch, run):
    plans = []
    write = near_dup.materialise

    def seen(df, tag, **options):
        plans.append((tag, df._jdf.queryExecution().executedPlan().toString()))
        return write(df, tag, **options)

    monkeypatch.setattr(near_dup, "materialise", seen)
    out = run(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text"))
    plans.append(("out", out._jdf.queryExecution().executedPlan().toString()))
    assert len(plans) > 10 and out.count() > 0
    assert [tag for tag, plan in plans if "Broadcast" in plan] == []
