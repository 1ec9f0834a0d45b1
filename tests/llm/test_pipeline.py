from __future__ import annotations

import re

import corpus_pipeline
from gnn_delta.llm.common import written

SF = "/root/testdata/sf0.001"


def lower(t: str) -> str:
    return re.sub("[A-Z]", lambda m: m[0].lower(), t)


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    items = [r.text for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        before = docs.collect()
        docs = written(stage(spark, docs, SF), f"test{k}")
        after = docs.collect()
        assert {r.doc_id for r in after} <= {r.doc_id for r in before}, name
        if k < 4:
            assert docs.columns == columns
        if name == "exact dedup":
            assert sorted(lower(r.text) for r in after) == sorted({lower(r.text) for r in before})
        if name == "benchmark decontamination":
            gone = {r.doc_id for r in before} - {r.doc_id for r in after}
            held = {r.doc_id for r in before if any(lower(i) in lower(r.text) for i in items)}
            assert held <= gone and len(gone - held) <= 2
        if k == 4:
            assert len(after) == len(before)
    assert corpus_pipeline.run(spark, SF).count() == docs.count()


def test_oracle_of_exact_dedup(spark):
    import duckdb

    from gnn_delta.llm import queries

    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    for name, sql in queries.ORACLES.items():
        want = con.sql(sql).df()
        got = queries.QUERIES[name](spark, SF).toPandas()[list(want.columns)]
        assert got.sort_values("doc_id").astype(str).values.tolist() == want.sort_values("doc_id").astype(str).values.tolist()
