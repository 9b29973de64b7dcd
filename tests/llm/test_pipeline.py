from __future__ import annotations

import corpus_pipeline

from sepkey.llm import common, decontaminate, fuzzy_lines, near_dup

SMALL = "/root/testdata/sf0.001"


def test_stages_take_effect_and_keep_columns(spark):
    docs = common.table(spark, SMALL, "documents").where("doc_id < 120")
    columns, counts = docs.columns, [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = common.durable(stage(spark, docs, SMALL), name)
        assert docs.columns == columns
        counts.append(docs.count())
    assert counts == sorted(counts, reverse=True) and counts[-1] > 0.6 * counts[0]
    # what a stage removes, a second run finds no more of
    assert near_dup.near_duplicates(docs, 80).where("not kept").isEmpty()
    assert decontaminate.find_contamination(docs, common.table(spark, SMALL, "benchmark")).where("n_hit > 0").isEmpty()
    assert fuzzy_lines.decide(docs).isEmpty()
    last = corpus_pipeline.STAGES[-1][1](spark, docs, SMALL)
    by_doc = {r.doc_id: r.n for r in last.groupBy("doc_id").agg({"length": "sum"}).withColumnRenamed("sum(length)", "n").collect()}
    assert set(by_doc) == {r.doc_id for r in docs.select("doc_id").collect()}
