"""Fuzzy lines with DataFrame functions only: no Python on the executors, exact verdicts, few unlike pairs of lines that share a passage."""

from __future__ import annotations

import random

from sepkey.llm import common, fuzzy_lines
from tests.llm.test_edits import _pair
from tests.llm.test_fuzzy_recall import _edits, _word


def test_no_stage_runs_python(spark, monkeypatch):
    plans, durable = [], common.durable
    monkeypatch.setattr(common, "durable", lambda df, *a, **k: plans.append(df._jdf.queryExecution().executedPlan().toString()) or durable(df, *a, **k))
    docs = spark.createDataFrame([(1, "one line of some words here"), (2, "one line of some word here"), (3, "x")], "doc_id long, text string").repartition(1)
    docs = spark.read.schema(docs.schema).parquet(durable(docs, "docs").inputFiles()[0])
    assert {r.doc_id: list(r.gone) for r in fuzzy_lines.decide(docs).collect()} == {2: [0]}
    assert plans and not [p for p in plans if "Arrow" in p or "Python" in p or "Pandas" in p]


def test_verdicts_equal_the_distance_table(spark):
    rng = random.Random(4)
    pairs = [_pair(rng) for _ in range(300)]
    rows = [(i, i, " ".join(x.split()), " ".join(y.split())) for i, (x, y) in enumerate(pairs)]
    got = {r.a: r.ok for r in fuzzy_lines._alike(spark.createDataFrame(rows, "a long, b long, x string, y string"), 80).collect()}
    assert got == {i: 5 * _edits(x, y) <= max(len(x), len(y)) for i, _, x, y in rows}
    assert 30 < sum(got.values()) < 270


def test_a_shared_passage_gives_few_unlike_pairs(spark, monkeypatch):
    """Lines half of whose words are one passage are not alike; nearly none of their pairs reaches the edit distance, and no alike pair is lost."""
    rng = random.Random(6)
    passage = [_word(rng) for _ in range(50)]
    lines = [[_word(rng) for _ in range(25)] + passage + [_word(rng) for _ in range(25)] for _ in range(120)]
    alike = [w[:10] + [_word(rng)] + w[11:] for w in lines[:20]]
    tested, test = [], fuzzy_lines._alike
    monkeypatch.setattr(fuzzy_lines, "_alike", lambda pairs, percent: tested.append(pairs.count()) or test(pairs, percent))
    docs = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(lines + alike)], "doc_id long, text string")
    assert {r.doc_id for r in fuzzy_lines.decide(docs).collect()} == set(range(120, 140))
    assert sum(tested) < 200
