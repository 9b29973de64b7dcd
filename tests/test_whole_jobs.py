"""Queries take in all of their input."""

from __future__ import annotations

import re

from sepkey.operators import setcover
from sepkey.plans import catalog, measures, queries
from sepkey.sources.stores import table


def test_greedy_cover_takes_in_every_word(spark, monkeypatch):
    d = "/root/testdata/sf0.001"
    left = {f"item{r.item_id:05d}": {w for w in re.split(r"[\x00-\x2f\x3a-\x60\x7b-\x7f]+", r.text.lower()) if w} for r in table(spark, d, "benchmark").where("text is not null").collect()}
    want = []
    while any(left.values()):
        name = min(left, key=lambda n: (-len(left[n]), n))
        done = set(left[name])
        want.append((len(want) + 1, name, len(done)))
        left = {n: w - done for n, w in left.items()}
    assert [tuple(r) for r in queries._cover(spark, d).orderBy("step").collect()] == want
    monkeypatch.setattr(setcover, "DRIVER_ROWS", 100)  # the first rounds in Spark
    assert [tuple(r) for r in queries._cover(spark, d).orderBy("step").collect()] == want


def test_sketch_sweep_judges_all_sets_of_at_most_k(spark):
    d, attrs = "/root/testdata/sf0.001", catalog.attributes("lineitem")[:5]
    got = measures.sketch_sweep(spark, table(spark, d, "lineitem"), catalog.identity("lineitem"), attrs, 42).collect()
    assert {(r.k, r.sets) for r in got} == {(1, 5), (2, 15), (3, 25)}
