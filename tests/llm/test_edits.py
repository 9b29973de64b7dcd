"""Many pairs at once against the distance table filled cell by cell."""

from __future__ import annotations

import random

import numpy as np
import pyarrow as pa

from sepkey.llm import edits, fuzzy_lines
from tests.llm.test_fuzzy_recall import _edits

VOCABULARY = ["ab", "b", "abba", "löwe", "日本語", "😀x", "the", "of", "passage"]


def _pair(rng):
    words = [rng.choice(VOCABULARY) for _ in range(rng.choice([1, 3, 12, 14, 15, 16, 17, 30, 33, 60]))]
    copy = list(words)
    for _ in range(rng.randint(0, 1 + len(words) // 2)):
        at = rng.randrange(len(copy) + 1)
        copy[at : at + rng.randint(0, 1)] = [rng.choice(VOCABULARY)] * rng.randint(0, 2)
    return " ".join(words), " ".join(copy) or "x"


def test_many_pairs_equal_the_distance_table(monkeypatch):
    rng = random.Random(3)
    pairs = [_pair(rng) for _ in range(500)] + [("a", "a"), ("a", "b"), ("a" * 64, "b" + "a" * 64), ("a" * 65, "a" * 63 + "b"), ("x" * 130, "y" * 128)]
    true = np.array([_edits(a, b) for a, b in pairs])
    x, y = pa.array([a for a, _ in pairs]), pa.array([b for _, b in pairs])
    for worth, chunk, masks in ((0, 7, 1 << 21), (0, 2048, 1 << 8), (12, 2048, 1 << 21), (10**9, 2048, 1 << 21)):  # chunks of all sizes; one by one
        monkeypatch.setattr(edits, "WORTH", worth)
        monkeypatch.setattr(edits, "CHUNK", chunk)
        monkeypatch.setattr(edits, "MASKS", masks)
        for most in (true, true - 1, np.array([max(len(a), len(b)) // 5 for a, b in pairs])):
            got = edits.alike(x, y, np.maximum(most, 0), fuzzy_lines.within)
            assert (got == (true <= np.maximum(most, 0))).all()
    monkeypatch.setattr(edits, "CELLS", 50)
    assert (edits.alike(x, y, true, fuzzy_lines.within)).all()
    assert len(edits.alike(x[:0], y[:0], np.zeros(0), fuzzy_lines.within)) == 0


def test_one_very_long_text_does_not_widen_all_pairs(monkeypatch):
    """Memory goes by the characters of the pairs, not by the longest times their number."""
    import tracemalloc

    x, y = pa.array(["ab " * 60] * 3000 + ["ab " * 40_000]), pa.array(["cd " * 60] * 3000 + ["ab " * 40_000])
    tracemalloc.start()
    got = edits.alike(x, y, np.full(3001, 10), fuzzy_lines.within)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert got.nonzero()[0].tolist() == [3000] and peak < 80 << 20


def test_documents_are_read_once_for_lines_that_are_tested_again(spark, monkeypatch):
    """A passage that many lines share takes several rounds of tests; their lines are fetched in the first."""
    rng = random.Random(1)
    word = lambda: "".join(rng.choice("abcdefghijklmnop") for _ in range(6))
    passage = " ".join(word() for _ in range(14))
    rows = [(i, f"{passage} {' '.join(word() for _ in range(10))}") for i in range(30)]
    docs = spark.createDataFrame(rows + [(100 + i, t.replace("a", "q", 1)) for i, t in rows], "doc_id long, text string")
    reads, fetch = [], fuzzy_lines._texts
    monkeypatch.setattr(fuzzy_lines, "_texts", lambda *a: reads.append(1) or fetch(*a))
    tests, alike = [], fuzzy_lines._alike
    monkeypatch.setattr(fuzzy_lines, "_alike", lambda *a: tests.append(1) or alike(*a))
    got = {r.doc_id for r in fuzzy_lines.decide(docs).collect()}
    assert got == {100 + i for i in range(30)}
    assert len(tests) > 1 and len(reads) == 1
