"""Shards as they are written: every row once, none lost or piled up by its key."""

from __future__ import annotations

from collections import Counter, defaultdict

from sepkey.llm import sharding


def test_written_shards_hold_null_and_hot_keys(spark, tmp_path):
    rows = [(7, f"{i:02d}" + "y" * 48, i) for i in range(40)] + [(None, "n" * 20, 1), (None, "m" * 20, 2), (8, None, 3)] + [(100 + i, "z" * 30, i) for i in range(30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, extra long").repartition(4)
    path = str(tmp_path / "shards")
    sharding.write_shards(docs, 300, path)
    got = spark.read.parquet(path).collect()
    assert Counter((r.doc_id, r.text, r.extra) for r in got) == Counter(rows)
    size, count = defaultdict(int), Counter()
    for r in got:
        size[r.depth, r.prefix, r.page] += len(r.text or "")
        count[r.depth, r.prefix, r.page] += 1
    assert all(n <= 300 or count[k] == 1 for k, n in size.items())
    want = Counter((r.depth, r.prefix, r.page) for r in sharding.assign(docs, 300).collect())
    assert sum(want.values()) == len(rows) and len({k[2] for k in count}) > 1
