"""The whole pipeline against plain Python on a small fixture, and on tables with nulls, repeated rows and nothing at all."""

from __future__ import annotations

import re
import zlib
from collections import defaultdict

import corpus_pipeline
import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from sepkey.llm import common, decontaminate, fuzzy_lines, toxicity

SMALL = "/root/testdata/sf0.001"
_GAP = re.compile(r"[\x00-\x2f\x3a-\x60\x7b-\x7f]+")
_COPIES = {900: (3, []), 901: (4, [(7, "changed")]), 902: (5, [(2, "other"), (40, "words")])}


def _groups(n, linked):
    root = list(range(n))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(n):
        for j in range(i):
            if linked(i, j):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [find(i) for i in range(n)]


def _without_repeated_lines(rows):
    places, names, seen = [], [], {}
    for doc, text in sorted(rows.items()):
        for k, line in enumerate((text or "").split("\n")):
            norm = " ".join(w for w in _GAP.split(line.lower()) if w)
            if norm:
                if norm not in seen:
                    seen[norm] = len(names)
                    names.append(norm)
                places.append((doc, k, seen[norm]))

    def alike(i, j):
        x, y = names[i], names[j]
        most = max(len(x), len(y)) * 20 // 100
        return abs(len(x) - len(y)) <= most and " " in x and " " in y and fuzzy_lines.within(x, y, most)

    root = _groups(len(names), alike)
    first, gone = set(), defaultdict(set)
    for doc, k, i in places:
        if root[i] in first:
            gone[doc].add(k)
        first.add(root[i])
    out = {}
    for doc, text in rows.items():
        lines = (text or "").split("\n")
        if text is None or not gone[doc]:
            out[doc] = text
        elif len(gone[doc]) < len(lines):
            out[doc] = "\n".join(x for k, x in enumerate(lines) if k not in gone[doc])
    return out


def _one_of_each_group(rows):
    ids, sets = sorted(rows), {}
    for i in ids:
        w = re.findall(r"[^\x20\x09-\x0D]+", (rows[i] or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")))
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} or ({tuple(w)} if w else set())

    def linked(a, b):
        a, b = sets[ids[a]], sets[ids[b]]
        return bool(a and b) and 100 * len(a & b) >= 80 * len(a | b)

    root = _groups(len(ids), linked)
    return {i: rows[i] for at, i in enumerate(ids) if root[at] == at}


def _clean(rows, items):
    windows = {w for text in items for w in decontaminate.windows_of(text)}
    sizes = {len(w) for w in windows}

    def hit(text):
        words = decontaminate.words_of(text)
        return any(tuple(words[i : i + n]) in windows for n in sizes for i in range(len(words) - n + 1))

    return {i: t for i, t in rows.items() if not hit(t)}


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("tables"))
    docs = common.table(spark, SMALL, "documents")
    rows = {r.doc_id: r for r in docs.where("doc_id < 70").collect()}
    extra = []
    for new, (old, changes) in _COPIES.items():
        words = rows[old].text.split(" ")
        for at, word in changes:
            if at < len(words):
                words[at] = word
        extra.append((new, " ".join(words), "en", "src0", None))
    item = common.table(spark, SMALL, "benchmark").first().text
    extra.append((903, f"before these words {item} and after them", "en", "src0", 7))
    whole = spark.createDataFrame([*rows.values(), *extra], docs.schema)
    whole.repartition(3).write.parquet(f"{d}/documents.parquet")
    common.table(spark, SMALL, "labels").write.parquet(f"{d}/labels.parquet")
    common.table(spark, SMALL, "benchmark").write.parquet(f"{d}/benchmark.parquet")
    return d


def test_run_equals_plain_python(spark, folder):
    docs = common.table(spark, folder, "documents")
    rows = {r.doc_id: r.text for r in docs.collect()}
    labels = common.table(spark, folder, "labels").where(~corpus_pipeline.held_out(common.F.col("doc_id"))).select("doc_id", "toxic")
    ids = sorted(rows)
    scores = toxicity.fit(docs, labels).scores(common.texts_of(pa.array([rows[i] or "" for i in ids])))
    left = {i: rows[i] for i, s in zip(ids, scores, strict=True) if s < 0.5}
    counts = [len(rows), len(left)]
    for stage in (_without_repeated_lines, _one_of_each_group, lambda r: _clean(r, [x.text for x in common.table(spark, folder, "benchmark").collect()])):
        left = stage(left)
        counts.append(len(left))
    assert counts[0] > counts[-1] > 30 and 903 not in left
    encode = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = {}
    for i, text in left.items():
        tokens = np.array([*encode.encode(text or "", add_special_tokens=False).ids, 0], "<u4")
        want[i] = (len(tokens), tokens)
    got = corpus_pipeline.run(spark, folder).collect()
    assert {r.doc_id for r in got} == set(want)
    ends = defaultdict(int)
    for r in sorted(got, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == ends[r.sequence_id] and r.doc_tokens == want[r.doc_id][0]
        ends[r.sequence_id] += r.length
        assert r.ids_crc32 == zlib.crc32(want[r.doc_id][1][r.start : r.start + r.length].tobytes())
    assert max(ends.values()) <= 1024 and sum(ends.values()) == sum(n for n, _ in want.values())


def test_run_on_nulls_repeated_rows_and_nothing(spark, folder, tmp_path):
    docs = common.table(spark, folder, "documents")
    odd = spark.createDataFrame([(None, "no id at all", None, None, None), (1, None, None, None, None), (2, "", "en", None, 0), (3, "same row", "en", "s", 8), (3, "same row", "en", "s", 8), (4, " \n\n ", "en", "s", 4)], docs.schema)
    for name, rows in (("odd", odd), ("none", docs.where("false"))):
        d = f"{tmp_path}/{name}"
        rows.write.parquet(f"{d}/documents.parquet")
        for t in ("labels", "benchmark"):
            common.table(spark, folder, t).write.parquet(f"{d}/{t}.parquet")
        got = corpus_pipeline.run(spark, d).collect()
        assert sorted((r.doc_id is None, r.doc_id or 0) for r in got) == ([(False, 1), (False, 2), (False, 3), (False, 4), (True, 0)] if name == "odd" else [])
