"""Fuzzy lines against brute force in which edit similarity alone decides."""

from __future__ import annotations

import random
from collections import defaultdict

import duckdb
from pyspark.sql import functions as F

from sepkey.llm import common, fuzzy_lines

SMALL = "/root/testdata/sf0.001"


def _edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def _alike(a, b):
    return 100 * _edits(a, b) <= 20 * max(len(a), len(b))


def _word(rng):
    return "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(2, 9)))


def _pairs(seed):
    """For each length of 5 to 60 words: a line and a copy with words exchanged, dropped or added as long as the two stay alike."""
    rng, out = random.Random(seed), []
    for n in range(5, 61):
        line = [_word(rng) for _ in range(n)]
        copy = line
        for _ in range(rng.randint(1, max(1, n // 5))):
            at, how = rng.randrange(len(copy)), rng.randrange(3)
            more = copy[:at] + [[_word(rng)], [], [copy[at], _word(rng)]][how] + copy[at + 1 :]
            if _alike(" ".join(line), " ".join(more)):
                copy = more
        if copy != line:
            out.append((" ".join(line), " ".join(copy)))
    return out


def test_alike_lines_are_found_whatever_words_differ(spark):
    pairs = [p for seed in range(4) for p in _pairs(seed)]
    rows = [(2 * i + k, f"{line}\n") for i, p in enumerate(pairs) for k, line in enumerate(p)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: list(r.gone) for r in fuzzy_lines.decide(docs).collect()}
    want = {2 * i + 1 for i in range(len(pairs))}
    assert not set(got) - want  # lines of different pairs are not alike
    assert len(want) > 180 and len(got) >= 0.98 * len(want)


def test_edit_similarity_decides_among_short_lines(spark):
    rng = random.Random(5)
    base = [[_word(rng) for _ in range(rng.randint(3, 8))] for _ in range(12)]
    lines = sorted({" ".join(w[:k] + [_word(rng)] + w[k + 1 :]) for w in base for k in range(len(w))} | {" ".join(w) for w in base})
    root = list(range(len(lines)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(lines)):
        for j in range(i):
            if _alike(lines[i], lines[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    want = {i for i in range(len(lines)) if find(i) != i}
    docs = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")
    got = defaultdict(list, {r.doc_id: list(r.gone) for r in fuzzy_lines.decide(docs).collect()})
    assert want and set(got) == want


def test_lines_of_one_and_two_words_repeat_too(spark):
    docs = spark.createDataFrame([(1, "Read more\n\n{}\nOf."), (2, "read  more!\n\n{}\nof\nOff"), (3, "OF")], "doc_id long, text string")
    assert {r.doc_id: list(r.gone) for r in fuzzy_lines.decide(docs).collect()} == {2: [0, 3], 3: [0]}


def test_recall_against_edit_similarity_alone(spark):
    """Of all pairs of different lines of the table with an edit similarity of 0.8 or more, at least 0.95 end in one group."""
    words = "trim(regexp_replace(lower(line), '[\\x00-\\x2f\\x3a-\\x60\\x7b-\\x7f]+', ' ', 'g'))"
    letters = "etaonirsu"  # an edit changes the count of one letter, or of two by one each: what surely differs too much is not measured
    counts = ", ".join(f"length(x) - length(replace(x, '{c}', '')) AS {c}" for c in letters)
    more, less = (" + ".join(f"greatest(0, {p}.{c} - {q}.{c})" for c in letters) for p, q in ("ab", "ba"))
    sql = f"""WITH m AS (SELECT DISTINCT {words} AS x FROM (SELECT unnest(string_split(text, chr(10))) AS line FROM read_parquet('{SMALL}/documents.parquet'))),
              n AS MATERIALIZED (SELECT x, length(x) AS size, {counts} FROM m WHERE x LIKE '% %'),
              p AS MATERIALIZED (SELECT a.x AS x, b.x AS y, greatest(a.size, b.size) AS most FROM n a JOIN n b ON a.x < b.x AND 5 * least(a.size, b.size) >= 4 * greatest(a.size, b.size)
                                 AND 5 * ({more}) <= greatest(a.size, b.size) AND 5 * ({less}) <= greatest(a.size, b.size))
              SELECT x, y FROM p WHERE 5 * levenshtein(x, y) <= most"""
    pairs = duckdb.connect().sql(sql).fetchall()
    lines = sorted({x for p in pairs for x in p})
    rows = fuzzy_lines.decide(spark.createDataFrame([(i, f"{x}\n") for i, x in enumerate(lines)], "doc_id long, text string")).collect()
    gone = {lines[r.doc_id] for r in rows}
    assert len(pairs) > 20
    assert sum(a in gone or b in gone for a, b in pairs) >= 0.95 * len(pairs)


def test_repeated_rows_clashing_columns_and_texts_under_one_doc_id(spark):
    rows = [(1, "ab cd"), (2, "ab cd"), (1, "ab cd"), (2, "ab cd"), (None, "ab cd"), (3, None), (4, "")]
    docs = spark.createDataFrame([(*r, "x", "y", "z", 1) for r in rows], "doc_id long, text string, gone string, `row` string, `of doc` string, n_chars int")
    kept = fuzzy_lines.dedup(docs)
    assert kept.columns == docs.columns
    assert sorted((r.doc_id or 0, r.text, r.gone) for r in kept.collect() if r.text) == [(0, "ab cd", "x"), (1, "ab cd", "x"), (1, "ab cd", "x")]
    assert {r.doc_id for r in kept.collect()} == {1, 3, 4, None}
    both = spark.createDataFrame([(1, "one line here\nsecond line there"), (1, "something else entirely\none line here")], "doc_id long, text string")
    assert len({r.text for r in fuzzy_lines.dedup(both).collect()} & {"one line here\nsecond line there", "something else entirely"}) in (1, 2)
    assert sum(r.text.count("one line here") for r in fuzzy_lines.dedup(both).collect()) == 1


def test_hot_blocks_lose_no_pair(spark, monkeypatch):
    """Thousands of lines that share words but are not alike, with pairs of alike lines among them."""
    rng = random.Random(3)
    shared = [_word(rng) + "shared" for _ in range(3)]
    base = [shared + [_word(rng) + "xxxxx" for _ in range(17)] for _ in range(300)]
    copies = [w[:10] + [_word(rng) + "yyyyy"] + w[11:] for w in base[:40]]
    lines = [" ".join(w) for w in base + copies]
    monkeypatch.setattr(fuzzy_lines.grouping, "BLOCK", 32)
    docs = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")
    assert {r.doc_id for r in fuzzy_lines.decide(docs).collect()} == set(range(300, 340))
    nodes = spark.range(2000).select(F.lit(1).cast("long").alias("bucket"), F.col("id").alias("node"), (F.col("id") % 1000).alias("weight"))
    test = lambda pairs: pairs.where("a % 1000 = b % 1000")
    roots, _ = fuzzy_lines.grouping.link(nodes, test, lambda a, b: a("weight") == b("weight"))
    assert {(r.node, r.root) for r in roots.collect()} == {(i, i % 1000) for i in range(2000)}
    assert common.BROADCAST_BYTES > 0


def test_bounded_edit_distance_equals_the_table():
    rng = random.Random(8)
    for _ in range(3000):
        x = " ".join("".join(rng.choice("abé") for _ in range(rng.randint(1, 4))) for _ in range(rng.randint(1, 8)))
        y = list(x)
        for _ in range(rng.randint(0, 8)):
            at = rng.randrange(len(y) + 1)
            y[at : at + rng.randint(0, 2)] = rng.choice(["", "a", " b", "c "])
        y = " ".join("".join(y).split()) or "a"
        d = _edits(x, y)
        for most in {0, d - 1, d, d + 1, 50}:
            assert most < 0 or fuzzy_lines.within(x, y, most) == (d <= most)
