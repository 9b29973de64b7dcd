"""Each operator against brute force on small cases: nulls, empty and long texts, ties, repeated rows, empty tables, extra columns."""

from __future__ import annotations

import hashlib
import json
import re
import zlib
from collections import defaultdict

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from sepkey.llm import chat, common, cotraining, decontaminate, fuzzy_lines, grouping, media, near_dup, packing, prefix_tokens, queries, sharding, toxicity, trees

SMALL = "/root/testdata/sf0.001"

WORD_BPE = public_tokenizers.path("word_bpe_49k.json")
BYTE_BPE = public_tokenizers.path("byte_bpe_50k.json")
LINE = "the quick brown fox jumps over the lazy dog and runs far away from here"
LONG = " ".join(f"w{i}" for i in range(3000))
TEXTS = [None, "", " ", "one", "two words", LINE, LINE + "\n" + LINE.upper(), LINE, LONG, LONG + " more", "É́ ½ <|endoftext|> don't 中文 😀", "x" * 5000, "a\n\nb\n" + LINE]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", "s", 1, "clash") for i, t in enumerate(TEXTS)] + [(None, LINE, None, None, None, None), (5, LINE, "en", "s", 1, "clash")]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, node string")


@pytest.fixture(scope="module")
def none(docs):
    return docs.where("false")


# -- prefix token counts


def test_prefix_counts_equal_the_library(spark, docs, none):
    library, own = Tokenizer.from_file(WORD_BPE), prefix_tokens.TokenCounter(WORD_BPE)
    rng = np.random.default_rng(1)
    letters = list("abcthe nsi's 'RE'll 12 ÀéÉßçü \n\t !?.,-_—“”ΣσςİÍé 　中文字あいう한국어😀\x00\x1c\x85नमस्ते")
    for _ in range(300):
        text = "".join(rng.choice(letters, rng.integers(0, 40))) + rng.choice(["", "<|endoftext|>", "don't", "O'REILLY'S"])
        want = [len(library.encode(text[:i], add_special_tokens=False).ids) for i in range(len(text) + 1)]
        assert own.prefix_counts(text).tolist() == want, text
        assert own.count(text) == want[-1]
        assert want[own.fits(text, 3)] <= 3
    assert own.prefix_counts("y" * 400)[-1] == len(library.encode("y" * 400).ids)
    got = {(r.doc_id, r.n_bytes, r.n_tokens, r.over_limit) for r in prefix_tokens.token_counts(docs, WORD_BPE, 2048).collect()}
    assert got == {(r.doc_id, len(t.encode()), n := len(library.encode(t, add_special_tokens=False).ids), n > 2048) for r in docs.collect() for t in [r.text or ""]}
    tables = prefix_tokens.token_counts(docs.where("doc_id = 10"), WORD_BPE, 2048, tables=True).first()
    assert np.frombuffer(tables.prefix_counts, "<u4").tolist() == own.prefix_counts(TEXTS[10]).tolist()
    for r in prefix_tokens.truncate(docs.where("doc_id in (0, 5, 8, 10)"), WORD_BPE, 7).collect():
        assert r.n_tokens == len(library.encode(r.text, add_special_tokens=False).ids) <= 7
    assert prefix_tokens.token_counts(none, WORD_BPE, 9).isEmpty()


# -- packing


def test_packing_places_every_id_once(spark, docs, none):
    library = Tokenizer.from_file(BYTE_BPE)
    got = packing.pack(packing.pieces(docs, BYTE_BPE, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)).collect()
    want = defaultdict(int)
    for r in docs.collect():
        ids = np.array([*library.encode(r.text or "", add_special_tokens=False).ids, 0], "<u4")
        for a in range(0, len(ids), 1024):
            want[r.doc_id, a, len(ids[a : a + 1024]), zlib.crc32(ids[a : a + 1024].tobytes()), len(ids)] += 1
    have = defaultdict(int)
    for r in got:
        have[r.doc_id, r.start, r.length, r.ids_crc32, r.doc_tokens] += 1
    assert have == want
    by = defaultdict(list)
    for r in got:
        by[r.sequence_id].append((r.offset, r.length))
    for x in by.values():
        at = 0
        for offset, length in sorted(x):
            assert offset == at
            at += length
        assert at <= 1024
    assert packing.pack(packing.pieces(none, BYTE_BPE)).isEmpty()


def test_patterns_equal_piece_by_piece_packing():
    rng = np.random.default_rng(3)
    for cap in (16, 64):
        lengths = sorted(rng.integers(1, cap + 1, 300).tolist(), reverse=True)
        rooms: list[int] = []
        for x in lengths:
            best = max(range(len(rooms)), key=lambda i: rooms[i], default=None)
            if best is not None and rooms[best] >= x:
                rooms[best] -= x
            else:
                rooms.append(cap - x)
        hist = {x: lengths.count(x) for x in set(lengths)}
        found = packing.patterns(hist, cap)
        assert sum(c for c, _ in found) == len(rooms)
        assert all(sum(a * k for a, k in p) <= cap for _, p in found)
        used = defaultdict(int)
        for length, lo, hi, _, _ in packing.slots(found):
            used[length] += hi - lo + 1
        assert used == hist
    assert sum(c for c, _ in packing.patterns({100: 1000}, 1024)) == 100


def test_sequences_hold_the_ids(spark, docs):
    some = docs.where("doc_id in (3, 5)").dropDuplicates(["doc_id"])
    packed = packing.pack(packing.pieces(some, BYTE_BPE, keep_ids=True))
    row = packing.sequences(packed).first()
    assert len(row.ids) == 1024 and row.n_ids == packed.agg(F.sum("length")).first()[0] and set(row.ids[row.n_ids :]) <= {0}


# -- sharding


def test_shards_fit_and_split_no_more_than_needed(spark, docs, none):
    got = sharding.assign(docs.drop("node"), 6000).collect()
    size = defaultdict(int)
    for r in got:
        size[r.depth, r.prefix, r.page] += r.n_bytes
    assert len(got) == docs.count()
    for r in got:
        assert size[r.depth, r.prefix, r.page] == r.shard_bytes
        assert r.shard_bytes <= 6000 or r.shard_docs == 1
    rows = {r.doc_id: int(hashlib.md5(str(r.doc_id if r.doc_id is not None else "").encode()).hexdigest()[:15], 16) for r in got}
    for r in got:  # the bucket one bit shorter had to be split
        if r.depth:
            mates = [x for x in got if rows[x.doc_id] >> (61 - r.depth) == r.prefix >> 1]
            assert sum(x.n_bytes for x in mates) > 6000
    assert sharding.assign(none, 100).isEmpty()


def test_one_key_beyond_the_limit_gets_pages(spark):
    df = spark.createDataFrame([(7, "y" * 50)] * 40 + [(i, "z" * 30) for i in range(10)], "doc_id long, text string").repartition(4)
    got = sharding.assign(df, 300).collect()
    assert len(got) == 50 and all(r.shard_bytes <= 300 for r in got)
    assert len({r.page for r in got if r.doc_id == 7}) > 1


# -- fuzzy lines


def _brute_lines(rows):
    split = re.compile(r"[\x00-\x2f\x3a-\x60\x7b-\x7f]+")
    nodes, occ = {}, []
    for i, t in rows:
        for k, line in enumerate((t or "").split("\n")):
            w = [x for x in split.split(line.lower()) if x]
            if i is not None and w:
                nodes[" ".join(w)] = w
                occ.append((i, k, " ".join(w)))
    names = list(nodes)
    root = list(range(len(names)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(names)):
        for j in range(i):
            a, b = names[i], names[j]
            if 5 * min(len(a), len(b)) >= 4 * max(len(a), len(b)) and _edits(a, b) <= max(len(a), len(b)) * 20 // 100:
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    at = {n: find(i) for i, n in enumerate(names)}
    first = {}
    for i, k, n in occ:
        first[at[n]] = min(first.get(at[n], (i, k)), (i, k))
    gone = defaultdict(set)
    for i, k, n in occ:
        if first[at[n]] != (i, k):
            gone[i].add(k)
    return {k: sorted(v) for k, v in gone.items()}


def _edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def test_fuzzy_lines_equal_brute_force(spark, docs, none):
    base = [f"word{i}" for i in range(120)]
    near = [" ".join(base[:k] + [f"other{k}"] + base[k + 1 :]) for k in range(0, 120, 5)]
    extra = [(100 + i, f"intro {i} goes here\n{line}\n\n!!") for i, line in enumerate(near)]
    more = spark.createDataFrame([(i, t) for i, t in extra], "doc_id long, text string")
    both = docs.where("not (doc_id = 11) or doc_id is null").select("doc_id", "text").unionByName(more)
    rows = [(r.doc_id, r.text) for r in both.dropDuplicates().collect()]
    want = _brute_lines(rows)
    got = {r.doc_id: list(r.gone) for r in fuzzy_lines.decide(both).collect()}
    assert got == want
    assert any(i >= 100 for i in want)
    kept = {r.doc_id: r for r in fuzzy_lines.dedup(docs).collect()}
    assert kept[0].text is None and kept[12].text == "a\n\nb" and kept[12].n_chars == 4 and kept[12].node == "clash"
    assert 7 not in kept and None in kept and 5 in kept  # 7 holds nothing but a line of 5
    assert fuzzy_lines.dedup(none).isEmpty()


# -- near duplicates


def _sets(rows):
    out = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")))
        out[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} or ({tuple(w)} if w else set())
    return out


def _brute_groups(sets, percent):
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in sets:
        for j in sets:
            if j < i and sets[i] and sets[j]:
                both = len(sets[i] & sets[j])
                if 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
                    a, b = find(i), find(j)
                    root[max(a, b)] = min(a, b)
    return {i: find(i) for i in sets}


def test_near_duplicates_equal_brute_force(spark, docs, none):
    rng = np.random.default_rng(5)
    base = [f"t{x}" for x in rng.integers(0, 400, 150)]
    rows = [(r.doc_id, r.text) for r in docs.where("doc_id is not null").dropDuplicates(["doc_id"]).collect()]
    for i in range(60):  # a large group around the threshold, some links only through others
        words = list(base)
        for at in rng.integers(0, 150, rng.integers(0, 7)):
            words[at] = f"n{i}_{at}"
        rows.append((200 + i, " ".join(words)))
    df = spark.createDataFrame(rows + [(None, LINE), rows[5]], "doc_id long, text string").repartition(3)
    for percent in (85, 80):
        sets = _sets(rows)
        want = _brute_groups(sets, percent)
        got = near_dup.near_duplicates(df, percent).collect()
        assert len(got) == len(rows) + 2
        for r in got:
            if r.doc_id is None:
                assert r.component_id is None and r.kept
            else:
                assert (r.n_shingles, r.component_id, r.kept) == (len(sets[r.doc_id]), want[r.doc_id], want[r.doc_id] == r.doc_id)
    stay = near_dup.keep_one(df, 85).select("doc_id").collect()
    want = _brute_groups(_sets(rows), 85)
    assert sorted(r.doc_id for r in stay if r.doc_id is not None) == sorted(i for i in want if want[i] == i)
    assert near_dup.near_duplicates(none).isEmpty()


def test_super_minhash_estimates_similarity_and_ignores_order():
    rng = np.random.default_rng(7)
    pool = rng.integers(0, 2**63, 900).astype(np.uint64)
    a, b = np.sort(pool[:600]), np.sort(pool[300:900])
    one = near_dup.super_minhash(np.concatenate([a, b, a[::-1], a[:1]]), np.array([0, 600, 1200, 1800, 1801]), 256)
    assert (one[0] == one[2]).all() and (one < np.uint64(2**63)).all()
    assert abs((one[0] == one[1]).mean() - 1 / 3) < 5 * np.sqrt(2 / 9 / 256)
    assert len(np.unique(one[3] >> np.uint64(32))) == 256  # one element offers each place at another step
    for t in (0.8, 0.85):
        bands, rows = near_dup.bands_for(t)
        assert bands * rows <= 256 and (1 - t**rows) ** bands < 1e-8


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(50)] + [(100, x) for x in range(101, 140)] + [(300, 200), (200, 250)]
    df = spark.createDataFrame(edges, "a long, b long")
    for native in (False, True):
        got = {r.node: r.root for r in grouping.components(df, native).collect()}
        assert all(got[i] == 0 for i in range(51)) and all(got[i] == 100 for i in range(100, 140)) and {got[200], got[250], got[300]} == {200}


# -- benchmark decontamination


def test_decontamination_equals_brute_force(spark, docs, none):
    words = [f"b{i}" for i in range(30)]
    items = spark.createDataFrame([(1, " ".join(words[:25])), (2, "Short Item"), (3, None), (4, "?!"), (5, " ".join(words[5:20]))], "item_id long, text string")
    extra = [(50, "pre " + ", ".join(words[3:16]).upper() + "! post"), (51, "short item"), (52, "shortitem short"), (53, " ".join(words[:9]))]
    df = docs.select("doc_id", "text", "lang").unionByName(spark.createDataFrame([(i, t, "x") for i, t in extra], "doc_id long, text string, lang string"))
    windows = {r.item_id: decontaminate.windows_of(r.text) for r in items.collect()}
    got = decontaminate.find_contamination(df, items, block_bytes=20).collect()
    for r, source in zip(sorted(got, key=lambda r: (r.doc_id is None, r.doc_id or 0)), sorted(df.collect(), key=lambda r: (r.doc_id is None, r.doc_id or 0)), strict=True):
        w = decontaminate.words_of(source.text)
        hit, found = set(), set()
        for item, ws in windows.items():
            for x in ws:
                for k in range(len(w) - len(x) + 1):
                    if tuple(w[k : k + len(x)]) == x:
                        hit |= set(range(k, k + len(x)))
                        found.add(str(item))
        assert (r.n_words, r.n_hit, r["items"]) == (len(w), len(hit), sorted(found))
        raw = (source.text or "").encode()
        assert sum(len(decontaminate.words_of(raw[s.start : s.end].decode())) for s in r.spans) == len(hit)
    assert {r.doc_id for r in decontaminate.clean(df, items).collect()} == {r.doc_id for r in got if not r.n_hit}
    assert decontaminate.find_contamination(none, items).isEmpty()
    assert decontaminate.clean(df, items.where("false")).count() == df.count()


# -- media


def test_png_round_trip_filters_and_damage():
    rng = np.random.default_rng(2)
    for shape in ((1, 192), (7, 64, 3), (5, 9, 4), (40, 33), (6, 5, 2)):
        pixels = rng.integers(0, 256, shape).astype(np.uint8)
        for kind in range(5):
            stored = media.write_png(pixels, row_filter=kind)
            assert (media.read_png(stored) == pixels).all()
            for broken in (stored[:-5], stored[:40] + bytes([stored[40] ^ 1]) + stored[41:], b"x" + stored[1:]):
                with pytest.raises(media.BadImage):
                    media.read_png(broken)
    smooth = np.kron(rng.integers(20, 235, (8, 8)), np.ones((8, 12))).astype(np.uint8)
    noisy = np.clip(smooth.astype(int) + rng.integers(-3, 4, smooth.shape), 0, 255).astype(np.uint8)
    near = (int(media.spectrum_hash(smooth), 16) ^ int(media.spectrum_hash(noisy), 16)).bit_count()
    far = (int(media.spectrum_hash(smooth), 16) ^ int(media.spectrum_hash(rng.integers(0, 256, smooth.shape).astype(np.uint8)), 16)).bit_count()
    assert near < far


def test_documents_as_media(spark, docs, none):
    for r, source in zip(media.documents_as_media(docs).collect(), docs.collect(), strict=True):
        raw = (source.text or "").encode()
        payload = raw.ljust(max(1, -(-len(raw) // 192)) * 192, b" ")
        assert media.read_png(r.media).tobytes() == payload
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]))
        assert (r.media_bytes, r.media_sha256) == (len(r.media), hashlib.sha256(r.media).hexdigest())
    assert media.documents_as_media(none).isEmpty()


# -- chat trees


def test_trees_are_enumerated_ranked_and_read_back(spark):
    rows = [(1, 1, None, "user", "hi", 0.0), (1, 2, 1, "assistant", "a", 1.0), (1, 3, 1, "assistant", "b\n<|im_end|>\\n<\\|", 5.0), (1, 4, 3, "us\ner", None, None), (1, 5, 4, "assistant", "d", 1.0), (1, 6, 4, None, "e", 1.0), (1, 7, 8, "user", "cycle", 0.0), (1, 8, 7, "user", "cycle", 0.0), (2, 1, 99, "user", "orphan", 0.0), (None, 1, None, "user", "x", 0.0), (2, None, 1, "user", "x", 0.0)]
    tree = spark.createDataFrame(rows + rows[:2], "tree_id long, node_id long, parent_id long, role string, text string, score double")
    got = {(r.tree_id, r.rank): (r.total, chat.parse(r.formatted), chat.digest(r.formatted, [(x.start, x.end) for x in r.loss])) for r in chat.format_trees(tree).collect()}
    assert {k: [t for _, t in v[1]] for k, v in got.items()} == {(1, 1): ["hi", rows[2][4], "", "d"], (1, 2): ["hi", rows[2][4], "", "e"], (1, 3): ["hi", "a"], (2, 1): ["orphan"]}
    assert got[1, 1][1][2][0] == "us\ner" and got[1, 1][0] == 6.0
    assert got[1, 1][2][2] == len(rows[2][4] + "d")
    assert {(r.tree_id, r.rank) for r in chat.format_trees(tree, top=1).collect()} == {(1, 1), (2, 1)}
    assert chat.format_trees(tree.where("false")).isEmpty()


def test_long_threads_and_ties(spark):
    rows = [(1, t // 2, "user" if t % 4 < 2 else "assistant", f"m{t}") for t in range(600)] + [(None, 0, "user", "x"), (2, None, None, None)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r.tree_id: chat.parse(r.formatted) for r in chat.format_trees(chat.turns_as_tree(df)).collect()}
    assert got[1] == [(r, t) for _, _, r, t in sorted(rows[:600], key=lambda x: (x[1], x[2], x[3]))] and got[2] == [("", "")] and set(got) == {1, 2}


def test_op2_contract(spark):
    said = "<|im_end|><|im_start|>assistant ok"
    row = queries.op2_chat_trees(spark, SMALL).where("conv_id = -1").first()
    assert (row.n_turns, row.loss_chars) == (2, len(said))
    assert row.turns_sha256 == hashlib.sha256(f"user\n{said}\nassistant\n{said}\n".encode()).hexdigest()
    assert row.loss_sha256 == hashlib.sha256(said.encode()).hexdigest()


# -- learners


def test_isotonic_and_trees():
    x, y = np.array([1.0, 2, 3, 4, 5, 6]), np.array([0.0, 1, 0, 1, 1, 1])
    knots, values = trees.isotonic(x, y)
    assert (np.diff(values) > 0).all() and np.isclose(np.interp(2.5, knots, values), 0.5)
    rng = np.random.default_rng(4)
    data = rng.random((800, 4))
    label = ((data[:, 0] > 0.5) ^ (data[:, 1] > 0.5)).astype(float)
    raw = trees.BoostedTrees(60, 3).fit(data[:600], label[:600]).raw(data[600:])
    assert ((raw > 0) == label[600:]).mean() > 0.93


def test_toxicity_on_held_out_rows(spark):
    from tests.llm.measures_of_rank import auc

    got = {r.doc_id: r for r in queries.op7_toxicity_trees(spark, "/root/testdata/sf0.01").collect()}
    labels = {r.doc_id: r.toxic for r in common.table(spark, "/root/testdata/sf0.01", "labels").collect()}
    held = [(got[i].score, y) for i, y in labels.items() if got[i].held_out]
    assert all(got[i].held_out == (zlib.crc32(str(i).encode()) % 5 == 0) for i in labels)
    assert auc(held) > 0.85 and all((r.score >= 0.5) == (r.predicted == 1) and 0 <= r.score <= 1 for r in got.values())


def test_toxicity_edges(spark, docs, none):
    labels = spark.createDataFrame([(i, i % 2) for i in range(12)] + [(None, 1), (3, None), (3, 0)], "doc_id long, toxic long")
    model = toxicity.fit(docs, labels)
    scores = toxicity.score(docs, model).collect()
    assert len(scores) == docs.count() and all(0 <= r.score <= 1 for r in scores)
    assert {r.doc_id: r.score for r in scores}[5] == {r.doc_id: r.score for r in scores}[7]
    assert toxicity.reject(docs, model, 2.0).count() == docs.count()
    empty = toxicity.fit(docs, labels.where("false"))
    assert {r.score for r in toxicity.score(docs, empty).collect()} == {0.0} and toxicity.score(none, empty).isEmpty()


def test_cotraining_on_held_out_rows(spark, docs, none):
    from tests.llm.measures_of_rank import auc

    got = {r.doc_id: r for r in queries.op1_cotrained_quality(spark, "/root/testdata/sf0.01").collect()}
    labels = {r.doc_id: r.quality for r in common.table(spark, "/root/testdata/sf0.01", "labels").collect()}
    held = [i for i in labels if zlib.crc32(str(i).encode()) % 5 == 0]
    assert auc([(got[i].score, labels[i]) for i in held]) > 0.95
    good = [i for i in held if labels[i]]
    assert sum(got[i].keep for i in good) >= 0.95 * len(good)
    few = spark.createDataFrame([(i, i % 2) for i in range(12)] + [(None, 1), (3, None)], "doc_id long, quality long")
    rows = cotraining.classify(docs, few).collect()
    assert len(rows) == docs.count() and all(0 <= r.score <= 1 for r in rows)
    assert {r.score for r in cotraining.classify(docs, few.where("false")).collect()} == {0.5}
    assert cotraining.classify(none, few).isEmpty()


def test_vocabularies_stay_outside_the_repository():
    with open(WORD_BPE, encoding="utf-8") as f:
        assert json.load(f)["model"]["end_of_word_suffix"] == "</w>"
