"""Inputs on which simpler code breaks: very long runs, algebraic hash collisions, clashing names, empty batches."""

from __future__ import annotations

import random

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from sepkey.llm import common, cotraining, decontaminate, media, near_dup, packing, prefix_tokens, toxicity

BYTE_BPE = public_tokenizers.path("byte_bpe_50k.json")


def _thue_morse(n):
    word = "a"
    for _ in range(n):
        word = "".join("ab" if c == "a" else "ba" for c in word)
    return word


def test_hashes_of_runs_have_no_algebraic_collisions(spark):
    words = []
    for n in range(4, 13):
        word = _thue_morse(n)
        words += [word, word.translate(str.maketrans("ab", "ba"))]
    words += ["", "x", "xx", "x" * 255, "x" * 256, "x" * 257, "\0", "\0\0", "abcdefgh", "abcdefghi"]
    data = np.frombuffer("".join(words).encode(), np.uint8)
    end = np.cumsum([len(w) for w in words])
    hashes = common.run_hashes(data, end - [len(w) for w in words], end)
    assert len(set(hashes.tolist())) == len(words)
    twice = common.run_hashes(np.concatenate([data[3:], data]), np.array([len(data) - 3]), np.array([len(data) + 13]))
    assert twice[0] == common.run_hashes(data, np.array([0]), np.array([16]))[0]  # the place does not matter
    docs = spark.createDataFrame([(1, _thue_morse(11)), (2, _thue_morse(11).translate(str.maketrans("ab", "ba")))], "doc_id long, text string")
    assert all(r.kept for r in near_dup.near_duplicates(docs).collect())


@pytest.mark.parametrize("blanks", [1_000_000, 2_000_000])
def test_very_long_runs_are_packed(spark, blanks):
    docs = spark.createDataFrame([(1, " " * blanks), (2, "a b")], "doc_id long, text string")
    rows = packing.pack(packing.pieces(docs, BYTE_BPE, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)).collect()
    want = len(Tokenizer.from_file(BYTE_BPE).encode(" " * blanks, add_special_tokens=False).ids) + 1
    assert sum(r.length for r in rows if r.doc_id == 1) == want == max(r.doc_tokens for r in rows)


def test_large_sets_are_compared_whole(spark, monkeypatch):
    """Many sets in one bucket, in blocks of few shingles each: links at the threshold, none lost, none made up."""
    monkeypatch.setattr(near_dup, "BLOCK_SHINGLES", 3000)
    rng = random.Random(4)
    base = [f"w{rng.randrange(10**6)}" for _ in range(700)]
    rows = []
    for i in range(30):
        words = list(base)
        for at in range(i * 4, i * 4 + 4):
            words[at * 5] = f"n{i}_{at}"
        rows.append((i, " ".join(words)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    sets = {i: {tuple(t.split()[k : k + 5]) for k in range(696)} for i, t in rows}
    linked = all(any(100 * len(sets[i] & sets[j]) >= 85 * len(sets[i] | sets[j]) for j in range(30) if j != i) for i in range(30))
    got = {r.component_id for r in near_dup.near_duplicates(docs).collect()}
    assert linked and got == {0}


def test_clashing_names_pass_through_the_stages(spark):
    names = ["drop_id", "row", "rows", "kept", "gone", "bucket", "node", "n_words", "items", "score", "x"]
    schema = "doc_id long, text string, " + ", ".join(f"{n} string" for n in names)
    text = "the quick brown fox jumps over the lazy dog and runs far away from here"
    docs = spark.createDataFrame([(i, t, *names) for i, t in ((1, text), (2, text), (2, text), (3, "other words"), (None, text), (4, None))], schema)
    items = spark.createDataFrame([(1, "one two three four five six seven eight nine ten eleven")], "item_id long, text string")
    labels = spark.createDataFrame([(1, 0), (3, 1)], "doc_id long, toxic int")
    for out, ids in ((near_dup.keep_one(docs), [1, 3, 4]), (decontaminate.clean(docs, items), [1, 2, 2, 3, 4]), (toxicity.reject(docs, toxicity.fit(docs, labels)), None)):
        assert out.columns == docs.columns
        rows = out.collect()
        assert all(list(r)[2:] == names for r in rows)
        assert ids is None or sorted(r.doc_id for r in rows if r.doc_id) == ids
    assert near_dup.keep_one(docs.where("false")).isEmpty()


def test_stored_images_use_the_row_filters():
    rng = np.random.default_rng(2)
    for shape in ((40, 192), (7, 5, 3), (3, 2, 2), (1, 1), (2, 3, 4)):
        pixels = np.cumsum(rng.integers(0, 4, shape), axis=0).astype(np.uint8)
        assert (media.read_png(media.write_png(pixels)) == pixels).all()
    texts = [b"", b"short", bytes(rng.integers(97, 123, 4000).astype(np.uint8)), b"line of text\n" * 400]
    stored = media.texts_as_png(texts)
    assert {int(k) for m in stored for k in media._stream(m)[0][:, 0]} >= {1, 2, 3}
    for text, pixels, one in zip(texts, media.read_many(stored), stored, strict=True):
        assert pixels.tobytes() == text.ljust(max(1, -(-len(text) // 192)) * 192, b" ")
        assert one == media.texts_as_png([text])[0]  # neighbours in a batch do not matter
    assert media.texts_as_png([]) == media.read_many([]) == []


def _corpus(rng):
    """Sources are good or bad; labels come from few of them; half of the texts tell nothing."""
    rows, labels = [], []
    for i in range(1600):
        source = rng.randrange(40)
        good = source % 2
        words = [f"w{rng.randrange(400)}" for _ in range(60)] if good else ["spam"] * 20 + [f"w{rng.randrange(20)}" for _ in range(40)]
        plain = i % 2
        if plain:
            words = [f"w{rng.randrange(60)}" for _ in range(60)]
        rows.append((i, " ".join(words), f"source{source}", "en", 300, good, plain))
        if source < 8:
            labels.append((i, good))
    return rows, labels


def test_exchange_of_labels_helps_the_metadata(spark):
    rows, labels = _corpus(random.Random(9))
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, lang string, n_chars long, good long, plain long")
    known = spark.createDataFrame(labels, "doc_id long, quality long")
    seen = common.durable(cotraining.views(docs))
    right = []
    for rounds in (0, 3):
        got = cotraining.score(seen, cotraining.fit(seen, known, rounds)).join(docs.select("doc_id", "good", "plain", "source"), "doc_id")
        hard = got.where("plain = 1 and cast(substr(source, 7) as int) >= 8")
        right.append(hard.agg(F.avg(((F.col("score") >= 0.5).cast("long") == F.col("good")).cast("double"))).first()[0])
    assert right[1] > right[0] + 0.2 and right[1] > 0.9


def test_views_share_no_input(spark):
    texts = common.texts_of(__import__("pyarrow").array(["a text", "another text with lines\nand marks!"]))
    assert cotraining.text_view(texts).shape == (2, len(cotraining.TEXT))
    meta = cotraining.meta_view(["a", None], ["en", None], np.array([5.0, np.nan]))
    assert meta.shape == (2, len(cotraining.META)) and not meta[1].any() and meta[0].all()
    many = cotraining._name([f"source{i}" for i in range(3000)])
    assert len(set(many.tolist())) > 2900


def test_prefix_counts_of_odd_chunks_equal_the_library():
    path = public_tokenizers.path("word_bpe_49k.json")
    library, tokens = Tokenizer.from_file(path), prefix_tokens.TokenCounter(path)
    rng = random.Random(3)
    alphabet = [*"abcXYZ'’s't½½12é#-_", "é", "́", "ᄀ", "ᅡ", "한", "中文", "😀", "‍", "<|endoftext|>", "<|", "|>", "ſ", "İ", "ß", "Σ", "ﬁ"]
    for _ in range(300):
        text = "".join(rng.choice(alphabet) for _ in range(rng.randint(1, 25)))
        want = [len(library.encode(text[:i], add_special_tokens=False).ids) for i in range(len(text) + 1)]
        assert tokens.prefix_counts(text).tolist() == want
    long = "éabc1" * 4000  # not in normal form, and one chunk
    assert tokens.prefix_counts(long)[-1] == len(library.encode(long, add_special_tokens=False).ids)


def test_of_texts_under_one_doc_id_the_same_one_is_learned_from(spark):
    docs = spark.createDataFrame([(1, "first text"), (1, "second text"), (2, "clean")], "doc_id long, text string")
    labels = spark.createDataFrame([(1, 1), (2, 0)], "doc_id long, toxic int")
    seen = {tuple(sorted(r.text for r in toxicity._sample(docs.orderBy("text", ascending=up).coalesce(1), labels).collect())) for up in (True, False)}
    assert len(seen) == 1
