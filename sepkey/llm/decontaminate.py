"""Benchmark decontamination with one Aho-Corasick automaton.

Words are runs of digits, ASCII letters (folded to lower case) and all characters beyond ASCII. A benchmark item gives its windows of
``window`` consecutive words (a shorter item is one window). All windows of all items go into one automaton, each as its words with one
blank around each; a document is folded in the same way, scanned once, and every occurrence is carried back through the word table to
byte offsets of the original text.

The benchmark is the query set. Its windows reach the executors by broadcast, in blocks of at most ``block_bytes`` of item text, so that
an automaton has a bounded size; a benchmark of one block, the usual case, is one scan. Documents are never shuffled.

Null and empty texts have no words; repeated rows and items count each; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
import sys
import uuid

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

WINDOW = 10
#: Item text of one automaton: a window of ten words lies at each word, so that an automaton holds some ten times as many nodes as bytes of text.
BLOCK_BYTES = 2 << 20
#: Fixed value: the bytes of words once A-Z are folded (in UTF-8, all bytes from 0x80 belong to characters beyond ASCII).
_INSIDE = common.byte_class(lambda b: 48 <= b <= 57 or 65 <= b <= 90 or 97 <= b <= 122 or b >= 128)
_WORD = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
_FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words_of(text: str | None) -> list[str]:
    return _WORD.findall((text or "").translate(_FOLD))


def windows_of(text: str | None, window: int = WINDOW) -> set[tuple[str, ...]]:
    words = words_of(text)
    return {tuple(words[i : i + window]) for i in range(max(1, len(words) - window + 1))} if words else set()


def build_automaton(items: list[tuple[str, str]], window: int = WINDOW):
    """items: (item id as text, text). Bytes are held as Latin-1 characters, one for one. A match gives its number of words and
    the items that have the window."""
    found: dict[str, tuple[int, list[str]]] = {}
    for item, text in items:
        for words in windows_of(text, window):
            key = " " + " ".join(words) + " "
            found.setdefault(key.encode().decode("latin-1"), (len(words), []))[1].append(item)
    automaton = ahocorasick.Automaton()
    for key, (n, ids) in found.items():
        automaton.add_word(key, (n, tuple(dict.fromkeys(ids))))
    if found:
        automaton.make_automaton()
    return automaton if found else None


def folded(texts: common.Texts, words: common.Words) -> tuple[str, np.ndarray]:
    """All rows as one string, each a bar, a blank, and its words with a blank after each; and for each word the place of that blank."""
    sizes = words.end - words.start
    place = np.concatenate([[0], np.cumsum(sizes + 1)])
    row = np.repeat(np.arange(len(texts)), words.counts())
    first = place[:-1] + 2 * (row + 1)
    out = np.full(place[-1] + 2 * len(texts), 32, np.uint8)
    out[place[words.first[:-1]] + 2 * np.arange(len(texts))] = 124
    skipped = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    out[np.repeat(first - skipped, sizes) + np.arange(int(sizes.sum()))] = common.LOWER[texts.data[_INSIDE[texts.data]]]
    return out.tobytes().decode("latin-1"), first + sizes


def hits(texts: common.Texts, automata: list) -> tuple[common.Words, np.ndarray, list[set]]:
    """The rows' words, which of them are hit, and the items found in each row."""
    words = common.Words(texts, _INSIDE)
    cover = np.zeros(len(words.start) + 1, np.int32)
    items: list[set] = [set() for _ in range(len(texts))]
    if len(words.start):
        text, ends = folded(texts, words)
        for automaton in automata:
            found = list(automaton.iter(text))
            if not found:
                continue
            last = np.searchsorted(ends, np.array([at for at, _ in found]))
            rows = np.searchsorted(words.first, last, "right") - 1
            sizes = np.array([x[0] for _, x in found])
            np.add.at(cover, last - sizes + 1, 1)
            np.add.at(cover, last + 1, -1)
            for r, (_, (_, ids)) in zip(rows.tolist(), found, strict=True):
                items[r].update(ids)
    return words, np.cumsum(cover[:-1]) > 0, items


def _broadcast_items(items: DataFrame, block_bytes: int) -> list[list[tuple[str, str]]]:
    """Blocks of the benchmark. It is the query set: what is held by the driver grows with it, not with the corpus."""
    blocks: list[list[tuple[str, str]]] = [[]]
    size = 0
    for r in items.select(F.col("item_id").cast("string").alias("item_id"), "text").where("text is not null").toLocalIterator():
        size += len(r.text)
        if size > block_bytes and blocks[-1]:
            blocks.append([])
            size = len(r.text)
        blocks[-1].append((r.item_id if r.item_id is not None else "", r.text))
    return blocks


def find_contamination(docs: DataFrame, items: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row for each row of ``docs``: doc_id, n_words, n_hit, items (sorted as strings), and ``spans``, the byte ranges [start, end) of
    the original text that the hit runs of words take."""
    sent, key = docs.sparkSession.sparkContext.broadcast(_broadcast_items(items, block_bytes)), uuid.uuid4().hex

    def run(batches):
        automata = _automata(key, sent, window)
        for batch in batches:
            for part, texts in common.steps(batch):
                words, hit, found = hits(texts, automata)
                row = np.repeat(np.arange(len(texts)), words.counts())
                n_hit = np.bincount(row[hit], minlength=len(texts))
                spans = [[] for _ in range(len(texts))]
                at = np.flatnonzero(hit)
                if len(at):
                    breaks = np.flatnonzero((np.diff(at) > 1) | (np.diff(row[at]) > 0)) + 1
                    for run_of in np.split(at, breaks):
                        r = row[run_of[0]]
                        base = texts.at[r]
                        spans[r].append({"start": int(words.start[run_of[0]] - base), "end": int(words.end[run_of[-1]] - base)})
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(words.counts()), pa.array(n_hit), pa.array([sorted(x) for x in found], pa.list_(pa.string())), pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))], ["doc_id", "n_words", "n_hit", "items", "spans"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return common.map_arrow(docs.select("doc_id", "text"), run, f"doc_id {kind}, n_words long, n_hit long, items array<string>, spans array<struct<start: long, end: long>>")


def _automata(key: str, sent, window: int) -> list:
    """Built once in each Python worker, which serves many tasks; those of an earlier run go."""
    kept = sys.__dict__.setdefault("_sepkey_automata", {})
    if key not in kept:
        kept.clear()
        kept[key] = [a for b in sent.value if (a := build_automaton(b, window))]
    return kept[key]


def items_digest(items) -> str:
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()


def clean(docs: DataFrame, items: DataFrame, share: float = 0.0, window: int = WINDOW) -> DataFrame:
    """The rows of ``docs`` whose hit share of words is at most ``share`` (0: no window of the benchmark occurs), all columns kept.

    The test runs beside the rows in one pass: nothing is joined back."""
    sent, key = docs.sparkSession.sparkContext.broadcast(_broadcast_items(items, BLOCK_BYTES)), uuid.uuid4().hex

    def run(batches):
        automata = _automata(key, sent, window)
        for batch in batches:
            for part, texts in common.steps(batch):
                words, hit, _ = hits(texts, automata)
                total = np.concatenate([[0], np.cumsum(hit)])
                n_hit = np.diff(total[words.first])
                yield part.filter(pa.array(n_hit <= share * words.counts()))

    return common.map_arrow(docs, run, docs.schema)
