"""Quality classifier by co-training.

Two views of a document see different evidence: its *text* (how its words repeat, vary and look, its lines and marks) and its *page metadata*
(source, language, both together, and the length that the page states in ``n_chars``; nothing of the text). Each view has a naive Bayes classifier over binned features, so that learning is counting:
one pass over all rows, summed before anything reaches the driver, whatever the number of rows. Names are counted by a 16-bit hash each, so that
thousands of sources keep counts of their own.

1. Both views learn from the labelled rows.
2. In each round the rows without a label that one view is sure of (probability at least ``SURE`` for good or for bad) join, with half weight, the
   training counts of the *other* view; both learn anew.
3. Each view's log-odds become probabilities by isotonic regression on labelled rows kept out of the counts, through a histogram.
4. The calibrated log-odds of both are weighted by logistic regression on the same rows, and every document is scored.

Null and empty texts are documents without words; null metadata is a value of its own. Rows without doc_id are scored, never learned from. Of
several labels of one document the largest counts. Without labels of both kinds every score is the rate of good labels there are, 0.5 if none. Repeated
rows get equal scores; other columns are ignored.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .trees import isotonic

ROUNDS = 3
SURE = 0.97
BINS = 16
#: Of FOLDS parts of the labelled rows one calibrates, the others are counted.
FOLDS = 4
_GRID = 64
_SPAN = 40.0

TEXT = ["distinct_share", "repeat_share", "longest_run", "top_share", "shout_words", "title_words", "word_length", "decorated", "lone_marks", "short_words", "lines", "line_length", "marks", "bars", "exclaims", "non_ascii"]
META = ["source", "lang", "source_and_lang", "stated_length"]
#: Bins of a name, and of the stated length (four for each doubling).
NAMES, LENGTHS = 1 << 16, 128
#: Rows that a name's counts are drawn towards the rate of all rows by.
_DRAWN = 2.0

_WORD = common.byte_class(lambda b: 48 <= b <= 57 or 65 <= b <= 90 or 97 <= b <= 122 or b >= 128)
_CHUNK = common.byte_class(lambda b: b > 32)
_UPPER = common.byte_class(lambda b: 65 <= b <= 90)
_MARK = common.byte_class(lambda b: 33 <= b <= 47 or 58 <= b <= 64 or 91 <= b <= 96 or 123 <= b <= 126)


def _share(x: np.ndarray) -> np.ndarray:
    """Bins of a share, finer near 0 and near 1."""
    x = np.clip(x, 0, 1)
    return np.clip(np.where(x < 0.5, np.sqrt(x / 2), 1 - np.sqrt((1 - x) / 2)) * BINS, 0, BINS - 1).astype(np.uint8)


def _size(x: np.ndarray) -> np.ndarray:
    return np.clip(np.log2(np.asarray(x, float) + 1), 0, BINS - 1).astype(np.uint8)


def _name(values) -> np.ndarray:
    """0 for null, else the name's own bin of NAMES."""
    known: dict = {None: 0}
    for v in set(values) - {None}:
        known[v] = 1 + zlib.crc32(v.encode()) % (NAMES - 1)
    return np.array([known[v] for v in values], "<u2")


def text_view(texts: common.Texts) -> np.ndarray:
    n = len(texts)
    words = common.Words(texts, _WORD)
    count = words.counts()
    per = 1 / np.maximum(count, 1)
    row = np.repeat(np.arange(n), count)
    token = common.run_hashes(common.LOWER[texts.data], words.start, words.end)
    order = np.lexsort((token, row))
    new = np.ones(len(token), bool)
    new[1:] = (token[order][1:] != token[order][:-1]) | (row[order][1:] != row[order][:-1])
    starts = np.flatnonzero(new)
    runs = np.diff(np.append(starts, len(token)))
    top = np.zeros(n)
    if len(starts):
        np.maximum.at(top, row[order][starts], runs)
    again = np.zeros(len(token), bool)
    again[1:] = (token[1:] == token[:-1]) & (row[1:] == row[:-1])
    # length of each run of one word: from the places where a run breaks
    run = np.zeros(n)
    if len(token):
        breaks = np.flatnonzero(~again)
        np.maximum.at(run, row[breaks], np.diff(np.append(breaks, len(token))))
    upper = np.concatenate([[0], np.cumsum(_UPPER[texts.data])])
    size_of = words.end - words.start
    caps = upper[words.end] - upper[words.start]
    shout = (caps == size_of) & (size_of > 1)
    title = (caps == 1) & (size_of > 1) & _UPPER[texts.data[words.start]] if len(size_of) else shout
    # words with two or more marks right behind them
    mark = np.concatenate([_MARK[texts.data], [False, False]])
    decorated = mark[words.end] & mark[words.end + 1] if len(size_of) else shout
    # marks with no word at either side
    word = np.concatenate([[False], _WORD[texts.data], [False]])
    lone = np.concatenate([[0], np.cumsum(_MARK[texts.data] & ~word[:-2] & ~word[2:])])
    apart = np.diff(lone[texts.at])
    sums = lambda flag: np.bincount(row[flag], minlength=n) * per
    distinct = np.bincount(row[order][starts], minlength=n)
    size, lines = texts.sizes(), _rows(texts, texts.data == 10) + 1
    part = lambda flag: _share(_rows(texts, flag) / np.maximum(size, 1))
    marks = [_size(lines), _size(size / lines), part(_MARK[texts.data]), part(np.isin(texts.data, np.frombuffer(b"|<>{}[]#*", np.uint8))), part(np.isin(texts.data, np.frombuffer(b"!?", np.uint8))), part(texts.data >= 128)]
    # a few words more, half of them new, keep short texts from the extremes
    return np.stack([_share((distinct + 4) / (count + 8)), _share(sums(again)), _size(run), _share(np.maximum(top - 1, 0) / (count + 8)), _share(sums(shout)), _share(sums(title)), _size(np.bincount(row, size_of, n) * per * 4), _share(sums(decorated)), _share(apart * per / 2), _share(sums(size_of <= 2)), *marks], axis=1)


def _rows(texts: common.Texts, flag: np.ndarray) -> np.ndarray:
    return np.diff(np.concatenate([[0], np.cumsum(flag)])[texts.at])


def meta_view(source: list, lang: list, n_chars: np.ndarray) -> np.ndarray:
    """``n_chars``: doubles, NaN where null (bin 0)."""
    both = [None if a is None and b is None else f"{a}\0{b}" for a, b in zip(source, lang, strict=True)]
    length = np.clip(np.nan_to_num(4 * np.log2(np.maximum(n_chars, 0) + 1), nan=-1.0) + 1, 0, LENGTHS - 1).astype("<u2")
    return np.stack([_name(source), _name(lang), _name(both), length], axis=1)


def views(docs: DataFrame) -> DataFrame:
    """doc_id and the binned features of both views: a byte for each of the text's, two for each of the metadata's."""

    def run(batches):
        for batch in batches:
            for part, texts in common.steps(batch):
                text = text_view(texts)
                meta = meta_view(part.column(2).to_pylist(), part.column(3).to_pylist(), part.column(4).to_numpy(zero_copy_only=False).astype(float))
                both = np.concatenate([text, np.ascontiguousarray(meta).view(np.uint8)], axis=1)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([r.tobytes() for r in both], pa.binary())], ["doc_id", "x"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    columns = [F.col(c).cast(t).alias(c) if c in docs.columns else F.lit(None).cast(t).alias(c) for c, t in (("source", "string"), ("lang", "string"), ("n_chars", "double"))]
    return common.map_arrow(docs.select("doc_id", "text", *columns), run, f"doc_id {kind}, x binary")


_VIEWS = (slice(0, len(TEXT)), slice(len(TEXT), len(TEXT) + len(META)))
_SIZES = np.array([BINS] * len(TEXT) + [NAMES, NAMES, NAMES, LENGTHS])
#: Where each feature's cells begin; a cell is a feature's bin.
_AT = np.concatenate([[0], np.cumsum(_SIZES)])


class Bayes:
    """One view's naive Bayes, from weighted counts[cell, class]. ``table``: the log-odds that a cell adds."""

    def __init__(self, counts: np.ndarray, view: slice):
        self.view, tables = view, []
        own = counts[_AT[view.start] : _AT[view.start + 1]].sum(axis=0) + 1.0
        self.prior = float(np.log(own[1] / own[0]))
        for f in range(view.start, view.stop):
            cells = counts[_AT[f] : _AT[f + 1]]
            if _SIZES[f] == NAMES:  # most names are rare: their odds are drawn towards those of all rows
                cells = cells + _DRAWN * own / own.sum()
                tables.append(np.log(cells[:, 1] / cells[:, 0]) - self.prior)
            else:
                cells = cells + 0.5
                cells = cells / cells.sum(axis=0)
                tables.append(np.log(cells[:, 1] / cells[:, 0]))
        self.table = np.concatenate(tables)

    def raw(self, cell: np.ndarray) -> np.ndarray:
        own = cell[:, self.view] - _AT[self.view.start]
        return self.prior + self.table[own].sum(axis=1)


def _features(part: pa.RecordBatch) -> np.ndarray:
    """Cells, rows by features."""
    x = np.frombuffer(b"".join(part.column(0).to_pylist()), np.uint8).reshape(part.num_rows, -1)
    meta = np.ascontiguousarray(x[:, len(TEXT) :]).view("<u2")
    return np.concatenate([x[:, : len(TEXT)].astype(np.int64), meta.astype(np.int64)], axis=1) + _AT[:-1]


def _count(rows: DataFrame, models: list[Bayes] | None) -> np.ndarray:
    """Training counts[cell, class] of both views. y: 0 or 1 for rows that are learned from, else -1."""
    sent = rows.sparkSession.sparkContext.broadcast(models)
    cut = float(np.log(SURE / (1 - SURE)))

    def run(batches):
        total = np.zeros(_AT[-1] * 2)
        for batch in batches:
            if not batch.num_rows:
                continue
            x, y = _features(batch), batch.column(1).to_numpy()
            for i, view in enumerate(_VIEWS):
                cls, weight = y.copy(), np.ones(len(y))
                if sent.value is not None:
                    other = sent.value[1 - i].raw(x)
                    free = y == -1
                    cls[free & (other >= cut)] = 1
                    cls[free & (other <= -cut)] = 0
                    weight[free] = 0.5
                use = cls >= 0
                cells = x[use, view] * 2 + cls[use, None]
                total += np.bincount(cells.ravel(), np.repeat(weight[use], cells.shape[1]), len(total))
        cell = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(cell), pa.array(total[cell])], ["cell", "n"])

    found = common.map_arrow(rows.select("x", "y"), run, "cell long, n double").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()  # at most two for each cell
    out = np.zeros(_AT[-1] * 2)
    out[found.column("cell").to_numpy()] = found.column("n").to_numpy()
    return out.reshape(-1, 2)


def _logit(p):
    p = np.clip(p, 1e-3, 1 - 1e-3)
    return np.log(p / (1 - p))


class Model:
    def __init__(self, bayes: list[Bayes] | None, knots: list, weights: np.ndarray, base: float):
        self.bayes, self.knots, self.weights, self.base = bayes, knots, weights, base

    def scores(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if self.bayes is None:
            flat = np.full(len(x), self.base)
            return flat, flat, flat
        own = [np.interp(np.clip(b.raw(x), -_SPAN, _SPAN), *k) for b, k in zip(self.bayes, self.knots, strict=True)]
        z = self.weights[0] + self.weights[1] * _logit(own[0]) + self.weights[2] * _logit(own[1])
        return own[0], own[1], 1 / (1 + np.exp(-z))


def _calibrate(rows: DataFrame, bayes: list[Bayes]) -> tuple[list, np.ndarray]:
    """Isotonic knots of each view and weights of both, from a grid of raw scores by class (at most _GRID * _GRID * 2 cells)."""
    sent = rows.sparkSession.sparkContext.broadcast(bayes)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                x = _features(batch)
                cell = batch.column(1).to_numpy().astype(np.int64)
                for b in sent.value:
                    cell = cell * _GRID + np.clip((b.raw(x) + _SPAN) / (2 * _SPAN) * _GRID, 0, _GRID - 1).astype(np.int64)
                values, n = np.unique(cell, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(values), pa.array(n)], ["cell", "n"])

    found = common.map_arrow(rows.select("x", "y"), run, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).collect()
    grid = np.zeros((2, _GRID, _GRID))
    for r in found:
        grid[r.cell // _GRID**2, r.cell // _GRID % _GRID, r.cell % _GRID] = r.n
    centre = (np.arange(_GRID) + 0.5) / _GRID * 2 * _SPAN - _SPAN
    knots = []
    for axis in (2, 1):
        each = grid.sum(axis=axis)
        n = each.sum(axis=0)
        use = n > 0
        knots.append(isotonic(centre[use], (each[1][use] + 0.01) / (n[use] + 0.02), n[use]))
    p = [_logit(np.interp(centre, *k)) for k in knots]
    y, a, b = np.nonzero(grid)
    w = grid[y, a, b]
    design = np.stack([np.ones(len(y)), p[0][a], p[1][b]], axis=1)
    beta = np.array([0.0, 0.5, 0.5])
    for _ in range(30):  # Newton steps, held near equal weights where the rows are few
        q = 1 / (1 + np.exp(-design @ beta))
        grad = design.T @ (w * (y - q)) - 1.0 * (beta - np.array([0.0, 0.5, 0.5]))
        hess = (design * (w * q * (1 - q))[:, None]).T @ design + np.eye(3)
        step = np.linalg.solve(hess, grad)
        beta = beta + step
        if np.abs(step).max() < 1e-9:
            break
    return knots, np.array([beta[0], max(beta[1], 0.0), max(beta[2], 0.0)])


def fit(seen: DataFrame, labels: DataFrame, rounds: int = ROUNDS) -> Model:
    """seen: the result of ``views``; labels: doc_id, quality."""
    known = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg((F.max("quality") > 0).cast("long").alias("label"))
    fold = F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(FOLDS))
    rows = common.durable(seen.join(known, "doc_id", "left").select("x", F.coalesce("label", F.lit(-1)).alias("label"), F.coalesce(fold == 0, F.lit(False)).alias("held")), "views")
    n = {r.label: r.n for r in rows.where("label >= 0").groupBy("label").agg(F.count("*").alias("n")).collect()}
    both = {(r.label, r.held) for r in rows.where("label >= 0").select("label", "held").distinct().collect()}
    if len(n) < 2:
        return Model(None, [], np.zeros(3), 0.5 if not n else float(next(iter(n))))
    apart = len(both) == 4  # too few labels for a part of their own: calibrate on the rows learned from
    train = rows.select("x", F.when(F.col("held") & F.lit(apart) & (F.col("label") >= 0), F.lit(-2)).otherwise(F.col("label")).alias("y"))
    models = None
    for _ in range(rounds + 1):
        counts = _count(train, models)
        models = [Bayes(counts, v) for v in _VIEWS]
    checked = rows.where((F.col("label") >= 0) & (F.col("held") | F.lit(not apart))).select("x", F.col("label").alias("y"))
    knots, weights = _calibrate(checked, models)
    return Model(models, knots, weights, 0.5)


def score(seen: DataFrame, model: Model) -> DataFrame:
    """doc_id, text_score, meta_score (each view calibrated) and score, for each row of ``seen``."""
    sent = seen.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                both = sent.value.scores(_features(batch))
                yield pa.RecordBatch.from_arrays([batch.column(1), *map(pa.array, both)], ["doc_id", "text_score", "meta_score", "score"])

    kind = seen.schema["doc_id"].dataType.simpleString()
    return common.map_arrow(seen.select("x", "doc_id"), run, f"doc_id {kind}, text_score double, meta_score double, score double")


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.5) -> DataFrame:
    """doc_id, text_score, meta_score, score, keep for each row of ``docs``."""
    seen = common.durable(views(docs), "views")
    return score(seen, fit(seen, labels)).withColumn("keep", F.col("score") >= threshold)
