"""Toxicity by gradient-boosted trees over dense features, with isotonic calibration.

1. A bounded sample of labelled rows (``POSITIVES`` and ``NEGATIVES`` at most, the smallest hashes of doc_id) is the only training text.
2. A lexicon is learned from it: words, and word beginnings of 4 to 6 bytes, that stand in more toxic than clean documents by a likelihood-ratio
   statistic. Counts are kept by fold, so that a training row's features come from a lexicon that never saw it.
3. Features of a document: lexicon densities and counts in tiers of the statistic, the strongest entries, second-person words and their
   nearness to lexicon words, capitals, punctuation, repeated characters, obfuscation (symbols or digits inside words, spelled-out words) and
   lexicon words that appear only once the obfuscation is undone.
4. Trees are fitted on the driver to the sample; isotonic regression on out-of-fold scores makes them probabilities.
5. Every whole text is scored in one pass.

The score uses the text alone. A null or empty text is scored as having no words. Rows without doc_id are scored, and never used to learn. Of
several labels of one document the largest counts. Without labels of both kinds every score is the base rate of what labels there are, 0 if none.
Repeated rows get equal scores; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .trees import BoostedTrees, isotonic

POSITIVES, NEGATIVES = 8_000, 12_000
FOLDS = 4
ENTRIES = 20_000
NEAR = 8
#: Bytes of text at a time: features take some hundred bytes of memory for each.
STEP = 512 << 10
_STEMS = (4, 5, 6)
_TIERS = (12.0, 25.0, 60.0, 200.0)

#: Second-person words of the four languages.
SECOND_PERSON = (
    "you your yours yourself yourselves u ur "
    "du dich dir dein deine deinen deinem deiner ihr euch euer eure "
    "tu te toi ton ta tes vous votre vos "
    "tú ti tus usted ustedes vosotros vuestro vuestra"
).split()

#: Characters that stand for letters.
_STANDS_FOR = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s"}

_WORD = common.byte_class(lambda b: 48 <= b <= 57 or 65 <= b <= 90 or 97 <= b <= 122 or b >= 128)
_CHUNK = common.byte_class(lambda b: b > 32)
_UPPER = common.byte_class(lambda b: 65 <= b <= 90)
_LETTER = common.byte_class(lambda b: 65 <= b <= 90 or 97 <= b <= 122 or b >= 128)
_MARK = common.byte_class(lambda b: 33 <= b <= 47 or 58 <= b <= 64 or 91 <= b <= 96 or 123 <= b <= 126)
_SHOUT = common.byte_class(lambda b: b in b"!?")
_PLAIN = common.LOWER.copy()
for _k, _v in _STANDS_FOR.items():
    _PLAIN[ord(_k)] = ord(_v)


def _hash_one(word: str) -> int:
    data = np.frombuffer(word.encode(), np.uint8)
    return int(common.run_hashes(data, np.array([0]), np.array([len(data)]))[0])


def _tokens(data: np.ndarray, words: common.Words) -> list[np.ndarray]:
    """Hashes of the whole words, and of their beginnings of each stem length (0 where the word is no longer than that)."""
    out = [common.run_hashes(data, words.start, words.end)]
    size = words.end - words.start
    for k in _STEMS:
        stem = common.run_hashes(data, words.start, np.minimum(words.start + k, words.end))
        out.append(np.where(size > k, common.mix(stem + np.uint64(k)), np.uint64(0)))
    return out


class Lexicon:
    """Token hashes with their statistic. ``look`` gives the statistic of each token, 0 for the others."""

    def __init__(self, token: np.ndarray, strength: np.ndarray):
        order = np.argsort(token)
        self.token, self.strength = token[order], strength[order]
        self.sieve = np.zeros(1 << 18, bool)
        self.sieve[(self.token & np.uint64((1 << 18) - 1)).astype(np.int64)] = True

    def look(self, token: np.ndarray) -> np.ndarray:
        out = np.zeros(len(token))
        if not len(self.token):
            return out
        may = np.flatnonzero(self.sieve[(token & np.uint64((1 << 18) - 1)).astype(np.int64)])
        at = np.minimum(np.searchsorted(self.token, token[may]), len(self.token) - 1)
        hit = self.token[at] == token[may]
        out[may[hit]] = self.strength[at[hit]]
        return out


FEATURES = [
    "log_words", *[f"density_{t:g}" for t in _TIERS], *[f"count_{t:g}" for t in _TIERS], "strongest", "second", "sum_per_word", "near_share", "near_count", "second_person",
    "capitals", "shouted_words", "punctuation", "exclamation", "repeated_marks", "stretched", "obfuscated", "spelled_out", "undone_hits", "word_length",
]


def features(texts: common.Texts, lexicon: Lexicon) -> np.ndarray:
    """Rows by FEATURES."""
    n = len(texts)
    data = common.LOWER[texts.data]
    words = common.Words(texts, _WORD)
    count = words.counts()
    per = 1 / np.maximum(count, 1)
    row = np.repeat(np.arange(n), count)
    tokens = _tokens(data, words)
    strength = np.zeros(len(row))
    for t in tokens:
        np.maximum(strength, lexicon.look(t), out=strength)
    cols = [np.log1p(count)]
    hits = [np.bincount(row[strength >= t], minlength=n) for t in _TIERS]
    cols += [h * per for h in hits] + [np.log1p(h) for h in hits]
    top, second = np.zeros(n), np.zeros(n)
    strong = np.flatnonzero(strength >= _TIERS[0])
    order = strong[np.lexsort((strength[strong], row[strong]))]
    if len(order):
        last = np.flatnonzero(np.append(row[order][1:] != row[order][:-1], True))
        top[row[order[last]]] = strength[order[last]]
        more = last[(last > 0)]
        more = more[row[order[more - 1]] == row[order[more]]]
        second[row[order[more]]] = strength[order[more - 1]]
    cols += [np.log1p(top), np.log1p(second), np.bincount(row, np.log1p(strength), n) * per]
    you = np.isin(tokens[0], np.array([_hash_one(w) for w in SECOND_PERSON], np.uint64))
    spot = np.flatnonzero(you)
    lexical = np.flatnonzero(strength >= _TIERS[1])
    near = np.zeros(len(lexical), bool)
    if len(spot) and len(lexical):
        after = np.searchsorted(spot, lexical)
        for side in (np.minimum(after, len(spot) - 1), np.maximum(after - 1, 0)):
            near |= (np.abs(spot[side] - lexical) <= NEAR) & (row[spot[side]] == row[lexical])
    near_n = np.bincount(row[lexical[near]], minlength=n)
    cols += [near_n / np.maximum(np.bincount(row[lexical], minlength=n), 1), np.log1p(near_n), np.bincount(row[you], minlength=n) * per]

    size = np.maximum(texts.sizes(), 1)
    inside = np.concatenate([[0], np.cumsum(_UPPER[texts.data])])
    letters = np.concatenate([[0], np.cumsum(_LETTER[texts.data])])
    rows_of = lambda c: c[texts.at[1:]] - c[texts.at[:-1]]
    cols.append(rows_of(inside) / np.maximum(rows_of(letters), 1))
    loud = (inside[words.end] - inside[words.start] == words.end - words.start) & (words.end - words.start > 1)
    cols.append(np.bincount(row[loud], minlength=n) * per)
    mark = _MARK[texts.data]
    same = np.zeros(len(data), bool)
    same[1:] = data[1:] == data[:-1]
    twice = same.copy()
    twice[1:] &= same[:-1]
    for flag in (mark, _SHOUT[texts.data], mark & same, twice & _LETTER[texts.data]):
        cols.append(rows_of(np.concatenate([[0], np.cumsum(flag)])) / size)

    # obfuscation: white-space chunks with digits or symbols between letters, and runs of single letters
    chunks = common.Words(texts, _CHUNK)
    c_row = np.repeat(np.arange(n), chunks.counts())
    plain = _PLAIN[texts.data]
    as_letter = _LETTER[plain]
    kept = np.concatenate([[0], np.cumsum(as_letter)])
    first_letter = np.concatenate([[0], np.cumsum(letters[1:] - letters[:-1])])  # letters seen before each place
    odd = np.zeros(len(data) + 1, np.int64)
    between = ~_LETTER[texts.data]
    if len(data) > 2:
        between[1:-1] &= _LETTER[texts.data][:-2] & (_LETTER[texts.data][2:] | as_letter[2:])
        between[0] = between[-1] = False
        between &= texts.data > 32
        between &= ~np.isin(texts.data, np.frombuffer(b"'-,.;:/", np.uint8)) | np.roll(between, 2)
        odd[1:] = np.cumsum(between)
    strange = odd[chunks.end] > odd[chunks.start]
    cols.append(np.bincount(c_row[strange], minlength=n) / np.maximum(chunks.counts(), 1))
    single = first_letter[chunks.end] - first_letter[chunks.start] == 1
    single &= chunks.end - chunks.start <= 2
    run = np.zeros(len(single), bool)
    if len(single) > 2:
        run[2:] = single[2:] & single[1:-1] & single[:-2] & (c_row[2:] == c_row[:-2])
    cols.append(np.bincount(c_row[run], minlength=n) / np.maximum(chunks.counts(), 1))
    undone = np.zeros(n)
    odd_ones = np.flatnonzero(strange)
    if len(odd_ones):
        body = plain[as_letter]
        a, b = kept[chunks.start[odd_ones]], kept[chunks.end[odd_ones]]
        found = lexicon.look(common.run_hashes(body, a, b)) >= _TIERS[1]
        undone += np.bincount(c_row[odd_ones[found]], minlength=n)
    cols.append(np.log1p(undone))
    cols.append(np.bincount(row, words.end - words.start, n) * per)
    return np.stack(cols, axis=1)


def _strength(pos, neg, all_pos, all_neg):
    """Likelihood-ratio statistic of a token's document counts; 0 unless it stands in relatively more toxic documents."""
    pos, neg = np.asarray(pos, float), np.asarray(neg, float)
    total = all_pos + all_neg
    share = (pos + neg) / total
    term = lambda k, e: np.where(k > 0, k * np.log(np.maximum(k, 1e-12) / np.maximum(e, 1e-12)), 0.0)
    g = 2 * (term(pos, share * all_pos) + term(neg, share * all_neg) + term(all_pos - pos, (1 - share) * all_pos) + term(all_neg - neg, (1 - share) * all_neg))
    return np.where((pos >= 3) & (pos * all_neg > neg * all_pos * 2), g, 0.0)


def _sample(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, text, toxic, fold of the training rows; at most POSITIVES + NEGATIVES documents."""
    known = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    order = F.xxhash64("doc_id")
    some = known.where("toxic > 0").orderBy(order, "doc_id").limit(POSITIVES).unionByName(known.where("toxic <= 0").orderBy(order, "doc_id").limit(NEGATIVES))
    some = common.durable(some.select("doc_id", F.col("toxic").cast("long").alias("toxic"), F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(FOLDS)).alias("fold")), "sample")
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(some.select("doc_id")), "doc_id")  # bounded by the sample
    one = rows.groupBy("doc_id").agg(F.min_by("text", F.xxhash64("text")).alias("text"))  # of several texts always the same one
    return common.durable(one.join(F.broadcast(some), "doc_id").select("doc_id", "text", "toxic", "fold"), "sample_texts")


def _lexicons(sample: DataFrame, totals: np.ndarray) -> list[Lexicon]:
    """For each fold the lexicon of the other folds, and last the one of all."""

    def count(batches):
        for batch in batches:
            for part, texts in common.steps(batch, size=STEP):
                words = common.Words(texts, _WORD)
                row = np.repeat(np.arange(len(texts)), words.counts())
                kind = (part.column(3).to_numpy() * 2 + part.column(2).to_numpy().clip(0, 1)).astype(np.int64)
                token = np.concatenate(_tokens(common.LOWER[texts.data], words))
                owner = np.tile(row, 1 + len(_STEMS))
                keep = token != 0
                token, owner = token[keep], owner[keep]
                order = np.lexsort((owner, token))
                token, owner = token[order], owner[order]
                new = np.ones(len(token), bool)
                new[1:] = (token[1:] != token[:-1]) | (owner[1:] != owner[:-1])
                token, owner = token[new], owner[new]
                values, where = np.unique(token, return_inverse=True)
                table = np.bincount(where * 2 * FOLDS + kind[owner], minlength=len(values) * 2 * FOLDS).reshape(len(values), 2 * FOLDS)
                yield pa.RecordBatch.from_arrays([pa.array(values.view(np.int64)), *(pa.array(table[:, i]) for i in range(2 * FOLDS))], ["token", *names])

    names = [f"c{i}" for i in range(2 * FOLDS)]
    counts = common.map_arrow(sample.select("doc_id", "text", "toxic", "fold"), count, "token long, " + ", ".join(f"{x} long" for x in names))
    counts = counts.groupBy("token").agg(*[F.sum(x).alias(x) for x in names])
    pos = sum(F.col(names[2 * f + 1]) for f in range(FOLDS))
    neg = sum(F.col(names[2 * f]) for f in range(FOLDS))
    lift = F.log((pos + 0.5) / (totals[1::2].sum() + 1)) - F.log((neg + 0.5) / (totals[0::2].sum() + 1))
    best = counts.where((pos >= 3) & (lift > 0)).orderBy(F.desc(pos * lift), "token").limit(ENTRIES).toPandas()  # at most ENTRIES rows
    token = best["token"].to_numpy(np.int64).view(np.uint64)
    table = best[names].to_numpy(np.int64).reshape(len(best), FOLDS, 2)
    all_of = totals.reshape(FOLDS, 2)
    out = []
    for f in [*range(FOLDS), None]:
        use = [x for x in range(FOLDS) if x != f]
        strength = _strength(table[:, use, 1].sum(axis=1), table[:, use, 0].sum(axis=1), all_of[use, 1].sum(), all_of[use, 0].sum())
        keep = strength >= _TIERS[0]
        out.append(Lexicon(token[keep], strength[keep]))
    return out


class Model:
    def __init__(self, lexicon: Lexicon, trees: BoostedTrees | None, knots: tuple[np.ndarray, np.ndarray], base: float):
        self.lexicon, self.trees, self.knots, self.base = lexicon, trees, knots, base

    def scores(self, texts: common.Texts) -> np.ndarray:
        if self.trees is None:
            return np.full(len(texts), self.base)
        raw = self.trees.raw(features(texts, self.lexicon))
        # a trace of the raw score keeps the order inside a pool
        return np.clip(0.999 * np.interp(raw, *self.knots) + 0.001 / (1 + np.exp(-raw)), 0.0, 1.0)


def fit(docs: DataFrame, labels: DataFrame) -> Model:
    """labels: doc_id, toxic. Every row of ``labels`` may be learned from."""
    sample = _sample(docs, labels)
    sizes = {(r.fold, min(r.toxic, 1)): r.n for r in sample.groupBy("fold", "toxic").agg(F.count("*").alias("n")).collect()}
    totals = np.array([sizes.get((f, t), 0) for f in range(FOLDS) for t in (0, 1)])
    if not totals[0::2].sum() or not totals[1::2].sum():
        return Model(Lexicon(np.zeros(0, np.uint64), np.zeros(0)), None, (np.zeros(1), np.zeros(1)), float(totals[1::2].sum() > 0))
    lexicons = _lexicons(sample, totals)
    sent = sample.sparkSession.sparkContext.broadcast(lexicons)

    def run(batches):
        for batch in batches:
            for part, texts in common.steps(batch, size=STEP):
                fold = part.column(3).to_numpy()
                x = np.zeros((len(texts), len(FEATURES)))
                for f in np.unique(fold).tolist():
                    own = common.texts_of(part.column(1).filter(pa.array(fold == f)))
                    x[fold == f] = features(own, sent.value[f])
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), part.column(3), pa.array(list(x), pa.list_(pa.float64()))], ["doc_id", "toxic", "fold", "x"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = common.map_arrow(sample.select("doc_id", "text", "toxic", "fold"), run, f"doc_id {kind}, toxic long, fold long, x array<double>").toPandas().sort_values("doc_id")  # the sample
    x, y, fold = np.stack(rows["x"].to_numpy()), rows["toxic"].to_numpy().clip(0, 1).astype(float), rows["fold"].to_numpy()
    raw = np.zeros(len(y))
    for f in range(FOLDS):
        if (fold == f).any():
            raw[fold == f] = BoostedTrees().fit(x[fold != f], y[fold != f]).raw(x[fold == f]) if (fold != f).any() else 0.0
    return Model(lexicons[-1], BoostedTrees().fit(x, y), isotonic(raw, y), float(y.mean()))


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id and score for each row of ``docs``."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            for part, texts in common.steps(batch, size=STEP):
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sent.value.scores(texts))], ["doc_id", "score"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return common.map_arrow(docs.select("doc_id", "text"), run, f"doc_id {kind}, score double")


def reject(docs: DataFrame, model: Model, threshold: float = 0.5) -> DataFrame:
    """The rows of ``docs`` with a score below the threshold, all columns kept; the scoring pass is the filter."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            for part, texts in common.steps(batch, size=STEP):
                yield part.filter(pa.array(sent.value.scores(texts) < threshold))

    return common.map_arrow(docs, run, docs.schema)
