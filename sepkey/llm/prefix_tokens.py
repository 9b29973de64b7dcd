"""Token counts by dynamic programming over prefixes.

A byte-pair encoding has the prefix property: cutting an encoding after any token gives the encoding of that shorter string.
So the encoding of a string is known from the last token at each of its prefixes: that token is the only one that ends
there and follows, as a compatible neighbour, the last token of what stands before it. The table of last tokens and counts grows
by one entry for each byte, never re-encodes, and answers the token count of every prefix, truncation to a budget and
splitting under a limit.

Vocabularies whose words end in a marked token (``end_of_word_suffix``) need one more step at the place asked for: the word
part before it closes with a marked token. ``TokenCounter`` does both, over white-space-delimited chunks whose results are kept.

Nulls and empty texts have 0 tokens; repeated rows give repeated results; extra columns are ignored.
"""

from __future__ import annotations

import json
import unicodedata

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from . import common

#: ASCII white space, which no token spans.
_SPACE = (32, 9, 10, 11, 12, 13)
_INSIDE = common.byte_class(lambda b: b not in _SPACE)
_KEPT = 300_000


def byte_symbols() -> list[str]:
    """The printable stand-ins that byte-level vocabularies use for the 256 byte values: visible Latin-1 characters stand for
    themselves, all others follow in order from code point 256."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    out, spare = [], 256
    for b in range(256):
        if b in own:
            out.append(chr(b))
        else:
            out.append(chr(spare))
            spare += 1
    return out


#: A letter (no Hangul jamo, which compose) after a digit or a mark that is neither a combining one nor the apostrophe.
_SEAM = regex.compile(r"(?<=[\p{N}\p{P}\p{S}--'])[\p{L}--[\u1100-\u11ff\ua960-\ua97f\ud7b0-\ud7ff]]", regex.V1)


class TokenCounter:
    """Counts for a vocabulary file of the ``tokenizers`` library: byte-level BPE with word ends, its normaliser being NFC, white space
    and lower case."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.end = model.get("end_of_word_suffix") or ""
        self.vocab = model["vocab"]
        self.rank = {(tuple(m) if not isinstance(m, str) else tuple(m.split(" "))): i for i, m in enumerate(model["merges"])}
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.special_re = regex.compile("|".join(regex.escape(x) for x in sorted(self.special, key=len, reverse=True))) if self.special else None
        split = spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]
        self.piece_re = regex.compile(split)
        self.symbol = byte_symbols()
        self.parts = list(self.rank)
        self.made: dict[str, int] = {}
        for i, (a, b) in enumerate(self.parts):
            self.made.setdefault(a + b, i)
        self.closing = {t.removesuffix(self.end) for t in self.vocab if self.end and t.endswith(self.end)}
        self.open = {t for t in self.vocab if not (self.end and t.endswith(self.end))}
        self.longest = max(map(len, self.open | self.closing))
        self.pair_ok: dict[tuple[str, str], bool] = {}
        self.alone: dict[str, bool] = {}
        self.state: dict[str, tuple[str, int]] = {}
        self.pieces: dict[str, int] = {}
        self.chunks: dict[bytes, int] = {}

    # -- which tokens may stand side by side

    def _merge(self, parts: list[str]) -> list[str]:
        """The merge rule by its definition; used once for each token of the vocabulary that comes up."""
        while len(parts) > 1:
            best = min(range(len(parts) - 1), key=lambda i: self.rank.get((parts[i], parts[i + 1]), 1 << 60))
            if (parts[best], parts[best + 1]) not in self.rank:
                break
            parts[best : best + 2] = [parts[best] + parts[best + 1]]
        return parts

    def _is_token(self, whole: str) -> bool:
        """Whether merging the symbols of this vocabulary entry gives the entry again."""
        if (ok := self.alone.get(whole)) is None:
            parts = list(whole.removesuffix(self.end)) if self.end else list(whole)
            if self.end and whole.endswith(self.end):
                parts[-1] += self.end
            ok = self.alone[whole] = self._merge(parts) == [whole]
        return ok

    def _follows(self, left: str, right: str) -> bool:
        """Whether the encoding of ``left + right`` is these two tokens. Undoes the merges next to the border, the latest first; the
        border holds if no pair that met there had an earlier claim than the merge undone last."""
        if (ok := self.pair_ok.get((left, right))) is not None:
            return ok
        x, y, limit, ok = left, right, 1 << 60, True
        while True:
            if self.rank.get((x, y), 1 << 60) < limit:
                ok = False
                break
            rx, ry = self.made.get(x, -1), self.made.get(y, -1)
            if rx < 0 and ry < 0:
                break
            if rx > ry:
                x, limit = self.parts[rx][1], rx
            else:
                y, limit = self.parts[ry][0], ry + 1  # of equal merges the one further left comes first
        if len(self.pair_ok) > 2 * _KEPT:
            self.pair_ok.clear()
        self.pair_ok[left, right] = ok
        return ok

    # -- the table

    def _last(self, word: str, n: int, before, closed: bool) -> tuple[str, int]:
        """Last token and count of ``word[:n]``; ``before(i)`` has those of the open prefix of length i."""
        known = self.closing if closed else self.open
        for i in range(max(0, n - self.longest), n):
            token = word[i:n]
            if token not in known:
                continue
            if closed:
                token += self.end
            if not self._is_token(token):
                continue
            if i == 0:
                return token, 1
            left, count = before(i)
            if self._follows(left, token):
                return token, count + 1
        raise ValueError(f"no token of the vocabulary ends {word[:n]!r}")

    def open_table(self, word: str) -> list[tuple[str, int]]:
        """For n = 0, 1, ...: last token and token count of the n first byte symbols, with the word still open."""
        table = [("", 0)]
        for n in range(1, len(word) + 1):
            table.append(self._last(word, n, table.__getitem__, False))
        return table

    def _open(self, prefix: str) -> tuple[str, int]:
        """The table's entry for a short prefix, kept for all words that begin with it."""
        if (found := self.state.get(prefix)) is None:
            found = self._last(prefix, len(prefix), lambda i: self._open(prefix[:i]), False)
            if len(self.state) > 2 * _KEPT:
                self.state.clear()
            self.state[prefix] = found
        return found

    def _word(self, piece: str) -> str:
        return "".join([self.symbol[b] for b in piece.encode()])

    def piece_counts(self, piece: str) -> list[int]:
        """Token counts of each non-empty character prefix of one pre-token."""
        word = self._word(piece)
        table = self.open_table(word)
        ends = np.cumsum([len(c.encode()) for c in piece]).tolist()
        return [self._last(word, n, table.__getitem__, True)[1] if self.end else table[n][1] for n in ends]

    def piece_count(self, piece: str) -> int:
        if (count := self.pieces.get(piece)) is None:
            word = piece if piece.isascii() and piece.isalpha() else self._word(piece)
            if len(word) > 64:
                table = self.open_table(word)
                before = table.__getitem__
            else:
                before = lambda i: self._open(word[:i])
            count = self._last(word, len(word), before, True)[1] if self.end else before(len(word))[1]
            if len(self.pieces) > _KEPT:
                self.pieces.clear()
            self.pieces[piece] = count
        return count

    def _normal(self, text: str) -> str:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text)
            if "Σ" in text:  # capital sigma: no word-end form
                return "".join(c.lower() for c in text)
        return text.lower()

    def count(self, text: str) -> int:
        parts = self.special_re.split(text) if any(x in text for x in self.special) else [text]
        return len(parts) - 1 + sum([self.piece_count(x) for part in parts for x in self.piece_re.findall(self._normal(part))])

    def chunk_count(self, chunk: bytes) -> int:
        """``count`` of bytes without ASCII white space, kept for the next time."""
        if (count := self.chunks.get(chunk)) is None:
            text = chunk.decode()
            if text.isalpha() and text.isascii():
                count = self.piece_count(text.lower())
            else:
                count = self.count(text)
                if len(self.chunks) > _KEPT:
                    self.chunks.clear()
                self.chunks[chunk] = count
        return count

    def prefix_counts(self, text: str) -> np.ndarray:
        """Token count of ``text[:i]`` for i = 0 .. len(text), as the library counts that prefix by itself."""
        out = np.zeros(len(text) + 1, np.int64)
        base = 0
        for run in regex.finditer(r"[ \t\n\x0b\x0c\r]+|[^ \t\n\x0b\x0c\r]+", text):
            a, b = run.span()
            if run[0][0] in " \t\n\x0b\x0c\r":
                out[a + 1 : b + 1] = base
            else:
                out[a + 1 : b + 1] = base + np.asarray(self._chunk_prefixes(run[0]))
                base = out[b]
        return out

    def _seams(self, chunk: str) -> list[int]:
        """Places at which every text that reaches beyond them falls apart: a letter that composes with nothing before it, right after a digit or a
        mark other than the apostrophe, and not inside a special token's string. Nothing is encoded twice across them."""
        inside = [m.span() for m in self.special_re.finditer(chunk)] if any(x in chunk for x in self.special) else []
        return [m.start() for m in _SEAM.finditer(chunk) if not any(a < m.start() < b for a, b in inside)]

    def _chunk_prefixes(self, chunk: str) -> list[int]:
        plain = not any(x in chunk for x in self.special) and len(self._normal(chunk)) == len(chunk) and unicodedata.is_normalized("NFC", chunk)
        if not plain:
            out, base = [], 0
            cuts = [0, *self._seams(chunk), len(chunk)]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                out += [base + self.count(chunk[a : i + 1]) for i in range(a, b)]
                base = out[-1]
            return out
        out: list[int] = []
        text, base, at = self._normal(chunk), 0, 0
        for m in self.piece_re.finditer(text):
            out += [base] * (m.start() - at)
            piece = m[0]
            if piece[0] == "'" and len(piece) > 1 and piece[1:].isalpha():  # a contraction is one piece only once it is whole
                inner = [sum(map(self.piece_count, self.piece_re.findall(piece[: i + 1]))) for i in range(len(piece))]
            else:
                inner = self.piece_counts(piece)
            out += [base + x for x in inner]
            base, at = base + inner[-1], m.end()
        return out + [base] * (len(text) - at)

    def fits(self, text: str, budget: int) -> int:
        """The most characters that a prefix of at most ``budget`` tokens can have."""
        return int(np.flatnonzero(self.prefix_counts(text) <= budget)[-1])


def counter(path: str) -> TokenCounter:
    return common.per_process(("tokens", path), lambda: TokenCounter(path))


def count_texts(texts: common.Texts, tokens: TokenCounter) -> np.ndarray:
    """Token counts of whole rows: the chunk counts of each distinct chunk, summed along the row."""
    words = common.Words(texts, _INSIDE)
    hashes = common.run_hashes(texts.data, words.start, words.end)
    _, where, which = np.unique(hashes, return_index=True, return_inverse=True)
    body = texts.data.tobytes()
    each = np.fromiter((tokens.chunk_count(body[a:b]) for a, b in zip(words.start[where].tolist(), words.end[where].tolist(), strict=True)), np.int64, len(where))
    total = np.concatenate([[0], np.cumsum(each[which])])
    return np.diff(total[words.first])


def token_counts(docs: DataFrame, vocabulary: str, limit: int, tables: bool = False) -> DataFrame:
    """One row for each row of ``docs``: doc_id, n_bytes, n_tokens, over_limit. With ``tables``, also ``prefix_counts``, the
    little-endian 32-bit counts at each character prefix, from which ``truncate`` cuts without another look at the text."""

    def run(batches):
        tokens = counter(vocabulary)
        for batch in batches:
            for part, texts in common.steps(batch):
                n = count_texts(texts, tokens)
                out = [part.column(0), pa.array(texts.sizes()), pa.array(n), pa.array(n > limit)]
                if tables:
                    out.append(pa.array([tokens.prefix_counts(texts.row(i).decode()).astype("<u4").tobytes() for i in range(len(texts))], pa.binary()))
                yield pa.RecordBatch.from_arrays(out, names)

    names = ["doc_id", "n_bytes", "n_tokens", "over_limit"] + ["prefix_counts"] * tables
    kind = docs.schema["doc_id"].dataType.simpleString()
    return common.map_arrow(docs.select("doc_id", "text"), run, f"doc_id {kind}, n_bytes long, n_tokens long, over_limit boolean" + ", prefix_counts binary" * tables)


def truncate(docs: DataFrame, vocabulary: str, budget: int) -> DataFrame:
    """doc_id, text cut to the longest prefix of at most ``budget`` tokens (a whole text that fits stays), and n_tokens of it."""

    def run(batches):
        tokens = counter(vocabulary)
        for batch in batches:
            for part, texts in common.steps(batch):
                whole = count_texts(texts, tokens)
                cut, left = [], []
                for i, n in enumerate(whole.tolist()):
                    text = texts.row(i).decode()
                    if n > budget:
                        table = tokens.prefix_counts(text)
                        end = int(np.flatnonzero(table <= budget)[-1])
                        text, n = text[:end], int(table[end])
                    cut.append(text)
                    left.append(n)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(cut, pa.string()), pa.array(left, pa.int64())], ["doc_id", "text", "n_tokens"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return common.map_arrow(docs.select("doc_id", "text"), run, f"doc_id {kind}, text string, n_tokens long")
