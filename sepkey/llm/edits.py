"""Whether few edits turn one text into another, for many pairs at once.

Bit-parallel columns of the distance table, 64 rows a word; numpy does the same step for all pairs of a chunk. What both texts begin and end with is
set aside first, pairs that exchanged characters alone make alike are settled by counting these, and a pair leaves as soon as the columns that remain cannot
bring it back under its bound. All answers are exact.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Pairs of a chunk, words of its masks, and columns after which settled pairs leave it.
CHUNK, MASKS, STRIDE = 2048, 1 << 21, 16
#: Characters of a side that are laid out at once: with very long texts, few pairs or one.
CELLS = 1 << 18
#: Pairs for each word of rows that make a chunk worth its steps; fewer are compared one by one.
WORTH = 12
ONE = np.uint64(1)


def _codes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all texts in a row, and where each begins (and the last ends)."""
    ends = np.concatenate([[0], np.cumsum(pc.utf8_length(texts).to_numpy(zero_copy_only=False))]).astype(np.int64)
    joined = "".join(texts.to_pylist())
    return np.frombuffer(joined.encode("utf-32-le"), np.uint32), ends


def _matrix(codes: np.ndarray, begin: np.ndarray, size: np.ndarray, width: int, fill: int) -> np.ndarray:
    """One row for each text, filled up to the width."""
    place = np.arange(width)
    inside = place < size[:, None]
    out = np.full(inside.shape, fill, np.uint32)
    out[inside] = codes[(begin[:, None] + place)[inside]]
    return out


def alike(x: pa.Array, y: pa.Array, most: np.ndarray, single) -> np.ndarray:
    """For each pair whether ``most`` edits turn its x into its y. ``single(x, y, most)`` answers where too few pairs are of one size."""
    n = len(x)
    ok = np.zeros(n, bool)
    if not n:
        return ok
    (cx, ex), (cy, ey) = _codes(x), _codes(y)
    bx, by, nx, ny = ex[:-1].copy(), ey[:-1].copy(), np.diff(ex), np.diff(ey)
    most = np.asarray(most, np.int64)
    for at in _parts(np.arange(n), np.maximum(nx, ny), CELLS):
        _trim(cx, cy, bx, by, nx, ny, at, ok, most)
    swap = nx > ny  # the shorter rest makes the rows
    left = np.flatnonzero(~ok & (np.abs(nx - ny) <= most))
    rows = np.where(swap, ny, nx)
    words = -(-rows // 64)
    words = np.where(words <= 6, words, -(-words // 4) * 4)
    for w in np.unique(words[left]):
        for at in _parts(left[words[left] == w], np.maximum(nx, ny), 4 * CELLS):
            if w and len(at) >= WORTH * w:
                s = swap[at]
                long = int(np.maximum(nx, ny)[at].max())
                p = np.where(s[:, None], _matrix(cy, by[at], ny[at], int(w) * 64, 0), _matrix(cx, bx[at], nx[at], int(w) * 64, 0))
                q = np.where(s[:, None], _matrix(cx, bx[at], nx[at], long, 0), _matrix(cy, by[at], ny[at], long, 0))
                ok[at] = _columns(p, rows[at], q, np.maximum(nx, ny)[at], most[at], int(w))
            else:
                for i in at:
                    ok[i] = single(x[int(i)].as_py(), y[int(i)].as_py(), int(most[i]))
    return ok


def _parts(which: np.ndarray, size: np.ndarray, cells: int):
    """Cuts the pairs, by size, into chunks whose number times largest size is bounded."""
    which = which[np.argsort(size[which], kind="stable")]
    end = len(which)
    while end:
        start = max(0, end - min(CHUNK, max(1, cells // max(1, int(size[which[end - 1]])))))
        yield which[start:end]
        end = start


def _trim(cx, cy, bx, by, nx, ny, at, ok, most) -> None:
    """Sets aside what the pairs ``at`` begin and end with; settles those whose rest is short, or as long on both sides with few unlike places."""
    least, width = np.minimum(nx[at], ny[at]), int(np.minimum(nx[at], ny[at]).max())
    place = np.arange(width)
    inside = place < least[:, None]
    px, py = np.where(inside, bx[at][:, None] + place, 0), np.where(inside, by[at][:, None] + place, 0)
    unlike = (cx[px] != cy[py]) & inside if width else inside
    even = nx[at] == ny[at]
    ok[at] |= even & (unlike.sum(axis=1) <= most[at])
    head = np.where(unlike.any(axis=1), unlike.argmax(axis=1), least) if width else least
    rest = least - head
    inside = place < rest[:, None]
    px, py = np.where(inside, (bx[at] + nx[at])[:, None] - 1 - place, 0), np.where(inside, (by[at] + ny[at])[:, None] - 1 - place, 0)
    unlike = (cx[px] != cy[py]) & inside if width else inside
    tail = np.where(unlike.any(axis=1), unlike.argmax(axis=1), rest) if width else rest
    bx[at] += head
    by[at] += head
    nx[at] -= head + tail
    ny[at] -= head + tail
    ok[at] |= np.maximum(nx[at], ny[at]) <= most[at]


def _columns(p: np.ndarray, m: np.ndarray, q: np.ndarray, n: np.ndarray, most: np.ndarray, words: int) -> np.ndarray:
    """p: pairs by rows of the table (m of them count), q: pairs by columns (n of them count), m <= n, m at least 1."""
    there = np.zeros(int(max(p.max(), q.max(initial=0))) + 1, bool)
    there[p] = there[q] = True
    dense = np.cumsum(there) - 1
    letters, p, q = int(there.sum()), dense[p], dense[q]
    step = MASKS // (letters * words)
    out = np.zeros(len(p), bool)
    for i in range(0, len(p), max(1, step)):
        s = slice(i, i + max(1, step))
        out[s] = _chunk(p[s], m[s], np.ascontiguousarray(q[s].T), n[s], most[s], words, letters)
    return out


def _chunk(p, m, q, n, most, words: int, letters: int) -> np.ndarray:
    pairs = len(p)
    mask = np.zeros((words, letters * pairs), np.uint64)
    who = np.arange(pairs)
    for r in range(int(m.max())):
        on = r < m
        mask[r // 64, (p[:, r] * pairs + who)[on]] |= ONE << np.uint64(r % 64)
    last = (m - 1) // 64
    bit = ONE << ((m - 1) % 64).astype(np.uint64)
    ends = [np.where(last == w, bit, np.uint64(0)) for w in range(words)]
    up, down = [np.full(pairs, ~np.uint64(0)) for _ in range(words)], [np.zeros(pairs, np.uint64) for _ in range(words)]
    ended = [bool((last == w).any()) for w in range(words)]
    score, out = m.astype(np.int64), np.zeros(pairs, bool)
    who, row = np.arange(pairs), np.arange(pairs)  # the pair's place in the masks, and in the answer
    top = np.uint64(63)
    for c in range(int(n.max())):
        if c % STRIDE == 0:
            done = (n <= c) | (score - np.maximum(n - c, 0) > most)
            if 4 * done.sum() >= len(done) or done.all():
                out[row[done]] = (score <= most)[done] & (n <= c)[done]
                keep = ~done
                if not keep.any():
                    return out
                who, row, score, n, most = who[keep], row[keep], score[keep], n[keep], most[keep]
                up, down, ends = [a[keep] for a in up], [a[keep] for a in down], [a[keep] for a in ends]
                q = q[:, keep]
        at = q[c] * pairs + who
        plus_in, minus_in = ONE, np.uint64(0)  # the row above the first: one more edit a column
        change = np.zeros(len(who), np.int64)
        for w in range(words):
            eq, u, d = mask[w][at], up[w], down[w]
            over = eq | d
            if w:
                eq |= minus_in
            same = eq & u
            same += u
            same ^= u
            same |= eq
            minus = u & same
            same |= u
            plus = np.bitwise_not(same, out=same)
            plus |= d
            if ended[w]:
                change += (plus & ends[w]) != 0
                change -= (minus & ends[w]) != 0
            if w + 1 < words:
                plus_out, minus_out = plus >> top, minus >> top
            plus <<= ONE
            plus |= plus_in
            minus <<= ONE
            if w:
                minus |= minus_in
            down[w] = plus & over
            over |= plus
            up[w] = np.bitwise_not(over, out=over)
            up[w] |= minus
            if w + 1 < words:
                plus_in, minus_in = plus_out, minus_out
        score += np.where(c < n, change, 0)
    out[row] = score <= most
    return out
