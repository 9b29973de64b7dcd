"""Images in binary columns: PNG through zlib chunks, and hashes of their low frequencies.

``write_png`` and ``read_png`` speak the format itself: signature, length-prefixed chunks with CRC-32, one zlib stream, and the five
row filters, undone with numpy. ``spectrum_hash`` reduces an image to 32 by 32 cell means, takes the cosine transform and
compares the low frequencies with their median: near-equal images get near-equal 64-bit hashes.

``documents_as_media`` stores each text losslessly as an 8-bit grey image of 192 samples a row, with a filter chosen for each row, and reads it back. A null text is an
empty one, which is one row of blanks; repeated rows give repeated results; extra columns are ignored. Damaged bytes raise ``BadImage``.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import common

# Fixed values of the format.
_SIGNATURE = b"\x89PNG\r\n\x1a\n"
_CHANNELS = {0: 1, 2: 3, 4: 2, 6: 4}

WIDTH = 192
_CELLS, _LOW = 32, 8


class BadImage(ValueError):
    """The bytes are no intact image of the supported kind (8 bits a sample, not interlaced, no palette)."""


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))


def write_png(pixels: np.ndarray, level: int = 1, row_filter: int | None = None) -> bytes:
    """``pixels``: uint8, rows by columns (grey) or rows by columns by 2, 3 or 4 channels. Without ``row_filter`` each row gets the one of filters
    1 to 4 whose signed residuals are smallest in sum."""
    rows, columns = pixels.shape[:2]
    channels = 1 if pixels.ndim == 2 else pixels.shape[2]
    flat = np.ascontiguousarray(pixels).reshape(rows, columns * channels)
    first = np.zeros(rows, bool)
    first[:1] = True
    if row_filter is None:
        body = filtered(flat, channels, first)
    else:
        body = np.empty((rows, flat.shape[1] + 1), np.uint8)
        body[:, 0] = row_filter
        body[:, 1:] = flat - _predictions(flat, channels, first)[row_filter]()
    return _file(body, columns, channels, level)


def _file(body: np.ndarray, columns: int, channels: int, level: int = 1) -> bytes:
    colour = next(k for k, v in _CHANNELS.items() if v == channels)
    head = struct.pack(">IIBBBBB", columns, len(body), 8, colour, 0, 0, 0)
    return _SIGNATURE + _chunk(b"IHDR", head) + _chunk(b"IDAT", zlib.compress(body.tobytes(), level)) + _chunk(b"IEND", b"")


def _nearest(left, up, corner):
    """The neighbour that is nearest to left + up - corner; ties go to left, then up."""
    left, up, corner = (x.astype(np.int16) for x in (left, up, corner))
    to_left, to_up, to_corner = abs(up - corner), abs(left - corner), abs(left + up - 2 * corner)
    return np.where((to_left <= to_up) & (to_left <= to_corner), left, np.where(to_up <= to_corner, up, corner)).astype(np.uint8)


def _predictions(flat: np.ndarray, step: int, first: np.ndarray) -> list:
    """For each filter a function that predicts the samples; ``first`` marks the top rows of images that lie below one another."""
    left = np.zeros_like(flat)
    left[:, step:] = flat[:, :-step]
    up = np.zeros_like(flat)
    up[1:] = flat[:-1]
    up[first] = 0
    corner = np.zeros_like(flat)
    corner[:, step:] = up[:, :-step]
    return [lambda: np.zeros_like(flat), lambda: left, lambda: up, lambda: ((left.astype(np.uint16) + up) // 2).astype(np.uint8), lambda: _nearest(left, up, corner)]


def filtered(flat: np.ndarray, step: int, first: np.ndarray) -> np.ndarray:
    """Rows with their filter in front, chosen for each row."""
    best, out = np.full(len(flat), np.iinfo(np.int64).max), np.empty((len(flat), flat.shape[1] + 1), np.uint8)
    predict = _predictions(flat, step, first)
    for kind in (1, 2, 3, 4):
        residual = flat - predict[kind]()
        cost = np.abs(residual.view(np.int8).astype(np.int16)).sum(axis=1, dtype=np.int64)
        better = cost < best
        best[better] = cost[better]
        out[better, 0] = kind
        out[better, 1:] = residual[better]
    return out


def _unfilter(raw: np.ndarray, step: int, first: np.ndarray) -> np.ndarray:
    """Undoes the row filters of images that lie below one another. A sample needs those to its left, above it and at the corner, so all samples
    on one diagonal, of all images, are undone at once."""
    kinds, rows, width = raw[:, 0], len(raw), raw.shape[1] - 1
    if kinds.max(initial=0) > 4:
        raise BadImage("unknown row filter")
    flat = raw[:, 1:].copy()
    if not kinds.any():
        return flat
    columns = width // step
    # a border of zeros at the left and above each image spares all tests
    top = np.cumsum(first) + np.arange(rows)
    wide = np.zeros((rows + int(first.sum()), columns + 1, step), np.uint8)
    wide[top, 1:] = flat.reshape(rows, columns, step)
    cells = wide.reshape(-1, step)
    starts = np.flatnonzero(first)
    depth = np.arange(rows) - starts[np.cumsum(first) - 1]
    order = np.argsort(depth, kind="stable")  # rows by their depth in their image
    depth, base, kind = depth[order], (top * (columns + 1) + 1)[order], kinds[order][:, None]
    for diagonal in range(int(depth[-1]) + columns if rows else 0):
        a, b = np.searchsorted(depth, (diagonal - columns + 1, diagonal + 1))
        at = base[a:b] + (diagonal - depth[a:b])
        k = kind[a:b]
        left, up = cells[at - 1], cells[at - columns - 1]
        guess = np.where(k == 1, left, np.where(k == 2, up, 0)).astype(np.uint8)
        if (k == 3).any():
            guess = np.where(k == 3, ((left.astype(np.uint16) + up) >> 1).astype(np.uint8), guess)
        if (k == 4).any():
            guess = np.where(k == 4, _nearest(left, up, cells[at - columns - 2]), guess)
        cells[at] += guess
    return wide[top, 1:].reshape(rows, width)


def _stream(media: bytes) -> tuple[np.ndarray, int, int]:
    """Filtered rows, columns and channels, with every chunk's checksum, the stream's checksum and the size tested."""
    if media[:8] != _SIGNATURE:
        raise BadImage("no PNG signature")
    at, head, stream, ended = 8, None, [], False
    while at < len(media) and not ended:
        if at + 12 > len(media):
            raise BadImage("cut off in a chunk")
        size, kind = struct.unpack_from(">I4s", media, at)
        body = media[at + 8 : at + 8 + size]
        if len(body) < size or at + 12 + size > len(media):
            raise BadImage("cut off in a chunk")
        if zlib.crc32(kind + body) != struct.unpack_from(">I", media, at + 8 + size)[0]:
            raise BadImage(f"checksum of {kind!r}")
        if kind == b"IHDR":
            head = struct.unpack(">IIBBBBB", body)
        elif kind == b"IDAT":
            stream.append(body)
        elif kind == b"IEND":
            ended = True
        elif not kind[0] & 32:
            raise BadImage(f"cannot read {kind!r}")
        at += 12 + size
    if head is None or not ended:
        raise BadImage("no header or no end")
    columns, rows, depth, colour, packing, filtering, interlace = head
    if depth != 8 or colour not in _CHANNELS or packing or filtering or interlace:
        raise BadImage("kind of image not supported")
    step = _CHANNELS[colour]
    try:
        raw = np.frombuffer(zlib.decompress(b"".join(stream)), np.uint8)
    except zlib.error as e:
        raise BadImage(str(e)) from e
    if raw.size != rows * (columns * step + 1):
        raise BadImage("size of the samples")
    return raw.reshape(rows, columns * step + 1), columns, step


def read_png(media: bytes) -> np.ndarray:
    """The samples: rows by columns, and by channels if there are more than one."""
    return read_many([media])[0]


def read_many(images: list[bytes]) -> list[np.ndarray]:
    """The samples of each image. Images of one width and channel count are undone together."""
    parts = [_stream(m) for m in images]
    out: list = [None] * len(parts)
    for shape in {p[1:] for p in parts}:
        mine = [i for i, p in enumerate(parts) if p[1:] == shape]
        sizes = np.array([len(parts[i][0]) for i in mine])
        ends = np.cumsum(sizes)
        first = np.zeros(int(ends[-1]), bool)
        first[(ends - sizes)[sizes > 0]] = True
        flat = _unfilter(np.concatenate([parts[i][0] for i in mine]), shape[1], first)
        for i, end, size in zip(mine, ends.tolist(), sizes.tolist(), strict=True):
            one = flat[end - size : end]
            out[i] = one if shape[1] == 1 else one.reshape(size, *shape)
    return out


def _cosines(n: int, low: int) -> np.ndarray:
    return np.cos(np.pi * (np.arange(n) + 0.5)[None, :] * np.arange(low)[:, None] / n)


_BASIS = _cosines(_CELLS, _LOW)


def spectrum_hash(pixels: np.ndarray) -> str:
    """16 hex digits: which of the 8 by 8 lowest frequencies of the 32 by 32 cell means are above their median (the mean level left out of
    it). Images smaller than the cells are stretched."""
    grey = pixels if pixels.ndim == 2 else pixels[:, :, : min(3, pixels.shape[2])].mean(axis=2)
    for axis in (0, 1):
        n = grey.shape[axis]
        if n < _CELLS:
            grey = np.take(grey, np.arange(_CELLS) * n // _CELLS, axis)
        else:
            edges = np.arange(_CELLS + 1) * n // _CELLS
            counts = np.diff(edges)
            sums = np.add.reduceat(grey, edges[:-1], axis, dtype=np.float64 if grey.dtype.kind == "f" else np.int64)
            grey = sums / (counts[:, None] if axis == 0 else counts[None, :])
    low = np.round(_BASIS @ grey @ _BASIS.T, 6).ravel()
    bits = low > np.median(low[1:])
    return f"{int.from_bytes(np.packbits(bits).tobytes(), 'big'):016x}"


def texts_as_png(texts: list[bytes], width: int = WIDTH) -> list[bytes]:
    """A grey image for each text: its bytes, filled up with blanks to whole rows, one row at least."""
    if not texts:
        return []
    padded = [t.ljust(max(1, -(-len(t) // width)) * width, b" ") for t in texts]
    ends = np.cumsum([len(t) // width for t in padded])
    first = np.zeros(int(ends[-1]), bool)
    first[np.concatenate([[0], ends[:-1]])] = True
    body = filtered(np.frombuffer(b"".join(padded), np.uint8).reshape(-1, width), 1, first)
    return [_file(rows, width, 1) for rows in np.split(body, ends[:-1])]


_OUT = {"n_bytes": pa.int64(), "media": pa.binary(), "payload_bytes": pa.int64(), "payload_sha256": pa.string(), "tail_crc32": pa.int64(), "media_bytes": pa.int64(), "media_sha256": pa.string(), "feature": pa.string()}
_SQL = "n_bytes long, media binary, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def documents_as_media(docs: DataFrame, keep_media: bool = True) -> DataFrame:
    """One row for each row of ``docs``: doc_id, n_bytes of the text, the stored image, and what was read back from it: payload_bytes,
    payload_sha256, tail_crc32 (of the last 16 bytes), media_bytes, media_sha256, feature. ``keep_media=False`` leaves the image out."""
    names = [k for k in _OUT if keep_media or k != "media"]

    def run(batches):
        for batch in batches:
            for part, texts in common.steps(batch):
                rows = []
                stored = texts_as_png([texts.row(i) for i in range(len(texts))])
                for i, (media, pixels) in enumerate(zip(stored, read_many(stored), strict=True)):
                    payload = pixels.tobytes()
                    rows.append((int(texts.at[i + 1] - texts.at[i]), media, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(media), hashlib.sha256(media).hexdigest(), spectrum_hash(pixels)))
                columns = dict(zip(_OUT, zip(*rows, strict=True), strict=True))
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(columns[k], _OUT[k]) for k in names)], ["doc_id", *names])

    kind = docs.schema["doc_id"].dataType.simpleString()
    fields = ", ".join(x for x in _SQL.split(", ") if keep_media or not x.startswith("media "))
    return common.map_arrow(docs.select("doc_id", "text"), run, f"doc_id {kind}, {fields}")
