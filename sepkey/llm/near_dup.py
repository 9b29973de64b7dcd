"""Near-duplicate documents by SuperMinHash.

A document's set is its distinct shingles of ``k`` words. An element's hash seeds a random permutation of the m signature places, drawn one
step at a time; at step j it offers j + (a random fraction) to the place drawn. A place keeps its least offer. As offers of later steps are
larger, a document stops as soon as all its places are filled: few steps for long documents. Places of one element differ in step
by construction, which makes the estimate of the Jaccard similarity less noisy than with independent hashes.

All documents of a step advance together in numpy. Permutations are kept as the draws made so far, and as whole rows once few documents
are left.

Documents of one set are one node. Bands of the signature give buckets; pairs that share one are confirmed on the full sets by
``grouping.link``; nodes reach their component's smallest document.

A null or empty text has an empty set and is linked with nothing. Of texts under one doc_id the largest set (then the largest hash)
stands for the document. A row without doc_id is linked with nothing and kept, its component is null. Repeated rows get the same result;
extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, grouping

K = 5
_INSIDE = common.byte_class(lambda b: b != 32 and not 9 <= b <= 13)
_FULL = np.uint64(0xFFFFFFFFFFFFFFFF)
_STEP = np.uint64(0x9E3779B97F4A7C15)
_DENSE_FROM = 12
#: Rows of a block, and columns of a matrix product, when a large bucket's rows are compared across groups.
BLOCK = 256
#: Shingles of a block, about: where sets are large a block has fewer rows.
BLOCK_SHINGLES = 500_000
_COLUMNS = 8192


def bands_for(threshold: float) -> tuple[int, int]:
    """(bands, rows) whose chance to miss a pair at the threshold is under 1e-8, with at most 256 places."""
    best = None
    for rows in range(1, 33):
        bands = 256 // rows
        if (1 - threshold**rows) ** bands < 1e-8:
            best = (bands, rows)
    if best is None:
        raise ValueError("threshold too low for 256 places")
    return best


def shingle_sets(texts: common.Texts, k: int = K) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes, ascending within each row, and where each row's begin."""
    data = common.LOWER[texts.data]
    words = common.Words(texts, _INSIDE)
    each = common.run_hashes(data, words.start, words.end)
    counts = words.counts()
    row = np.repeat(np.arange(len(texts)), counts)
    n = len(each)
    whole = np.zeros(0, np.int64)
    if n >= k:
        whole = np.flatnonzero(row[: n - k + 1] == row[k - 1 :])
    value = np.zeros(len(whole), np.uint64)
    for i in range(k):
        value = common.mix(value * _STEP + each[whole + i])
    owner = row[whole]
    short = np.flatnonzero((counts > 0) & (counts < k))
    if len(short):
        extra = np.zeros(len(short), np.uint64)
        for i in range(k - 1):
            has = counts[short] > i
            at = words.first[short[has]] + i
            extra[has] = common.mix(extra[has] * _STEP + each[at])
        extra = common.mix(extra + counts[short].astype(np.uint64))
        value, owner = np.concatenate([value, extra]), np.concatenate([owner, short])
        order = np.argsort(owner, kind="stable")
        value, owner = value[order], owner[order]
    at = np.searchsorted(owner, np.arange(len(texts) + 1))
    for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        value[a:b].sort()
    new = np.ones(len(value), bool)
    new[1:] = (value[1:] != value[:-1]) | (owner[1:] != owner[:-1])
    return value[new], np.searchsorted(owner[new], np.arange(len(texts) + 1))


def super_minhash(value: np.ndarray, at: np.ndarray, places: int) -> np.ndarray:
    """Signatures (rows by places) of sets ``value[at[i]:at[i + 1]]``; rows of empty sets are all ones."""
    rows = len(at) - 1
    sig = np.full((rows, places), _FULL, np.uint64)
    flat = sig.reshape(-1)
    owner = np.repeat(np.arange(rows), np.diff(at))
    x = value
    draws: list[np.ndarray] = []
    dense = None
    for j in range(places):
        if not len(x):
            break
        u = common.mix(x + np.uint64((j + 1) * int(_STEP) % (1 << 64)))
        place = (j + (((u >> np.uint64(32)) * np.uint64(places - j)) >> np.uint64(32)).astype(np.int64)).astype(np.int64)
        offer = (np.uint64(j) << np.uint64(32)) | (u & np.uint64(0xFFFFFFFF))
        if dense is None and j == _DENSE_FROM:
            dense = np.tile(np.arange(places, dtype=np.int16), (len(x), 1))
            every = np.arange(len(x))
            for t, d in enumerate(draws):
                dense[every, d], dense[:, t] = dense[:, t].copy(), dense[every, d]
        if dense is None:
            drawn = place
            for t in range(j - 1, -1, -1):
                drawn = np.where(draws[t] == drawn, t, drawn)
            draws.append(place)
        else:
            every = np.arange(len(x))
            drawn = dense[every, place].astype(np.int64)
            dense[every, place] = dense[:, j]
            dense[:, j] = drawn
        np.minimum.at(flat, owner * places + drawn, offer)
        live = np.unique(owner) if j else np.flatnonzero(np.diff(at))
        open_rows = live[(sig[live] == _FULL).any(axis=1)]
        if len(open_rows) < len(live):
            flag = np.zeros(rows, bool)
            flag[open_rows] = True
            stay = flag[owner]
            x, owner = x[stay], owner[stay]
            if dense is None:
                draws = [d[stay] for d in draws]
            else:
                dense = dense[stay]
    return sig


def band_keys(sig: np.ndarray, bands: int, rows: int) -> np.ndarray:
    out = np.zeros((len(sig), bands), np.uint64) + np.arange(1, bands + 1, dtype=np.uint64)
    parts = sig.reshape(len(sig), bands, rows)
    for i in range(rows):
        out = common.mix(out * _STEP + parts[:, :, i])
    return out.view(np.int64)


def signatures(docs: DataFrame, bands: int, rows: int, k: int = K) -> DataFrame:
    """doc_id, n_shingles, two 64-bit hashes of the set, and its band keys (none for an empty set)."""

    def run(batches):
        for batch in batches:
            for part, texts in common.steps(batch):
                value, at = shingle_sets(texts, k)
                n = np.diff(at)
                total = np.zeros((2, len(value) + 1), np.uint64)
                np.cumsum(value, out=total[0, 1:])
                np.cumsum(common.mix(value ^ _STEP), out=total[1, 1:])
                both = [common.mix(t[at[1:]] - t[at[:-1]]).view(np.int64) for t in total]
                keys = band_keys(super_minhash(value, at, bands * rows), bands, rows)
                full = n > 0
                where = np.concatenate([[0], np.cumsum(full * bands)]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(where), pa.array(keys[full].reshape(-1)))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n), pa.array(both[0]), pa.array(both[1]), lists], ["doc_id", "n_shingles", "set_a", "set_b", "keys"])

    return common.map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, "doc_id long, n_shingles long, set_a long, set_b long, keys array<long>")


def _sets(docs: DataFrame, nodes: DataFrame, k: int) -> DataFrame:
    """(node, n, hashes) of the documents in ``nodes`` (node, set_a, set_b)."""
    nodes = common.small(nodes, F.lit(32))

    def run(batches):
        for batch in batches:
            for part, texts in common.steps(batch):
                value, at = shingle_sets(texts, k)
                total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(value)])
                first = common.mix(total[at[1:]] - total[at[:-1]]).view(np.int64)
                same = pa.array(first == part.column(2).to_numpy(zero_copy_only=False))
                lists = pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(value.view(np.int64)))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.diff(at)), lists], ["node", "n", "hashes"]).filter(same)

    rows = docs.select(F.col("doc_id").cast("long").alias("node"), "text").join(nodes, "node").select("node", "text", "set_a")
    return common.map_arrow(rows, run, "node long, n long, hashes array<long>").dropDuplicates(["node"])


def _compare(percent: int):
    """Pairs of one task's rows (node, root, side, hashes as bytes; i, j: its blocks) that lie in different groups and are linked. Intersections
    come from one matrix product over the shingles that more than one row has."""

    def run(batch: pa.Table) -> pa.Table:
        node, root, side = (batch.column(c).to_numpy() for c in ("node", "root", "side"))
        order = np.argsort(node, kind="stable")
        node, root, side = node[order], root[order], side[order]
        blobs = batch.column("hashes").to_pylist()
        sets = [np.frombuffer(blobs[k], np.uint64) for k in order.tolist()]
        n = np.array([len(x) for x in sets])
        row = np.repeat(np.arange(len(sets)), n)
        _, column, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        keep = times[column] > 1
        row, column = row[keep], column[keep]
        used, column = np.unique(column, return_inverse=True)
        by = np.argsort(column, kind="stable")
        row, column = row[by], column[by]
        both = np.zeros((len(sets), len(sets)), np.int64)
        for lo in range(0, len(used), _COLUMNS):
            a, b = np.searchsorted(column, (lo, lo + _COLUMNS))
            part = np.zeros((len(sets), min(_COLUMNS, len(used) - lo)), np.float32)
            part[row[a:b], column[a:b] - lo] = 1
            both += (part @ part.T).astype(np.int64)
        may = 100 * both >= percent * (n[:, None] + n[None, :] - both)
        may &= (root[:, None] != root[None, :]) & (node[:, None] < node[None, :])
        if batch.column("i")[0].as_py() != batch.column("j")[0].as_py():
            may &= side[:, None] != side[None, :]
        a, b = np.nonzero(may)
        return pa.table({"a": node[a], "b": node[b]})

    return run


def _across(docs: DataFrame, nodes: DataFrame, k: int, percent: int):
    def run(spots: DataFrame) -> DataFrame:
        wanted = common.durable(spots.select("node").distinct().join(nodes, "node").select("node", "set_a"), "ends")

        def narrow(batches):
            for batch in batches:
                lists = batch.column(1)
                at, flat = lists.offsets.to_numpy(), lists.values.to_numpy()
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([flat[i:j].tobytes() for i, j in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)], pa.binary())], ["node", "hashes"])

        sets = common.durable(common.map_arrow(_sets(docs, wanted, k).select("node", "hashes"), narrow, "node long, hashes binary"), "narrow")
        load = spots.groupBy("bucket").agg(F.greatest(F.ceil(F.count("*") / BLOCK), F.ceil(F.sum("weight") / BLOCK_SHINGLES)).cast("int").alias("blocks"))
        side = F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")
        tasks = spots.join(load, "bucket").select("bucket", "node", "root", side.alias("side"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("o"))
        tasks = tasks.select("bucket", "node", "root", "side", F.least("side", "o").alias("i"), F.greatest("side", "o").alias("j")).join(sets, "node")
        return tasks.groupBy("bucket", "i", "j").applyInArrow(_compare(percent), "a long, b long")

    return run


def near_duplicates(docs: DataFrame, percent: int = 85, k: int = K) -> DataFrame:
    """One row for each row of ``docs``: doc_id, n_shingles, component_id, kept. Sets A and B are linked if
    100 |A and B| >= percent |A or B|."""
    bands, rows = bands_for(percent / 100)
    marks = common.durable(signatures(docs, bands, rows, k), "signatures")
    mine = marks.where("doc_id is not null and n_shingles > 0")
    picked = mine.groupBy("doc_id").agg(F.max(F.struct("n_shingles", "set_a", "set_b")).alias("s")).select("doc_id", "s.*")
    of_set = ["n_shingles", "set_a", "set_b"]
    nodes = common.durable(picked.groupBy(*of_set).agg(F.min("doc_id").alias("node")), "nodes")
    same = nodes.select(F.col("node").alias("doc_id"), *[F.col(c).alias(f"of_{c}") for c in of_set])
    keyed = mine.join(same, "doc_id").where(" and ".join(f"{c} = of_{c}" for c in of_set)).dropDuplicates(["doc_id"])
    members = keyed.select(F.explode("keys").alias("bucket"), F.col("doc_id").alias("node"), F.col("n_shingles").alias("weight"))

    def test(pairs: DataFrame) -> DataFrame:
        ends = pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct()
        sets = common.durable(_sets(docs, common.durable(ends.join(nodes, "node").select("node", "set_a"), "ends"), k), "sets")
        left = pairs.join(sets.select(F.col("node").alias("a"), F.col("n").alias("n_a"), F.col("hashes").alias("h_a")), "a")
        both = left.join(sets.select(F.col("node").alias("b"), F.col("n").alias("n_b"), F.col("hashes").alias("h_b")), "b")
        common_n = F.size(F.array_intersect("h_a", "h_b"))
        return both.where(100 * common_n >= percent * (F.col("n_a") + F.col("n_b") - common_n)).select("a", "b")

    may = lambda p, q: 100 * F.least(p("weight"), q("weight")) >= percent * F.greatest(p("weight"), q("weight"))
    roots, _ = grouping.link(members, test, may, across=_across(docs, nodes, k, percent))
    ids = picked.join(nodes, of_set).join(roots, "node", "left").select("doc_id", F.coalesce("root", "node").alias("component_id"))
    out = marks.select("doc_id", "n_shingles").join(ids, "doc_id", "left")
    own = F.coalesce("component_id", "doc_id")
    return out.select("doc_id", "n_shingles", own.alias("component_id"), F.coalesce(own == F.col("doc_id"), F.lit(True)).alias("kept"))


def keep_one(docs: DataFrame, percent: int = 80, k: int = K) -> DataFrame:
    """``docs`` with one row of each linked group, that of the smallest doc_id; of rows under one doc_id any one stays. Rows without doc_id, and
    texts without words, stay. Texts move only where the ids to drop are too many to broadcast."""
    with common.scratch():
        found = near_duplicates(docs, percent, k).groupBy("doc_id").agg(F.count("*").alias("rows"), F.min("kept").alias("kept"))
        found = common.durable(found.where("doc_id is not null and (rows > 1 or not kept)"), "drops", keep=True)
    # whole rows travel as one struct, so that no name of theirs can clash
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").cast("long").alias("doc_id"))
    out = rows.join(common.small(found.select("doc_id"), F.lit(24)), "doc_id", "left_anti").select("row.*")
    again = found.where("kept").select("doc_id")
    if again.isEmpty():
        return out
    return out.unionByName(rows.join(common.small(again, F.lit(24)), "doc_id", "left_semi").dropDuplicates(["doc_id"]).select("row.*"))
