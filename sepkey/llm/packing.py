"""Packing by shortest-pack-first over the length histogram.

Each document is tokenised, closed with id 0, and cut into pieces of at most ``capacity`` ids. Lengths are placed from the longest down: a piece
goes into the pack with the most room that still takes it, and opens a pack only where none does. Packs of one composition are one
pattern with a count, so the work on the driver depends on ``capacity`` alone, never on the number of documents. Patterns are then joined
back to the pieces: the k-th piece of a length takes the k-th slot of that length.

Ranks within a length come from two levels (a row number inside a length and salt, and the counts of the salts before), so that a length
that holds a third of all pieces is spread over many tasks.

Null and empty texts give the closing id alone; repeated rows are packed each; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import base64
import heapq
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

CAPACITY = 1024
SALTS = 64


class Encoder:
    """Ids as the ``tokenizers`` library gives them for ``json_path``. Where the same vocabulary lies beside it as ranks, plain texts go
    through ``tiktoken``, which is faster; texts that hold a special token's string go through ``tokenizers``, which reads it as that token, and so do texts that
    ``tiktoken`` cannot split."""

    def __init__(self, json_path: str, ranks_path: str | None, pattern: str | None):
        from tokenizers import Tokenizer

        self.full = Tokenizer.from_file(json_path)
        self.full.no_truncation()
        self.full.no_padding()
        self.special = [t.content for t in self.full.get_added_tokens_decoder().values()]
        self.fast = None
        if ranks_path:
            import tiktoken

            with open(ranks_path, "rb") as f:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            self.fast = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})

    def ids(self, text: str) -> np.ndarray:
        if self.fast is None or any(x in text for x in self.special):
            return np.array(self.full.encode(text, add_special_tokens=False).ids, "<u4")
        try:
            return np.asarray(self.fast.encode_to_numpy(text), "<u4")
        except ValueError:  # its pattern engine gives up on very long runs of blanks
            return np.array(self.full.encode(text, add_special_tokens=False).ids, "<u4")


def pieces(docs: DataFrame, json_path: str, ranks_path: str | None = None, pattern: str | None = None, capacity: int = CAPACITY, keep_ids: bool = False) -> DataFrame:
    """Rows for each document: doc_id, start, length, ids_crc32, doc_tokens, and with ``keep_ids`` the ids of the piece."""
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"] + ["ids"] * keep_ids

    def run(batches):
        encoder = common.per_process(("encoder", json_path, ranks_path), lambda: Encoder(json_path, ranks_path, pattern))
        for batch in batches:
            for part, texts in common.steps(batch):
                row, start, length, crc, total, kept = [], [], [], [], [], []
                for i in range(len(texts)):
                    ids = np.append(encoder.ids(texts.row(i).decode()), np.uint32(0)).astype("<u4")
                    for a in range(0, len(ids), capacity):
                        piece = ids[a : a + capacity]
                        row.append(i)
                        start.append(a)
                        length.append(len(piece))
                        crc.append(zlib.crc32(piece.tobytes()))
                        total.append(len(ids))
                        if keep_ids:
                            kept.append(piece.astype(np.int32))
                out = [part.column(0).take(pa.array(row, pa.int32())), *(pa.array(x, pa.int64()) for x in (start, length, crc, total))]
                yield pa.RecordBatch.from_arrays(out + ([pa.array(kept, pa.list_(pa.int32()))] if keep_ids else []), names)

    kind = docs.schema["doc_id"].dataType.simpleString()
    return common.map_arrow(docs.select("doc_id", "text"), run, f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long" + ", ids array<int>" * keep_ids)


def patterns(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, tuple[tuple[int, int], ...]]]:
    """(count, ((length, how many), ...)) for each pattern, its lengths from the longest down.

    Room is kept in a heap. Equal packs move together: a step either fills one piece into each pack of a pattern or uses up the pieces."""
    by_room: dict[int, list[list]] = {}
    heap: list[int] = []
    closed: list[tuple[int, tuple]] = []

    def put(room: int, count: int, content: tuple) -> None:
        if room == 0:
            closed.append((count, content))
            return
        if room not in by_room:
            by_room[room] = []
            heapq.heappush(heap, -room)
        for group in by_room[room]:
            if group[1] == content:
                group[0] += count
                return
        by_room[room].append([count, content])

    def add(content: tuple, length: int, times: int = 1) -> tuple:
        if content and content[-1][0] == length:
            return (*content[:-1], (length, content[-1][1] + times))
        return (*content, (length, times))

    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        while left:
            if heap and -heap[0] >= length:
                room = -heap[0]
                count, content = by_room[room].pop()
                if not by_room[room]:
                    del by_room[room]
                    heapq.heappop(heap)
                n = min(count, left)
                if n < count:
                    put(room, count - n, content)
                put(room - length, n, add(content, length))
                left -= n
            else:  # one by one, each new pack would be filled up before the next is opened
                each = capacity // length
                full, rest = divmod(left, each)
                if full:
                    put(capacity - each * length, full, add((), length, each))
                if rest:
                    put(capacity - rest * length, 1, add((), length, rest))
                left = 0
    for room in sorted(by_room):
        closed += [(count, content) for count, content in by_room[room]]
    return closed


def slots(found: list[tuple[int, tuple[tuple[int, int], ...]]]) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, last rank, first sequence, offset): pieces of these ranks go, one each, to consecutive sequences."""
    out, used, sequence = [], {}, 0
    for count, content in found:
        offset = 0
        for length, times in content:
            for _ in range(times):
                first = used.get(length, 0)
                out.append((length, first, first + count - 1, sequence, offset))
                used[length] = first + count
                offset += length
        sequence += count
    return out


def pack(cut: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """``cut`` (the result of ``pieces``) with sequence_id and offset."""
    spark = cut.sparkSession
    cut = common.durable(cut, "pieces").withColumn("salt", F.pmod(F.xxhash64("doc_id", "start"), F.lit(SALTS)))
    counts = common.durable(cut.groupBy("length", "salt").agg(F.count("*").alias("n")), "lengths")  # at most capacity * SALTS rows
    histogram = {r.length: r.n for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most capacity rows
    before = counts.select("length", "salt", (F.sum("n").over(Window.partitionBy("length").orderBy("salt")) - F.col("n")).alias("before"))
    ranked = cut.withColumn("nth", F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "start", "ids_crc32", "doc_tokens")))
    ranked = ranked.join(F.broadcast(before), ["length", "salt"]).withColumn("rank", F.col("before") + F.col("nth") - 1)
    kind = T.StructType([T.StructField(x, T.LongType()) for x in ("length", "lo", "hi", "sequence", "offset")])
    where = spark.createDataFrame(slots(patterns(histogram, capacity)), kind)  # grows with capacity, not with the corpus
    placed = ranked.join(F.broadcast(where), (ranked["length"] == where["length"]) & F.col("rank").between(F.col("lo"), F.col("hi"))).drop(where["length"])
    return placed.withColumn("sequence_id", F.col("sequence") + F.col("rank") - F.col("lo")).drop("salt", "nth", "before", "rank", "lo", "hi", "sequence")


def sequences(packed: DataFrame, capacity: int = CAPACITY, pad: int = 0) -> DataFrame:
    """sequence_id, ids filled up to ``capacity``, and n_ids; ``packed`` must hold the ids of its pieces."""
    rows = packed.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("p"))
    ids = F.flatten(F.transform("p", lambda x: x["ids"]))
    return rows.select("sequence_id", F.concat(ids, F.array_repeat(F.lit(pad), F.lit(capacity) - F.size(ids))).alias("ids"), F.size(ids).alias("n_ids"))
