"""Sharding by extendible hashing, with DataFrame functions only.

A document's hash is 60 bits of its key. The directory is a set of buckets, each a number of leading bits (its depth) and their value;
a bucket is split on its next bit as long as its bytes exceed the limit and its rows do not all have one hash. Both halves then
stand for themselves: no other bucket moves.

The whole directory is found level by level from one pre-aggregate: bytes per cell of leading bits, a few bits finer than the
expected shards. A cell that is still too large (rare: hashes are even) is cut finer in the next round, over its own rows alone. The
directory stays a DataFrame, for it grows with the corpus.

Rows with one hash (repeated keys) cannot be told apart by more bits. If together they exceed the limit they go to numbered overflow
pages of that bucket, each within the limit. One text larger than the limit is a shard of its own.

A null key counts as the empty string, a null text has 0 bytes; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

BITS = 60
FINER = 4
PAGE_SALTS = 64


def key_hash(key: Column) -> Column:
    """60 bits: the first 15 hex digits of the MD5 of the key as text."""
    return F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit(""))), 1, 15), 16, 10).cast("long")


def _bits(h: Column, depth) -> Column:
    """The first ``depth`` bits of the hash."""
    n = F.lit(BITS) - (depth if isinstance(depth, Column) else F.lit(depth))
    return F.call_function("shiftright", h, n.cast("int"))


def assign(docs: DataFrame, limit: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each row of ``docs``: the key, n_bytes, depth and prefix of its bucket, its overflow page (0: none), and the rows and
    bytes of that shard."""
    return _assigned(docs, limit, key, text, F.col(key).alias(key)).select(key, "n_bytes", "depth", "prefix", "page", "shard_docs", "shard_bytes")


def _assigned(docs: DataFrame, limit: int, key: str, text: str, carried: Column) -> DataFrame:
    """Each row's ``carried`` column with its place: a key does not tell rows apart."""
    slim = docs.select(carried, key_hash(F.col(key)).alias("h"), F.octet_length(F.coalesce(F.col(text), F.lit(""))).cast("long").alias("n_bytes"), F.spark_partition_id().alias("part"))
    slim = common.durable(slim, "sizes")
    total = slim.agg(F.sum("n_bytes")).first()[0] or 0
    bits = min(BITS, max(0, math.ceil(math.log2(max(1, total / limit)))) + FINER)
    pending, directory, above = slim.select("h", "n_bytes"), [], 0
    while True:
        leaves, left = _split(pending, limit, bits, above)
        directory.append(leaves)
        if left.isEmpty():
            break
        pending = common.durable(pending.withColumn("cell", _bits(F.col("h"), bits)).join(left.select("cell"), "cell", "left_semi").drop("cell"), "finer")
        above, bits = bits, min(BITS, bits + 2 * FINER)
    placed = None
    for leaves in directory:
        cell_bits = leaves["bits"]
        rows = slim.withColumn("cell", _bits(F.col("h"), cell_bits)).join(leaves["map"], "cell").drop("cell")
        placed = rows if placed is None else placed.unionByName(rows)
    return _pages(placed, limit)


def _split(rows: DataFrame, limit: int, bits: int, above: int) -> tuple[dict, DataFrame]:
    """The buckets of depth ``above`` (all of them known to be split, unless 0) to ``bits``: the map from cells to finished buckets, and the
    cells still to be split."""
    cells = rows.groupBy(_bits(F.col("h"), bits).alias("cell")).agg(F.sum("n_bytes").alias("bytes"), F.count("*").alias("docs"), F.min("h").alias("lo"), F.max("h").alias("hi"))
    cells = common.durable(cells, "cells")
    steps = cells.withColumn("depth", F.explode(F.sequence(F.lit(above), F.lit(bits)))).withColumn("prefix", F.call_function("shiftright", F.col("cell"), (F.lit(bits) - F.col("depth")).cast("int")))
    nodes = steps.groupBy("depth", "prefix").agg(F.sum("bytes").alias("bytes"), F.sum("docs").alias("docs"), F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    nodes = common.durable(nodes.withColumn("split", (F.col("bytes") > limit) & (F.col("lo") < F.col("hi"))), "nodes")
    parents = nodes.where("split").select((F.col("depth") + 1).alias("depth"), F.col("prefix").alias("half"))
    ends = nodes.where("not split").withColumn("half", F.call_function("shiftright", F.col("prefix"), F.lit(1)))
    under = ends.join(parents, ["depth", "half"], "left_semi")
    if above == 0:
        under = under.unionByName(ends.where("depth = 0"))
    leaves = under.select("depth", "prefix", "bytes", "docs", (F.col("lo") == F.col("hi")).alias("one_hash"))
    # each cell lies in one leaf: blow leaves up to their cells
    found = steps.select("cell", "depth", "prefix").join(leaves, ["depth", "prefix"])
    return {"bits": bits, "map": found}, nodes.where((F.col("depth") == bits) & F.col("split")).select(F.col("prefix").alias("cell"))


def _pages(placed: DataFrame, limit: int) -> DataFrame:
    over = (F.col("bytes") > limit) & F.col("one_hash") & (F.col("docs") > 1)
    whole = placed.where(~over).withColumn("page", F.lit(0).cast("long")).withColumnsRenamed({"docs": "shard_docs", "bytes": "shard_bytes"})
    hot = placed.where(over)
    # running bytes in two levels: inside a salt, and over the salts before it
    hot = hot.withColumn("salt", F.pmod("part", F.lit(PAGE_SALTS)))
    sums = hot.groupBy("h", "salt").agg(F.sum("n_bytes").alias("n"), F.max("n_bytes").alias("top"))
    by = Window.partitionBy("h")
    sums = sums.select("h", "salt", F.max("top").over(by).alias("top"), (F.sum("n").over(by.orderBy("salt")) - F.col("n")).alias("base"))
    run = F.sum("n_bytes").over(Window.partitionBy("h", "salt").orderBy("n_bytes", "part").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n_bytes")
    hot = hot.withColumn("run", run).join(sums, ["h", "salt"])
    hot = hot.withColumn("page", F.floor((F.col("base") + F.col("run")) / F.greatest(F.lit(1), F.lit(limit) - F.col("top"))).cast("long"))
    of_page = hot.groupBy("h", "page").agg(F.count("*").alias("shard_docs"), F.sum("n_bytes").alias("shard_bytes"))
    hot = hot.join(of_page, ["h", "page"])
    return whole.unionByName(hot.select(*whole.columns))


def write_shards(docs: DataFrame, limit: int, path: str, key: str = "doc_id", text: str = "text") -> None:
    """Writes all rows with all columns, one folder for each shard (depth, prefix and page), each written by few tasks. Rows go through the
    assignment themselves, so null keys have their shard and the rows of a repeated key their own pages."""
    placed = _assigned(docs, limit, key, text, F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    placed.select("row.*", "depth", "prefix", "page").repartition("depth", "prefix", "page").write.partitionBy("depth", "prefix", "page").parquet(path)
