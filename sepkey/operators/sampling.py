"""Uniform samples of tuples and of pairs.

Sampling is by row, never by content: a rank is a hash of a row's identity. Hashing the content would keep or drop groups of equal rows as a whole,
which is what the filters must not do.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from sepkey.functions import portable
from sepkey.sources.stores import durable

#: Most drawn ordinals that may be broadcast; more are joined by a shuffle.
BROADCAST_DRAWS = 2_000_000


def _rank(seed: int, identity: list[Column], kind: str) -> Column:
    if kind == "md5":
        return portable.rank(seed, identity)
    if kind == "xxhash64":
        return F.xxhash64(F.lit(seed), *identity)
    if kind == "rand":
        return F.rand(seed)
    raise ValueError(kind)


def tuples(df: DataFrame, r: int, seed: int, identity: list[Column], rank: str = "md5", n: int | None = None, write: bool = True) -> DataFrame:
    """Exactly ``min(r, rows)`` tuples without replacement: the least ranks, ties by identity.

    Without ``n`` the plan keeps r rows a task and gathers tasks * r of them. Where ``n``, the number of rows, is known, one scan writes the rows
    with a rank under a threshold, about r of them in all, and counts them on the way; only should they be fewer than r, which the threshold makes
    rare, a second scan follows. ``write=False`` leaves writing and that test to the caller."""
    columns = df.columns
    ids = [f"__id{i}" for i in range(len(identity))]
    ranked = df.select("*", *[c.alias(i) for c, i in zip(identity, ids, strict=True)]).withColumn("__rank", _rank(seed, [F.col(i) for i in ids], rank))

    def least(rows: DataFrame) -> DataFrame:
        return rows.orderBy("__rank", *ids).limit(r).select(*columns)

    if n is None or rank == "rand" or r >= n:
        return least(ranked)
    share = (r + 6 * math.sqrt(r) + 20) / n
    while share < 1:
        if rank == "md5":
            under = portable.number(portable.rank_text(seed, [F.col(i) for i in ids])) < int(share * portable.SPAN)
        else:
            under = F.col("__rank") < int(-(2**63) + share * 2**64)
        if not write:
            return least(ranked.where(under))
        seen = Observation()
        some = durable(ranked.where(under).observe(seen, F.count(F.lit(1)).alias("rows")), "under")
        if seen.get["rows"] >= r:
            return least(some)
        share *= 2
    return least(ranked)


def ordinals(df: DataFrame, identity: list[Column]) -> DataFrame:
    """``df`` with ``ordinal``: 0, 1, ... by identity. A range partitioning, row numbers within its parts, and the parts' counts before: no single sort.

    Ordinals are the same whatever the number of parts."""
    ids = [f"__id{i}" for i in range(len(identity))]
    spread = df.select("*", *[c.alias(i) for c, i in zip(identity, ids, strict=True)]).repartitionByRange(*ids).withColumn("__part", F.spark_partition_id())
    fixed = durable(spread, "ranges")  # the bounds of the ranges are drawn at run time: written once, read by both
    before = fixed.groupBy("__part").agg(F.count("*").alias("c")).withColumn("__before", F.sum("c").over(Window.orderBy("__part")) - F.col("c")).drop("c")
    numbered = fixed.withColumn("__nth", F.row_number().over(Window.partitionBy("__part").orderBy(*ids)))
    return numbered.join(F.broadcast(before), "__part").withColumn("ordinal", F.col("__before") + F.col("__nth") - 1).select(*df.columns, "ordinal")


def file_ordinals(df: DataFrame) -> DataFrame:
    """``df``, read straight from Parquet, with ``ordinal`` by file and row index: no data is moved, and counting reads no column."""
    place = df.select("*", F.col("_metadata.file_path").alias("__file"), F.col("_metadata.row_index").alias("__row"))
    before = place.groupBy("__file").agg((F.max("__row") + 1).alias("c")).withColumn("__before", F.sum("c").over(Window.orderBy("__file")) - F.col("c")).drop("c")
    return place.join(F.broadcast(before), "__file").withColumn("ordinal", F.col("__before") + F.col("__row")).select(*df.columns, "ordinal")


def single_draws(df: DataFrame, slots: int, n: int, seed: int) -> DataFrame:
    """slot, ordinal: independent draws with replacement."""
    return df.sparkSession.range(slots).select(F.col("id").alias("slot"), F.pmod(portable.draw(seed, F.col("id"), "w"), F.lit(n)).alias("ordinal"))


def pair_draws(df: DataFrame, s: int, n: int, seed: int) -> DataFrame:
    """slot, i, j with i <> j: j is drawn from the n - 1 others."""
    if n < 2:
        return df.sparkSession.range(0).select(F.col("id").alias("slot"), F.col("id").alias("i"), F.col("id").alias("j"))
    i = F.pmod(portable.draw(seed, F.col("slot"), "i"), F.lit(n))
    j = F.pmod(portable.draw(seed, F.col("slot"), "j"), F.lit(n - 1))
    return df.sparkSession.range(s).select(F.col("id").alias("slot")).select("slot", i.alias("i"), j.alias("j0")).select("slot", "i", (F.col("j0") + (F.col("j0") >= F.col("i")).cast("long")).alias("j"))


def tuples_wr(df: DataFrame, r: int, seed: int, identity: list[Column], rows: DataFrame | None = None, n: int | None = None) -> DataFrame:
    """``r`` independent draws: slot and the drawn row; a row drawn twice comes twice."""
    rows = rows if rows is not None else ordinals(df, identity)
    n = rows.count() if n is None else n
    if n == 0:
        return rows.select(F.lit(0).cast("long").alias("slot"), *df.columns).limit(0)
    drawn = single_draws(df, r, n, seed)
    return rows.join(_small(drawn, r), "ordinal").select("slot", *df.columns, "ordinal")


def _small(draws: DataFrame, count: int) -> DataFrame:
    return F.broadcast(draws) if count <= BROADCAST_DRAWS else draws


def pairs(df: DataFrame, s: int, seed: int, identity: list[Column], mode: str = "independent", rows: DataFrame | None = None, n: int | None = None) -> DataFrame:
    """slot, l and r (structs of the two rows).

    independent: uniform pairs of distinct rows by drawn ordinals; the table is scanned once, against the drawn ordinals. disjoint: 2 s rows of the
    least ranks, paired in that order: each pair is uniform, pairs share no row, and one pass without ordinals is enough; needs 2 s <= n."""
    columns = df.columns
    if mode == "disjoint":
        ids = [f"__id{i}" for i in range(len(identity))]
        some = df.select("*", *[c.alias(i) for c, i in zip(identity, ids, strict=True)]).withColumn("__rank", portable.rank(seed, [F.col(i) for i in ids])).orderBy("__rank", *ids).limit(2 * s)
        numbered = some.withColumn("__nth", F.row_number().over(Window.orderBy("__rank", *ids)) - 1)  # 2 s rows
        slot, side = F.floor(F.col("__nth") / 2).cast("long"), F.col("__nth") % 2
        both = numbered.select(slot.alias("slot"), side.alias("side"), F.struct(*columns).alias("row")).groupBy("slot").agg(F.max(F.when(F.col("side") == 0, F.col("row"))).alias("l"), F.max(F.when(F.col("side") == 1, F.col("row"))).alias("r"), F.count("*").alias("c"))
        return both.where("c = 2").select("slot", "l", "r")
    if mode != "independent":
        raise ValueError(mode)
    n = (df if rows is None else rows).count() if n is None else n
    rows = rows if rows is not None else ordinals(df, identity)
    drawn = pair_draws(df, s, n, seed)
    ends = drawn.select("slot", F.explode(F.array(F.struct(F.lit(0).alias("side"), F.col("i").alias("ordinal")), F.struct(F.lit(1).alias("side"), F.col("j").alias("ordinal")))).alias("e")).select("slot", "e.side", "e.ordinal")
    met = rows.join(_small(ends, 2 * s), "ordinal").select("slot", "side", F.struct(*columns).alias("row"))
    end = lambda side: F.first(F.when(F.col("side") == side, F.col("row")), ignorenulls=True)  # noqa: E731  both ends from one pass over the rows
    return met.groupBy("slot").agg(end(0).alias("l"), end(1).alias("r"))


def equal_flags(pairs_df: DataFrame, attrs: list[str]) -> DataFrame:
    """slot and one boolean for each attribute: whether the pair agrees on it (nulls agree)."""
    return pairs_df.select("slot", *[F.col(f"l.{a}").eqNullSafe(F.col(f"r.{a}")).alias(a) for a in attrs])
