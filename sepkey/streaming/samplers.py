"""Samples of streams, and pair counts by window.

The r smallest ranks of a union are the r smallest of the parts' r smallest, so a sample merges over micro-batches, replays and shards.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sepkey.functions import portable
from sepkey.operators import exact, nonsep
from sepkey.sources.stores import shared_folder


class _Versions:
    """Numbered folders under ``path``, each a whole state. A new state is written beside the last finished one and older ones go, so that a restart,
    or another sampler on the same path, goes on from there. Batches that are delivered again change nothing."""

    def __init__(self, spark, path: str):
        self.spark, self.path = spark, path

    def _finished(self) -> list[int]:
        jvm = self.spark.sparkContext._jvm
        top = jvm.org.apache.hadoop.fs.Path(self.path)
        files = top.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        if not files.exists(top):
            return []
        names = [(f.getPath().getName(), f.getPath()) for f in files.listStatus(top) if f.isDirectory()]
        return sorted(int(n) for n, p in names if n.isdigit() and files.exists(jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS")))

    def last(self) -> DataFrame | None:
        found = self._finished()
        return self.spark.read.parquet(f"{self.path}/{found[-1]:012d}") if found else None

    def put(self, state: DataFrame) -> None:
        found = self._finished()
        state.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/{found[-1] + 1 if found else 0:012d}")
        jvm = self.spark.sparkContext._jvm
        for old in found[:-1]:
            gone = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{old:012d}")
            gone.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(gone, True)


class BottomRankSampler:
    """Keeps the r rows of the least ranks of all rows seen. Rows of one identity are one row, so redelivered rows change nothing.

    Each micro-batch is merged by ``foreachBatch`` into a new version under ``path``; a sampler made on the same path, after a restart or elsewhere,
    goes on from the last finished one. Without a path the sample lives as long as the session's folder."""

    def __init__(self, spark, r: int, seed: int, identity: list[Column], path: str | None = None):
        self.spark, self.r, self.seed, self.identity = spark, r, seed, identity
        self.path = path or f"{shared_folder(spark)}/sampler-{uuid.uuid4().hex}"
        self._state = _Versions(spark, self.path)

    def merge(self, batch: DataFrame, batch_id: int) -> None:
        ids = [f"__id{i}" for i in range(len(self.identity))]
        rows = batch.select("*", *[c.alias(i) for c, i in zip(self.identity, ids, strict=True)], portable.rank(self.seed, self.identity).alias("__rank"))
        # each part gives its r least before anything is put together
        least = lambda df: df.dropDuplicates(ids).orderBy("__rank", *ids).limit(self.r)
        known = self._state.last()
        self._state.put(least(rows) if known is None else least(least(rows).unionByName(known)))

    def start(self, stream: DataFrame, checkpoint: str, **trigger):
        return stream.writeStream.foreachBatch(self.merge).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()

    def sample(self) -> DataFrame:
        known = self._state.last()
        if known is None:
            raise ValueError(f"no batch has been merged under {self.path}")
        return known.drop("__rank", *[f"__id{i}" for i in range(len(self.identity))])


class PairSlotSampler:
    """For each of s slots the two rows with the least hash of (slot, row): a uniform pair of distinct rows, slots independent of one another. Work is s for each
    row, so s is small; merges and restarts like the sampler of tuples."""

    def __init__(self, spark, s: int, seed: int, identity: list[Column], path: str | None = None):
        self.spark, self.s, self.seed, self.identity = spark, s, seed, identity
        self.path = path or f"{shared_folder(spark)}/slots-{uuid.uuid4().hex}"
        self._state = _Versions(spark, self.path)

    def merge(self, batch: DataFrame, batch_id: int) -> None:
        row = F.struct(*batch.columns)
        marks = batch.select(F.explode(F.sequence(F.lit(0), F.lit(self.s - 1))).alias("slot"), F.concat_ws("|", *map(portable.part_text, self.identity)).alias("key"), row.alias("row"))
        marks = marks.withColumn("h", F.md5(F.concat_ws("|", F.lit(str(self.seed)), "slot", "key"))).select("slot", "key", "h", "row")
        known = self._state.last()
        if known is not None:
            marks = marks.unionByName(known)
        # the least, then the least of the others: two partial aggregates, no list of rows
        marks = marks.select("slot", F.struct("h", "key", "row").alias("x"))
        first = marks.groupBy("slot").agg(F.min("x").alias("first"))
        rest = marks.join(first, "slot").where(F.col("x.key") != F.col("first.key")).groupBy("slot").agg(F.min("x").alias("x"))
        self._state.put(first.select("slot", F.col("first").alias("x")).unionByName(rest).select("slot", "x.key", "x.h", "x.row"))

    def start(self, stream: DataFrame, checkpoint: str, **trigger):
        return stream.writeStream.foreachBatch(self.merge).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()

    def pairs(self) -> DataFrame:
        """slot, l, r."""
        rows = self._state.last()
        if rows is None:
            raise ValueError(f"no batch has been merged under {self.path}")
        both = rows.groupBy("slot").agg(F.min(F.struct("h", "key", "row")).alias("l"), F.max(F.struct("h", "key", "row")).alias("r"), F.count("*").alias("c"))
        return both.where("c = 2").select("slot", F.col("l.row").alias("l"), F.col("r.row").alias("r"))

    def sketch(self, n: int, k: int, alpha: float, eps: float, attrs: list[str], big_k: float = 1.0) -> nonsep.PairSketch:
        """The pair sketch over the pairs of the slots; ``n``: rows seen. The sketch's guarantee needs ``bounds.sketch_pairs`` slots."""
        return nonsep.PairSketch.of_pairs(self.pairs(), self.s, n, k, alpha, eps, attrs, big_k)


def fresh(stream: DataFrame, at: str, key: list[str], delay: str) -> DataFrame:
    """The stream with an event time that watermarks accept, each key once within the delay."""
    return stream.withColumn(at, F.col(at).cast("timestamp")).withWatermark(at, delay).dropDuplicatesWithinWatermark(key)


def window_gamma(df: DataFrame, at: str, attrs: list[str], length: str, slide: str | None = None) -> DataFrame:
    """start, n, gamma of one set in each tumbling or sliding window; for batches and, with a watermark, for streams."""
    span = F.window(F.col(at).cast("timestamp"), length, slide) if slide else F.window(F.col(at).cast("timestamp"), length)
    counted = df.groupBy(span.alias("w"), *attrs).agg(F.count("*").alias("k"))
    return counted.groupBy("w").agg(F.sum("k").alias("n"), F.sum(exact.pairs(F.col("k"))).cast(exact.BIG).alias("gamma")).select(F.col("w.start").alias("start"), "n", "gamma")


def session_gamma(df: DataFrame, at: str, by: str, attrs: list[str], gap: str) -> DataFrame:
    """by, start, n, gamma of one set in each session of ``by``: events less than ``gap`` apart."""
    s = df.withColumn("__at", F.col(at).cast("timestamp"))
    sessions = s.groupBy(by, F.session_window("__at", gap).alias("w")).agg(F.count("*").alias("n")).select(F.col(by).alias("__by"), F.col("w.start").alias("start"), F.col("w.end").alias("end"))
    # each event lies in the one session of its key that spans it; a session is never held as a list
    inside = F.col(by).eqNullSafe(F.col("__by")) & (F.col("__at") >= F.col("start")) & (F.col("__at") < F.col("end"))
    counted = s.join(sessions, inside).groupBy(by, "start", *attrs).agg(F.count("*").alias("k"))
    return counted.groupBy(by, "start").agg(F.sum("k").alias("n"), F.sum(exact.pairs(F.col("k"))).cast(exact.BIG).alias("gamma"))
