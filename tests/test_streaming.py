from __future__ import annotations

from pyspark.sql import functions as F

from sepkey.operators import exact, sampling
from sepkey.sources.stores import table
from sepkey.streaming import samplers
from tests.paths import SMALL


def test_stream_sample_equals_batch_sample_for_any_split(spark, tmp_path):
    events = table(spark, SMALL, "events").select("event_id", "user_id", "event_type")
    want = {r.event_id for r in sampling.tuples(events, 40, 9, [F.col("event_id")]).collect()}
    for parts in (1, 3):
        folder = str(tmp_path / f"in{parts}")
        events.repartition(parts).write.parquet(folder)
        events.limit(50).write.mode("append").parquet(folder)  # some rows are delivered twice
        stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(folder)
        sampler = samplers.BottomRankSampler(spark, 40, 9, [F.col("event_id")])
        sampler.start(stream, str(tmp_path / f"log{parts}")).awaitTermination()
        assert {r.event_id for r in sampler.sample().collect()} == want


def test_stream_pairs_are_distinct_and_independent_of_batches(spark, tmp_path):
    rows = spark.range(60).select(F.col("id").alias("k"))
    found = []
    for parts in (1, 2):
        folder = str(tmp_path / f"in{parts}")
        rows.repartition(parts).write.parquet(folder)
        stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(folder)
        sampler = samplers.PairSlotSampler(spark, 30, 4, [F.col("k")])
        sampler.start(stream, str(tmp_path / f"log{parts}")).awaitTermination()
        found.append({(r.slot, r.l.k, r.r.k) for r in sampler.pairs().collect()})
    assert found[0] == found[1] and len(found[0]) == 30
    assert all(a != b for _, a, b in found[0])


def test_windows_add_up_and_stream(spark, tmp_path):
    events = table(spark, SMALL, "events")
    days = samplers.window_gamma(events, "ts", ["event_type"], "1 day")
    assert days.agg(F.sum("n")).first()[0] == events.count()
    whole = samplers.window_gamma(events, "ts", ["event_type"], "10000 days").agg(F.sum("gamma")).first()[0]
    assert int(whole) <= int(exact.unseparated(events, ["event_type"]).first().gamma)
    folder = str(tmp_path / "in")
    events.write.parquet(folder)
    stream = samplers.fresh(spark.readStream.schema(events.schema).parquet(folder), "ts", ["event_id"], "1 hour")
    counted = stream.groupBy(F.window("ts", "1 day")).count()
    q = counted.writeStream.outputMode("append").format("memory").queryName("days").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "log")).start()
    q.awaitTermination()
    assert spark.table("days").count() > 0


def test_samplers_go_on_after_a_restart(spark, tmp_path):
    rows, ids = spark.range(300).select(F.col("id").alias("k")), [F.col("k")]
    want = {r.k for r in sampling.tuples(rows, 25, 3, ids).collect()}
    for i, part in enumerate(("k < 100", "k between 100 and 199", "k >= 150")):
        samplers.BottomRankSampler(spark, 25, 3, ids, str(tmp_path / "tuples")).merge(rows.where(part), i % 2)
        samplers.PairSlotSampler(spark, 20, 3, ids, str(tmp_path / "pairs")).merge(rows.where(part), i % 2)
    assert {r.k for r in samplers.BottomRankSampler(spark, 25, 3, ids, str(tmp_path / "tuples")).sample().collect()} == want
    at_once = samplers.PairSlotSampler(spark, 20, 3, ids)
    at_once.merge(rows, 0)
    found = [{(r.slot, r.l.k, r.r.k) for r in s.pairs().collect()} for s in (at_once, samplers.PairSlotSampler(spark, 20, 3, ids, str(tmp_path / "pairs")))]
    assert found[0] == found[1] and len(found[0]) == 20


def test_identities_are_told_apart(spark):
    rows = spark.createDataFrame([("a", None), (None, "a"), ("a|b", "c"), ("a", "b|c"), ("\\N", None), (None, None), ("a\\", "b"), ("a", "\\b"), ("a", None)], "x string, y string")
    ids = [F.col("x"), F.col("y")]
    sampler = samplers.BottomRankSampler(spark, 100, 1, ids)
    sampler.merge(rows, 0)
    sampler.merge(rows, 1)
    assert sampler.sample().count() == 8
    slots = samplers.PairSlotSampler(spark, 15, 1, ids)
    slots.merge(rows, 0)
    assert all(r.l != r.r for r in slots.pairs().collect()) and slots.pairs().count() == 15


def test_a_sketch_of_streamed_pairs(spark):
    rows = spark.range(400).select(F.col("id").alias("k"), (F.col("id") % 2).alias("half"))
    slots = samplers.PairSlotSampler(spark, 200, 5, [F.col("k")])
    slots.merge(rows.where("k < 150"), 0)
    slots.merge(rows.where("k >= 150"), 1)
    sketch = slots.sketch(400, 1, 0.1, 0.2, ["k", "half"])
    got = {r.set_name: r for r in sketch.estimate_many([("half", ["half"]), ("k", ["k"])]).collect()}
    assert got["k"].status == "small" and abs(got["half"].gamma_hat / (2 * 200 * 199 / 2) - 1) < 0.2
    assert sketch.stored_bits() == 400
