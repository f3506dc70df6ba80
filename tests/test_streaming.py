import os
import time

import pytest
from pyspark.sql import functions as F

from pairbundle.operators import convert
from pairbundle.sources.corpora import corpus, table
from pairbundle.streaming import ingest, windows


@pytest.fixture()
def pair_files(spark, small, tmp_path):
    path = f"{tmp_path}/pairs"
    corpus(spark, small, "doc_copies").repartition(4, "pair_ord").write.parquet(path)
    return path


def test_ingestion_equals_conversion(spark, small, pair_files, tmp_path):
    out, check = f"{tmp_path}/out", f"{tmp_path}/check"
    ingest.ingest(ingest.pair_stream(spark, pair_files), out, check).awaitTermination()
    assert len([d for d in os.listdir(out) if d.startswith("generation=")]) > 1
    key = ["bundle_id", "fingerprint", "start_idx", "end_idx", "byte_offset", "byte_len"]
    want = convert.summary(corpus(spark, small, "doc_copies")).select(key).orderBy("bundle_id").collect()
    assert ingest.compact(spark, out).select(key).orderBy("bundle_id").collect() == want
    ingest.ingest(ingest.pair_stream(spark, pair_files), out, check).awaitTermination()  # a restart adds nothing
    assert ingest.compact(spark, out).select(key).orderBy("bundle_id").collect() == want


def run(df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def test_first_copies(spark, pair_files):
    run(ingest.first_copies(ingest.pair_stream(spark, pair_files)), "pb_first")
    assert spark.table("pb_first").count() == 189


@pytest.fixture()
def event_files(spark, small, tmp_path):
    path = f"{tmp_path}/events"
    e = table(spark, small, "events")
    for k, part in enumerate(e.randomSplit([1.0] * 3, 5)):
        part.coalesce(1).write.parquet(f"{path}/part={k}")
    return spark.readStream.schema(e.schema).option("recursiveFileLookup", True).parquet(path)


@pytest.mark.parametrize("shape", ["tumbling", "sliding", "sessions"])
def test_windows_equal_batch(spark, small, event_files, shape):
    f = getattr(windows, shape)
    run(f(event_files), f"pb_{shape}", "complete")
    assert sorted(map(tuple, spark.table(f"pb_{shape}").collect())) == sorted(map(tuple, f(table(spark, small, "events")).collect()))


def test_late_rows_are_dropped(spark, small, tmp_path):
    e = table(spark, small, "events").orderBy("ts")
    first, last = e.limit(50), table(spark, small, "events")
    last.coalesce(1).write.parquet(f"{tmp_path}/e/a")
    stream = spark.readStream.schema(e.schema).option("recursiveFileLookup", True).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/e")
    check = f"{tmp_path}/c"

    def go():
        q = windows.tumbling(stream, delay="1 hour").writeStream.format("parquet").option("path", f"{tmp_path}/o").option("checkpointLocation", check).trigger(availableNow=True).start()
        q.awaitTermination()
        return sum(s.get("numRowsDroppedByWatermark", 0) for p in q.recentProgress for s in p["stateOperators"])

    go()
    first.coalesce(1).write.parquet(f"{tmp_path}/e/b")  # the same rows once more, far behind the watermark
    assert go() > 0


def test_stream_joins(spark, small, event_files):
    e = table(spark, small, "events")
    run(windows.interval_join(event_files, event_files), "pb_interval")
    from pairbundle.operators.relational import QUERIES

    assert sorted(map(tuple, spark.table("pb_interval").collect())) == sorted(map(tuple, QUERIES["op_join_interval"](spark, small).collect()))
    profile = e.groupBy("user_id").agg(F.count("*").alias("seen"))
    run(windows.with_profile(event_files, profile), "pb_profile")
    assert spark.table("pb_profile").where("seen > 0").count() == e.count()


def test_stateful_bundles(spark, pair_files, tmp_path):
    q = ingest.stateful_bundles(ingest.pair_stream(spark, pair_files), 0).writeStream.format("memory").queryName("pb_state").outputMode("append").trigger(processingTime="500 milliseconds").start()
    try:
        done = lambda: spark.table("pb_state").agg(F.sum("n_texts")).first()[0] or 0
        for _ in range(120):  # timers keep the query busy, so it is never idle
            if q.exception() or done() >= 200:
                break
            time.sleep(0.5)
        assert q.exception() is None and done() == 200
    finally:
        q.stop()
