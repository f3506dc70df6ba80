"""Continuous conversion: pairs arrive as a stream of files and become bundles."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from pairbundle.model import PAIRS
from pairbundle.operators import addressing, convert


def pair_stream(spark: SparkSession, path: str, files_each: int = 1) -> DataFrame:
    """A file stream of pairs in Parquet."""
    return spark.readStream.schema(PAIRS).option("maxFilesPerTrigger", files_each).parquet(path)


def _generation(spark: SparkSession, path: str, batch_id: int) -> str:
    return f"{path}/generation={batch_id}"


def ingest(pairs: DataFrame, path: str, checkpoint: str, once: bool = True):
    """Each micro-batch becomes a generation of bundles (fingerprint, media_bytes, rep_ord, media, texts). A batch that runs again after a
    failure overwrites its own generation, so every pair counts once. ``compact`` joins generations and numbers the result."""

    def store(batch: DataFrame, batch_id: int) -> None:
        marked = convert.fingerprint(batch)
        found = convert.assemble(batch, convert.detect(marked))
        found.select("fingerprint", "media_bytes", "rep_ord", "media", "texts").write.mode("overwrite").parquet(_generation(batch.sparkSession, path, batch_id))

    writer = pairs.writeStream.foreachBatch(store).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if once else writer).start()


def compact(spark: SparkSession, path: str, order: str = "first_seen") -> DataFrame:
    """All generations as numbered bundles. Ranges are given anew, since late texts lengthen bundles."""
    rows = spark.read.parquet(path)
    texts = F.array_sort(F.flatten(F.collect_list("texts")))
    found = rows.groupBy("fingerprint", "media_bytes").agg(F.min("rep_ord").alias("rep_ord"), F.min_by("media", "rep_ord").alias("media"), texts.alias("texts"))
    sizes = F.aggregate("texts", F.lit(0).cast("long"), lambda s, t: s + F.octet_length(t["text"]))
    light = found.select("fingerprint", "media_bytes", "rep_ord", F.size("texts").cast("long").alias("n_texts"), sizes.alias("text_bytes"))
    return addressing.number(light, order).join(found.select("fingerprint", "media_bytes", "media", "texts"), ["fingerprint", "media_bytes"])


def first_copies(stream: DataFrame, delay: str | None = None) -> DataFrame:
    """The first row of each fingerprint; with a delay, state is kept no longer than that."""
    marked = convert.fingerprint(stream)
    return marked.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["fingerprint"]) if delay else marked.dropDuplicates(["fingerprint"])


class BundleState(StatefulProcessor):
    """Collects the texts of a fingerprint and reports the bundle when no text came for ``quiet_ms``; a late text opens it again and is
    reported as an appendix."""

    def __init__(self, quiet_ms: int):
        self.quiet_ms = quiet_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.texts = handle.getListState("texts", "pair_ord long, text string")
        self.rounds = handle.getValueState("rounds", "n int")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        for part in rows:
            self.texts.appendList([(int(o), t) for o, t in zip(part["pair_ord"], part["text"])])
        for timer in self.handle.listTimers():
            self.handle.deleteTimer(timer)
        self.handle.registerTimer(timerValues.getCurrentProcessingTimeInMs() + self.quiet_ms)
        return iter(())

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        texts = sorted(self.texts.get())
        n = (self.rounds.get()[0] if self.rounds.exists() else 0) + 1
        self.rounds.update((n,))
        self.texts.clear()
        yield pd.DataFrame({"fingerprint": [key[0]], "appendix": [n - 1], "n_texts": [len(texts)], "texts": ["\n".join(t[1] for t in texts)]})

    def close(self) -> None:
        pass


def stateful_bundles(stream: DataFrame, quiet_ms: int = 1000) -> DataFrame:
    """Needs the RocksDB state store, which a session chooses."""
    marked = convert.fingerprint(stream).select("fingerprint", "pair_ord", "text")
    return marked.groupBy("fingerprint").transformWithStateInPandas(BundleState(quiet_ms), "fingerprint string, appendix int, n_texts int, texts string", "Append", "processingTime")
