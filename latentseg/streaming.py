"""Structured Streaming: labelling, label mixes in time windows, running counts, deduplication, and models that follow the stream."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery
from pyspark.sql.types import StructType

from . import em
from .io import stash
from .model import SegmentModel
from .text import chunk_counts


def source(spark: SparkSession, path: str, schema: StructType, per_trigger: int = 1, fmt: str = "parquet") -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).format(fmt).load(path)


def label_stream(stream: DataFrame, model: SegmentModel, text_col: str = "text") -> DataFrame:
    """Stateless scoring by the map engine: no shuffle, so a partition of the stream is labelled where it arrives."""
    return model.transform(stream, text_col, engine="map")


def write(df: DataFrame, path: str, checkpoint: str, by: str | None = "label", fmt: str = "parquet") -> StreamingQuery:
    w = df.writeStream.format(fmt).option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True)
    return (w.partitionBy(by) if by else w).start()


def memory(df: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> StreamingQuery:
    w = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    return (w.option("checkpointLocation", checkpoint) if checkpoint else w).start()


def console(df: DataFrame, mode: str = "append") -> StreamingQuery:
    return df.writeStream.format("console").outputMode(mode).trigger(availableNow=True).start()


def label_mix(stream: DataFrame, window: str = "1 hour", slide: str | None = None, watermark: str = "1 hour", ts_col: str = "ts", label_col: str = "label") -> DataFrame:
    """(start, label, n) by tumbling or sliding windows; rows later than the watermark are dropped and counted by Spark's metrics."""
    w = F.window(ts_col, window, slide) if slide else F.window(ts_col, window)
    return stream.withWatermark(ts_col, watermark).groupBy(w.alias("w"), label_col).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), label_col, "n")


def sessions(stream: DataFrame, gap: str = "30 minutes", watermark: str = "1 hour", ts_col: str = "ts", user_col: str = "user_id") -> DataFrame:
    return stream.withWatermark(ts_col, watermark).groupBy(user_col, F.session_window(ts_col, gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(user_col, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def late_rows(query: StreamingQuery) -> int:
    """Rows that came after the watermark, over the batches of a query."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in p["stateOperators"])


def running_counts(stream: DataFrame, label_col: str = "label", text_col: str = "text") -> DataFrame:
    """(label, chunk, n) so far: additive state, in update mode."""
    return chunk_counts(stream, label_col, text_col)


def dedup(stream: DataFrame, key_cols: list[str], ts_col: str = "ts", watermark: str = "1 hour") -> DataFrame:
    """First rows of each key within the watermark. The watermark of an empty state is the epoch: rows at or before it are late and dropped."""
    return stream.withWatermark(ts_col, watermark).dropDuplicatesWithinWatermark(key_cols)


def with_documents(stream: DataFrame, docs: DataFrame, key: str = "doc_id") -> DataFrame:
    """Stream-static join."""
    return stream.join(docs, key)


def within(left: DataFrame, right: DataFrame, key: str, ts_col: str, interval: str, watermark: str = "1 hour") -> DataFrame:
    """Stream-stream join of rows of one key at most `interval` apart; both sides are watermarked, so state stays bounded."""
    a = left.withWatermark(ts_col, watermark).select(F.col(key).alias("key"), F.col(ts_col).alias("ts_a"), F.struct("*").alias("a"))
    b = right.withWatermark(ts_col, watermark).select(F.col(key).alias("key_b"), F.col(ts_col).alias("ts_b"), F.struct("*").alias("b"))
    return a.join(b, F.expr(f"key = key_b and ts_b >= ts_a and ts_b <= ts_a + interval {interval}")).select("key", "a", "b")


class DriftAlarm(StatefulProcessor):
    """For each source, the share of a label over all rows so far and in the batch at hand; an alarm where they differ by more than a limit. State is two numbers."""

    def __init__(self, label: str, limit: float, least: int) -> None:
        self.label, self.limit, self.least = label, limit, least

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("seen", "n long, hits long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        n = hits = 0
        for pdf in rows:
            n += len(pdf)
            hits += int((pdf["label"] == self.label).sum())
        before = self.state.get() if self.state.exists() else (0, 0)
        self.state.update((before[0] + n, before[1] + hits))
        gap = abs(hits / n - before[1] / before[0]) if n and before[0] >= self.least else 0.0
        yield pd.DataFrame({"source": [key[0]], "n": [n], "gap": [gap], "alarm": [gap > self.limit]})

    def close(self) -> None:
        pass


def drift(stream: DataFrame, label: str, limit: float = 0.2, least: int = 20) -> DataFrame:
    """Needs the RocksDB state store."""
    return stream.select("source", "label").groupBy("source").transformWithStateInPandas(DriftAlarm(label, limit, least), "source string, n long, gap double, alarm boolean", "update", "none")


def refresher(model: SegmentModel, path: str, label_col: str = "label", text_col: str = "text", rounds: int = 4) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: adds a batch's chunk counts to the stored ones, fits the labels it touches, and publishes a new version of the model. A batch that is run again replaces
    its own counts, so recovery counts nothing twice."""
    held = {"model": model}

    def run(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        chunk_counts(batch, label_col, text_col, model.kind, model.prefix_space, model.unit).write.mode("overwrite").parquet(f"{path}/counts/batch={batch_id}")
        batch.groupBy(F.col(label_col).alias("label")).agg(F.count(F.lit(1)).alias("n")).write.mode("overwrite").parquet(f"{path}/sizes/batch={batch_id}")
        touched = [r[0] for r in batch.select(label_col).distinct().collect()]  # labels
        if not touched:
            return
        counts = spark.read.parquet(f"{path}/counts").where(F.col("label").isin(touched)).groupBy("label", "chunk").agg(F.sum("n").alias("n"))
        fitted = em.fit(stash(counts, "counts"), model.vocab, rounds=rounds)
        # the guard's sizes count rows of text, not chunks
        sizes = spark.read.parquet(f"{path}/sizes").where(F.col("label").isin(touched)).groupBy("label").agg(F.sum("n").alias("n_samples"))
        stats = fitted.stats.drop("n_samples").join(sizes, "label").select(*fitted.stats.columns)
        old = held["model"]
        keep = ~F.col("label").isin(touched)
        new = replace(model, theta=old.theta.where(keep).unionByName(fitted.theta), stats=old.stats.where(keep).unionByName(stats), trace=None)
        new.save(f"{path}/model")
        held["model"] = SegmentModel.load(spark, f"{path}/model")

    return run
